"""Declarative message passing on embeddings: initial rows, gather, softmax over incoming edges, weighted sum.

The fused form, which never stores a message, is in ``functions.layers``; these plans are its checkable twins and serve
the invariant part at any scale.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def init_nodes(atoms: DataFrame, table: DataFrame, l_max: int, channels: int) -> DataFrame:
    """Row l=m=0 holds the embedding of the species, all other rows are zero. ``table``: species, emb (a row a species)."""
    rest = F.array_repeat(F.lit(0.0), ((l_max + 1) ** 2 - 1) * channels)
    return atoms.join(F.broadcast(table), "species").select("atom_id", F.concat("emb", rest).alias("emb"))


def radial_basis(r: Column, r_cut: float, n: int, factor: float = 1.0) -> Column:
    """Gaussians with centres evenly over [0, r_cut] and a width of their spacing times ``factor``."""
    gap = r_cut / (n - 1)
    width = gap * factor
    return F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda k: F.exp(-(r - k * F.lit(gap)) * (r - k * F.lit(gap)) / F.lit(2 * width * width)))


def ring_edges(nodes: DataFrame, key: str, n: int, hops: tuple[int, ...] = (1, 2, -1, -2)) -> DataFrame:
    """Each node sends to its neighbours on a ring of ``n`` nodes."""
    return nodes.select(F.col(key).alias("src"), F.explode(F.array(*(F.pmod(F.col(key) + h, F.lit(n)) for h in hops))).alias("dst"))


def assemble(nodes: DataFrame, edges: DataFrame, edge_emb: Column | None = None) -> DataFrame:
    """Messages: source row, destination row and edge row joined end to end. nodes: id, emb."""
    one = nodes.select(F.col("id").alias("src"), F.col("emb").alias("e1"))
    two = nodes.select(F.col("id").alias("dst"), F.col("emb").alias("e2"))
    third = edge_emb if edge_emb is not None else F.zip_with("e1", "e2", lambda a, b: (a + b) / 2)
    return edges.join(one, "src").join(two, "dst").withColumn("message", F.concat("e1", "e2", third)).drop("e1", "e2")


def assemble_spmm(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """The same gathered rows as sparse products A·diag(T) and diag(T)·A over exploded entries: a twin for checking."""
    entries = nodes.select("id", F.posexplode("emb").alias("pos", "v"))
    left = edges.join(entries.withColumnRenamed("id", "src"), "src").groupBy("src", "dst", "pos").agg(F.sum("v").alias("v1"))
    right = edges.join(entries.withColumnRenamed("id", "dst"), "dst").groupBy("src", "dst", "pos").agg(F.sum("v").alias("v2"))
    return left.join(right, ["src", "dst", "pos"])


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def edge_softmax(scores: DataFrame, score: str = "score") -> DataFrame:
    """Adds ``weight``: softmax over the incoming edges of each destination."""
    w = Window.partitionBy("dst")
    top = F.max(score).over(w)
    return scores.withColumn("_e", F.exp(F.col(score) - top)).withColumn("weight", F.col("_e") / F.sum("_e").over(w)).drop("_e")


def aggregate(weighted: DataFrame, nodes: DataFrame) -> DataFrame:
    """(dst, pos, value): weighted sum of source rows over incoming edges."""
    rows = weighted.join(nodes.select(F.col("id").alias("src"), "emb"), "src").select("dst", "weight", F.posexplode("emb").alias("pos", "v"))
    return rows.groupBy("dst", "pos").agg(F.sum(F.col("weight") * F.col("v").cast("double")).alias("value"))


def nearest(nodes: DataFrame, k: int, queries: Column) -> DataFrame:
    """The k nearest nodes (by inner product, ties by id) of the nodes chosen by ``queries``: a stated query set."""
    q = nodes.where(queries).select(F.col("id").alias("dst"), F.col("emb").alias("e2"))
    pairs = nodes.select(F.col("id").alias("src"), F.col("emb").alias("e1")).crossJoin(F.broadcast(q)).where("src <> dst")
    scored = pairs.select("src", "dst", F.round(dot(F.col("e1"), F.col("e2")), 6).alias("score"))
    order = Window.partitionBy("dst").orderBy(F.desc("score"), "src")
    return scored.withColumn("n", F.row_number().over(order)).where(F.col("n") <= k)
