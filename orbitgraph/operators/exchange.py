"""Placement of edges on ranks, and the plan of what ranks send to each other.

Destination-owned edges: an edge lives with its destination, so attention and sums stay local and only rows of remote
sources travel, once for each pair of ranks.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .graph import EDGE_KEY


def with_ranks(edges: DataFrame, ranks: DataFrame) -> DataFrame:
    """Edges with the ranks of both ends."""
    one = ranks.select(F.col("atom_id").alias("src"), F.col("rank").alias("src_rank"))
    two = ranks.select(F.col("atom_id").alias("dst"), F.col("rank").alias("dst_rank"))
    return edges.join(one, "src").join(two, "dst")


def place_edges(edges: DataFrame, ranks: DataFrame, owner: str = "destination", parts: int | None = None, n_atoms: int | None = None) -> DataFrame:
    """Edges with the rank that holds each. owner: destination, source, or the free placements sequential and random,
    which split the edges evenly whatever their ends."""
    both = with_ranks(edges, ranks)
    if owner in ("destination", "source"):
        return both.withColumn("rank", F.col("dst_rank" if owner == "destination" else "src_rank"))
    if parts is None:
        raise ValueError("free placements need the number of parts")
    key = F.col("src") * 1_000_003 + F.col("dst") + (F.col("sx") + 8) * 64 + (F.col("sy") + 8) * 8 + F.col("sz") if "sx" in edges.columns else F.col("src") * 1_000_003 + F.col("dst")
    if owner == "random":
        return both.withColumn("rank", ((key * 48_271 + 12_345) % 2_147_483_647 % parts).cast("int"))
    # sequential: contiguous runs of (dense) sources, as a split of an edge list in their order would give
    n = n_atoms or ranks.count()
    return both.withColumn("rank", F.least(F.floor(F.col("src") * parts / F.lit(n)), F.lit(parts - 1)).cast("int"))


def plan(edges: DataFrame, ranks: DataFrame) -> DataFrame:
    """(from_rank, to_rank, atom_id, slot): which rows travel, each once for a pair of ranks, and their place in the buffer."""
    both = with_ranks(edges, ranks).where(F.col("src_rank") != F.col("dst_rank"))
    rows = both.select(F.col("src_rank").alias("from_rank"), F.col("dst_rank").alias("to_rank"), F.col("src").alias("atom_id")).distinct()
    slot = F.row_number().over(Window.partitionBy("from_rank", "to_rank").orderBy("atom_id")) - 1
    return rows.withColumn("slot", slot.cast("int"))


def local_order(ranks: DataFrame, plan_: DataFrame) -> DataFrame:
    """(rank, atom_id, sent, position): local order of nodes with those to be sent at the end."""
    sent = plan_.select(F.col("from_rank").alias("rank"), "atom_id").distinct().withColumn("sent", F.lit(1))
    rows = ranks.select("rank", "atom_id").join(sent, ["rank", "atom_id"], "left").withColumn("sent", F.coalesce("sent", F.lit(0)))
    return rows.withColumn("position", (F.row_number().over(Window.partitionBy("rank").orderBy("sent", "atom_id")) - 1).cast("int"))


def halo(nodes: DataFrame, plan_: DataFrame, columns: list[str]) -> DataFrame:
    """(rank, atom_id, ...): the rows each rank receives. Pack is this join, sending the shuffle by ``rank`` that follows."""
    return plan_.select(F.col("to_rank").alias("rank"), "atom_id").join(nodes.select("atom_id", *columns), "atom_id").select("rank", "atom_id", *columns)


def rank_view(nodes: DataFrame, ranks: DataFrame, plan_: DataFrame, columns: list[str]) -> DataFrame:
    """Local and received rows of every rank."""
    own = ranks.select("rank", "atom_id").join(nodes.select("atom_id", *columns), "atom_id").select("rank", "atom_id", *columns)
    return own.unionByName(halo(nodes, plan_, columns))


def exchanges(owner: str) -> int:
    """Exchanges of a node block: sources only, or end rows and both reductions."""
    return 1 if owner == "destination" else 3


def missing_sources(edges: DataFrame, ranks: DataFrame, plan_: DataFrame) -> DataFrame:
    """Sources that a rank needs and has neither locally nor in its halo: must be empty."""
    need = with_ranks(edges, ranks).select(F.col("dst_rank").alias("rank"), F.col("src").alias("atom_id")).distinct()
    have = ranks.select("rank", "atom_id").unionByName(plan_.select(F.col("to_rank").alias("rank"), "atom_id"))
    return need.join(have, ["rank", "atom_id"], "left_anti")


KINDS = {"fp16": "<f2", "fp32": "<f4", "fp64": "<f8"}


def packed(emb: str, precision: str) -> Column:
    """Rows as bytes of the stored precision, which is what a halo sends: a quarter of the doubles for fp16."""
    kind = KINDS[precision]

    @F.pandas_udf("binary")
    def run(rows: pd.Series) -> pd.Series:
        return rows.map(lambda v: np.asarray(v, float).astype(kind).tobytes())

    return run(F.col(emb))


def unpacked(data: bytes, precision: str) -> np.ndarray:
    return np.frombuffer(data, KINDS[precision]).astype(np.float64)


def edge_key() -> list[Column]:
    return [F.col(c) for c in EDGE_KEY]
