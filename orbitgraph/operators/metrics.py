"""Cost and accuracy measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .exchange import with_ranks


def _all_ranks(spark_df: DataFrame, parts: int) -> DataFrame:
    return spark_df.sparkSession.range(parts).select(F.col("id").cast("int").alias("rank"))


def neighbours(plan: DataFrame, parts: int) -> DataFrame:
    """Ranks received from, sent to, and either, for each rank; empty ranks have 0."""
    got = plan.groupBy(F.col("to_rank").alias("rank")).agg(F.countDistinct("from_rank").alias("receives_from"))
    gave = plan.groupBy(F.col("from_rank").alias("rank")).agg(F.countDistinct("to_rank").alias("sends_to"))
    pairs = plan.select("from_rank", "to_rank").distinct()
    either = pairs.unionAll(pairs.select("to_rank", "from_rank")).distinct().groupBy(F.col("from_rank").alias("rank")).agg(F.count(F.lit(1)).alias("either"))
    out = _all_ranks(plan, parts).join(got, "rank", "left").join(gave, "rank", "left").join(either, "rank", "left")
    return out.na.fill(0)


def volume(plan: DataFrame, parts: int) -> DataFrame:
    """Embeddings sent and received by each rank."""
    sent = plan.groupBy(F.col("from_rank").alias("rank")).agg(F.count(F.lit(1)).alias("sent"))
    received = plan.groupBy(F.col("to_rank").alias("rank")).agg(F.count(F.lit(1)).alias("received"))
    return _all_ranks(plan, parts).join(sent, "rank", "left").join(received, "rank", "left").na.fill(0)


def rank_graph(plan: DataFrame) -> DataFrame:
    """(from_rank, to_rank, n_emb): the weighted graph of ranks."""
    return plan.groupBy("from_rank", "to_rank").agg(F.count(F.lit(1)).alias("n_emb"))


def approximate_volume(edges: DataFrame, ranks: DataFrame, rsd: float = 0.02) -> DataFrame:
    """Embeddings received by each rank, estimated without the exact distinct: one small sketch a rank."""
    both = with_ranks(edges, ranks).where(F.col("src_rank") != F.col("dst_rank"))
    return both.groupBy(F.col("dst_rank").alias("rank")).agg(F.approx_count_distinct("src", rsd).alias("received"))


def embedding_bytes(l_max: int, channels: int, dtype_bytes: int = 4) -> int:
    return (l_max + 1) ** 2 * channels * dtype_bytes


def message_bytes(l_max: int, channels: int, dtype_bytes: int = 4) -> int:
    return 3 * embedding_bytes(l_max, channels, dtype_bytes)


def max_useful_ranks(n_messages: int, floor: float = 2e5) -> int:
    """Ranks beyond which each has fewer messages than keeps it busy."""
    return max(1, int(n_messages / floor))


def volume_bytes(plan: DataFrame, parts: int, l_max: int = 4, channels: int = 16, dtype_bytes: int = 4, directions: int = 1, blocks: int = 1, layers: int = 1) -> DataFrame:
    each = embedding_bytes(l_max, channels, dtype_bytes) * directions * blocks * layers
    return volume(plan, parts).select("rank", (F.col("sent") * each).alias("sent_bytes"), (F.col("received") * each).alias("received_bytes"))


def imbalance(ranks: DataFrame, edges: DataFrame, parts: int) -> DataFrame:
    """Largest over mean count of nodes and of edges (by destination); empty ranks count in the mean."""
    nodes = ranks.groupBy("rank").agg(F.count(F.lit(1)).alias("n"))
    held = edges.join(ranks.select(F.col("atom_id").alias("dst"), "rank"), "dst").groupBy("rank").agg(F.count(F.lit(1)).alias("k"))
    each = _all_ranks(ranks, parts).join(nodes, "rank", "left").join(held, "rank", "left").na.fill(0)
    return each.agg(F.round(F.max("n") / F.avg("n"), 6).alias("node_imbalance"), F.round(F.max("k") / F.avg("k"), 6).alias("edge_imbalance"))


def edge_cut(edges: DataFrame, ranks: DataFrame) -> DataFrame:
    both = with_ranks(edges, ranks)
    cut = F.sum((F.col("src_rank") != F.col("dst_rank")).cast("long"))
    return both.agg(cut.alias("cut_edges"), F.count(F.lit(1)).alias("n_edges"), F.round(cut / F.count(F.lit(1)), 6).alias("cut_share"))


def pack_cost(edges: DataFrame, ranks: DataFrame, plan: DataFrame, parts: int) -> DataFrame:
    """Buffers and rows to pack, and remote-source edges to unpack, of each rank."""
    packed = plan.groupBy(F.col("from_rank").alias("rank")).agg(F.countDistinct("to_rank").alias("buffers"), F.count(F.lit(1)).alias("pack_rows"))
    both = with_ranks(edges, ranks).where(F.col("src_rank") != F.col("dst_rank"))
    unpacked = both.groupBy(F.col("dst_rank").alias("rank")).agg(F.count(F.lit(1)).alias("unpack_edges"))
    return _all_ranks(plan, parts).join(packed, "rank", "left").join(unpacked, "rank", "left").na.fill(0)


def is_ring(plan: DataFrame, parts: int) -> DataFrame:
    """Whether every rank exchanges with its predecessor and successor only."""
    pairs = plan.select("from_rank", "to_rank").distinct()
    step = F.pmod(F.col("to_rank") - F.col("from_rank"), F.lit(parts))
    return pairs.agg(F.count(F.lit(1)).alias("pairs"), F.coalesce(F.bool_and((step == 1) | (step == parts - 1)), F.lit(True)).alias("ring"))


def rank_hops(plan: DataFrame, start: int, parts: int) -> DataFrame:
    """Hops from one rank to every other over the graph of ranks (recursive SQL; the graph has a row for each pair)."""
    plan.select("from_rank", "to_rank").distinct().createOrReplaceTempView("og_rank_pairs")
    return plan.sparkSession.sql(
        f"""
        WITH RECURSIVE reach(rank, hops) AS (
          SELECT {int(start)}, 0
          UNION ALL
          SELECT p.to_rank, r.hops + 1 FROM reach r JOIN og_rank_pairs p ON p.from_rank = r.rank WHERE r.hops < {min(int(parts), 4)}
        )
        SELECT rank, CAST(min(hops) AS INT) AS hops FROM reach GROUP BY rank
        """
    )


def alpha_beta(
    edges: DataFrame, ranks: DataFrame, parts: int, alpha: float = 2e-5, beta: float = 20.4e9, pack: float = 2e-9, unpack: float = 1e-9, theta: float = 2e7, half: float = 11_111.0, row_bytes: int = 1600
) -> DataFrame:
    """Modelled seconds of each rank: latency for each neighbour, bytes over bandwidth, packing, unpacking, and messages
    over a throughput that saturates (nine tenths of ``theta`` at 1e5 messages with the default ``half``).

    alpha, pack, unpack and theta are free parameters; beta is the published bandwidth."""
    c = phase_costs(edges, ranks, parts, alpha, beta, pack, unpack, theta, half, row_bytes)
    comm = F.col("t_pack") + F.col("t_send") + F.col("t_unpack")
    return c.select("rank", "messages", "received", "neighbours", F.round(comm, 9).alias("t_comm"), F.round("t_compute", 9).alias("t_compute"), F.round(comm + F.col("t_compute"), 9).alias("t_total"))


def rank_pairs(edges: DataFrame, ranks: DataFrame) -> DataFrame:
    """(from_rank, to_rank, rows, messages): rows that one rank needs of another (or of itself) and the edges they feed.

    One pass over the edges: counts of a source within a rank combine within tasks, and what follows has a row for each
    source and receiving rank, then for each pair of ranks."""
    by_source = with_ranks(edges, ranks).groupBy("src_rank", "dst_rank", "src").agg(F.count(F.lit(1)).alias("k"))
    return by_source.groupBy(F.col("src_rank").alias("from_rank"), F.col("dst_rank").alias("to_rank")).agg(F.count(F.lit(1)).alias("rows"), F.sum("k").alias("messages"))


def phase_costs(
    edges: DataFrame, ranks: DataFrame, parts: int, alpha: float = 2e-5, beta: float = 20.4e9, pack: float = 2e-9, unpack: float = 1e-9, theta: float = 2e7, half: float = 11_111.0, row_bytes: int = 1600
) -> DataFrame:
    """Modelled seconds of each rank by phase: packing, sending and receiving, unpacking, computing.

    Edges are read and joined once: every pair of ranks counts for its receiver and for its sender."""
    return costs_of_pairs(rank_pairs(edges, ranks), _all_ranks(ranks, parts), alpha, beta, pack, unpack, theta, half, row_bytes)


def costs_of_pairs(pairs: DataFrame, all_ranks: DataFrame, alpha: float = 2e-5, beta: float = 20.4e9, pack: float = 2e-9, unpack: float = 1e-9, theta: float = 2e7, half: float = 11_111.0, row_bytes: int = 1600) -> DataFrame:
    """:func:`phase_costs` from pairs of ranks. all_ranks: rank, and the columns of ``pairs`` that tell placements apart."""
    zero, moved = F.lit(0).cast("long"), F.col("from_rank") != F.col("to_rank")
    receiver = {"rank": F.col("to_rank"), "messages": F.col("messages"), "unpack_edges": F.when(moved, F.col("messages")).otherwise(zero), "received": F.when(moved, F.col("rows")).otherwise(zero), "neighbours": moved.cast("long"), "pack_rows": zero}
    sender = {k: zero for k in receiver} | {"rank": F.col("from_rank"), "pack_rows": receiver["received"]}
    roles = F.inline(F.array(*(F.struct(*(c.alias(k) for k, c in role.items())) for role in (receiver, sender))))
    which = [c for c in all_ranks.columns if c != "rank"]
    keys = [*(c for c in which if c in pairs.columns), "rank"]
    counts = pairs.select(*keys[:-1], roles).groupBy(*keys).agg(*(F.sum(k).alias(k) for k in receiver if k != "rank"))
    all_ = all_ranks.join(counts, keys, "left").na.fill(0, [k for k in receiver if k != "rank"])
    return all_.select(
        *which, "rank", "messages", "received", "neighbours",
        (F.col("pack_rows") * F.lit(pack * row_bytes)).alias("t_pack"),
        (F.col("neighbours") * F.lit(alpha) + F.col("received") * F.lit(float(row_bytes)) / F.lit(beta)).alias("t_send"),
        (F.col("unpack_edges") * F.lit(unpack * row_bytes)).alias("t_unpack"),
        ((F.col("messages") + F.lit(half)) / F.lit(theta)).alias("t_compute"),
    )


def rank_memory(edges: DataFrame, ranks: DataFrame, plan: DataFrame, parts: int, l_max: int = 4, channels: int = 16, dtype_bytes: int = 4, max_messages: int = 100_000) -> DataFrame:
    """Modelled bytes of each rank: own rows, received rows, edge rows, and the messages of one chunk."""
    row = embedding_bytes(l_max, channels, dtype_bytes)
    own = ranks.groupBy("rank").agg(F.count(F.lit(1)).alias("n"))
    held = edges.select("dst").join(ranks.select(F.col("atom_id").alias("dst"), "rank"), "dst").groupBy("rank").agg(F.count(F.lit(1)).alias("k"))
    got = volume(plan, parts).select("rank", "received")
    all_ = got.join(own, "rank", "left").join(held, "rank", "left").na.fill(0)
    chunk = F.least(F.col("k"), F.lit(max_messages))
    parts_ = {"nodes": F.col("n") * row, "halo": F.col("received") * row, "edges": F.col("k") * row, "messages": chunk * (3 * row)}
    return all_.select("rank", *(c.alias(k) for k, c in parts_.items()), sum(parts_.values(), F.lit(0)).alias("total"))


def memory_model(n_atoms: int, n_edges: int, l_max: int, channels: int, dtype_bytes: int = 4) -> dict[str, int]:
    row = embedding_bytes(l_max, channels, dtype_bytes)
    return {"nodes": n_atoms * row, "edges": n_edges * row, "messages": 3 * n_edges * row, "total": (n_atoms + 4 * n_edges) * row}


def absolute_errors(pred: DataFrame, truth: DataFrame, keys: list[str], value: str = "val") -> DataFrame:
    """Elements of both sides, missing ones as zero, with their absolute difference."""
    p, t = pred.withColumnRenamed(value, "p"), truth.withColumnRenamed(value, "t")
    both = p.join(t, keys, "full").withColumns({"p": F.coalesce("p", F.lit(0.0)), "t": F.coalesce("t", F.lit(0.0))})
    return both.withColumn("err", F.abs(F.col("p") - F.col("t")))


def mae(errors: DataFrame, by: str = "kind") -> DataFrame:
    """Mean absolute error by kind (node, edge) and over all (rollup)."""
    out = errors.rollup(by).agg(F.round(F.avg("err"), 6).alias("mae"), F.count(F.lit(1)).alias("n"))
    return out.select(F.coalesce(by, F.lit("all")).alias(by), "mae", "n")


def error_quantiles(errors: DataFrame, by: str = "kind", low: float = 0.025, high: float = 0.975) -> DataFrame:
    return errors.groupBy(by).agg(F.round(F.avg("err"), 6).alias("mean_err"), F.round(F.percentile("err", F.lit(low)), 6).alias("low"), F.round(F.percentile("err", F.lit(high)), 6).alias("high"))


def l1_l2(errors: DataFrame, w1: float = 1.0, w2: float = 1.0) -> DataFrame:
    l1, l2 = F.avg("err"), F.avg(F.col("err") * F.col("err"))
    return errors.agg(F.round(l1, 6).alias("l1"), F.round(l2, 6).alias("l2"), F.round(l1 * w1 + l2 * w2, 6).alias("loss"))


def share_of_total(column: str) -> Column:
    return F.col(column) / F.sum(column).over(Window.partitionBy())


def spring_layout(pairs: list[tuple[int, int, float]], parts: int, rounds: int = 200, seed: int = 0):
    """Force-directed places (parts, 2) of the graph of ranks for a picture: a rank graph has a node for each rank, so it
    fits the driver."""
    import numpy as np

    rng = np.random.default_rng(seed)
    place, ideal = rng.random((parts, 2)), 1.0 / max(parts, 1) ** 0.5
    tie = np.zeros((parts, parts))
    for a, b, w in pairs:
        tie[a, b] += w
        tie[b, a] += w
    tie /= max(tie.max(), 1.0)
    for k in range(rounds):
        gap = place[:, None] - place[None]
        far = np.maximum(np.sqrt((gap**2).sum(-1)), 1e-9)
        force = (gap / far[..., None] * (ideal**2 / far - tie * far**2 / ideal)[..., None]).sum(1)
        size = np.maximum(np.sqrt((force**2).sum(-1, keepdims=True)), 1e-9)
        place = place + force / size * np.minimum(size, 0.1 * (1 - k / rounds))
    return place
