"""Named queries of the scaling experiments on partitioned structures: partition quality, strong and weak scaling with the
time of every phase, bandwidth and memory, all by the cost model on plans of real partitions."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import boxes, exchange, graph, metrics, mincut, partition, structure, telemetry
from ..session import ensure_checkpoint_dir
from .structures import bisection_sql, load, tiled_sql, with_edges_sql

QUERIES: dict = {}
SQL: dict[str, str] = {}
RANKS_A_TILE = 8
THREE_D = ((1, 1, 1), (2, 1, 1), (2, 2, 1), (2, 2, 2))
ONE_D = ((1, 1, 1), (2, 1, 1), (4, 1, 1))
FULL = ((1, 1, 1), (2, 2, 2), (4, 4, 4))


def query(name, sql=None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def placed(spark: SparkSession, d: str, tiles: tuple[int, int, int], r_cut: float, depth: int | None = None):
    """Atoms of the oxide's cell with the few-neighbour ranks of its tiled structure (an array, one for each tile), by default
    eight ranks a tile; the cell, the number of atoms in it and that of parts."""
    atoms, cell, n = load(spark, d, "oxide")
    k = math.prod(tiles)
    depth = depth or int(math.log2(RANKS_A_TILE * k))
    # degrees are joined in the cell, and base and tile stay with the copies: nothing as long as the tiled structure is joined,
    # whose size Spark takes for the cell's (it would broadcast it)
    many = max(24, int(spark.conf.get("spark.sql.shuffle.partitions")))
    weighed = atoms.join(boxes.degree(atoms, cell, r_cut, n), "atom_id", "left").withColumn("base", F.col("atom_id")).repartition(many, "atom_id")
    big = structure.tile(weighed, cell, n, *tiles, keep=("base", "t", "n_in"))
    ranks, tree = partition.few_neighbour(big, None, cell.tiled(*tiles), depth, r_cut, keep=("base", "t"))
    each = ranks.groupBy("base").agg(F.transform(F.array_sort(F.collect_list(F.struct("t", "rank"))), lambda v: v["rank"]).alias("ranks"))
    ensure_checkpoint_dir(spark)
    out = atoms.join(each, F.col("atom_id") == F.col("base")).select(*atoms.columns, "ranks").checkpoint()
    tree.table.unpersist()
    return out, cell, n, 1 << depth


def tiled(spark: SparkSession, d: str, tiles: tuple[int, int, int], r_cut: float, depth: int | None = None):
    """Edges, atoms, cell and few-neighbour ranks of a tiled oxide, by default with eight ranks a tile."""
    atoms, cell, n = load(spark, d, "oxide")
    e = graph.radius_edges(atoms, cell, r_cut).persist()
    big, big_edges = structure.tile(atoms, cell, n, *tiles), graph.tile_edges(e, n, *tiles)
    index = F.explode(F.sequence(F.lit(0), F.lit(math.prod(tiles) - 1))).alias("t")
    degree = graph.degree(e).select("atom_id", "n_in", index).select((F.col("atom_id") + F.col("t").cast("long") * n).alias("atom_id"), "n_in")
    depth = depth or int(math.log2(RANKS_A_TILE * math.prod(tiles)))
    ranks = partition.few_neighbour(big, degree, cell.tiled(*tiles), depth, r_cut)[0].persist()
    return big_edges, big, cell.tiled(*tiles), ranks, 1 << depth


def placements(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    """Every rank of placements given as (parts, ...): rank beside the placement's columns."""
    return spark.createDataFrame(rows, schema).withColumn("rank", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def phase_summary(costs: DataFrame, *by: str) -> DataFrame:
    """One row, or one for each of ``by``: what the slowest rank of each phase takes, the slowest of all, and the mean share
    of the exchange."""
    comm = F.col("t_pack") + F.col("t_send") + F.col("t_unpack")
    total = comm + F.col("t_compute")
    return costs.groupBy(*by).agg(
        F.round(F.avg("received"), 6).alias("volume_per_rank"), F.max("neighbours").alias("max_neighbours"),
        *(F.round(F.max(c), 9).alias(c) for c in ("t_pack", "t_send", "t_unpack", "t_compute")),
        F.round(F.max(total), 9).alias("t_total"), F.round(F.avg(comm / total), 6).alias("exchange_share"),
    )


# the same costs in SQL, after CTEs edges and ranks
COSTS = """,
both_ends AS (SELECT e.src, e.dst, a.rank AS src_rank, b.rank AS dst_rank FROM edges e JOIN ranks a ON a.atom_id = e.src JOIN ranks b ON b.atom_id = e.dst),
plan AS (SELECT DISTINCT src_rank AS from_rank, dst_rank AS to_rank, src AS atom_id FROM both_ends WHERE src_rank <> dst_rank),
held AS (SELECT dst_rank AS rank, count(*) AS messages, count(CASE WHEN src_rank <> dst_rank THEN 1 END) AS unpack_edges FROM both_ends GROUP BY dst_rank),
got AS (SELECT to_rank AS rank, count(*) AS received, count(DISTINCT from_rank) AS neighbours FROM plan GROUP BY to_rank),
gave AS (SELECT from_rank AS rank, count(*) AS pack_rows FROM plan GROUP BY from_rank),
costs AS (SELECT rank, coalesce(messages, 0) AS messages, coalesce(received, 0) AS received, coalesce(neighbours, 0) AS neighbours, coalesce(pack_rows, 0)*(2e-9*1600) AS t_pack, coalesce(neighbours, 0)*2e-5 + coalesce(received, 0)*1600e0/20.4e9 AS t_send, coalesce(unpack_edges, 0)*(1e-9*1600) AS t_unpack, (coalesce(messages, 0)+11111e0)/2e7 AS t_compute
 FROM (SELECT CAST(unnest(range({parts})) AS INT) AS rank) LEFT JOIN held USING (rank) LEFT JOIN got USING (rank) LEFT JOIN gave USING (rank))"""
SUMMARY = """round(avg(received), 6) AS volume_per_rank, CAST(max(neighbours) AS BIGINT) AS max_neighbours, round(max(t_pack), 9) AS t_pack, round(max(t_send), 9) AS t_send, round(max(t_unpack), 9) AS t_unpack, round(max(t_compute), 9) AS t_compute,
 round(max(t_pack+t_send+t_unpack+t_compute), 9) AS t_total, round(avg((t_pack+t_send+t_unpack)/(t_pack+t_send+t_unpack+t_compute)), 6) AS exchange_share"""


def _weak_sql(tilings: tuple, r_cut: float) -> str:
    rows = []
    for nx, ny, nz in tilings:
        parts = RANKS_A_TILE * nx * ny * nz
        ctes = tiled_sql("oxide", r_cut, nx, ny, nz) + bisection_sql(int(math.log2(parts)), r_cut, sides=(f"l*{nx}", f"l*{ny}", f"l*{nz}")) + COSTS.format(parts=parts)
        rows.append(f"(SELECT '{nx}x{ny}x{nz}' AS tiling, {parts} AS parts, (SELECT count(*) FROM atoms) AS n_atoms, {SUMMARY} FROM ({ctes} SELECT * FROM costs) c)".replace("(SELECT count(*) FROM atoms)", f"(SELECT count(*)*{nx * ny * nz} FROM part)"))
    return f"SELECT *, round(first_value(t_total) OVER (ORDER BY parts)/t_total, 6) AS efficiency FROM ({' UNION ALL '.join(rows)})"


def _weak(tilings: tuple, r_cut: float):
    def run(spark: SparkSession, d: str) -> DataFrame:
        rows = []
        for tiles in tilings:
            atoms, cell, n, parts = placed(spark, d, tiles, r_cut)
            pairs = boxes.rank_pairs(atoms, cell, r_cut, F.col("ranks"), n, tiles).drop("scheme")
            every = placements(spark, [("x".join(map(str, tiles)), parts, n * math.prod(tiles))], "tiling string, parts int, n_atoms long")
            one = phase_summary(metrics.costs_of_pairs(pairs, every), "tiling", "parts", "n_atoms")
            rows += one.collect()  # one row
            # what the driver and the executors hold for a tiling goes when the driver collects its garbage
            spark.sparkContext._jvm.System.gc()
        out = spark.createDataFrame(rows, one.schema)
        base = out.where(F.col("parts") == RANKS_A_TILE).select(F.col("t_total").alias("_base"))
        return out.crossJoin(base).withColumn("efficiency", F.round(F.col("_base") / F.col("t_total"), 6)).drop("_base")

    run.__doc__ = "Tiled by " + ", ".join("x".join(map(str, t)) for t in tilings) + ", partitioned into eight ranks a tile: volume, neighbours, modelled phases, efficiency."
    return run


query("weak_scaling", _weak_sql(THREE_D, 6.0))(_weak(THREE_D, 6.0))
query("weak_scaling_row", _weak_sql(ONE_D, 6.0))(_weak(ONE_D, 6.0))
# to 512 ranks (rows only: at 64 tiles the brute-force twin takes too long)
query("weak_scaling_512")(_weak(FULL, 6.0))

SCHEMES = ("few_neighbour", "bricks", "random", "sequential")
BRICKS = {8: (2, 2, 2), 16: (4, 2, 2), 32: (4, 4, 2), 64: (4, 4, 4), 128: (8, 4, 4)}
DEPTHS = (3, 4, 5)


def scheme_ranks(finest: int, cell: structure.Cell, n: int, depth: int) -> dict[str, Column]:
    """Ranks by scheme, of atoms with column ``rank``: few-neighbour ranks of ``finest`` levels."""
    parts = 1 << depth
    return {
        "few_neighbour": F.shiftright("rank", finest - depth),
        "bricks": partition.bricks_rank(cell, BRICKS[parts]),
        "random": partition.random_rank(parts),
        "sequential": partition.sequential_rank(parts, n),
    }


def _scheme_sql(scheme: str, depth: int, r_cut: float) -> str:
    parts, (bx, by, bz) = 1 << depth, BRICKS[1 << depth]
    if scheme == "few_neighbour":
        return bisection_sql(depth, r_cut)
    rank = {
        "bricks": f"CAST((least(floor(x/l*{bx}), {bx - 1})*{by} + least(floor(y/l*{by}), {by - 1}))*{bz} + least(floor(z/l*{bz}), {bz - 1}) AS INT)",
        "random": f"CAST((((atom_id+1)*48271+12345)%2147483647*48271+12345)%2147483647%{parts} AS INT)",
        "sequential": f"CAST(floor(atom_id*{parts}/n) AS INT)",
    }[scheme]
    return f", ranks AS (SELECT atom_id, {rank} AS rank FROM atoms, cell)"


def _schemes_sql(r_cuts: tuple, depths: tuple, columns: str) -> str:
    rows = []
    for r in r_cuts:
        for depth in depths:
            for scheme in SCHEMES:
                ctes = with_edges_sql("oxide", r) + _scheme_sql(scheme, depth, r) + COSTS.format(parts=1 << depth)
                rows.append(f"SELECT {r}e0 AS r_cut, '{scheme}' AS scheme, {1 << depth} AS parts, {columns} FROM ({ctes} SELECT *, (SELECT count(*) FROM both_ends WHERE src_rank <> dst_rank) AS cut FROM costs)")
    return " UNION ALL ".join(rows)


def _schemes(spark: SparkSession, d: str, r_cuts: tuple, depths: tuple, summary, name: str = "oxide") -> DataFrame:
    """summary(costs, *by) of every cutoff, number of parts and scheme: for each cutoff one pass over the graph, box by box,
    counts what all placements exchange."""
    out = []
    for r in r_cuts:
        atoms, cell, n = load(spark, d, name)
        finest = partition.few_neighbour(atoms, boxes.degree(atoms, cell, r, n), cell, max(depths), r)[0]
        placed_ = atoms.join(finest.select("atom_id", "rank"), "atom_id")
        ranks = {(depth, scheme): c for depth in depths for scheme, c in scheme_ranks(max(depths), cell, n, depth).items()}
        pairs = boxes.rank_pairs(placed_, cell, r, F.array(*ranks.values()), n)
        pairs = pairs.withColumnRenamed("scheme", "placement")
        every = placements(spark, [(i, r, scheme, 1 << depth) for i, (depth, scheme) in enumerate(ranks)], "placement int, r_cut double, scheme string, parts int")
        out.append(summary(metrics.costs_of_pairs(pairs, every), "placement", "r_cut", "scheme", "parts").drop("placement"))
    return _union(out)


QUALITY = """round(avg(received), 6) AS volume_per_rank, CAST(max(neighbours) AS BIGINT) AS max_neighbours, round(avg(neighbours), 6) AS mean_neighbours, round(max(messages)/avg(messages), 6) AS edge_imbalance"""


def quality(costs: DataFrame, *by: str) -> DataFrame:
    return costs.groupBy(*by).agg(F.round(F.avg("received"), 6).alias("volume_per_rank"), F.max("neighbours").alias("max_neighbours"), F.round(F.avg("neighbours"), 6).alias("mean_neighbours"), F.round(F.max("messages") / F.avg("messages"), 6).alias("edge_imbalance"))


@query("partition_study", _schemes_sql((6.0, 7.0), (3, 5), QUALITY))
def _(spark, d):
    """Anticipated exchange and load imbalance of every scheme, for two cutoffs and two numbers of parts."""
    return _schemes(spark, d, (6.0, 7.0), (3, 5), quality)


def _strong_of(times: DataFrame) -> DataFrame:
    return telemetry.strong(times.select("scheme", "parts", F.col("t_total").alias("t")), 8)


@query("strong_scaling", f"""SELECT scheme, parts, round(t_total, 9) AS t, round(base/t_total, 6) AS speedup, round(parts/8, 6) AS ideal, round(base/t_total*8/parts, 6) AS efficiency, round(worst/t_total-1, 6) AS gain_over_worst FROM (
 SELECT *, min(CASE WHEN parts = 8 THEN t_total END) OVER () AS base, max(t_total) OVER (PARTITION BY parts) AS worst FROM ({_schemes_sql((6.0,), DEPTHS, SUMMARY)}))""")
def _(spark, d):
    """Strong scaling of the node block by scheme, from the costs of partitions into 8, 16 and 32 ranks."""
    return _strong_of(_schemes(spark, d, (6.0,), DEPTHS, phase_summary))


@query("overhead_decomposition", _schemes_sql((6.0,), DEPTHS, SUMMARY))
def _(spark, d):
    """Packing, sending, unpacking and computing of the slowest rank, and the share of the exchange, by scheme and ranks."""
    return _schemes(spark, d, (6.0,), DEPTHS, phase_summary)


def _fewer_levels(levels: int):
    return lambda rank: F.shiftright(rank, levels)


@query("strong_scaling_128")
def _(spark, d):
    """Strong scaling on a 2x2x2 tile at 32, 64 and 128 ranks, few-neighbour beside the multilevel minimum cut of the same
    graph (rows only: the cut is iterative)."""
    tiles, depths = (2, 2, 2), (5, 6, 7)
    atoms, cell, n, _ = placed(spark, d, tiles, 6.0, 7)
    cut = mincut.min_cut_boxes(atoms, cell, 6.0, n, tuple(1 << k for k in depths), tiles)
    few = [F.transform("ranks", _fewer_levels(7 - k)) for k in depths]
    both = atoms.join(cut.withColumnRenamed("ranks", "cut_ranks"), "atom_id")
    pairs = boxes.rank_pairs(both, cell, 6.0, F.concat(*few, "cut_ranks"), n, tiles).withColumnRenamed("scheme", "placement")
    names = [(scheme, 1 << k) for scheme in ("few_neighbour", "min_cut") for k in depths]
    every = placements(spark, [(i, scheme, parts) for i, (scheme, parts) in enumerate(names)], "placement int, scheme string, parts int")
    times = phase_summary(metrics.costs_of_pairs(pairs, every), "scheme", "parts").select("scheme", "parts", F.col("t_total").alias("t"))
    return telemetry.strong(spark.createDataFrame(times.collect(), times.schema), 32)


@query("bandwidth", "SELECT round(sum(received*1600)/max(t_pack+t_send+t_unpack)/1e9, 6) AS gb_per_s, round(sum(received*1600)/max(t_pack+t_send+t_unpack)/1e9/48.6, 6) AS share_of_peak FROM (" + with_edges_sql("oxide", 6.0) + bisection_sql(5, 6.0) + COSTS.format(parts=32) + " SELECT * FROM costs)")
def _(spark, d):
    """Bytes of an exchange over the slowest rank's modelled time of exchange, at 32 ranks."""
    e, _, _, ranks, parts = tiled(spark, d, (1, 1, 1), 6.0, 5)
    costs = metrics.phase_costs(e, ranks, parts)
    return costs.agg(*telemetry.bandwidth(F.col("received") * 1600, F.col("t_pack") + F.col("t_send") + F.col("t_unpack"), 48.6))


@query("rank_memory", "SELECT rank, n*1600 AS nodes, received*1600 AS halo, messages*1600 AS edges, least(messages, 10000)*4800 AS messages, (n + received + messages)*1600 + least(messages, 10000)*4800 AS total FROM (" + with_edges_sql("oxide", 6.0) + bisection_sql(3, 6.0) + COSTS.format(parts=8) + " SELECT rank, messages, received, (SELECT count(*) FROM ranks r WHERE r.rank = costs.rank) AS n FROM costs)")
def _(spark, d):
    """Bytes that each of eight ranks holds in a block: own rows, received rows, edge rows, one chunk of messages."""
    e, _, _, ranks, parts = tiled(spark, d, (1, 1, 1), 6.0, 3)
    return metrics.rank_memory(e, ranks, exchange.plan(e, ranks), parts, max_messages=10_000)
