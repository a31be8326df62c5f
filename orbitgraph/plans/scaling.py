"""Named queries of the scaling experiments: strong scaling by the cost model, weak scaling in three dimensions,
bandwidth, throughput samples, partition times, and the SQL surface."""

from __future__ import annotations

import time

import numpy as np
from pyspark.sql import functions as F

from ..functions import layers
from ..functions.layers import Shape
from ..operators import boxes, exchange, graph, metrics, mincut, partition, telemetry
from .core import RANDOM, scheme_ranks
from .structures import atoms_sql, edges, load, with_edges_sql

QUERIES: dict = {}
SQL: dict[str, str] = {}
R_CUT = 6.0


def query(name, sql=None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


TILES = ((1, 1, 1), (2, 1, 1), (2, 2, 1), (2, 2, 2), (3, 2, 2))


@query(
    "weak_scaling_3d",
    with_edges_sql("oxide", R_CUT)
    + """,
tiles AS (SELECT * FROM (VALUES (1, 1, 1), (2, 1, 1), (2, 2, 1), (2, 2, 2), (3, 2, 2)) AS v(nx, ny, nz)),
te AS (SELECT nx, ny, nz, src, ix, iy, iz, ((ix+sx)%nx+nx)%nx AS jx, ((iy+sy)%ny+ny)%ny AS jy, ((iz+sz)%nz+nz)%nz AS jz FROM edges, tiles, LATERAL (SELECT unnest(range(nx)) AS ix) a, LATERAL (SELECT unnest(range(ny)) AS iy) b, LATERAL (SELECT unnest(range(nz)) AS iz) c),
vol AS (SELECT nx, ny, nz, count(*) AS volume FROM (SELECT DISTINCT nx, ny, nz, src, ix, iy, iz, jx, jy, jz FROM te WHERE (ix, iy, iz) <> (jx, jy, jz)) GROUP BY ALL),
nb AS (SELECT nx, ny, nz, count(*) AS links FROM (SELECT DISTINCT nx, ny, nz, ix, iy, iz, jx, jy, jz FROM te WHERE (ix, iy, iz) <> (jx, jy, jz)) GROUP BY ALL)
SELECT CAST(nx*ny*nz AS INT) AS parts, concat_ws('x', nx, ny, nz) AS tiling, coalesce(volume, 0) AS volume, round(coalesce(volume, 0)/(nx*ny*nz), 6) AS volume_per_rank, round(coalesce(links, 0)/(nx*ny*nz), 6) AS neighbours_per_rank FROM tiles LEFT JOIN vol USING (nx, ny, nz) LEFT JOIN nb USING (nx, ny, nz)""",
)
def _(spark, d):
    """One rank for each tile of a block of tiles; volume grows until every axis has three parts."""
    e, _, _, n = edges(spark, d, "oxide", R_CUT)
    e = e.persist()
    out = None
    for nx, ny, nz in TILES:
        tiled = graph.tile_edges(e, n, nx, ny, nz)
        rank = lambda c: F.floor(F.col(c) / n).cast("int")
        pairs = tiled.select(rank("src").alias("a"), rank("dst").alias("b"), "src").where("a <> b").distinct()
        k = nx * ny * nz
        one = pairs.agg(F.count(F.lit(1)).alias("volume"), F.countDistinct("a", "b").alias("links"))
        one = one.select(F.lit(k).alias("parts"), F.lit(f"{nx}x{ny}x{nz}").alias("tiling"), "volume", F.round(F.col("volume") / k, 6).alias("volume_per_rank"), F.round(F.col("links") / k, 6).alias("neighbours_per_rank"))
        out = one if out is None else out.unionByName(one)
    return out


@query("strong_scaling_model")
def _(spark, d):
    """Strong scaling of the node block by the cost model, with the gain of each scheme (rows only: min cut is iterative)."""
    atoms, cell, n = load(spark, d, "oxide")
    finest = partition.few_neighbour(atoms, boxes.degree(atoms, cell, R_CUT, n), cell, 3, R_CUT)[0].select("atom_id", "rank")
    cut = mincut.min_cut_boxes(atoms, cell, R_CUT, n, (4, 8))
    placed = atoms.join(finest, "atom_id").join(cut, "atom_id")
    ranks = {}
    for i, depth in enumerate((2, 3)):
        parts = 1 << depth
        ranks |= {("few_neighbour", parts): F.shiftright("rank", 3 - depth), ("min_cut", parts): F.col("ranks")[i], ("random", parts): partition.random_rank(parts)}
    pairs = boxes.rank_pairs(placed, cell, R_CUT, F.array(*ranks.values()), n).withColumnRenamed("scheme", "placement")
    every = spark.createDataFrame([(i, *k) for i, k in enumerate(ranks)], "placement int, scheme string, parts int").withColumn("rank", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    total = F.round(F.col("t_pack") + F.col("t_send") + F.col("t_unpack") + F.col("t_compute"), 9)
    return telemetry.strong(metrics.costs_of_pairs(pairs, every).groupBy("scheme", "parts").agg(F.max(total).alias("t")), 4)


def throughput(rows, sizes: tuple[int, ...], channels: tuple[int, ...], reps: int = 120, warmup: int = 20, l_max: int = 4):
    """(channels, n, rep, seconds) of timed message transforms, the first ``warmup`` of each batch left out.

    rows: id, emb. For every width and size all rows are dealt into batches by id; a batch of fewer rows repeats them. The
    values of a row fill its message in turn, its first three are the direction."""

    def run(frame):
        import pandas as pd

        width, n = int(frame["channels"].iloc[0]), int(frame["n"].iloc[0])
        shape = Shape(l_max=l_max, channels=width)
        values = np.stack(frame.sort_values("id")["emb"].to_numpy()).astype(float)
        values = values[np.arange(n) % len(values)]
        v = np.where(np.abs(values[:, :3]).sum(1, keepdims=True) > 0, values[:, :3], (0.0, 0.0, 1.0))
        x = values[:, np.arange(shape.rows * width) % values.shape[1]].reshape(n, shape.rows, width)
        p, out = layers.block_params(shape, 1), []
        for rep in range(reps):
            began = time.perf_counter()
            for c in layers.chunks(n, 10_000):
                layers.transform(x[c], x[c], x[c], v[c], p, shape)
            out.append((width, n, rep, time.perf_counter() - began))
        return pd.DataFrame(out[warmup:], columns=["channels", "n", "rep", "seconds"])

    grid = F.explode(F.array(*(F.struct(F.lit(c).alias("channels"), F.lit(n).alias("n")) for c in channels for n in sizes)))
    dealt = rows.withColumn("_g", grid).select("id", "emb", "_g.channels", "_g.n", F.floor(F.col("id") / F.col("_g.n")).alias("batch"))
    return dealt.groupBy("channels", "n", "batch").applyInPandas(run, "channels int, n int, rep int, seconds double")


@query("throughput_samples")
def _(spark, d):
    """Knee of the timed transform over all rows of embeddings (rows only: times), with fewer repetitions than
    :func:`throughput` has by default."""
    rows = spark.read.parquet(f"{d}/embeddings.parquet").where("vec_id IS NOT NULL AND size(embedding) >= 3").select(F.col("vec_id").alias("id"), F.col("embedding").alias("emb"))
    return telemetry.knee(throughput(rows, (100, 1_000, 10_000), (16, 32), reps=6, warmup=2))


@query("partition_times")
def _(spark, d):
    """Seconds to partition the oxide by each method, in all and for each step of a training run of the published length
    (rows only: times). The minimum cut makes its own graph, within its time; degrees are given to the other."""
    atoms, cell, n = load(spark, d, "oxide")
    deg = boxes.degree(atoms, cell, R_CUT, n).persist()
    deg.count()
    rows = []
    for name, f in (("few_neighbour", lambda: partition.few_neighbour(atoms, deg, cell, 3, R_CUT)[0]), ("min_cut", lambda: mincut.min_cut_boxes(atoms, cell, R_CUT, n, (8,)))):
        began = time.time()
        f().count()
        rows.append((name, time.time() - began))
    return spark.createDataFrame(rows, "scheme string, seconds double").withColumn("seconds_a_step", F.col("seconds") / F.lit(7_700.0))


@query("modelled_bandwidth")
def _(spark, d):
    """Bytes of an exchange over the slowest rank's modelled communication time, and its share of the published peak."""
    e, atoms, cell, _ = edges(spark, d, "oxide", R_CUT)
    e = e.persist()
    ranks = partition.few_neighbour(atoms, graph.degree(e), cell, 3, R_CUT)[0]
    return metrics.alpha_beta(e, ranks, 8).agg(*telemetry.bandwidth(F.col("received") * 1600, F.col("t_comm"), 48.6))


@query("cell_shape_ablation")
def _(spark, d):
    """Neighbours, volume and cut of every simple scheme under skewed density: the trade of balance for locality."""
    e, atoms, cell, n = edges(spark, d, "oxide", R_CUT, skew_x=True)
    e = e.persist()
    out = None
    for name, ranks in scheme_ranks(spark, d, e, atoms, cell, n).items():
        plan = exchange.plan(e, ranks)
        one = plan.agg(F.count(F.lit(1)).alias("volume")).crossJoin(metrics.imbalance(ranks, e, 8)).withColumn("scheme", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return out


@query("sql_surface", f"WITH {atoms_sql('oxide')} SELECT {RANDOM} AS rank, count(*) AS n, CAST(sum(species) AS BIGINT) AS total_z FROM atoms GROUP BY 1")
def _(spark, d):
    """Methods from SQL: views of a structure and a SQL function."""
    register(spark, d, "oxide")
    return spark.sql("SELECT og_random_rank(atom_id, 8) AS rank, count(*) AS n, CAST(sum(species) AS BIGINT) AS total_z FROM og_atoms GROUP BY 1")


def register(spark, d, name: str) -> None:
    """Views og_atoms and og_edges of a structure, and SQL functions for placement, spherical index and images."""
    e, atoms, cell, _ = edges(spark, d, name, R_CUT)
    atoms.createOrReplaceTempView("og_atoms")
    e.createOrReplaceTempView("og_edges")
    for text in (
        "og_random_rank(id BIGINT, parts INT) RETURNS INT RETURN CAST((((id + 1) * 48271 + 12345) % 2147483647 * 48271 + 12345) % 2147483647 % parts AS INT)",
        "og_lm_index(l INT, m INT) RETURNS INT RETURN l * l + l + m",
        "og_nearest_image(d DOUBLE, side DOUBLE) RETURNS DOUBLE RETURN d - side * round(d / side)",
    ):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {text}")


@query("min_image_pairs", f"WITH {atoms_sql('small_box')} SELECT i.atom_id AS src, j.atom_id AS dst, round(abs((j.x-i.x) - l*round((j.x-i.x)/l)), 6) AS dx FROM atoms i, atoms j, cell WHERE i.atom_id < j.atom_id")
def _(spark, d):
    """Nearest-image distance along x of every pair of atoms: a brute-force measure, whose rows grow with the square of the
    atoms by definition; radius graphs are built from boxes instead."""
    register(spark, d, "small_box")
    side = load(spark, d, "small_box")[1].lengths[0]
    # a small file is one partition, which would make all pairs in one task
    spark.table("og_atoms").repartition(max(48, int(spark.conf.get("spark.sql.shuffle.partitions")))).createOrReplaceTempView("og_spread")
    return spark.sql(f"SELECT i.atom_id AS src, j.atom_id AS dst, round(abs(og_nearest_image(j.x - i.x, {side}D)), 6) AS dx FROM og_spread i JOIN og_atoms j ON i.atom_id < j.atom_id")
