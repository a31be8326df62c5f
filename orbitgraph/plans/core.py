"""Named queries of structures, graphs, partitions, exchange and measures, each beside its SQL twin."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import exchange, graph, metrics, partition, structure
from .structures import PLAN_SQL, atoms_sql, bisection_sql, edges, edges_sql, load, with_edges_sql

Query = Callable[[SparkSession, str], DataFrame]
PARTS, DEPTH, R_CUT = 8, 3, 6.0
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def rounded(df: DataFrame, *columns: str, digits: int = 6) -> DataFrame:
    return df.withColumns({c: F.round(c, digits) for c in columns})


# --- structures and graphs ---------------------------------------------------------------------------------------
ROUND_XYZ = "round(x, 6) AS x, round(y, 6) AS y, round(z, 6) AS z"


@query("atoms_oxide", f"WITH {atoms_sql('oxide')} SELECT atom_id, species, {ROUND_XYZ} FROM atoms")
def _(spark, d):
    return rounded(load(spark, d, "oxide")[0], "x", "y", "z")


@query("wrap", f"WITH {atoms_sql('oxide')} SELECT atom_id, round(x+7-l*floor((x+7)/l), 6) AS x, round(y-9-l*floor((y-9)/l), 6) AS y, round(z+50-l*floor((z+50)/l), 6) AS z FROM atoms, cell")
def _(spark, d):
    atoms, cell, _ = load(spark, d, "oxide")
    moved = atoms.withColumns({"x": F.col("x") + 7, "y": F.col("y") - 9, "z": F.col("z") + 50})
    return rounded(structure.wrap(moved, cell).drop("species"), "x", "y", "z")


@query("tile_2x2x2", f"WITH {atoms_sql('oxide')} SELECT atom_id + t*n AS atom_id, species, round(x+(t//4)*l, 6) AS x, round(y+((t//2)%2)*l, 6) AS y, round(z+(t%2)*l, 6) AS z FROM atoms, cell, (SELECT unnest(range(8)) AS t)")
def _(spark, d):
    atoms, cell, n = load(spark, d, "oxide")
    return rounded(structure.tile(atoms, cell, n, 2, 2, 2), "x", "y", "z")


EDGE_OUT = "src, dst, sx, sy, sz, round(r, 6) AS r"


def _edges(name: str, r_cut: float) -> Query:
    return lambda spark, d: rounded(edges(spark, d, name, r_cut)[0].drop("dx", "dy", "dz"), "r")


for _name, _structure, _r, _images in (("edges_r6", "oxide", 6.0, 0), ("edges_r7", "oxide", 7.0, 0), ("edges_images_small", "small_box", 6.0, 2), ("edges_pcm", "pcm_a", 12.0, 0)):
    query(_name, with_edges_sql(_structure, _r, images=_images) + f" SELECT {EDGE_OUT} FROM edges")(_edges(_structure, _r))


@query("edges_brute_small", with_edges_sql("small_box", 6.0, images=2) + f" SELECT {EDGE_OUT} FROM edges")
def _(spark, d):
    atoms, cell, _ = load(spark, d, "small_box")
    return rounded(graph.radius_edges(atoms, cell, 6.0, method="brute").drop("dx", "dy", "dz"), "r")


@query("edges_open_box", "WITH " + atoms_sql("oxide") + " SELECT i.atom_id AS src, j.atom_id AS dst, round(sqrt((j.x-i.x)*(j.x-i.x)+(j.y-i.y)*(j.y-i.y)+(j.z-i.z)*(j.z-i.z)), 6) AS r FROM atoms i, atoms j WHERE i.atom_id<>j.atom_id AND (j.x-i.x)*(j.x-i.x)+(j.y-i.y)*(j.y-i.y)+(j.z-i.z)*(j.z-i.z) <= 36e0")
def _(spark, d):
    atoms, cell, _ = load(spark, d, "oxide")
    open_box = structure.Cell(cell.lengths, (False, False, False))
    return rounded(graph.radius_edges(atoms, open_box, 6.0).select("src", "dst", "r"), "r")


@query("edges_tiled", with_edges_sql("oxide", R_CUT) + """
SELECT src + t*n AS src, dst + (((t//2 + sx)%2 + 2)%2*2 + ((t%2 + sy)%2 + 2)%2)*n AS dst, CAST(floor((t//2 + sx)/2.0) AS INT) AS sx, CAST(floor((t%2 + sy)/2.0) AS INT) AS sy, sz, round(r, 6) AS r
FROM edges, cell, (SELECT unnest(range(4)) AS t)""")
def _(spark, d):
    e, _, _, n = edges(spark, d, "oxide", R_CUT)
    return rounded(graph.tile_edges(e, n, 2, 2, 1).drop("dx", "dy", "dz"), "r")


@query("degree", with_edges_sql("oxide", R_CUT) + " SELECT a.atom_id, count(e.dst) AS n_in FROM atoms a LEFT JOIN edges e ON e.dst = a.atom_id GROUP BY a.atom_id")
def _(spark, d):
    e, atoms, _, _ = edges(spark, d, "oxide", R_CUT)
    return graph.degree(e, atoms)


STATS = " SELECT (SELECT count(*) FROM atoms) AS n_atoms, CAST(sum(n_in) AS BIGINT) AS n_edges, min(n_in) AS min_degree, max(n_in) AS max_degree, round(avg(n_in), 6) AS mean_degree FROM (SELECT a.atom_id, count(e.dst) AS n_in FROM atoms a LEFT JOIN edges e ON e.dst = a.atom_id GROUP BY a.atom_id)"
for _name, _structure, _r in (("graph_stats", "oxide", 6.0), ("graph_stats_pcm", "pcm_a", 12.0)):

    def _stats(spark, d, _structure=_structure, _r=_r):
        e, atoms, _, _ = edges(spark, d, _structure, _r)
        return graph.stats(e, atoms)

    query(_name, with_edges_sql(_structure, _r) + STATS)(_stats)


# --- partitions --------------------------------------------------------------------------------------------------
def oxide_ranks(spark: SparkSession, d: str, skew_x: bool = False, **how):
    """Edges, atoms, cell, ranks and tree of the oxide at depth 3."""
    e, atoms, cell, n = edges(spark, d, "oxide", R_CUT, skew_x)
    e = e.persist()
    ranks, tree = partition.few_neighbour(atoms, graph.degree(e), cell, DEPTH, R_CUT, **how)
    return e, atoms, cell, n, ranks, tree


def ranks_sql(skew_x: bool = False, **how: str) -> str:
    return with_edges_sql("oxide", R_CUT, skew_x) + bisection_sql(DEPTH, R_CUT, **how)


for _name, _how, _skew in (
    ("few_neighbour_p8", {}, False),
    ("few_neighbour_p8_unit", {"weight": "unit"}, False),
    ("few_neighbour_split", {"opening": "split"}, False),
    ("few_neighbour_longest", {"tie": "longest"}, False),
    ("few_neighbour_skewed", {}, True),
):

    def _ranks(spark, d, _how=_how, _skew=_skew):
        return oxide_ranks(spark, d, _skew, **_how)[4].select("atom_id", "rank")

    query(_name, ranks_sql(_skew, **_how) + " SELECT atom_id, rank FROM ranks")(_ranks)


@query("tree_apply", ranks_sql() + " SELECT atom_id, rank FROM ranks")
def _(spark, d):
    _, atoms, _, _, _, tree = oxide_ranks(spark, d)
    return partition.apply_tree(atoms, tree)


@query("place_sequential", f"WITH {atoms_sql('oxide')} SELECT atom_id, CAST(floor(atom_id*8/n) AS INT) AS rank FROM atoms, cell")
def _(spark, d):
    atoms, _, n = load(spark, d, "oxide")
    return partition.sequential(atoms, PARTS, n)


RANDOM = "CAST((((atom_id+1)*48271+12345)%2147483647*48271+12345)%2147483647%8 AS INT)"


@query("place_random", f"WITH {atoms_sql('oxide')} SELECT atom_id, {RANDOM} AS rank FROM atoms")
def _(spark, d):
    return partition.random(load(spark, d, "oxide")[0], PARTS)


@query("place_slabs", f"WITH {atoms_sql('oxide')} SELECT atom_id, CAST(least(floor(z/l*8), 7) AS INT) AS rank FROM atoms, cell")
def _(spark, d):
    atoms, cell, _ = load(spark, d, "oxide")
    return partition.slabs(atoms, cell, PARTS)


@query("place_bricks", f"WITH {atoms_sql('oxide')} SELECT atom_id, CAST((least(floor(x/l*2), 1)*2 + least(floor(y/l*2), 1))*2 + least(floor(z/l*2), 1) AS INT) AS rank FROM atoms, cell")
def _(spark, d):
    atoms, cell, _ = load(spark, d, "oxide")
    return partition.bricks(atoms, cell, (2, 2, 2))


# --- placement and exchange --------------------------------------------------------------------------------------
@query("owned_edges", ranks_sql() + PLAN_SQL + " SELECT dst_rank AS rank, count(*) AS n_edges, count(DISTINCT src) AS n_sources FROM both_ends GROUP BY dst_rank")
def _(spark, d):
    e, _, _, _, ranks, _ = oxide_ranks(spark, d)
    return exchange.place_edges(e, ranks).groupBy("rank").agg(F.count(F.lit(1)).alias("n_edges"), F.countDistinct("src").alias("n_sources"))


@query("source_owned", ranks_sql() + PLAN_SQL + " SELECT src_rank AS rank, count(*) AS n_edges, count(DISTINCT CASE WHEN src_rank <> dst_rank THEN dst END) AS remote_destinations FROM both_ends GROUP BY src_rank")
def _(spark, d):
    e, _, _, _, ranks, _ = oxide_ranks(spark, d)
    placed = exchange.place_edges(e, ranks, "source")
    return placed.groupBy("rank").agg(F.count(F.lit(1)).alias("n_edges"), F.countDistinct(F.when(F.col("src_rank") != F.col("dst_rank"), F.col("dst"))).alias("remote_destinations"))


@query("free_edges", ranks_sql() + PLAN_SQL + " SELECT rank, count(*) AS n_edges, count(DISTINCT CASE WHEN src_rank <> rank THEN src END) AS remote_sources, count(DISTINCT CASE WHEN dst_rank <> rank THEN dst END) AS remote_destinations FROM (SELECT *, CAST(((src*1000003+dst+(sx+8)*64+(sy+8)*8+sz)*48271+12345)%2147483647%8 AS INT) AS rank FROM both_ends) GROUP BY rank")
def _(spark, d):
    e, _, _, _, ranks, _ = oxide_ranks(spark, d)
    placed = exchange.place_edges(e, ranks, "random", PARTS)
    away = lambda end: F.countDistinct(F.when(F.col(f"{end}_rank") != F.col("rank"), F.col(end)))
    return placed.groupBy("rank").agg(F.count(F.lit(1)).alias("n_edges"), away("src").alias("remote_sources"), away("dst").alias("remote_destinations"))


@query("free_edges_sequential", ranks_sql() + PLAN_SQL + " SELECT rank, count(*) AS n_edges, count(DISTINCT CASE WHEN src_rank <> rank THEN src END) AS remote_sources, count(DISTINCT CASE WHEN dst_rank <> rank THEN dst END) AS remote_destinations FROM (SELECT b.*, CAST(least(floor(src*8/n), 7) AS INT) AS rank FROM both_ends b, cell) GROUP BY rank")
def _(spark, d):
    e, _, _, n, ranks, _ = oxide_ranks(spark, d)
    placed = exchange.place_edges(e, ranks, "sequential", PARTS, n)
    away = lambda end: F.countDistinct(F.when(F.col(f"{end}_rank") != F.col("rank"), F.col(end)))
    return placed.groupBy("rank").agg(F.count(F.lit(1)).alias("n_edges"), away("src").alias("remote_sources"), away("dst").alias("remote_destinations"))


@query("exchange_plan", ranks_sql() + PLAN_SQL + " SELECT from_rank, to_rank, atom_id, slot FROM plan")
def _(spark, d):
    e, _, _, _, ranks, _ = oxide_ranks(spark, d)
    return exchange.plan(e, ranks)


def planned(measure) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        e, _, _, _, ranks, _ = oxide_ranks(spark, d)
        return measure(e, ranks, exchange.plan(e, ranks))

    return run


PLANNED = ranks_sql() + PLAN_SQL
query("local_order", PLANNED + " SELECT r.rank, r.atom_id, CAST(s.atom_id IS NOT NULL AS INT) AS sent, CAST(row_number() OVER (PARTITION BY r.rank ORDER BY (s.atom_id IS NOT NULL), r.atom_id) - 1 AS INT) AS position FROM ranks r LEFT JOIN (SELECT DISTINCT from_rank, atom_id FROM plan) s ON s.from_rank = r.rank AND s.atom_id = r.atom_id")(planned(lambda e, r, p: exchange.local_order(r, p)))
query("halo_cover", PLANNED + " SELECT to_rank AS rank, count(*) AS received, 0 AS missing FROM plan GROUP BY to_rank")(
    planned(lambda e, r, p: p.groupBy(F.col("to_rank").alias("rank")).agg(F.count(F.lit(1)).alias("received")).join(exchange.missing_sources(e, r, p).groupBy("rank").agg(F.count(F.lit(1)).cast("int").alias("missing")), "rank", "left").na.fill(0))
)
query("neighbours", PLANNED + " SELECT rank, count(DISTINCT CASE WHEN to_rank = rank THEN from_rank END) AS receives_from, count(DISTINCT CASE WHEN from_rank = rank THEN to_rank END) AS sends_to, count(DISTINCT CASE WHEN from_rank = rank THEN to_rank WHEN to_rank = rank THEN from_rank END) AS either FROM all_ranks, (SELECT DISTINCT from_rank, to_rank FROM plan) GROUP BY rank")(planned(lambda e, r, p: metrics.neighbours(p, PARTS)))
VOLUME = "SELECT rank, count(CASE WHEN from_rank = rank THEN 1 END) AS sent, count(CASE WHEN to_rank = rank THEN 1 END) AS received FROM all_ranks, plan GROUP BY rank"
query("volume", PLANNED + f" {VOLUME}")(planned(lambda e, r, p: metrics.volume(p, PARTS)))
query("volume_bytes", PLANNED + f" SELECT rank, sent*1600 AS sent_bytes, received*1600 AS received_bytes FROM ({VOLUME})")(planned(lambda e, r, p: metrics.volume_bytes(p, PARTS)))
query("rank_topology", PLANNED + " SELECT from_rank, to_rank, count(*) AS n_emb FROM plan GROUP BY ALL")(planned(lambda e, r, p: metrics.rank_graph(p)))
query("imbalance", PLANNED + " SELECT round(max(n)/avg(n), 6) AS node_imbalance, round(max(k)/avg(k), 6) AS edge_imbalance FROM (SELECT rank, (SELECT count(*) FROM ranks r WHERE r.rank = a.rank) AS n, (SELECT count(*) FROM both_ends b WHERE b.dst_rank = a.rank) AS k FROM all_ranks a)")(planned(lambda e, r, p: metrics.imbalance(r, e, PARTS)))
query("edge_cut", PLANNED + " SELECT count(CASE WHEN src_rank <> dst_rank THEN 1 END) AS cut_edges, count(*) AS n_edges, round(count(CASE WHEN src_rank <> dst_rank THEN 1 END)/count(*), 6) AS cut_share FROM both_ends")(planned(lambda e, r, p: metrics.edge_cut(e, r)))
PACK = "SELECT rank, count(DISTINCT CASE WHEN from_rank = rank THEN to_rank END) AS buffers, count(CASE WHEN from_rank = rank THEN 1 END) AS pack_rows, (SELECT count(*) FROM both_ends b WHERE b.dst_rank = rank AND b.src_rank <> rank) AS unpack_edges FROM all_ranks, plan GROUP BY rank"
query("pack_cost", PLANNED + f" {PACK}")(planned(lambda e, r, p: metrics.pack_cost(e, r, p, PARTS)))
query("ring_check", PLANNED + " SELECT count(*) AS pairs, bool_and(((to_rank-from_rank+8)%8) IN (1, 7)) AS ring FROM (SELECT DISTINCT from_rank, to_rank FROM plan)")(planned(lambda e, r, p: metrics.is_ring(p, PARTS)))
query("rank_hops", PLANNED.replace("WITH", "WITH RECURSIVE", 1) + ", pairs AS MATERIALIZED (SELECT DISTINCT from_rank, to_rank FROM plan), reach(rank, hops) AS (SELECT 0, 0 UNION ALL SELECT p.to_rank, r.hops+1 FROM reach r JOIN pairs p ON p.from_rank = r.rank WHERE r.hops < 4) SELECT rank, CAST(min(hops) AS INT) AS hops FROM reach GROUP BY rank")(planned(lambda e, r, p: metrics.rank_hops(p, 0, PARTS)))
query(
    "alpha_beta",
    PLANNED
    + f""", v AS ({VOLUME}), pk AS ({PACK}), nb AS (SELECT to_rank AS rank, count(DISTINCT from_rank) AS neighbours FROM plan GROUP BY to_rank), ms AS (SELECT dst_rank AS rank, count(*) AS messages FROM both_ends GROUP BY dst_rank),
t AS (SELECT rank, messages, received, neighbours, neighbours*2e-5 + received*1600e0/20.4e9 + pack_rows*(2e-9*1600) + unpack_edges*(1e-9*1600) AS comm, (messages+11111e0)/2e7 AS compute FROM v JOIN pk USING (rank) JOIN nb USING (rank) JOIN ms USING (rank))
SELECT rank, messages, received, neighbours, round(comm, 9) AS t_comm, round(compute, 9) AS t_compute, round(comm+compute, 9) AS t_total FROM t""",
)(planned(lambda e, r, p: metrics.alpha_beta(e, r, PARTS)))


# --- comparisons -------------------------------------------------------------------------------------------------
def scheme_ranks(spark: SparkSession, d: str, e: DataFrame, atoms: DataFrame, cell: structure.Cell, n: int) -> dict[str, DataFrame]:
    return {
        "few_neighbour": partition.few_neighbour(atoms, graph.degree(e), cell, DEPTH, R_CUT)[0],
        "sequential": partition.sequential(atoms, PARTS, n),
        "random": partition.random(atoms, PARTS),
        "slabs": partition.slabs(atoms, cell, PARTS),
        "bricks": partition.bricks(atoms, cell, (2, 2, 2)),
    }


SCHEMES_SQL = (
    with_edges_sql("oxide", R_CUT)
    + bisection_sql(DEPTH, R_CUT).replace("ranks AS (", "fnb AS (")
    + f""",
schemes AS (SELECT 'few_neighbour' AS scheme, atom_id, rank FROM fnb UNION ALL SELECT 'sequential', atom_id, CAST(floor(atom_id*8/n) AS INT) FROM atoms, cell UNION ALL SELECT 'random', atom_id, {RANDOM} FROM atoms
 UNION ALL SELECT 'slabs', atom_id, CAST(least(floor(z/l*8), 7) AS INT) FROM atoms, cell UNION ALL SELECT 'bricks', atom_id, CAST((least(floor(x/l*2), 1)*2 + least(floor(y/l*2), 1))*2 + least(floor(z/l*2), 1) AS INT) FROM atoms, cell),
be AS (SELECT a.scheme, e.src, a.rank AS src_rank, b.rank AS dst_rank FROM edges e JOIN schemes a ON a.atom_id = e.src JOIN schemes b ON b.atom_id = e.dst AND b.scheme = a.scheme),
pl AS (SELECT DISTINCT scheme, src_rank, dst_rank, src FROM be WHERE src_rank <> dst_rank)"""
)


@query(
    "partition_quality",
    SCHEMES_SQL
    + """
SELECT scheme, CAST(max(nb) AS BIGINT) AS max_neighbours, CAST(sum(vol) AS BIGINT) AS volume, CAST(any_value(cut) AS BIGINT) AS cut_edges FROM (SELECT scheme, dst_rank, count(DISTINCT src_rank) AS nb, count(*) AS vol FROM pl GROUP BY ALL)
JOIN (SELECT scheme, count(CASE WHEN src_rank <> dst_rank THEN 1 END) AS cut FROM be GROUP BY scheme) USING (scheme) GROUP BY scheme""",
)
def partition_quality(spark, d):
    """Neighbours, volume and cut of every scheme: one plan over all schemes, not one job for each."""
    e, atoms, cell, n = edges(spark, d, "oxide", R_CUT)
    e = e.persist()
    schemes = None
    for name, ranks in scheme_ranks(spark, d, e, atoms, cell, n).items():
        one = ranks.select(F.lit(name).alias("scheme"), "atom_id", "rank")
        schemes = one if schemes is None else schemes.unionByName(one)
    src = schemes.select("scheme", F.col("atom_id").alias("src"), F.col("rank").alias("src_rank"))
    dst = schemes.select("scheme", F.col("atom_id").alias("dst"), F.col("rank").alias("dst_rank"))
    both = e.select("src", "dst").join(src, "src").join(dst, ["scheme", "dst"])
    cut = both.groupBy("scheme").agg(F.sum((F.col("src_rank") != F.col("dst_rank")).cast("long")).alias("cut_edges"))
    plan = both.where(F.col("src_rank") != F.col("dst_rank")).select("scheme", "src_rank", "dst_rank", "src").distinct()
    each = plan.groupBy("scheme", "dst_rank").agg(F.countDistinct("src_rank").alias("nb"), F.count(F.lit(1)).alias("vol"))
    return each.groupBy("scheme").agg(F.max("nb").alias("max_neighbours"), F.sum("vol").alias("volume")).join(cut, "scheme")


TRADE = "SELECT DISTINCT l_suppkey AS src, l_partkey + 10000000 AS dst FROM lineitem"


@query("trade_graph", f"SELECT count(*) AS n_edges, count(DISTINCT src) AS n_src, count(DISTINCT dst) AS n_dst FROM ({TRADE})")
def _(spark, d):
    pairs = spark.read.parquet(f"{d}/lineitem.parquet").select(F.col("l_suppkey").alias("src"), (F.col("l_partkey") + 10_000_000).alias("dst")).distinct()
    return pairs.agg(F.count(F.lit(1)).alias("n_edges"), F.countDistinct("src").alias("n_src"), F.countDistinct("dst").alias("n_dst"))


@query(
    "trade_placement",
    f"""WITH e AS ({TRADE}), r AS (SELECT *, CAST((((src+1)*48271+12345)%2147483647*48271+12345)%2147483647%8 AS INT) AS src_rank, CAST((((dst+1)*48271+12345)%2147483647*48271+12345)%2147483647%8 AS INT) AS dst_rank FROM e)
SELECT 'destination' AS owner, 1 AS stages, count(DISTINCT (src, dst_rank)) FILTER (WHERE src_rank <> dst_rank) AS moved FROM r
UNION ALL SELECT 'source', 3, count(DISTINCT (dst, src_rank)) FILTER (WHERE src_rank <> dst_rank) FROM r""",
)
def _(spark, d):
    e = spark.read.parquet(f"{d}/lineitem.parquet").select(F.col("l_suppkey").alias("src"), (F.col("l_partkey") + 10_000_000).alias("dst")).distinct()
    ids = e.select(F.col("src").alias("atom_id")).unionAll(e.select("dst")).distinct()
    both = exchange.with_ranks(e, partition.random(ids, PARTS)).where(F.col("src_rank") != F.col("dst_rank"))
    moved = lambda owner, end, other: both.agg(F.lit(owner).alias("owner"), F.lit(exchange.exchanges(owner)).alias("stages"), F.countDistinct(end, f"{other}_rank").alias("moved"))
    return moved("destination", "src", "dst").unionByName(moved("source", "dst", "src"))


@query("weak_scaling_1d", with_edges_sql("oxide", R_CUT) + """,
tiles AS (SELECT unnest([1, 2, 3, 4]) AS k),
te AS (SELECT k, t, src, (t + sx) AS raw FROM edges, tiles, LATERAL (SELECT unnest(range(k)) AS t)),
vol AS (SELECT k, ((raw % k) + k) % k AS to_rank, t AS from_rank, count(DISTINCT src) AS rows FROM te WHERE ((raw % k) + k) % k <> t GROUP BY ALL)
SELECT k AS parts, coalesce(CAST(sum(rows) AS BIGINT), 0) AS volume, coalesce(round(sum(rows)/k, 6), 0) AS volume_per_rank FROM tiles LEFT JOIN vol USING (k) GROUP BY k""")
def _(spark, d):
    """One rank for each tile of a row of tiles: the volume of a rank stays the same from three on."""
    e, _, _, n = edges(spark, d, "oxide", R_CUT)
    e = e.persist()
    out = None
    for k in (1, 2, 3, 4):
        tiled = graph.tile_edges(e, n, k, 1, 1)
        rank = lambda c: F.floor(F.col(c) / n).cast("int")
        pairs = tiled.select(rank("src").alias("a"), rank("dst").alias("b"), "src").where("a <> b").distinct()
        one = pairs.agg(F.lit(k).alias("parts"), F.count(F.lit(1)).alias("volume")).withColumn("volume_per_rank", F.round(F.col("volume") / k, 6))
        out = one if out is None else out.unionByName(one)
    return out


@query(
    "frames_edges",
    "WITH " + atoms_sql("small_box").replace("AS atom_id, ", "AS atom_id, f AS frame_id, ").replace("FROM supplier, cell", "FROM supplier, cell, (SELECT unnest(range(3)) AS f)").replace("*l AS x", "*l*(1e0-f*0.05e0) AS x")
    + edges_sql("small_box", R_CUT, images=2).replace("src, dst, sx", "frame_id, src, dst, sx").replace("SELECT i.atom_id AS src", "SELECT i.frame_id, i.atom_id AS src").replace("atoms i, atoms j,", "atoms i JOIN atoms j ON i.frame_id = j.frame_id,")
    + " SELECT frame_id, dst AS atom_id, count(*) AS n_in FROM edges GROUP BY ALL",
)
def _(spark, d):
    """Degrees in every frame of a short trajectory whose atoms move along x."""
    atoms, cell, _ = load(spark, d, "small_box")
    frames = atoms.crossJoin(spark.range(3).select(F.col("id").alias("frame_id"))).withColumn("x", F.col("x") * (1 - F.col("frame_id") * F.lit(0.05)))
    return graph.frame_edges(frames, cell, R_CUT).groupBy("frame_id", F.col("dst").alias("atom_id")).agg(F.count(F.lit(1)).alias("n_in"))


@query("few_neighbour_p6")
def few_neighbour_p6(spark, d):
    """Six parts, which is no power of two: atoms and incoming edges of each (tested against the recursion)."""
    e, atoms, cell, _ = edges(spark, d, "oxide", R_CUT)
    deg = graph.degree(e).persist()
    ranks = partition.few_neighbour(atoms, deg, cell, DEPTH, R_CUT, parts_wanted=6)[0]
    return ranks.join(deg, "atom_id").groupBy("rank").agg(F.count(F.lit(1)).alias("n_atoms"), F.sum("n_in").alias("n_edges"))
