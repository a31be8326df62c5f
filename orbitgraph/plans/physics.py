"""Named queries of embeddings, messages and Hamiltonian blocks."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..operators import graph, hamiltonian, message, metrics
from .structures import edges, load, with_edges_sql

QUERIES: dict = {}
SQL: dict[str, str] = {}
R_SMALL = 6.0


def query(name, sql=None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


# --- embeddings and messages on the ring of given vectors ----------------------------------------------------------
def vectors(spark, d):
    v = spark.read.parquet(f"{d}/embeddings.parquet").select(F.col("vec_id").alias("id"), F.col("embedding").alias("emb"))
    n = v.count()
    return v, message.ring_edges(v, "id", n)


RING = """v AS (SELECT vec_id AS id, embedding AS emb FROM embeddings), n AS (SELECT count(*) AS n FROM v),
e AS (SELECT id AS src, (id + h + n) % n AS dst FROM v, n, (SELECT unnest([1, 2, -1, -2]) AS h)),
g AS (SELECT src, dst, a.emb AS e1, b.emb AS e2 FROM e JOIN v a ON a.id = src JOIN v b ON b.id = dst),
sc AS (SELECT src, dst, list_sum(list_transform(generate_series(1, 64), lambda k: e1[k]::DOUBLE*e2[k]::DOUBLE)) AS score FROM g),
sm AS (SELECT src, dst, score, exp(score - max(score) OVER (PARTITION BY dst)) AS x FROM sc),
wt AS (SELECT src, dst, score, x / sum(x) OVER (PARTITION BY dst) AS weight FROM sm)"""


@query("node_init", """SELECT p_partkey AS atom_id, len(emb) AS n_values, round(list_sum(emb), 6) AS total, round(emb[1], 6) AS first_value FROM (
 SELECT p_partkey, list_concat(CASE WHEN p_partkey%3=0 THEN [0.72e0, 1e0, -0.5e0, 0.25e0] ELSE [0.08e0, 1e0, 0.5e0, -0.25e0] END, list_transform(range(32), lambda k: 0e0)) AS emb FROM part)""")
def _(spark, d):
    table = spark.createDataFrame([(72, [0.72, 1.0, -0.5, 0.25]), (8, [0.08, 1.0, 0.5, -0.25])], "species int, emb array<double>")
    out = message.init_nodes(load(spark, d, "oxide")[0], table, 2, 4)
    total = F.aggregate("emb", F.lit(0.0), lambda a, x: a + x)
    return out.select("atom_id", F.size("emb").cast("long").alias("n_values"), F.round(total, 6).alias("total"), F.round(F.get("emb", F.lit(0)), 6).alias("first_value"))


@query("rbf_edges", with_edges_sql("small_box", R_SMALL, images=2) + " SELECT src, dst, sx, sy, sz, k, round(exp(-(r-k*1.2e0)*(r-k*1.2e0)/(2*1.2e0*1.2e0)), 6) AS v FROM edges, (SELECT unnest(range(6)) AS k)")
def _(spark, d):
    e = edges(spark, d, "small_box", R_SMALL)[0]
    return e.select("src", "dst", "sx", "sy", "sz", F.posexplode(message.radial_basis(F.col("r"), 6.0, 6)).alias("k", "v")).withColumns({"v": F.round("v", 6), "k": F.col("k").cast("long")})


@query("messages_join", f"WITH {RING} SELECT src, dst, 192 AS n_values, round(list_sum(list_transform(generate_series(1, 64), lambda k: (e1[k]::DOUBLE + e2[k]::DOUBLE)*k)), 4) AS digest FROM g")
def _(spark, d):
    v, e = vectors(spark, d)
    m = message.assemble(v, e)
    digest = F.aggregate(F.transform(F.sequence(F.lit(0), F.lit(63)), lambda k: (F.get("message", k).cast("double") + F.get("message", k + 64).cast("double")) * (k + 1)), F.lit(0.0), lambda a, x: a + x)
    return m.select("src", "dst", F.size("message").alias("n_values"), F.round(digest, 4).alias("digest"))


@query("messages_spmm", f"WITH {RING} SELECT src, dst, CAST(k-1 AS INT) AS pos, round(e1[k]::DOUBLE, 6) AS v1, round(e2[k]::DOUBLE, 6) AS v2 FROM g, (SELECT unnest(generate_series(1, 64)) AS k)")
def _(spark, d):
    v, e = vectors(spark, d)
    return message.assemble_spmm(v, e).withColumns({"v1": F.round("v1", 6), "v2": F.round("v2", 6)})


def weighted(spark, d):
    v, e = vectors(spark, d)
    pairs = e.join(v.select(F.col("id").alias("src"), F.col("emb").alias("e1")), "src").join(v.select(F.col("id").alias("dst"), F.col("emb").alias("e2")), "dst")
    return v, message.edge_softmax(pairs.select("src", "dst", message.dot(F.col("e1"), F.col("e2")).alias("score")))


@query("edge_softmax", f"WITH {RING} SELECT src, dst, round(score, 6) AS score, round(weight, 6) AS weight FROM wt")
def _(spark, d):
    return weighted(spark, d)[1].withColumns({"score": F.round("score", 6), "weight": F.round("weight", 6)})


@query("attention_aggregate", f"WITH {RING} SELECT dst, CAST(k-1 AS INT) AS pos, round(sum(weight*emb[k]::DOUBLE), 6) AS value FROM wt JOIN v ON v.id = src, (SELECT unnest(generate_series(1, 64)) AS k) GROUP BY ALL")
def _(spark, d):
    v, w = weighted(spark, d)
    return message.aggregate(w, v).withColumn("value", F.round("value", 6))


@query("knn_embed", """WITH s AS (SELECT a.vec_id AS src, q.vec_id AS dst, round(list_sum(list_transform(generate_series(1, 64), lambda k: a.embedding[k]::DOUBLE*q.embedding[k]::DOUBLE)), 6) AS score FROM embeddings a, (SELECT * FROM embeddings WHERE vec_id % 50 = 0) q WHERE a.vec_id <> q.vec_id)
SELECT src, dst, score, CAST(n AS INT) AS n FROM (SELECT *, row_number() OVER (PARTITION BY dst ORDER BY score DESC, src) AS n FROM s) WHERE n <= 5""")
def _(spark, d):
    return message.nearest(vectors(spark, d)[0], 5, F.col("id") % 50 == 0)


@query("chain_degree", "SELECT conv_id, count(*) AS n_nodes, CAST(2*sum(CASE WHEN nxt = turn + 1 THEN 1 ELSE 0 END) AS BIGINT) AS n_edges FROM (SELECT conv_id, turn, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS nxt FROM (SELECT DISTINCT conv_id, turn FROM conversations)) GROUP BY conv_id")
def _(spark, d):
    """Many small graphs in one table: turns are nodes, consecutive turns are edges both ways."""
    from pyspark.sql import Window

    nodes = spark.read.parquet(f"{d}/conversations.parquet").select("conv_id", "turn").distinct()
    linked = nodes.withColumn("nxt", F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn")))
    return linked.groupBy("conv_id").agg(F.count(F.lit(1)).alias("n_nodes"), F.sum(F.when(F.col("nxt") == F.col("turn") + 1, 2).otherwise(0)).cast("long").alias("n_edges"))


# --- Hamiltonian blocks --------------------------------------------------------------------------------------------
def elements(spark, d):
    e, atoms, _, _ = edges(spark, d, "small_box", R_SMALL)
    return hamiltonian.two_centre(e, atoms, R_SMALL), atoms


def matrix(spark, d):
    off, atoms = elements(spark, d)
    both = off.select("src", "dst", "a", "b", "val").unionByName(hamiltonian.onsite(atoms))
    offs = hamiltonian.offsets(atoms)
    return hamiltonian.to_coo(both, offs), offs, off, atoms


H_SQL = (
    with_edges_sql("small_box", R_SMALL, images=2)
    + f""",
orb AS (SELECT atom_id, species, CASE WHEN species=72 THEN 4 ELSE 1 END AS n_orb FROM atoms),
offs AS (SELECT atom_id, n_orb, CAST(sum(n_orb) OVER (ORDER BY atom_id) - n_orb AS BIGINT) AS first FROM orb),
el AS (SELECT src, dst, sx, sy, sz, r, z1, z2, a, b, {hamiltonian.two_centre_value(R_SMALL)} AS val FROM (
 SELECT e.*, p.species AS z1, q.species AS z2, a, b FROM edges e JOIN orb p ON p.atom_id = src JOIN orb q ON q.atom_id = dst, (SELECT unnest(range(4)) AS a) aa, (SELECT unnest(range(4)) AS b) bb WHERE a < p.n_orb AND b < q.n_orb)),
ons AS (SELECT atom_id AS src, atom_id AS dst, a, a AS b, species*(-0.05e0) + a*0.25e0 AS val FROM orb, (SELECT unnest(range(4)) AS a) WHERE a < n_orb),
coo AS (SELECT p.first + a AS row, q.first + b AS col, sum(val) AS val FROM (SELECT src, dst, a, b, val FROM el UNION ALL SELECT src, dst, a, b, val FROM ons) JOIN offs p ON p.atom_id = src JOIN offs q ON q.atom_id = dst GROUP BY ALL)"""
)


@query("two_centre_h_sp", H_SQL + " SELECT src, dst, sx, sy, sz, CAST(a AS INT) AS a, CAST(b AS INT) AS b, round(val, 6) AS val FROM el")
def _(spark, d):
    return elements(spark, d)[0].select("src", "dst", "sx", "sy", "sz", "a", "b", F.round("val", 6).alias("val"))


@query("h_offsets", H_SQL + " SELECT atom_id, n_orb, first FROM offs")
def _(spark, d):
    return hamiltonian.offsets(load(spark, d, "small_box")[0])


@query("h_coo", H_SQL + " SELECT row, col, round(val, 6) AS val FROM coo")
def _(spark, d):
    return matrix(spark, d)[0].withColumn("val", F.round("val", 6))


@query("h_blocks", H_SQL + """ SELECT p.atom_id AS i, q.atom_id AS j, p.n_orb AS ni, q.n_orb AS nj, CASE WHEN p.atom_id = q.atom_id THEN 'node' ELSE 'edge' END AS kind, round(sum(val), 5) AS total, round(sum(val*val), 5) AS squares
FROM coo JOIN offs p ON row >= p.first AND row < p.first + p.n_orb JOIN offs q ON col >= q.first AND col < q.first + q.n_orb GROUP BY ALL""")
def _(spark, d):
    coo, offs, _, _ = matrix(spark, d)
    b = hamiltonian.to_blocks(coo, offs)
    return b.select("i", "j", "ni", "nj", "kind", F.round(F.aggregate("block", F.lit(0.0), lambda s, x: s + x), 5).alias("total"), F.round(F.aggregate("block", F.lit(0.0), lambda s, x: s + x * x), 5).alias("squares"))


@query("h_assemble", H_SQL + " SELECT row, col, round(val, 6) AS val FROM coo WHERE val <> 0")
def _(spark, d):
    """Blocks split and put together again give the matrix they came from."""
    coo, offs, _, _ = matrix(spark, d)
    return hamiltonian.assemble(hamiltonian.to_blocks(coo, offs), offs).where("val <> 0").withColumn("val", F.round("val", 6))


@query("h_symmetrise", H_SQL + " SELECT row, col, round(sum(val)/2, 6) AS val FROM (SELECT row, col, val FROM coo UNION ALL SELECT col, row, val FROM coo) GROUP BY row, col")
def _(spark, d):
    return hamiltonian.symmetrise(matrix(spark, d)[0]).withColumn("val", F.round("val", 6))


@query("h_shape", H_SQL + " SELECT (SELECT CAST(sum(n_orb) AS BIGINT) FROM offs) AS size, count(*) AS nnz, round(count(*)/pow((SELECT sum(n_orb) FROM offs), 2), 6) AS density FROM coo")
def _(spark, d):
    coo, offs, _, _ = matrix(spark, d)
    return hamiltonian.shape(coo, offs)


PP = H_SQL + ", pp AS (SELECT src, dst, sx, sy, sz, list(val ORDER BY a, b) AS m FROM el WHERE a > 0 AND b > 0 GROUP BY ALL)"


def pp_blocks(spark, d):
    off, _ = elements(spark, d)
    inner = off.where("a > 0 AND b > 0")
    rows = inner.groupBy("src", "dst", "sx", "sy", "sz").agg(F.sort_array(F.collect_list(F.struct("a", "b", "val"))).alias("s"))
    return rows.select("src", "dst", "sx", "sy", "sz", F.transform("s", lambda x: x["val"]).alias("m"))


S2, S3, S6 = 2**0.5, 3**0.5, 6**0.5


@query("couple_pp", PP + f""" SELECT src, dst, sx, sy, sz, round((m[1]+m[5]+m[9])/{S3}e0, 6) AS l0, round((m[6]-m[8])/{S2}e0, 6) AS l1x, round((m[7]-m[3])/{S2}e0, 6) AS l1y, round((m[2]-m[4])/{S2}e0, 6) AS l1z,
round((m[2]+m[4])/{S2}e0, 6) AS l2a, round((m[6]+m[8])/{S2}e0, 6) AS l2b, round((m[9]*2-m[1]-m[5])/{S6}e0, 6) AS l2c, round((m[3]+m[7])/{S2}e0, 6) AS l2d, round((m[1]-m[5])/{S2}e0, 6) AS l2e FROM pp""")
def _(spark, d):
    c = pp_blocks(spark, d).withColumn("c", hamiltonian.couple_pp(F.col("m")))
    names = ("l0", "l1x", "l1y", "l1z", "l2a", "l2b", "l2c", "l2d", "l2e")
    return c.select("src", "dst", "sx", "sy", "sz", *((F.round(F.get("c", F.lit(i)), 6) + F.lit(0.0)).alias(n) for i, n in enumerate(names)))


@query("uncouple_pp", PP + " SELECT src, dst, sx, sy, sz, k, round(m[k], 6) AS v FROM pp, (SELECT CAST(unnest(range(1, 10)) AS INT) AS k)")
def _(spark, d):
    back = pp_blocks(spark, d).withColumn("u", hamiltonian.uncouple_pp(hamiltonian.couple_pp(F.col("m"))))
    return back.select("src", "dst", "sx", "sy", "sz", F.posexplode("u").alias("k", "v")).withColumns({"k": F.col("k") + 1, "v": F.round("v", 6) + F.lit(0.0)})


@query("magnitude_vs_distance", H_SQL + " SELECT least(z1, z2) AS za, greatest(z1, z2) AS zb, CAST(floor(r/0.5e0) AS INT) AS bin, round(max(abs(val)), 6) AS largest, count(*) AS n FROM el GROUP BY ALL")
def _(spark, d):
    return hamiltonian.magnitude_vs_distance(elements(spark, d)[0], 0.5)


CUTS = (3.0, 4.0, 5.0, 5.5, 6.0)
COVER = H_SQL + ", cov AS (SELECT c AS r_cut, count(*) FILTER (WHERE abs(val) > 1e-4 AND r <= c) AS kept, count(*) FILTER (WHERE abs(val) > 1e-4) AS total, sum(CASE WHEN r <= c THEN val*val ELSE 0 END)/sum(val*val) AS w FROM el, (SELECT unnest([3e0, 4e0, 5e0, 5.5e0, 6e0]) AS c) GROUP BY c)"


@query("cutoff_coverage", COVER + " SELECT r_cut, kept, total, round(kept/total, 6) AS coverage, round(w, 6) AS weight_coverage FROM cov")
def _(spark, d):
    return graph.cutoff_coverage(elements(spark, d)[0], list(CUTS), F.col("val"), 1e-4)


@query("cutoff_choice", COVER + " SELECT min(r_cut) AS r_cut FROM cov WHERE round(kept/total, 6) >= 0.9")
def _(spark, d):
    return graph.choose_cutoff(graph.cutoff_coverage(elements(spark, d)[0], list(CUTS), F.col("val"), 1e-4), 0.9)


def errors(spark, d):
    """A prediction that drops weak elements and shrinks the rest, against the truth."""
    coo, _, _, _ = matrix(spark, d)
    pred = coo.where(F.abs("val") > 0.01).withColumn("val", F.col("val") * 0.9)
    out = metrics.absolute_errors(pred, coo, ["row", "col"])
    return out.withColumn("kind", F.when(F.col("row") == F.col("col"), "node").otherwise("edge"))


ERR = H_SQL + ", er AS (SELECT CASE WHEN row = col THEN 'node' ELSE 'edge' END AS kind, abs((CASE WHEN abs(val) > 0.01 THEN val*0.9 ELSE 0 END) - val) AS err FROM coo)"


@query("mae_by_kind", ERR + " SELECT coalesce(kind, 'all') AS kind, round(avg(err), 6) AS mae, count(*) AS n FROM er GROUP BY ROLLUP (kind)")
def _(spark, d):
    return metrics.mae(errors(spark, d))


@query("error_quantiles", ERR + " SELECT kind, round(avg(err), 6) AS mean_err, round(quantile_cont(err, 0.025), 6) AS low, round(quantile_cont(err, 0.975), 6) AS high FROM er GROUP BY kind")
def _(spark, d):
    return metrics.error_quantiles(errors(spark, d))


@query("l1_l2", ERR + " SELECT round(avg(err), 6) AS l1, round(avg(err*err), 6) AS l2, round(avg(err)+avg(err*err), 6) AS loss FROM er")
def _(spark, d):
    return metrics.l1_l2(errors(spark, d))
