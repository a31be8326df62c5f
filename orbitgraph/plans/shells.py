"""Named queries of blocks of s, p and d shells and of the network trained on them."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from ..functions.layers import Shape
from ..functions.so3 import rotate, wigner
from ..operators import basis, blocktrain, boxblocks, boxnet, exchange, graph, message, model, partition, structure
from .core import oxide_ranks, ranks_sql
from .learning import _settle, rank_count, structure_space
from .structures import PLAN_SQL, edges, load, with_edges_sql

QUERIES: dict = {}
SQL: dict[str, str] = {}
R_CUT = 6.0
OXIDE = (8, 72)
PCM = (32, 51, 52)


def query(name, sql=None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def _values(rows: list[tuple], names: str) -> str:
    lit = lambda v: f"{v!r}e0" if isinstance(v, float) and "e" not in repr(v) else repr(v)
    return f"(VALUES {', '.join('(' + ', '.join(map(lit, r)) + ')' for r in rows)}) AS t({names})"


def coupled_sql(name: str, species: tuple[int, ...]) -> str:
    ys = ", ".join(basis.harmonics_sql(4))
    return with_edges_sql(name, R_CUT, images=2) + f""",
comp AS (SELECT * FROM {_values(basis.components(species), "z1, z2, i, j, l1, l2, ord, k")}),
cg AS (SELECT * FROM {_values(basis.coefficients(), "l1, l2, ord, m, m1, m2, c")}),
ends AS (SELECT e.*, p.species AS z1, q.species AS z2 FROM edges e JOIN atoms p ON p.atom_id = src JOIN atoms q ON q.atom_id = dst),
har AS (SELECT src, dst, sx, sy, sz, z1, z2, {basis.decay_sql(R_CUT)} AS amp, [{ys}] AS ys FROM ends),
cou AS (SELECT src, dst, sx, sy, sz, i, j, l1, l2, ord, m, amp*k*ys[ord*ord+m+1] AS y FROM har JOIN comp USING (z1, z2), LATERAL (SELECT unnest(range(2*ord+1)) AS m) u),
ele AS (SELECT src, dst, sx, sy, sz, i, j, m1, m2, sum(c*y) AS val FROM cou JOIN cg USING (l1, l2, ord, m) GROUP BY ALL)"""


COUPLED = coupled_sql("small_box", OXIDE)


def parts(spark, d):
    e, atoms, _, _ = edges(spark, d, "small_box", R_CUT)
    return basis.coupled(e, atoms, R_CUT, OXIDE), e, atoms


@query("coupled_spd", COUPLED + " SELECT src, dst, sx, sy, sz, i, j, CAST(ord AS INT) AS L, CAST(m AS INT) AS M, round(y, 6) + 0.0 AS y FROM cou")
def _(spark, d):
    """Coupled components of the blocks of s, p and d shells."""
    return parts(spark, d)[0].select(*basis.KEYS, "i", "j", "L", "M", (F.round("y", 6) + F.lit(0.0)).alias("y"))


@query("elements_spd", COUPLED + " SELECT src, dst, sx, sy, sz, i, j, m1, m2, round(val, 6) + 0.0 AS val FROM ele")
def _(spark, d):
    """The same blocks in the uncoupled basis."""
    u = basis.uncouple(parts(spark, d)[0], basis.KEYS)
    return u.select(*basis.KEYS, "i", "j", "m1", "m2", (F.round("val", 6) + F.lit(0.0)).alias("val"))


@query("couple_spd", COUPLED + " SELECT src, dst, sx, sy, sz, i, j, CAST(ord AS INT) AS L, CAST(m AS INT) AS M, round(y, 6) + 0.0 AS y FROM cou WHERE abs(y) > 1e-5")
def _(spark, d):
    """Uncoupled elements coupled again: the components they came from, and nothing of unnatural parity."""
    rows, _, _ = parts(spark, d)
    shells = rows.select(*basis.KEYS, "i", "j", "l1", "l2").distinct()
    back = basis.couple(basis.uncouple(rows, basis.KEYS).join(shells, [*basis.KEYS, "i", "j"]), basis.KEYS)
    return back.where(F.abs("y") > 1e-5).select(*basis.KEYS, "i", "j", "L", "M", (F.round("y", 6) + F.lit(0.0)).alias("y"))


@query("onsite_spd", COUPLED + f""", sums AS (SELECT dst AS atom_id, list_transform(range(25), lambda q: 0e0) AS z0, {", ".join(f"sum(amp*ys[{q + 1}]) AS s{q}" for q in range(25))} FROM har GROUP BY dst),
ons AS (SELECT a.atom_id, i, j, l1, ord, m, k, species, [{", ".join(f"coalesce(s{q}, 0)" for q in range(25))}] AS s FROM atoms a LEFT JOIN sums USING (atom_id) JOIN comp ON z1 = species AND z2 = species, LATERAL (SELECT unnest(range(2*ord+1)) AS m) u)
SELECT atom_id, i, j, CAST(ord AS INT) AS L, CAST(m AS INT) AS M, round(CASE WHEN ord = 0 AND i = j THEN (species*(-0.05e0)+i*0.25e0)*sqrt(2*l1+1) ELSE 0 END + {basis.ENVIRONMENT}e0*k*s[ord*ord+m+1], 6) + 0.0 AS y FROM ons""")
def _(spark, d):
    """Coupled components of the diagonal blocks."""
    _, e, atoms = parts(spark, d)
    return basis.coupled_onsite(e, atoms, R_CUT, OXIDE).select("atom_id", "i", "j", "L", "M", (F.round("y", 6) + F.lit(0.0)).alias("y"))


@query("magnitude_spd", COUPLED + ", mg AS (SELECT i, j, sqrt(dx*dx+dy*dy+dz*dz) AS r, val FROM ele JOIN edges USING (src, dst, sx, sy, sz)) SELECT i, j, CAST(floor(r/0.5e0) AS INT) AS bin, round(max(abs(val)), 6) AS largest, count(*) AS n FROM mg GROUP BY ALL")
def _(spark, d):
    """Largest element by pair of shells and distance: where the cutoff may stand."""
    rows, e, _ = parts(spark, d)
    u = basis.uncouple(rows, basis.KEYS).join(e.select(*basis.KEYS, "r"), basis.KEYS)
    return u.groupBy("i", "j", F.floor(F.col("r") / F.lit(0.5)).cast("int").alias("bin")).agg(F.round(F.max(F.abs("val")), 6).alias("largest"), F.count(F.lit(1)).alias("n"))


# --- the network on these blocks (rows only: iterative; tested against finite differences) ----------------------------
SHAPE = Shape(l_max=4, channels=4, r_cut=R_CUT)


def boxed(spark, d, name, snap: float = 0.0):
    """A whole structure in boxes."""
    return boxblocks.Boxed(structure_space(spark, d, name, snap), SHAPE, PCM, _settle)


@query("train_blocks")
def _(spark, d):
    """Loss and mean absolute errors of diagonal and off-diagonal blocks along steps on all parameters, whole structure."""
    g = boxed(spark, d, "pcm_c")
    start = boxblocks.fit_heads(g, blocktrain.initial(SHAPE, PCM, 1))
    t = blocktrain.descend(spark, lambda params: boxblocks.loss_and_gradient(g, params), blocktrain.begin(start, 0.003), 3)
    return spark.createDataFrame([(i, x["loss"], x["node_mae"], x["edge_mae"]) for i, x in enumerate(t.losses)], "step int, loss double, node_mae double, edge_mae double")


@query("validate_blocks")
def _(spark, d):
    """Trained on the whole amorphous stand-in, errors of node and edge blocks there and on the near-lattice structure,
    beside the mean size of what is predicted."""
    params, fitted, rows = blocktrain.initial(SHAPE, PCM, 1), None, []
    for name, g in (("train", boxed(spark, d, "pcm_a")), ("validate", boxed(spark, d, "pcm_c", snap=2.5))):
        nodes = g.nodes(params)  # heads do not change them
        fitted = fitted or boxblocks.fit_heads(g, params, nodes=nodes)
        losses, size = boxblocks.measure(g, fitted, nodes)
        rows.append((name, losses["node_mae"], size["node"], losses["edge_mae"], size["edge"]))
    return spark.createDataFrame(rows, "structure string, node_mae double, node_size double, edge_mae double, edge_size double")


@query("tiled_blocks")
def _(spark, d):
    """The matrix of a 2x2x2 tile predicted from its graph alone: size, stored elements, errors of node and edge blocks."""
    g = boxed(spark, d, "pcm_c")
    params = boxblocks.fit_heads(g, blocktrain.initial(SHAPE, PCM, 1))
    s = g.space
    big = boxnet.Space(structure.tile(s.atoms, s.cell, s.n_atoms, 2, 2, 2), s.cell.tiled(2, 2, 2), R_CUT, 8 * s.n_atoms, least=s.least)
    each = _settle(boxblocks.errors(boxblocks.Boxed(big, SHAPE, PCM, _settle), params))
    size = each.agg(F.sum("orbitals").alias("all"), F.sum("stored").alias("nnz"))
    mean = lambda c, name: F.round(F.col(c) / F.col("n"), 6).alias(name)
    return each.where("n > 0").crossJoin(size).select("kind", F.col("all").alias("size"), "nnz", mean("err", "mae"), mean("size", "mean_size"), "n")


@query("equivariance_error")
def _(spark, d):
    """Largest difference between the rows of a turned structure and the turned rows, by order."""
    atoms, cell, n = load(spark, d, "pcm_c")
    e = graph.radius_edges(atoms, cell, R_CUT).persist()
    q, _ = np.linalg.qr(np.random.default_rng(3).normal(size=(3, 3)))
    q *= np.sign(np.linalg.det(q))
    turned = e.withColumns({f"d{a}": sum((F.col(f"d{b}") * F.lit(float(q[i, j])) for j, b in enumerate("xyz")), F.lit(0.0)) for i, a in enumerate("xyz")})
    ranks = partition.sequential(atoms, 4, n)
    one, two = (model.forward(atoms, x, ranks, SHAPE, 1, list(PCM), settle=_settle)[0] for x in (e, turned))
    matrices, shape = wigner(q[None], SHAPE.l_max), SHAPE

    def run(frames):
        import pandas as pd

        for f in frames:
            a, b = (np.array(f[c].tolist(), float).reshape(len(f), 1, shape.rows, shape.channels) for c in ("emb", "emb2"))
            far = np.abs(rotate(a, [m.repeat(len(f), axis=0) for m in matrices]) - b)[:, 0]
            yield pd.DataFrame({"l": range(shape.l_max + 1), "far": [far[:, k * k : (k + 1) ** 2].max() for k in range(shape.l_max + 1)]})

    both = one.join(two.withColumnRenamed("emb", "emb2"), "atom_id").select("emb", "emb2")
    return both.mapInPandas(run, "l int, far double").groupBy("l").agg(F.round(F.max("far"), 9).alias("largest_difference"))


@query("exchange_bytes", ranks_sql() + PLAN_SQL + " SELECT precision, count(*)*36*w AS bytes FROM plan, (VALUES ('fp16', 2), ('fp32', 4), ('fp64', 8)) AS p(precision, w) GROUP BY precision, w")
def _(spark, d):
    """Bytes of one exchange of rows of 36 values by precision: what really travels."""
    e, atoms, _, _, ranks, _ = oxide_ranks(spark, d)
    table = spark.createDataFrame([(72, [0.72, 1.0, -0.5, 0.25]), (8, [0.08, 1.0, 0.5, -0.25])], "species int, emb array<double>")
    nodes = message.init_nodes(atoms, table, 2, 4)
    sent = exchange.halo(nodes, exchange.plan(e, ranks), ["emb"])
    sizes = sent.select(*(F.octet_length(exchange.packed("emb", p)).alias(p) for p in exchange.KINDS)).agg(*(F.sum(p).alias(p) for p in exchange.KINDS))
    return sizes.select(F.inline(F.array(*(F.struct(F.lit(p).alias("precision"), F.col(p).alias("bytes")) for p in exchange.KINDS))))


@query("batch_energies")
def _(spark, d):
    """Many small molecules in one table, through the network at once: conversations as chains, an energy of each. A chain
    lies in one rank, so nothing travels."""
    from pyspark.sql import Window

    shape, base = Shape(l_max=1, channels=4, r_cut=R_CUT), 1 << 20
    turns = spark.read.parquet(f"{d}/conversations.parquet").select("conv_id", "turn").where("conv_id is not null and turn is not null").distinct()
    ident = F.col("conv_id") * base + F.col("turn")
    atoms = _settle(turns.select(ident.alias("atom_id"), (F.when(F.col("turn") % 2 == 0, 8).otherwise(72)).alias("species")))
    linked = turns.withColumn("nxt", F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn"))).where("nxt = turn + 1")
    one = linked.select(ident.alias("src"), (ident + 1).alias("dst"), (F.lit(1.5) + (F.col("turn") % 3) * 0.2).alias("r"))
    both = one.withColumn("dx", F.col("r")).unionByName(one.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "r", (-F.col("r")).alias("dx")))
    edges_ = both.select("src", "dst", *(F.lit(0).alias(s) for s in ("sx", "sy", "sz")), "dx", *(F.lit(0.0).alias(s) for s in ("dy", "dz")), "r")
    ranks = atoms.select("atom_id", F.pmod(F.floor(F.col("atom_id") / base), F.lit(rank_count(atoms.count()))).cast("int").alias("rank"))
    nodes, _ = model.forward(atoms, edges_, ranks, shape, 2, [8, 72], settle=_settle)
    row = F.aggregate(F.slice("emb", 1, shape.channels), F.lit(0.0), lambda s, x: s + x)
    return nodes.groupBy(F.floor(F.col("atom_id") / base).alias("conv_id")).agg(F.count(F.lit(1)).alias("n_atoms"), F.round(F.sum(row), 6).alias("energy"))
