"""Named queries of the min-cut baselines, the network and its training (rows only: iterative, tested in Python)."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from ..functions.layers import Shape
from ..operators import boxes, boxheads, boxnet, exchange, hamiltonian, mincut, model, partition, train
from ..operators import graph as graphs
from .structures import edges, load

QUERIES: dict = {}
SQL: dict[str, str] = {}
R_CUT = 6.0
SHAPE = Shape(l_max=2, channels=16, r_cut=R_CUT)


def query(name):
    def add(f):
        QUERIES[name] = f
        return f

    return add


def _settle(df):
    """A reliable checkpoint where a folder is set, else a persisted frame (small local runs)."""
    if df.sparkSession.sparkContext._jsc.sc().getCheckpointDir().isDefined():
        return df.checkpoint()
    return df.persist()


@query("min_cut_p8")
def _(spark, d):
    """Multilevel minimum cut with its measures, beside the few-neighbour partition."""
    atoms, cell, n = load(spark, d, "oxide")
    few = partition.few_neighbour(atoms, boxes.degree(atoms, cell, R_CUT, n), cell, 3, R_CUT)[0].select("atom_id", "rank")
    placed = atoms.join(few, "atom_id").join(mincut.min_cut_boxes(atoms, cell, R_CUT, n, (8,)), "atom_id").withColumn("ranks", F.array(F.col("ranks")[0], "rank")).drop("rank").persist()
    every = spark.createDataFrame([(0, "min_cut"), (1, "few_neighbour")], "placement int, scheme string").withColumn("rank", F.explode(F.sequence(F.lit(0), F.lit(7))))
    moved = F.col("from_rank") != F.col("to_rank")
    pairs = boxes.rank_pairs(placed, cell, R_CUT, F.col("ranks"), n)
    got = pairs.groupBy(F.col("scheme").alias("placement"), F.col("to_rank").alias("rank")).agg(
        F.sum("messages").alias("k"), F.sum(moved.cast("long")).alias("near"), F.sum(F.when(moved, F.col("rows")).otherwise(0)).alias("volume"), F.sum(F.when(moved, F.col("messages")).otherwise(0)).alias("cut")
    )
    nodes = placed.select(F.posexplode("ranks").alias("placement", "rank")).groupBy("placement", "rank").agg(F.count(F.lit(1)).alias("n"))
    each = every.join(got, ["placement", "rank"], "left").join(nodes, ["placement", "rank"], "left").na.fill(0)
    imbalance = {f"{kind}_imbalance": F.round(F.max(c) / F.avg(c), 6) for kind, c in (("node", "n"), ("edge", "k"))}
    return each.groupBy("scheme").agg(F.max("near").alias("max_neighbours"), F.sum("volume").alias("volume"), F.sum("cut").alias("cut_edges"), *(v.alias(k) for k, v in imbalance.items()))


def supplier_graph(spark, d):
    """The whole supplier structure: all its atoms, their radius graph, the cell and the number of atoms."""
    atoms, cell, n = load(spark, d, "pcm_c")
    atoms = atoms.persist()
    return atoms, graphs.radius_edges(atoms, cell, R_CUT).persist(), cell, n


@query("forward_energy")
def _(spark, d):
    """Energy of the structure by the network on four ranks and on one: equal up to rounding. A rank works box by box, so its
    memory is bounded whatever their number."""
    atoms, cell, n = load(spark, d, "pcm_c")
    weights, blocks = np.linspace(-1, 1, SHAPE.channels).tolist(), boxnet.seeded(SHAPE, 2)
    out = None
    for parts in (4, 1):
        nodes = boxnet.node_rows(boxnet.Space(atoms, cell, R_CUT, n, parts=parts), SHAPE, blocks, [32, 51, 52], settle=_settle)
        one = model.energy(nodes.select(F.col("n2").alias("emb")), SHAPE, weights).select(F.lit(parts).alias("parts"), F.round("energy", 6).alias("energy"))
        out = one if out is None else out.unionByName(one)
    return out


def block_targets(spark, d):
    """Coupled p-p components of the stand-in matrix on the edges of the structure, and the edge features."""
    atoms, e, cell, n = supplier_graph(spark, d)
    nodes, rows = model.forward(atoms, e, partition.sequential(atoms, 4, n), SHAPE, 1, [32, 51, 52], settle=_settle)
    el = hamiltonian.two_centre(e, atoms, R_CUT).where("a > 0 AND b > 0")
    m = el.groupBy("src", "dst", "sx", "sy", "sz", "z1", "z2").agg(F.sort_array(F.collect_list(F.struct("a", "b", "val"))).alias("s"))
    c = m.select("src", "dst", "sx", "sy", "sz", F.least("z1", "z2").alias("za"), F.greatest("z1", "z2").alias("zb"), hamiltonian.couple_pp(F.transform("s", lambda x: x["val"])).alias("c"))
    # order of the coupled vector: L=0, L=1 as x y z, L=2; harmonics order L=1 as y z x
    places = [(0, 0, 0), (1, 0, 2), (1, 1, 3), (1, 2, 1), *((2, k, 4 + k) for k in range(5))]
    entries = F.array(*(F.struct(F.lit(l).alias("l"), F.lit(k).alias("m"), F.get("c", F.lit(i)).alias("y")) for l, k, i in places))  # noqa: E741
    targets = c.select("src", "dst", "sx", "sy", "sz", "za", "zb", F.inline(entries))
    head = F.concat_ws("-", F.lit("pp"), "za", "zb", "l")
    return train.features(rows, targets.withColumn("head", head), ["src", "dst", "sx", "sy", "sz"], SHAPE)


@query("train_heads")
def _(spark, d):
    """Least-squares heads and their errors against predicting zero."""
    data = block_targets(spark, d).persist()
    heads = train.fit_least_squares(data)
    p = train.predict(data, heads)
    return p.groupBy("head").agg(F.round(F.avg(F.abs(F.col("p") - F.col("y"))), 6).alias("mae"), F.round(F.avg(F.abs("y")), 6).alias("mae_of_zero"), F.count(F.lit(1)).alias("n"))


@query("train_curve")
def _(spark, d):
    """Loss along gradient steps with the plateau schedule."""
    data = block_targets(spark, d).persist()
    _, losses = train.fit(data, steps=8)
    return spark.createDataFrame([(i, float(v)) for i, v in enumerate(losses)], "step int, loss double")


@query("predict_tiled")
def _(spark, d):
    """Network on a cell and on its 2x1x1 tile: every copy's rows agree with the cell's."""
    from ..operators import structure

    atoms, cell, n = load(spark, d, "pcm_c")
    blocks = boxnet.seeded(SHAPE, 1)
    one = boxnet.node_rows(boxnet.Space(atoms, cell, R_CUT, n), SHAPE, blocks, [32, 51, 52], settle=_settle)
    tiled = boxnet.Space(structure.tile(atoms, cell, n, 2, 1, 1), cell.tiled(2, 1, 1), R_CUT, 2 * n, parts=2)
    two = boxnet.node_rows(tiled, SHAPE, blocks, [32, 51, 52], settle=_settle)
    far = F.array_max(F.zip_with("n1", "emb1", lambda a, b: F.abs(a - b)))
    # checkpointed rows pass for as small as the table they came from: without the hint they are broadcast
    return two.join(one.select((F.col("atom_id")).alias("home"), F.col("n1").alias("emb1")).hint("merge"), F.col("atom_id") % n == F.col("home")).agg(F.count(F.lit(1)).alias("n_atoms"), F.round(F.max(far), 6).alias("largest_difference"))


@query("label_propagation_p8")
def _(spark, d):
    e, atoms, _, n = edges(spark, d, "oxide", R_CUT)
    from ..session import ensure_checkpoint_dir

    ensure_checkpoint_dir(spark)
    ranks = mincut.label_propagation(e.persist(), partition.sequential(atoms, 8, n), 8, rounds=2)
    return ranks.groupBy("rank").agg(F.count(F.lit(1)).alias("n"))


def rank_count(n: int) -> int:
    """Ranks for n atoms: at most about 1,000 atoms each, as a rank's rows are in memory at once."""
    return max(4, -(-n // 1000))


def structure_rows(spark, d, name, snap=0.0, layers_=1):
    """Edge rows of the network and coupled targets of a whole structure; ``snap`` rounds positions towards a lattice."""
    from ..operators import structure

    atoms, cell, n = load(spark, d, name)
    if snap:
        atoms = structure.wrap(atoms.withColumns({a: F.round(F.col(a) / snap) * F.lit(snap) + F.lit(0.05) * F.col(a) / F.lit(cell.lengths[0]) for a in "xyz"}), cell)
    atoms = atoms.persist()
    e = graphs.radius_edges(atoms, cell, R_CUT).where("r > 0.5").persist()
    _, rows = model.forward(atoms, e, partition.sequential(atoms, rank_count(n), n), SHAPE, layers_, [32, 51, 52], settle=_settle)
    return atoms, cell, e, rows, hamiltonian.two_centre(e, atoms, R_CUT)


def structure_space(spark, d, name, snap=0.0):
    """A whole structure in boxes; ``snap`` rounds positions towards a lattice."""
    from ..operators import structure

    atoms, cell, n = load(spark, d, name)
    if snap:
        atoms = structure.wrap(atoms.withColumns({a: F.round(F.col(a) / snap) * F.lit(snap) + F.lit(0.05) * F.col(a) / F.lit(cell.lengths[0]) for a in "xyz"}), cell)
    return boxnet.Space(atoms, cell, R_CUT, n, least=0.5)


@query("train_validate")
def _(spark, d):
    """Heads fitted on the amorphous stand-in, errors there and on the near-lattice one, against predicting zero."""
    blocks, species, heads, out = boxnet.seeded(SHAPE, 1), [32, 51, 52], None, None
    for name, space in (("train", structure_space(spark, d, "pcm_a")), ("validate", structure_space(spark, d, "pcm_c", snap=2.5))):
        nodes = boxnet.node_rows(space, SHAPE, blocks, species, settle=_settle)
        heads = heads or boxheads.fit(nodes, space, SHAPE, blocks, species)
        both = boxheads.errors(nodes, space, SHAPE, blocks, heads, species)
        one = both.select(F.lit(name).alias("structure"), F.round(F.col("err") / F.col("n"), 6).alias("mae"), F.round(F.col("size") / F.col("n"), 6).alias("mae_of_zero"), "n")
        out = one if out is None else out.unionByName(one)
    return out


@query("tiled_inference")
def _(spark, d):
    """Trained heads on a 2x2x2 tile: size and stored elements of the assembled matrix, and its error."""
    from ..operators import structure

    blocks, species = boxnet.seeded(SHAPE, 1), [32, 51, 52]
    space = structure_space(spark, d, "pcm_c")
    heads = boxheads.fit(boxnet.node_rows(space, SHAPE, blocks, species, settle=_settle), space, SHAPE, blocks, species)
    n = space.n_atoms
    big = boxnet.Space(structure.tile(space.atoms, space.cell, n, 2, 2, 2), space.cell.tiled(2, 2, 2), R_CUT, 8 * n, least=0.5)
    err = boxheads.errors(boxnet.node_rows(big, SHAPE, blocks, species, settle=_settle), big, SHAPE, blocks, heads, species, fold=True)
    size = hamiltonian.offsets(big.atoms).agg(F.sum("n_orb").cast("long").alias("size"))
    both = err.withColumnRenamed("size", "size_sum").crossJoin(size).withColumn("nnz", F.col("n"))
    return both.select("size", "nnz", F.round(F.col("nnz") / (F.col("size") * F.col("size")), 6).alias("density"), F.round(F.col("err") / F.col("n"), 6).alias("mae"), F.round(F.col("size_sum") / F.col("n"), 6).alias("mae_of_zero"))


@query("train_network")
def _(spark, d):
    """Loss along full-batch steps on all parameters of a small network, by the distributed reverse pass."""
    from ..functions import layers
    from ..operators import backward

    shape = Shape(l_max=1, channels=4, r_cut=R_CUT)
    atoms, e, _, n = supplier_graph(spark, d)
    params = [layers.block_params(shape, 1)]
    _, _, losses = backward.fit(atoms, e, partition.sequential(atoms, 4, n), shape, params, np.full(4, 0.1), 3.0, [32, 51, 52], steps=3, settle=_settle)
    return spark.createDataFrame([(i, float(v)) for i, v in enumerate(losses)], "step int, loss double")
