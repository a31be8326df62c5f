import numpy as np
import pytest
from pyspark.sql import functions as F

from orbitgraph.functions.layers import Shape
from orbitgraph.operators import basis, blocktrain, graph, model, partition
from orbitgraph.operators.structure import Cell

SPECIES = (8, 72)
SHAPE = Shape(l_max=4, channels=3, r_cut=6.0, max_messages=50)


@pytest.fixture(scope="module")
def small(spark):
    rng = np.random.default_rng(5)
    cell = Cell((14.0, 14.0, 14.0))
    atoms = spark.createDataFrame([(i, 72 if i % 3 == 0 else 8, *map(float, p)) for i, p in enumerate(rng.random((9, 3)) * 14)], "atom_id long, species int, x double, y double, z double").persist()
    edges = graph.radius_edges(atoms, cell, 6.0).persist()
    return atoms, edges


def graph_of(small, ranks):
    atoms, edges = small
    node_y = blocktrain.targets(basis.coupled_onsite(edges, atoms, 6.0, SPECIES), ["atom_id"])
    edge_y = blocktrain.targets(basis.coupled(edges, atoms, 6.0, SPECIES), basis.KEYS)
    return blocktrain.distribute(atoms, edges, ranks, SHAPE, SPECIES, None, node_y, edge_y)


def some_params(layers=2):
    params = blocktrain.initial(SHAPE, SPECIES, layers)
    rng = np.random.default_rng(7)
    return {k: rng.normal(size=v.shape) * 0.1 if "head" in k else v for k, v in params.items()}


def test_shells_have_the_stated_orbitals():
    assert [basis.orbitals(z) for z in (72, 8, 32, 51, 52)] == [10, 4, 13, 13, 13]


def test_matrix_is_symmetric(small):
    atoms, edges = small
    h = blocktrain.truth(edges, atoms, 6.0, SPECIES).where("kind = 'edge'")
    back = h.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *((-F.col(s)).alias(s) for s in ("sx", "sy", "sz")), F.col("b").alias("a"), F.col("a").alias("b"), F.col("val").alias("t"))
    both = h.join(back, ["src", "dst", "sx", "sy", "sz", "a", "b"], "left")
    assert both.where("t is null").count() == 0 and both.agg(F.max(F.abs(F.col("val") - F.col("t")))).first()[0] < 1e-12
    assert h.agg(F.max(F.abs("val"))).first()[0] > 0.01


def test_gradient_of_every_parameter(spark, small):
    """The same on one rank and on three, and right by finite differences in every kind of block."""
    atoms, _ = small
    params = some_params()
    one = blocktrain.loss_and_gradient(graph_of(small, model.single_rank(atoms)), params, SHAPE)
    three_graph = graph_of(small, partition.random(atoms, 3))
    three = blocktrain.loss_and_gradient(three_graph, params, SHAPE)
    assert one[0] == pytest.approx(three[0])
    for k in params:
        assert np.allclose(one[1][k], three[1][k], atol=1e-10), k
    rng = np.random.default_rng(1)
    single = graph_of(small, model.single_rank(atoms))
    for name in ("1.node.first.1i", "1.node.ff.in", "1.edge.second.0r", "2.node.attention", "0.nodehead.72.0"):
        at = tuple(int(rng.integers(0, n)) for n in params[name].shape)
        value = {}
        for sign in (1, -1):
            moved = {**params, name: params[name].copy()}
            moved[name][at] += sign * 1e-5
            value[sign] = blocktrain.loss_and_gradient(single, moved, SHAPE, gradient=False)[0]["loss"]
        assert (value[1] - value[-1]) / 2e-5 == pytest.approx(one[1][name][at], rel=2e-3, abs=1e-7), name


def test_training_lowers_the_loss_and_goes_on_after_a_stop(spark, small, tmp_path):
    atoms, edges = small
    g = graph_of(small, partition.random(atoms, 2))
    params = blocktrain.fit_heads(g, blocktrain.initial(SHAPE, SPECIES, 1), SHAPE)
    whole = blocktrain.fit(g, blocktrain.begin(params, 0.003), SHAPE, 4)
    assert whole.losses[-1]["loss"] < whole.losses[0]["loss"]
    path = f"file://{tmp_path}/run"
    blocktrain.fit(g, blocktrain.begin(params, 0.003), SHAPE, 2, path=path)
    resumed = blocktrain.fit(g, blocktrain.begin(params, 9.9), SHAPE, 4, path=path)
    assert resumed.step == 4 and [x["loss"] for x in resumed.losses] == pytest.approx([x["loss"] for x in whole.losses])
    for k, v in whole.params.items():
        assert np.allclose(resumed.params[k], v)
    h = blocktrain.truth(edges, atoms, 6.0, SPECIES)
    blank = blocktrain.distribute(atoms, edges, partition.random(atoms, 2), SHAPE, SPECIES)
    p = blocktrain.predict(blank, whole.params, SHAPE, SPECIES)
    rows = {r.kind: r for r in blocktrain.errors(p, h).groupBy("kind").agg(F.avg("err").alias("err"), F.avg("size").alias("size"), F.count("*").alias("n")).collect()}
    assert rows["node"].err < rows["node"].size and rows["edge"].err < rows["edge"].size
    # natural parity alone is predicted, and every element of a block that has any
    assert p.count() == h.count()
