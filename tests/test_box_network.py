import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from orbitgraph.functions import so3
from orbitgraph.functions.layers import Shape
from orbitgraph.operators import boxheads, boxnet, graph, hamiltonian, metrics, model, partition, train
from orbitgraph.operators.structure import Cell
from orbitgraph.plans import learning, shells

SPECIES = [32, 51, 52]
SHAPE = Shape(l_max=2, channels=4, r_cut=6.0)


@pytest.fixture(scope="module")
def few(spark):
    """Atoms in a small cell, whose pairs have several images, and one far from all others in a wide one."""
    rng = np.random.default_rng(5)
    out = []
    for side, places in ((9.0, rng.random((7, 3)) * 9), (40.0, np.vstack([rng.random((9, 3)) * 12, [[30.0, 30.0, 30.0]]]))):
        cell = Cell((side,) * 3)
        atoms = spark.createDataFrame([(i, SPECIES[i % 3], *map(float, p)) for i, p in enumerate(places)], "atom_id long, species int, x double, y double, z double").persist()
        out.append((atoms, cell, len(places), graph.radius_edges(atoms, cell, 6.0).persist()))
    return out


def test_closed_form_turns():
    v = np.vstack([np.random.default_rng(1).normal(size=(50, 3)), [[0, 0, 2], [0, 0, -1], [1, 0, 0], [0, -1, 0]]])
    for a, b in zip(so3.wigner(so3.bond_rotations(v), 4), so3.bond_wigner(v, 4), strict=True):
        assert np.abs(a - b).max() < 1e-13


@pytest.mark.parametrize("parts", [1, 3])
def test_node_rows_equal_those_of_the_joined_graph(few, parts):
    for atoms, cell, n, e in few:
        want = {r.atom_id: r.emb for r in model.forward(atoms, e, model.single_rank(atoms), SHAPE, 2, SPECIES)[0].collect()}
        got = boxnet.node_rows(boxnet.Space(atoms, cell, 6.0, n, parts=parts, box_atoms=1), SHAPE, boxnet.seeded(SHAPE, 2), SPECIES).collect()
        assert len(got) == n and all(np.allclose(r.n2, want[r.atom_id], atol=1e-10) for r in got)


def test_heads_and_errors_equal_those_of_tables(few):
    for atoms, cell, n, e in few:
        e = e.where("r > 0.5")
        _, rows = model.forward(atoms, e, partition.sequential(atoms, 2, n), SHAPE, 1, SPECIES)
        truth = hamiltonian.two_centre(e, atoms, 6.0)
        targets = train.coupled_targets(truth)
        want = train.fit_least_squares(train.features(rows, targets, train.EDGE_KEYS, SHAPE), ridge=1e-3)
        space, blocks = boxnet.Space(atoms, cell, 6.0, n, least=0.5, box_atoms=1), boxnet.seeded(SHAPE, 1)
        nodes = boxnet.node_rows(space, SHAPE, blocks, SPECIES)
        got = boxheads.fit(nodes, space, SHAPE, blocks, SPECIES, ridge=1e-3)
        assert want.keys() == got.keys() and all(np.allclose(got[k], want[k], rtol=1e-6, atol=1e-9) for k in want)
        p = train.predicted_elements(rows, targets, want, SHAPE).withColumnRenamed("p", "val")
        for fold in (False, True):
            if fold:
                offs = hamiltonian.offsets(atoms)
                both = metrics.absolute_errors(hamiltonian.to_coo(p, offs), hamiltonian.to_coo(truth, offs), ["row", "col"])
            else:
                both = metrics.absolute_errors(p, truth, [*train.EDGE_KEYS, "a", "b"])
            ref = both.agg(F.count(F.lit(1)), F.sum("err"), F.sum(F.abs("t"))).first()
            one = boxheads.errors(nodes, space, SHAPE, blocks, want, SPECIES, fold=fold).first()
            assert one.n == ref[0] and np.allclose([one.err, one.size], ref[1:], rtol=1e-7)


@pytest.mark.parametrize("name", ["forward_energy", "predict_tiled", "train_validate", "tiled_inference"])
def test_no_table_of_edges(spark, sf, monkeypatch, name):
    """Edge rows in tables were what filled the disk and the executors."""

    def never(*_, **__):
        raise AssertionError("a table of edges")

    for where in (graph, learning.graphs, shells.graph):
        monkeypatch.setattr(where, "radius_edges", never)
        monkeypatch.setattr(where, "tile_edges", never)
    assert entry.queries()[name](spark, sf).count() > 0


def test_pairs_are_made_by_many_tasks(spark, sf):
    assert entry.queries()["min_image_pairs"](spark, sf).rdd.getNumPartitions() >= 48
