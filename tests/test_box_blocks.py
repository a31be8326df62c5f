import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry
from orbitgraph.functions.layers import Shape
from orbitgraph.operators import basis, blocktrain, boxblocks, boxnet, graph, hamiltonian, model
from orbitgraph.operators.structure import Cell
from orbitgraph.plans import learning, shells

SPECIES = (8, 32, 72)
SHAPE = Shape(l_max=4, channels=3, r_cut=6.0, max_messages=50)


@pytest.fixture(scope="module")
def few(spark):
    """Atoms in a small cell, whose pairs have several images, and one far from all others in a wide one: as tables and in boxes."""
    rng = np.random.default_rng(5)
    out = []
    for side, places in ((9.0, rng.random((6, 3)) * 9), (40.0, np.vstack([rng.random((8, 3)) * 12, [[30.0, 30.0, 30.0]]]))):
        cell = Cell((side,) * 3)
        atoms = spark.createDataFrame([(i, SPECIES[i % 3], *map(float, p)) for i, p in enumerate(places)], "atom_id long, species int, x double, y double, z double").persist()
        e = graph.radius_edges(atoms, cell, 6.0).where("r > 0.5").persist()
        node_y = blocktrain.targets(basis.coupled_onsite(e, atoms, 6.0, SPECIES), ["atom_id"])
        edge_y = blocktrain.targets(basis.coupled(e, atoms, 6.0, SPECIES), basis.KEYS)
        g = blocktrain.distribute(atoms, e, model.single_rank(atoms), SHAPE, SPECIES, None, node_y, edge_y)
        out.append((atoms, e, g, boxblocks.Boxed(boxnet.Space(atoms, cell, 6.0, len(places), least=0.5, box_atoms=1), SHAPE, SPECIES)))
    return out


def some_params(layers):
    rng = np.random.default_rng(7)
    return {k: rng.normal(size=v.shape) * 0.1 if "head" in k else v for k, v in blocktrain.initial(SHAPE, SPECIES, layers).items()}


@pytest.mark.parametrize("layers", [1, 2])
def test_gradient_equals_that_of_tables(few, layers):
    params = some_params(layers)
    for _, _, g, boxed in few:
        want, got = blocktrain.loss_and_gradient(g, params, SHAPE, 1.0, 0.5), boxblocks.loss_and_gradient(boxed, params, 1.0, 0.5)
        assert got[0] == pytest.approx(want[0])
        for k in params:
            assert np.allclose(got[1][k], want[1][k], atol=1e-10), k


def test_heads_sizes_and_errors_equal_those_of_tables(few):
    params = blocktrain.initial(SHAPE, SPECIES, 1)
    for atoms, e, g, boxed in few:
        want, got = (f(x, params, *s, ridge=1e-2) for f, x, s in ((blocktrain.fit_heads, g, (SHAPE,)), (boxblocks.fit_heads, boxed, ())))
        assert all(np.allclose(got[k], want[k], rtol=1e-6, atol=1e-9) for k in params)
        losses, size = boxblocks.measure(boxed, want)
        assert losses == pytest.approx(blocktrain.loss_and_gradient(g, want, SHAPE, gradient=False)[0])
        for kind, df in (("node", g.own), ("edge", g.edges)):
            assert size[kind] == pytest.approx(df.select(F.explode("y").alias("y")).agg(F.avg(F.abs("y"))).first()[0])
        p, offs = blocktrain.predict(g, want, SHAPE, SPECIES).persist(), basis.offsets(atoms)
        ref = {r.kind: r for r in blocktrain.errors(p, blocktrain.truth(e, atoms, 6.0, SPECIES)).groupBy("kind").agg(F.count("*").alias("n"), F.sum("err").alias("err"), F.sum("size").alias("s")).collect()}
        whole = hamiltonian.shape(hamiltonian.to_coo(p.select("src", "dst", "a", "b", "val"), offs), offs).first()
        rows = {r.kind: r for r in boxblocks.errors(boxed, want).collect()}
        for kind, r in ref.items():
            assert rows[kind].n == r.n and np.allclose([rows[kind].err, rows[kind]["size"]], [r.err, r.s], rtol=1e-8)
        assert (sum(r.orbitals for r in rows.values()), sum(r.stored for r in rows.values())) == (whole["size"], whole.nnz)


@pytest.mark.parametrize("name", ["train_blocks", "validate_blocks", "tiled_blocks"])
def test_no_table_of_edges(spark, sf, monkeypatch, name):
    """Edge rows and targets in tables were what filled the disk."""

    def never(*_, **__):
        raise AssertionError("a table of edges")

    for where in (graph, learning.graphs, shells.graph):
        monkeypatch.setattr(where, "radius_edges", never)
        monkeypatch.setattr(where, "tile_edges", never)
    assert entry.queries()[name](spark, sf).count() > 0
