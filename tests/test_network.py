import numpy as np
import pytest
from pyspark.sql import functions as F

from orbitgraph.functions import layers, so3
from orbitgraph.operators import graph, hamiltonian, model, partition, train
from orbitgraph.operators.telemetry import PlateauSchedule
from orbitgraph.plans import structures

RNG = np.random.default_rng(0)


def rotations(n):
    q, _ = np.linalg.qr(RNG.normal(size=(n, 3, 3)))
    return q * np.sign(np.linalg.det(q))[:, None, None]


def test_wigner_turns_harmonics():
    p = RNG.normal(size=(9, 3))
    p /= np.linalg.norm(p, axis=1, keepdims=True)
    for q in rotations(4):
        for l, d in enumerate(so3.wigner(q[None], 4)):  # noqa: E741
            rows = slice(l * l, (l + 1) ** 2)
            assert np.allclose(so3.harmonics(p @ q.T, 4)[:, rows], so3.harmonics(p, 4)[:, rows] @ d[0].T)
            assert np.allclose(d[0] @ d[0].T, np.eye(2 * l + 1), atol=1e-10)


def test_bond_rotations_with_polar_bonds():
    v = np.vstack([RNG.normal(size=(20, 3)), [[0, 0, 2], [0, 0, -3], [1, 0, 0]]])
    r = so3.bond_rotations(v)
    assert np.allclose(np.einsum("nij,nj->ni", r, v / np.linalg.norm(v, axis=1, keepdims=True)), [0, 0, 1]) and np.allclose(np.linalg.det(r), 1)


@pytest.mark.parametrize(("l1", "l2"), [(0, 0), (1, 1), (1, 2), (2, 2)])
def test_coupling_round_trip(l1, l2):
    b = RNG.normal(size=(5, 2 * l1 + 1, 2 * l2 + 1))
    parts = so3.couple(b, l1, l2)
    assert sum(p.shape[1] for p in parts.values()) == b[0].size
    assert np.allclose(so3.uncouple(parts, l1, l2), b, atol=1e-12)
    q = rotations(1)
    d = so3.wigner(q, l1 + l2)
    turned = so3.couple(d[l1][0] @ b @ d[l2][0].T, l1, l2)
    for l, p in parts.items():  # noqa: E741
        assert np.allclose(turned[l], p @ d[l][0].T, atol=1e-9)


def test_m_major_is_a_permutation():
    assert sorted(so3.m_major(3)) == list(range(16)) and so3.m_major(2).tolist() == [0, 2, 6, 3, 7, 1, 5, 8, 4]


def turned(x, q, l_max):
    d = so3.wigner(q[None], l_max)
    return so3.rotate(x[:, None], [np.repeat(m, len(x), 0) for m in d])[:, 0]


def test_blocks_are_equivariant():
    s = layers.Shape(l_max=3, channels=5)
    n = 7
    src, dst = (a.ravel() for a in np.meshgrid(range(n), range(n)))
    src, dst = src[src != dst], dst[src != dst]
    pos = RNG.normal(size=(n, 3)) * 2
    vec = pos[dst] - pos[src]
    t, e, p, q = RNG.normal(size=(n, s.rows, 5)), layers.radial(np.linalg.norm(vec, axis=1), s), layers.block_params(s, 3), rotations(1)[0]
    for f in (lambda t, e, v: layers.node_update(t, e, src, dst, v, np.arange(n), p, s), lambda t, e, v: layers.edge_update(t, e, src, dst, v, p, s)):
        assert np.allclose(turned(f(t, e, vec), q, 3), f(turned(t, q, 3), turned(e, q, 3), vec @ q.T), atol=1e-10)


def test_so2_commutes_with_turns_about_the_bond():
    s = layers.Shape(l_max=2, channels=4)
    p, x = layers.block_params(s, 1), RNG.normal(size=(6, s.rows, 12))
    a = 0.7
    q = np.array([[np.cos(a), -np.sin(a), 0], [np.sin(a), np.cos(a), 0], [0, 0, 1]])
    assert np.allclose(layers.so2_linear(turned(x, q, 2), p, "first", s), turned(layers.so2_linear(x, p, "first", s), q, 2))


def test_chunks_and_precision():
    n = 6
    src, dst = np.arange(n), (np.arange(n) + 1) % n
    vec, t = RNG.normal(size=(n, 3)), RNG.normal(size=(n, 9, 8))
    out = {}
    for name, s in {"wide": layers.Shape(), "chunked": layers.Shape(max_messages=2), "half": layers.Shape(precision="fp16")}.items():
        e = layers.radial(np.linalg.norm(vec, axis=1), s)
        out[name] = layers.node_update(t, e, src, dst, vec, np.arange(n), layers.block_params(s, 2), s)
    assert np.allclose(out["wide"], out["chunked"]) and np.abs(out["wide"] - out["half"]).max() <= np.abs(out["wide"]).max() * 2**-10


def test_softmax_adds_up():
    w = layers.segment_softmax(RNG.normal(size=50) * 30, RNG.integers(0, 7, 50), 9)
    assert (w > 0).all() and w.sum() == pytest.approx(7)


@pytest.fixture(scope="module")
def small(spark, sf):
    atoms, cell, n = structures.load(spark, sf, "pcm_c")
    return atoms.persist(), graph.radius_edges(atoms, cell, 6.0).persist(), n


@pytest.mark.parametrize("shape", [layers.Shape(l_max=2, channels=4)])
def test_ranks_do_not_matter(small, shape):
    atoms, edges, n = small
    results = []
    for ranks in (model.single_rank(atoms), partition.random(atoms, 3)):
        nodes, rows = model.forward(atoms, edges, ranks, shape, 2, [32, 51, 52])
        results.append(({r.atom_id: r.emb for r in nodes.collect()}, {(r.src, r.dst, r.sx, r.sy, r.sz): r.emb for r in rows.collect()}))
    for a, b in zip(*results, strict=True):
        assert a.keys() == b.keys() and all(np.allclose(a[k], b[k], atol=1e-12) for k in a)


def test_gradient_and_training(spark):
    x = RNG.normal(size=(60, 3))
    y = x @ [1.0, -2.0, 0.5]
    data = spark.createDataFrame([("h" if i % 2 else "g", v.tolist(), float(t)) for i, (v, t) in enumerate(zip(x, y, strict=True))], "head string, x array<double>, y double").persist()
    w = {"g": np.array([0.3, 0.1, 0.2]), "h": np.array([-0.2, 0.4, 0.1])}
    loss, grad = train.loss_and_gradient(data, w)
    for h in w:
        for i in range(3):
            step = {k: v.copy() for k, v in w.items()}
            step[h][i] += 1e-6
            assert (train.loss_and_gradient(data, step)[0] - loss) / 1e-6 == pytest.approx(grad[h][i], abs=1e-4)
    heads = train.fit_least_squares(data)
    assert all(np.allclose(v, [1, -2, 0.5], atol=1e-5) for v in heads.values())
    assert train.predict(data, heads).agg(F.max(F.abs(F.col("p") - F.col("y")))).first()[0] < 1e-4
    _, losses = train.fit(data, 6)
    assert losses[-1] < losses[0]


def test_plateau_schedule():
    s = PlateauSchedule(lr=1.0, patience=1, factor=0.5, min_lr=0.3)
    assert [s.step(v) for v in (5, 4, 4, 4, 4, 4, 4, 4)] == [1, 1, 1, 0.5, 0.5, 0.3, 0.3, 0.3]


def test_blocks_and_assembly(spark, small):
    atoms, edges, n = small
    both = hamiltonian.two_centre(edges, atoms, 6.0).select("src", "dst", "a", "b", "val").unionByName(hamiltonian.onsite(atoms))
    offs = hamiltonian.offsets(atoms)
    coo = hamiltonian.to_coo(both, offs).persist()
    back = hamiltonian.assemble(hamiltonian.to_blocks(coo, offs), offs)
    assert coo.join(back.withColumnRenamed("val", "v2"), ["row", "col"], "left").where("v2 IS NULL OR abs(val - v2) > 1e-12").count() == 0
    twin = coo.select(F.col("col").alias("row"), F.col("row").alias("col"), F.col("val").alias("v2"))
    assert coo.join(twin, ["row", "col"], "left").where("v2 IS NULL OR abs(val - v2) > 1e-9").count() == 0
    assert hamiltonian.shape(coo, offs).first().size == 4 * n
