from dataclasses import replace

import numpy as np
import pytest

from orbitgraph.functions import layers, reverse
from orbitgraph.operators import backward, graph, model, partition
from orbitgraph.plans import structures


def small_graph(rng, s, n=5):
    src, dst = (a.ravel() for a in np.meshgrid(range(n), range(n)))
    src, dst = src[src != dst], dst[src != dst]
    pos = rng.normal(size=(n, 3)) * 2
    vec = pos[dst] - pos[src]
    return src, dst, vec, rng.normal(size=(n, s.rows, s.channels)), layers.radial(np.linalg.norm(vec, axis=1), s) + 0.1 * rng.normal(size=(len(src), s.rows, s.channels))


def slope(f, x, at):
    up, down = x.copy(), x.copy()
    up[at] += 1e-6
    down[at] -= 1e-6
    return (f(up) - f(down)) / 2e-6


@pytest.mark.parametrize("feed_forward", [False, True])
def test_kernel_against_finite_differences(feed_forward):
    rng = np.random.default_rng(3)
    s = layers.Shape(l_max=2, channels=3, max_messages=6)
    src, dst, vec, t, e = small_graph(rng, s)
    p, own = layers.block_params(s, 5, feed_forward), np.array([0, 2, 3])
    g = rng.normal(size=(3, s.rows, 3))
    f = lambda t, e, p: (layers.node_update(t, e, src, dst, vec, own, p, s) * g).sum()
    back, back_e, grads = reverse.node_update_back(t, e, src, dst, vec, own, p, s, g)
    assert set(grads) == set(p)
    for _ in range(12):
        at, ae = (tuple(rng.integers(0, k) for k in x.shape) for x in (t, e))
        assert slope(lambda x: f(x, e, p), t, at) == pytest.approx(back[at], abs=1e-5)
        assert slope(lambda x: f(t, x, p), e, ae) == pytest.approx(back_e[ae], abs=1e-5)
    for name, v in p.items():
        at = tuple(rng.integers(0, k) for k in v.shape)
        assert slope(lambda x, name=name: f(t, e, {**p, name: x}), v, at) == pytest.approx(grads[name][at], abs=1e-5)


def test_edge_kernel_against_finite_differences():
    rng = np.random.default_rng(4)
    s = layers.Shape(l_max=2, channels=3, max_messages=7)
    src, dst, vec, t, e = small_graph(rng, s)
    p, g = layers.block_params(s, 6), rng.normal(size=e.shape)
    f = lambda t, e, p: (layers.edge_update(t, e, src, dst, vec, p, s) * g).sum()
    back, back_e, grads = reverse.edge_update_back(t, e, src, dst, vec, p, s, g)
    for _ in range(12):
        at, ae = (tuple(rng.integers(0, k) for k in x.shape) for x in (t, e))
        assert slope(lambda x: f(x, e, p), t, at) == pytest.approx(back[at], abs=1e-5)
        assert slope(lambda x: f(t, x, p), e, ae) == pytest.approx(back_e[ae], abs=1e-5)
    for name, v in grads.items():
        at = tuple(rng.integers(0, k) for k in v.shape)
        assert slope(lambda x, name=name: f(t, e, {**p, name: x}), p[name], at) == pytest.approx(v[at], abs=1e-5)


def test_chunks_do_not_change_the_sum():
    rng = np.random.default_rng(8)
    s = layers.Shape(l_max=2, channels=3)
    src, dst, vec, t, e = small_graph(rng, s, 7)
    p, own = layers.block_params(s, 5, True), np.arange(7)
    whole = layers.node_update(t, e, src, dst, vec, own, p, s)
    for most in (1, 3, 11):
        assert np.allclose(layers.node_update(t, e, src, dst, vec, own, p, replace(s, max_messages=most)), whole, atol=1e-12)


def test_feed_forward_turns_with_its_input():
    from orbitgraph.functions.so3 import rotate, wigner

    rng = np.random.default_rng(2)
    s = layers.Shape(l_max=3, channels=4)
    q, _ = np.linalg.qr(rng.normal(size=(3, 3)))
    d = wigner((q * np.sign(np.linalg.det(q)))[None].repeat(6, axis=0), 3)
    x, p = rng.normal(size=(6, s.rows, 4)), layers.block_params(s, 1, True)
    turn = lambda y: rotate(y[:, None], d)[:, 0]
    assert np.allclose(layers.feed_forward(turn(x), p, s), turn(layers.feed_forward(x, p, s)), atol=1e-9)


def test_distributed_gradient(spark, sf):
    """The same on one rank and on three, and right by finite differences."""
    s = layers.Shape(l_max=1, channels=3)
    atoms, cell, n = structures.load(spark, sf, "pcm_c")
    edges = graph.radius_edges(atoms, cell, 6.0).persist()
    params, head = [layers.block_params(s, k) for k in (1, 2)], np.array([0.5, -1.0, 0.25])
    run = lambda ranks, params: backward.loss_and_gradient(atoms, edges, ranks, s, params, head, 1.5, [32, 51, 52], settle=lambda df: df.persist())
    one, three = run(model.single_rank(atoms), params), run(partition.random(atoms, 3), params)
    assert one[0] == pytest.approx(three[0]) and np.allclose(one[2], three[2])
    for a, b in zip(one[1], three[1], strict=True):
        assert all(np.allclose(a[k], b[k], atol=1e-9) for k in a)
    for block, name in ((0, "first.0r"), (1, "attention")):
        moved = [{k: v.copy() for k, v in p.items()} for p in params]
        at = (0,) * moved[block][name].ndim
        moved[block][name][at] += 1e-5
        assert (run(model.single_rank(atoms), moved)[0] - one[0]) / 1e-5 == pytest.approx(one[1][block][name][at], rel=1e-2, abs=1e-4)
