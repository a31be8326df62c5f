"""Reverse pass of the node and the edge block, by recomputing what the forward pass did: nothing is kept between the passes."""

from __future__ import annotations

from dataclasses import replace

import numpy as np

from .layers import Shape, chunks, envelope, equi_norm, gate, node_update, per_degree, segment_softmax, so2_linear
from .so3 import bond_wigner, lm_index, rotate

EPS = 1e-6


def so2_back(x: np.ndarray, grad: np.ndarray, p: dict[str, np.ndarray], name: str, shape: Shape, out: dict[str, np.ndarray]) -> np.ndarray:
    n, back = len(x), np.zeros_like(x)

    def add(key: str, value: np.ndarray) -> None:
        out[key] = out.get(key, 0) + value

    for m in range(shape.l_max + 1):
        ls = range(m, shape.l_max + 1)
        plus = [lm_index(l, m) for l in ls]
        a, gp = x[:, plus].reshape(n, -1), grad[:, plus].reshape(n, -1)
        r = p[f"{name}.{m}r"]
        if m == 0:
            back[:, plus] = (gp @ r.T).reshape(n, len(plus), -1)
            add(f"{name}.0r", a.T @ gp)
            continue
        minus = [lm_index(l, -m) for l in ls]
        b, gm, i = x[:, minus].reshape(n, -1), grad[:, minus].reshape(n, -1), p[f"{name}.{m}i"]
        back[:, plus] = (gp @ r.T + gm @ i.T).reshape(n, len(plus), -1)
        back[:, minus] = (gm @ r.T - gp @ i.T).reshape(n, len(minus), -1)
        add(f"{name}.{m}r", a.T @ gp + b.T @ gm)
        add(f"{name}.{m}i", a.T @ gm - b.T @ gp)
    return back


def gate_back(x: np.ndarray, grad: np.ndarray, w: np.ndarray, shape: Shape, out: dict[str, np.ndarray]) -> np.ndarray:
    s = x[:, 0]
    sig = 1 / (1 + np.exp(-s))
    scale = (1 / (1 + np.exp(-(s @ w)))).reshape(len(x), shape.l_max, shape.channels)
    back, dscale = np.zeros_like(x), np.zeros_like(scale)
    for l in range(1, shape.l_max + 1):  # noqa: E741
        rows = slice(l * l, (l + 1) ** 2)
        back[:, rows] = grad[:, rows] * scale[:, l - 1][:, None]
        dscale[:, l - 1] = (grad[:, rows] * x[:, rows]).sum(axis=1)
    z = (dscale * scale * (1 - scale)).reshape(len(x), -1)
    out["gate"] = out.get("gate", 0) + s.T @ z
    back[:, 0] = grad[:, 0] * (sig + s * sig * (1 - sig)) + z @ w.T
    return back


def norm_back(x: np.ndarray, grad: np.ndarray, shape: Shape) -> np.ndarray:
    back = np.empty_like(x)
    for l in range(shape.l_max + 1):  # noqa: E741
        rows = slice(l * l, (l + 1) ** 2)
        v, g = x[:, rows], grad[:, rows]
        q = 1 / np.sqrt((v**2).mean(axis=(1, 2), keepdims=True) + EPS)
        back[:, rows] = q * g - v * q**3 * (v * g).mean(axis=(1, 2), keepdims=True)
    return back


def per_degree_back(x: np.ndarray, grad: np.ndarray, w: np.ndarray, shape: Shape) -> tuple[np.ndarray, np.ndarray]:
    back, dw = np.empty_like(x), np.empty_like(w)
    for l in range(shape.l_max + 1):  # noqa: E741
        rows = slice(l * l, (l + 1) ** 2)
        back[:, rows] = grad[:, rows] @ w[l].T
        dw[l] = np.einsum("nrc,nrd->cd", x[:, rows], grad[:, rows])
    return back, dw


def feed_forward_back(x: np.ndarray, grad: np.ndarray, p: dict[str, np.ndarray], shape: Shape, out: dict[str, np.ndarray]) -> np.ndarray:
    if "ff.in" not in p:
        return np.zeros_like(x)
    normed = equi_norm(x, shape)
    h = per_degree(normed, p["ff.in"], shape)
    mine: dict[str, np.ndarray] = {}
    dg, out["ff.out"] = per_degree_back(gate(h, p["ff.gate"], shape), grad, p["ff.out"], shape)
    dn, out["ff.in"] = per_degree_back(normed, gate_back(h, dg, p["ff.gate"], shape, mine), p["ff.in"], shape)
    out["ff.gate"] = mine["gate"]
    return norm_back(x, dn, shape)


def _chunk(normed: np.ndarray, edge: np.ndarray, src: np.ndarray, dst: np.ndarray, vectors: np.ndarray, p: dict[str, np.ndarray], shape: Shape) -> tuple:
    """What the transform of a chunk computes on its way, and its messages."""
    d = bond_wigner(vectors, shape.l_max)
    flat = rotate(np.concatenate([normed[src], normed[dst], edge], axis=2)[:, None], d)[:, 0]
    h = so2_linear(flat, p, "first", shape)
    g = gate(h, p["gate"], shape)
    env = envelope(np.linalg.norm(vectors, axis=1), shape.r_cut)[:, None, None]
    return d, flat, h, g, env, rotate((so2_linear(g, p, "second", shape) * env)[:, None], d, back=True)[:, 0]


def _chunk_back(made: tuple, dm: np.ndarray, src: np.ndarray, dst: np.ndarray, p: dict[str, np.ndarray], shape: Shape, back_normed: np.ndarray, out: dict[str, np.ndarray]) -> np.ndarray:
    """Gradient of a chunk's edge rows; those of its end rows and of the parameters are added in place."""
    d, flat, h, g, env, _ = made
    dy = rotate(dm[:, None], d)[:, 0] * env
    df = so2_back(flat, gate_back(h, so2_back(g, dy, p, "second", shape, out), p["gate"], shape, out), p, "first", shape, out)
    k = shape.channels
    dx = rotate(df[:, None], d, back=True)[:, 0]
    add_rows(back_normed, src, dx[:, :, :k])
    add_rows(back_normed, dst, dx[:, :, k : 2 * k])
    return dx[:, :, 2 * k :]


def add_rows(total: np.ndarray, index: np.ndarray, rows: np.ndarray) -> None:
    """Rows added in place at their indices, which may repeat."""
    order = np.argsort(index, kind="stable")
    at = index[order]
    first = np.flatnonzero(np.r_[True, at[1:] != at[:-1]][: len(at)])
    if len(first):
        total[at[first]] += np.add.reduceat(rows[order], first, axis=0)


def node_update_back(
    nodes: np.ndarray, edge: np.ndarray, src: np.ndarray, dst: np.ndarray, vectors: np.ndarray, own: np.ndarray, p: dict[str, np.ndarray], shape: Shape, grad_own: np.ndarray
) -> tuple[np.ndarray, np.ndarray, dict[str, np.ndarray]]:
    """Gradients of all local and received node rows, of the edge rows and of the parameters, from that of the updated own
    rows. Messages are made twice, a chunk at a time: for scores and sums, then for the way back."""
    normed, out = equi_norm(nodes, shape), {}
    n, back_normed, back_edge = len(nodes), np.zeros_like(nodes), np.zeros_like(edge)
    grad_out = grad_own
    if "ff.in" in p:
        before = node_update(nodes, edge, src, dst, vectors, own, {k: v for k, v in p.items() if not k.startswith("ff.")}, replace(shape, precision="fp64"))
        grad_out = grad_own + feed_forward_back(before, grad_own, p, shape, out)
    grad_all = np.zeros_like(nodes)
    grad_all[own] = grad_out
    if not len(src):
        return grad_all, back_edge, out
    s, dw, raw = np.empty(len(src)), np.empty(len(src)), np.empty(len(src))
    for c in chunks(len(src), shape.max_messages):
        messages = _chunk(normed, edge[c], src[c], dst[c], vectors[c], p, shape)[-1]
        raw[c] = messages[:, 0] @ p["attention"]
        dw[c] = (messages * grad_all[dst[c]]).sum(axis=(1, 2))
    s = np.where(raw > 0, raw, 0.2 * raw)
    weight = segment_softmax(s, dst, n)
    mean = np.bincount(dst, weights=weight * dw, minlength=n)
    ds = weight * (dw - mean[dst]) * np.where(raw > 0, 1.0, 0.2)
    out["attention"] = np.zeros_like(p["attention"])
    for c in chunks(len(src), shape.max_messages):
        made = _chunk(normed, edge[c], src[c], dst[c], vectors[c], p, shape)
        out["attention"] += ds[c] @ made[-1][:, 0]
        dm = weight[c][:, None, None] * grad_all[dst[c]]
        dm[:, 0] += ds[c][:, None] * p["attention"]
        back_edge[c] = _chunk_back(made, dm, src[c], dst[c], p, shape, back_normed, out)
    return grad_all + norm_back(nodes, back_normed, shape), back_edge, out


def edge_update_back(nodes: np.ndarray, edge: np.ndarray, src: np.ndarray, dst: np.ndarray, vectors: np.ndarray, p: dict[str, np.ndarray], shape: Shape, grad: np.ndarray) -> tuple[np.ndarray, np.ndarray, dict[str, np.ndarray]]:
    """Gradients of the node rows, the edge rows and the parameters of an edge block."""
    normed, out = equi_norm(nodes, shape), {}
    back_normed, back_edge = np.zeros_like(nodes), grad.copy()
    for c in chunks(len(src), shape.max_messages):
        made = _chunk(normed, edge[c], src[c], dst[c], vectors[c], p, shape)
        back_edge[c] += _chunk_back(made, grad[c], src[c], dst[c], p, shape, back_normed, out)
    return norm_back(nodes, back_normed, shape), back_edge, out
