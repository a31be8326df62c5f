"""NumPy kernels of the rotation-equivariant network: SO(2) linear maps in the bond frame, gates, attention, sums.

Arrays are (messages, parts, rows, channels); rows are spherical indices. Everything works on the edges of one rank, in
chunks of at most ``max_messages``, so a worker's memory is bounded whatever the size of the graph.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np

from .so3 import bond_wigner, lm_index, rotate


@dataclass(frozen=True)
class Shape:
    """Hyper-parameters."""

    l_max: int = 2
    channels: int = 8
    r_cut: float = 6.0
    n_basis: int = 8
    max_messages: int = 100_000
    precision: str = "fp64"  # of what is stored and sent; sums run at least in fp32

    @property
    def rows(self) -> int:
        return (self.l_max + 1) ** 2


def stored(x: np.ndarray, precision: str) -> np.ndarray:
    """Rounded to the stored precision, returned wide."""
    kind = {"fp16": np.float16, "fp32": np.float32, "fp64": np.float64}[precision]
    return x.astype(kind).astype(np.float64)


def block_params(shape: Shape, seed: int, feed_forward_: bool = False) -> dict[str, np.ndarray]:
    """Parameters of one block: two SO(2) maps, a gate, an attention row, and the maps of the feed-forward part if asked."""
    rng = np.random.default_rng(seed)
    c, out = shape.channels, {}
    for name, c_in in (("first", 3 * c), ("second", c)):
        for m in range(shape.l_max + 1):
            n = shape.l_max + 1 - m
            for part in ("r", "i") if m else ("r",):
                out[f"{name}.{m}{part}"] = rng.normal(size=(n * c_in, n * c)) / np.sqrt(n * c_in * (2 if m else 1))
    out["gate"] = rng.normal(size=(c, shape.l_max * c)) / np.sqrt(c)
    out["attention"] = rng.normal(size=c) / np.sqrt(c)
    if feed_forward_:
        out |= {"ff.in": rng.normal(size=(shape.l_max + 1, c, c)) / np.sqrt(c), "ff.gate": rng.normal(size=(c, shape.l_max * c)) / np.sqrt(c), "ff.out": rng.normal(size=(shape.l_max + 1, c, c)) / np.sqrt(c)}
    return out


def so2_linear(x: np.ndarray, p: dict[str, np.ndarray], name: str, shape: Shape) -> np.ndarray:
    """(n, rows, c_in) to (n, rows, c): for m > 0 rows +m and -m mix like real and imaginary part, which commutes with
    turns about the bond."""
    n, c = len(x), shape.channels
    out = np.zeros((n, shape.rows, c))
    for m in range(shape.l_max + 1):
        ls = range(m, shape.l_max + 1)
        plus = [lm_index(l, m) for l in ls]
        a = x[:, plus].reshape(n, -1)
        if m == 0:
            out[:, plus] = (a @ p[f"{name}.0r"]).reshape(n, len(plus), c)
            continue
        minus = [lm_index(l, -m) for l in ls]
        b = x[:, minus].reshape(n, -1)
        r, i = p[f"{name}.{m}r"], p[f"{name}.{m}i"]
        both = np.concatenate([a, b], axis=1) @ np.block([[r, i], [-i, r]])
        out[:, plus], out[:, minus] = (v.reshape(n, len(plus), c) for v in np.split(both, 2, axis=1))
    return out


def gate(x: np.ndarray, w: np.ndarray, shape: Shape) -> np.ndarray:
    """Scalars pass a smooth step; rows of l > 0 are scaled by a function of the scalars of their channel mix."""
    s = x[:, 0]
    out = x.copy()
    out[:, 0] = s / (1 + np.exp(-s))
    scale = (1 / (1 + np.exp(-(s @ w)))).reshape(len(x), shape.l_max, shape.channels)
    for l in range(1, shape.l_max + 1):  # noqa: E741
        out[:, l * l : (l + 1) ** 2] *= scale[:, l - 1][:, None]
    return out


def equi_norm(x: np.ndarray, shape: Shape, eps: float = 1e-6) -> np.ndarray:
    """Rows of each l divided by their root mean square over rows and channels."""
    out = np.empty_like(x)
    for l in range(shape.l_max + 1):  # noqa: E741
        rows = slice(l * l, (l + 1) ** 2)
        out[:, rows] = x[:, rows] / np.sqrt((x[:, rows] ** 2).mean(axis=(1, 2), keepdims=True) + eps)
    return out


def envelope(r: np.ndarray, r_cut: float) -> np.ndarray:
    return 0.5 * (1 + np.cos(np.pi * np.minimum(r / r_cut, 1.0)))


def radial(r: np.ndarray, shape: Shape) -> np.ndarray:
    """Initial edge rows: a Gaussian basis of the distance in the row l=m=0, repeated over the channels."""
    centres = np.linspace(0, shape.r_cut, shape.channels)
    width = shape.r_cut / max(shape.channels - 1, 1)
    out = np.zeros((len(r), shape.rows, shape.channels))
    out[:, 0] = np.exp(-((r[:, None] - centres) ** 2) / (2 * width * width)) * envelope(r, shape.r_cut)[:, None]
    return out


def transform(src: np.ndarray, dst: np.ndarray, edge: np.ndarray, vectors: np.ndarray, p: dict[str, np.ndarray], shape: Shape) -> np.ndarray:
    """Message of three parts: into the bond frame, linear, gate, linear, and back."""
    d = bond_wigner(vectors, shape.l_max)
    if not (edge[:, 1:].any() or src[:, 1:].any() or dst[:, 1:].any()):
        return _of_scalars(np.concatenate([src[:, 0], dst[:, 0], edge[:, 0]], axis=1), d, vectors, p, shape)
    flat = rotate(np.concatenate([src, dst, edge], axis=2)[:, None], d)[:, 0]
    y = so2_linear(gate(so2_linear(flat, p, "first", shape), p["gate"], shape), p, "second", shape)
    y *= envelope(np.linalg.norm(vectors, axis=1), shape.r_cut)[:, None, None]
    return rotate(y[:, None], d, back=True)[:, 0]


def _of_scalars(x: np.ndarray, d: list[np.ndarray], vectors: np.ndarray, p: dict[str, np.ndarray], shape: Shape) -> np.ndarray:
    """The message of invariant rows alone, as in a first layer: nothing is turned on the way in, and only rows of m = 0
    come out of the linear maps."""
    n, c = len(x), shape.channels
    h = (x @ p["first.0r"][: 3 * c]).reshape(n, shape.l_max + 1, c)
    s = h[:, 0].copy()
    h[:, 0] = s / (1 + np.exp(-s))
    h[:, 1:] *= (1 / (1 + np.exp(-(s @ p["gate"])))).reshape(n, shape.l_max, c)
    y = (h.reshape(n, -1) @ p["second.0r"]).reshape(n, shape.l_max + 1, c)
    y *= envelope(np.linalg.norm(vectors, axis=1), shape.r_cut)[:, None, None]
    return np.concatenate([m[:, l, :, None] * y[:, l, None] for l, m in enumerate(d)], axis=1)  # noqa: E741


def chunks(n: int, most: int) -> Iterator[slice]:
    for a in range(0, n, most):
        yield slice(a, min(a + most, n))


def segment_softmax(score: np.ndarray, segment: np.ndarray, n: int) -> np.ndarray:
    top = np.full(n, -np.inf)
    np.maximum.at(top, segment, score)
    e = np.exp(score - top[segment])
    return e / np.bincount(segment, weights=e, minlength=n)[segment]


def node_update(nodes: np.ndarray, edge: np.ndarray, src: np.ndarray, dst: np.ndarray, vectors: np.ndarray, own: np.ndarray, p: dict[str, np.ndarray], shape: Shape) -> np.ndarray:
    """Updated rows of ``own`` nodes: attention over their incoming edges, weighted sum, residual, feed-forward.

    nodes: local and received rows; src and dst point into them; every edge of an own destination is here. Messages are
    made, weighed and added up a chunk at a time: a destination keeps its largest score so far, and what it has added up is
    scaled down when a larger one comes, so only ``max_messages`` messages exist at once."""
    normed = equi_norm(nodes, shape)
    top, mass, total = np.full(len(nodes), -np.inf), np.zeros(len(nodes)), np.zeros_like(nodes)
    for c in chunks(len(src), shape.max_messages):
        messages = transform(normed[src[c]], normed[dst[c]], edge[c], vectors[c], p, shape)
        s = scores(messages, p)
        here, segment = np.unique(dst[c], return_inverse=True)
        high = np.full(len(here), -np.inf)
        np.maximum.at(high, segment, s)
        high = np.maximum(high, top[here])
        fade, e = np.exp(top[here] - high), np.exp(s - high[segment])
        order = np.argsort(segment, kind="stable")
        sums = np.add.reduceat(messages[order] * e[order][:, None, None], np.searchsorted(segment[order], np.arange(len(here))), axis=0)
        total[here] = total[here] * fade[:, None, None] + sums
        mass[here] = mass[here] * fade + np.bincount(segment, weights=e, minlength=len(here))
        top[here] = high
    out = nodes[own] + total[own] / np.where(mass[own] > 0, mass[own], 1.0)[:, None, None]
    return stored(out + feed_forward(out, p, shape), shape.precision)


def scores(messages: np.ndarray, p: dict[str, np.ndarray]) -> np.ndarray:
    s = messages[:, 0] @ p["attention"]
    return np.where(s > 0, s, 0.2 * s)


def per_degree(x: np.ndarray, w: np.ndarray, shape: Shape) -> np.ndarray:
    """Channels mixed by one matrix for each l (l_max + 1, c, c): the rows of an l keep their turn."""
    out = np.empty((len(x), shape.rows, w.shape[2]))
    for l in range(shape.l_max + 1):  # noqa: E741
        out[:, l * l : (l + 1) ** 2] = x[:, l * l : (l + 1) ** 2] @ w[l]
    return out


def feed_forward(x: np.ndarray, p: dict[str, np.ndarray], shape: Shape) -> np.ndarray:
    """Norm, a linear map for each l, gate, and another; nothing for parameters without these maps."""
    if "ff.in" not in p:
        return np.zeros_like(x)
    h = per_degree(equi_norm(x, shape), p["ff.in"], shape)
    return per_degree(gate(h, p["ff.gate"], shape), p["ff.out"], shape)


def edge_update(nodes: np.ndarray, edge: np.ndarray, src: np.ndarray, dst: np.ndarray, vectors: np.ndarray, p: dict[str, np.ndarray], shape: Shape) -> np.ndarray:
    normed = equi_norm(nodes, shape)
    out = edge.copy()
    for c in chunks(len(src), shape.max_messages):
        out[c] += transform(normed[src[c]], normed[dst[c]], edge[c], vectors[c], p, shape)
    return stored(out, shape.precision)
