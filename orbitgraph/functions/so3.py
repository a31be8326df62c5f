"""Rotations of real spherical-harmonic rows; index of (l, m) is l*l + l + m, polar axis z."""

from __future__ import annotations

import math
from functools import lru_cache

import numpy as np


def lm_index(l: int, m: int) -> int:  # noqa: E741
    return l * l + l + m


def m_major(l_max: int) -> np.ndarray:
    """Permutation from l-major to m-major rows: all l of m = 0, then of m = 1 and -1, and so on."""
    order = [lm_index(l, 0) for l in range(l_max + 1)]  # noqa: E741
    for m in range(1, l_max + 1):
        order += [lm_index(l, s * m) for s in (1, -1) for l in range(m, l_max + 1)]  # noqa: E741
    return np.array(order)


def harmonics(points: np.ndarray, l_max: int) -> np.ndarray:
    """Real spherical harmonics of unit vectors (n, 3): (n, (l_max+1)²), orthonormal on the sphere."""
    x, y, z = points.T
    n = len(points)
    # associated Legendre functions without the power of sin, and cos/sin of m phi times that power
    cos, sin = [np.ones(n)], [np.zeros(n)]
    for _ in range(l_max):
        cos, sin = [*cos, x * cos[-1] - y * sin[-1]], [*sin, x * sin[-1] + y * cos[-1]]
    out = np.zeros((n, (l_max + 1) ** 2))
    for m in range(l_max + 1):
        p = {m: np.full(n, math.prod(range(1, 2 * m, 2)) or 1.0)}
        if m < l_max:
            p[m + 1] = (2 * m + 1) * z * p[m]
        for l in range(m + 2, l_max + 1):  # noqa: E741
            p[l] = ((2 * l - 1) * z * p[l - 1] - (l + m - 1) * p[l - 2]) / (l - m)
        for l in range(m, l_max + 1):  # noqa: E741
            norm = math.sqrt((2 * l + 1) / (4 * math.pi) * math.factorial(l - m) / math.factorial(l + m)) * (math.sqrt(2) if m else 1)
            out[:, lm_index(l, m)] = norm * p[l] * cos[m]
            if m:
                out[:, lm_index(l, -m)] = norm * p[l] * sin[m]
    return out


@lru_cache(maxsize=8)
def _points(l_max: int) -> tuple[np.ndarray, tuple[np.ndarray, ...]]:
    """Fixed well-spread points and, for each l, the pseudo-inverse of the harmonics there."""
    k = 4 * (l_max + 1) ** 2
    i = np.arange(k) + 0.5
    z, phi = 1 - 2 * i / k, math.pi * (1 + 5**0.5) * i
    p = np.stack([np.sqrt(1 - z * z) * np.cos(phi), np.sqrt(1 - z * z) * np.sin(phi), z], axis=1)
    y = harmonics(p, l_max)
    return p, tuple(np.linalg.pinv(y[:, l * l : (l + 1) ** 2]) for l in range(l_max + 1))  # noqa: E741


def wigner(rotations: np.ndarray, l_max: int) -> list[np.ndarray]:
    """For each l the (n, 2l+1, 2l+1) matrices D with Y(R p) = D Y(p), fitted at fixed points: one convention throughout."""
    p, inverse = _points(l_max)
    turned = np.einsum("nij,kj->nki", rotations, p)
    y = harmonics(turned.reshape(-1, 3), l_max).reshape(len(rotations), len(p), -1)
    return [np.einsum("nkb,ak->nba", y[:, :, l * l : (l + 1) ** 2], inverse[l]) for l in range(l_max + 1)]  # noqa: E741


def bond_rotations(vectors: np.ndarray) -> np.ndarray:
    """Rotations that bring each bond to the polar axis; bonds along it are turned by 0 or pi about x."""
    n = vectors / np.linalg.norm(vectors, axis=1, keepdims=True)
    rho = np.hypot(n[:, 0], n[:, 1])
    polar = rho < 1e-12
    c, s = np.where(polar, 1.0, n[:, 0] / np.where(polar, 1.0, rho)), np.where(polar, 0.0, n[:, 1] / np.where(polar, 1.0, rho))
    z = n[:, 2]
    zero = np.zeros_like(z)
    first = np.stack([np.stack([c, s, zero], 1), np.stack([-s, c, zero], 1), np.stack([zero, zero, zero + 1], 1)], 1)
    second = np.stack([np.stack([z, zero, -rho], 1), np.stack([zero, zero + 1, zero], 1), np.stack([rho, zero, z], 1)], 1)
    return second @ first


@lru_cache(maxsize=8)
def _polar(l_max: int) -> tuple[np.ndarray, ...]:
    """For each l, what turns about y by an angle t are made of: (2l+1, (2l+1)²) factors of 1, cos t, .., sin t, .. ."""
    t = np.linspace(0, 2 * np.pi, 4 * l_max + 5)[:-1]
    zero = np.zeros_like(t)
    about_y = np.stack([np.stack([np.cos(t), zero, -np.sin(t)], 1), np.stack([zero, zero + 1, zero], 1), np.stack([np.sin(t), zero, np.cos(t)], 1)], 1)
    made = wigner(about_y, l_max)
    return tuple(np.linalg.pinv(np.stack([np.cos(m * t) for m in range(l + 1)] + [np.sin(m * t) for m in range(1, l + 1)], 1)) @ made[l].reshape(len(t), -1) for l in range(l_max + 1))  # noqa: E741


def bond_wigner(vectors: np.ndarray, l_max: int) -> list[np.ndarray]:
    """The matrices of :func:`wigner` for :func:`bond_rotations`, in closed form: a turn about z, then one about y."""
    v = vectors / np.linalg.norm(vectors, axis=1, keepdims=True)
    rho = np.hypot(v[:, 0], v[:, 1])
    polar = rho < 1e-12
    safe = np.where(polar, 1.0, rho)
    c, s, z = np.where(polar, 1.0, v[:, 0] / safe), np.where(polar, 0.0, v[:, 1] / safe), v[:, 2]
    cos, sin, cos_y, sin_y = [np.ones(len(v))], [np.zeros(len(v))], [np.ones(len(v))], [np.zeros(len(v))]
    for _ in range(l_max):
        cos, sin = [*cos, c * cos[-1] - s * sin[-1]], [*sin, c * sin[-1] + s * cos[-1]]
        cos_y, sin_y = [*cos_y, z * cos_y[-1] - rho * sin_y[-1]], [*sin_y, z * sin_y[-1] + rho * cos_y[-1]]
    out = []
    for l, factors in enumerate(_polar(l_max)):  # noqa: E741
        d = (np.stack([*cos_y[: l + 1], *sin_y[1 : l + 1]], 1) @ factors).reshape(len(v), 2 * l + 1, 2 * l + 1)
        for m in range(1, l + 1):
            plus, minus = d[:, :, l + m].copy(), d[:, :, l - m].copy()
            d[:, :, l + m] = plus * cos[m][:, None] - minus * sin[m][:, None]
            d[:, :, l - m] = plus * sin[m][:, None] + minus * cos[m][:, None]
        out.append(d)
    return out


def rotate(x: np.ndarray, d: list[np.ndarray], back: bool = False) -> np.ndarray:
    """Rows (n, g, h, c) turned block by block; back applies the transposes."""
    out = np.empty_like(x)
    for l, m in enumerate(d):  # noqa: E741
        rows = slice(l * l, (l + 1) ** 2)
        out[:, :, rows] = (m.transpose(0, 2, 1) if back else m)[:, None] @ x[:, :, rows] if l else x[:, :, rows] * m[:, None]
    return out


@lru_cache(maxsize=64)
def clebsch(l1: int, l2: int, l: int) -> np.ndarray:  # noqa: E741
    """Intertwiner (2l+1, 2l1+1, 2l2+1) with orthonormal rows, unique up to the sign, which makes the first entry positive.

    Found from the null space of D1 ⊗ D2 against D over a few fixed rotations."""
    rng = np.random.default_rng(5)
    q, _ = np.linalg.qr(rng.normal(size=(4, 3, 3)))
    q *= np.sign(np.linalg.det(q))[:, None, None]
    d = wigner(q, max(l1, l2, l))
    size = (2 * l1 + 1) * (2 * l2 + 1)
    rows = [np.kron(np.eye(2 * l + 1), np.kron(d[l1][k], d[l2][k]).T) - np.kron(d[l][k], np.eye(size)) for k in range(len(q))]
    # C (D1⊗D2) = D C, vectorised row by row
    _, s, vt = np.linalg.svd(np.vstack(rows))
    c = vt[-1].reshape(2 * l + 1, size)
    c *= math.sqrt(2 * l + 1) / np.linalg.norm(c)
    flat = c.ravel()
    c *= np.sign(flat[np.flatnonzero(np.abs(flat) > 1e-8)[0]])
    return c.reshape(2 * l + 1, 2 * l1 + 1, 2 * l2 + 1)


def couple(block: np.ndarray, l1: int, l2: int) -> dict[int, np.ndarray]:
    """Blocks (n, 2l1+1, 2l2+1) in the coupled basis: l -> (n, 2l+1)."""
    return {l: np.einsum("mab,nab->nm", clebsch(l1, l2, l), block) for l in range(abs(l1 - l2), l1 + l2 + 1)}  # noqa: E741


def uncouple(parts: dict[int, np.ndarray], l1: int, l2: int) -> np.ndarray:
    return sum(np.einsum("mab,nm->nab", clebsch(l1, l2, l), v) for l, v in parts.items())  # noqa: E741
