"""Plain NumPy references."""

import math
from itertools import product

import numpy as np


def edges(pos, lengths, r_cut, periodic=(True, True, True)):
    """All (src, dst, shift) within the cutoff, by brute force over images."""
    reach = [math.ceil(r_cut / side) if p else 0 for side, p in zip(lengths, periodic, strict=True)]
    out = set()
    for s in product(*(range(-k, k + 1) for k in reach)):
        d = pos[None] + np.array(s) * np.array(lengths) - pos[:, None]
        for i, j in zip(*np.nonzero((d**2).sum(-1) <= r_cut * r_cut), strict=True):
            if i != j or any(s):
                out.add((int(i), int(j), *s))
    return out


def bisect(pos, weight, lengths, depth, reach, tie="index"):
    """Recursive few-neighbour bisection with ring opening: rank of each row."""
    pos = pos.copy()
    ids = np.arange(len(pos))

    def cut(rows, values):
        order = rows[np.lexsort((ids[rows], values[rows]))]
        before = np.cumsum(weight[order]) - weight[order]
        k = int((before * 2 < weight[order].sum()).sum())
        return order[:k], order[k:]

    for a in range(3):
        left, _ = cut(ids, pos[:, a])
        origin = pos[left[-1], a]
        pos[:, a] = np.where(pos[:, a] > origin, pos[:, a] - origin, pos[:, a] - origin + lengths[a])
    rank = np.zeros(len(pos), int)

    def split(rows, cuts, level, code):
        if level == 0:
            rank[rows] = code
            return
        extent = pos[rows].max(0) - pos[rows].min(0)
        cost = [1 if cuts[a] <= 1 else math.ceil(2 * reach / extent[a]) for a in range(3)]
        best = [a for a in range(3) if cost[a] == min(cost)]
        axis = max(best) if tie == "index" else max(best, key=lambda a: (extent[a], a))
        left, right = cut(rows, pos[:, axis])
        cuts = tuple(c + (a == axis) for a, c in enumerate(cuts))
        split(left, cuts, level - 1, 2 * code)
        split(right, cuts, level - 1, 2 * code + 1)

    split(ids, (1, 1, 1), depth, 0)
    return rank
