"""Work on radius graphs that never exist as tables: every box of space gets its atoms and those around it, and a kernel
sees the whole neighbourhood of the box's own atoms.

Only atoms move, about three times over; edges live in one chunk of a task. Distances are those of
:func:`.graph.radius_edges`, bit for bit.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from itertools import product

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .structure import AXES, Cell

BOX_ATOMS = 2_000  # about so many atoms of its own has a box
CANDIDATES = 1_000_000  # pairs that are measured at once
SLACK = 1e-6  # of the halo beyond the cutoff, far more than rounding


def _copies(atoms: DataFrame, cell: Cell, r_cut: float, columns: list[str], n_atoms: int, box_atoms: int) -> DataFrame:
    """Atoms by box (bx, by, bz), own ones and those within the cutoff of the box, with the shift (sx, sy, sz) at which the
    box sees them."""
    volume = math.prod(cell.lengths)
    want = max(r_cut, (volume * box_atoms / max(n_atoms, 1)) ** (1 / 3))
    n = [max(1, int(side // want)) for side in cell.lengths]
    widths = [side / k for side, k in zip(cell.lengths, n, strict=True)]
    out = atoms.select("atom_id", *AXES, *columns)
    for i, a in enumerate(AXES):
        w, k, periodic = widths[i], n[i], cell.periodic[i]
        look = math.ceil((r_cut + SLACK) / w)
        at = F.floor(F.col(a) / F.lit(w)).cast("int")
        at = F.least(F.greatest(at, F.lit(0)), F.lit(k - 1)) if periodic else at
        near = []
        for o in range(-look, look + 1):
            gap = (F.lit(0.0) if o == 0 else (at + o) * F.lit(w) - F.col(a) if o > 0 else F.col(a) - (at + (o + 1)) * F.lit(w))
            near.append(F.when(gap <= F.lit(r_cut + SLACK), F.lit(o)))
        raw = at + F.col("_o")
        shift = F.floor(raw / F.lit(k)).cast("int") if periodic else F.lit(0)
        out = out.withColumn("_o", F.explode(F.array_compact(F.array(*near)))).withColumns({f"s{a}": -shift, f"b{a}": raw - shift * k, f"_own{a}": F.col("_o") == 0}).drop("_o")
    own = F.col("_ownx") & F.col("_owny") & F.col("_ownz")
    return out.withColumn("own", own).drop("_ownx", "_owny", "_ownz")


def _ranges(at: np.ndarray, cells: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First and number of the sorted cells' members around each place, a row for each line of cells along z."""
    starts = np.searchsorted(cells, np.arange(n.prod() + 1))
    first, last = [], []
    for ox, oy in product(range(-2, 3), repeat=2):
        x, y = at[:, 0] + ox, at[:, 1] + oy
        inside = (x >= 0) & (x < n[0]) & (y >= 0) & (y < n[1])
        line = (np.where(inside, x, 0) * n[1] + np.where(inside, y, 0)) * n[2]
        lo, hi = line + np.maximum(at[:, 2] - 2, 0), line + np.minimum(at[:, 2] + 2, n[2] - 1) + 1
        first.append(starts[lo])
        last.append(np.where(inside, starts[hi], starts[lo]))
    first = np.stack(first, 1)
    return first, np.stack(last, 1) - first


def neighbourhoods(xyz: np.ndarray, shift: np.ndarray, own: np.ndarray, lengths: tuple, r_cut: float, role: str = "src", candidates: int = CANDIDATES) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Edges as pairs of indices (own atom, other atom), in chunks that hold whole neighbourhoods.

    ``own``: indices of the atoms whose edges are wanted, which have no shift; ``role``: what they are in their edges.
    The other atom's image is at ``shift`` cells."""
    if not len(own):
        return
    side = np.asarray(lengths, float)
    seen = xyz + shift * side
    low = seen.min(0)
    step = r_cut / 2 * (1 + 1e-9)
    n = ((seen.max(0) - low) // step).astype(np.int64) + 1
    cell = np.minimum(((seen - low) // step).astype(np.int64), n - 1)
    code = (cell[:, 0] * n[1] + cell[:, 1]) * n[2] + cell[:, 2]
    order = np.argsort(code, kind="stable")
    first, count = _ranges(cell[own], code[order], n)
    upto = np.cumsum(count.sum(1))
    begin = 0
    while begin < len(own):
        base = upto[begin - 1] if begin else 0
        end = max(begin + 1, int(np.searchsorted(upto, base + candidates, side="right")))
        f, c = first[begin:end].ravel(), count[begin:end].ravel()
        total = int(c.sum())
        place = np.arange(total) + np.repeat(f - (np.cumsum(c) - c), c)
        other = order[place]
        me = np.repeat(own[begin:end], count[begin:end].sum(1))
        r2 = np.zeros(total)
        for i in range(3):
            # as the join has it: (dst + shift * side) - src, with the shift of dst's image
            if role == "src":
                d = (xyz[other, i] + shift[other, i] * side[i]) - xyz[me, i]
            else:
                d = (xyz[me, i] + -shift[other, i] * side[i]) - xyz[other, i]
            r2 = d * d if i == 0 else r2 + d * d
        keep = (r2 <= r_cut * r_cut) & (me != other)
        yield me[keep], other[keep]
        begin = end


def over(atoms: DataFrame, cell: Cell, r_cut: float, columns: list[str], kernel: Callable, schema: str, n_atoms: int, role: str = "src", box_atoms: int = BOX_ATOMS) -> DataFrame:
    """kernel(frame, own, edges) of every box: frame has atom_id, sx, sy, sz and ``columns`` of all atoms the box sees, own
    the indices of its own atoms, edges the iterator of :func:`neighbourhoods`."""
    lengths = cell.lengths

    def run(frame: pd.DataFrame) -> pd.DataFrame:
        own = np.flatnonzero(frame["own"].to_numpy(bool))
        if not len(own):
            return kernel(frame, own, iter(()))
        xyz, shift = frame[list(AXES)].to_numpy(float), frame[[f"s{a}" for a in AXES]].to_numpy(np.int64)
        return kernel(frame, own, neighbourhoods(xyz, shift, own, lengths, r_cut, role))

    parts = int(atoms.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    keys = [f"b{a}" for a in AXES]
    return _copies(atoms, cell, r_cut, columns, n_atoms, box_atoms).repartition(max(parts, 12), *keys).groupBy(*keys).applyInPandas(run, schema)


def degree(atoms: DataFrame, cell: Cell, r_cut: float, n_atoms: int, box_atoms: int = BOX_ATOMS) -> DataFrame:
    """atom_id and number of incoming edges, 0 included."""

    def kernel(frame, own, edges):
        n_in = np.zeros(len(frame), np.int64)
        for me, _ in edges:
            n_in += np.bincount(me, minlength=len(frame))
        return pd.DataFrame({"atom_id": frame["atom_id"].to_numpy()[own], "n_in": n_in[own]})

    return over(atoms, cell, r_cut, [], kernel, "atom_id long, n_in long", n_atoms, "dst", box_atoms)


def tile_of(t: int, shift: np.ndarray, tiles: tuple[int, int, int]) -> np.ndarray:
    """Tile in which the image at ``shift`` cells from tile t lies."""
    nx, ny, nz = tiles
    at = (t // (ny * nz), t // nz % ny, t % nz)
    home = [(at[i] + shift[:, i]) % tiles[i] for i in range(3)]
    return (home[0] * ny + home[1]) * nz + home[2]


def _summed(code: np.ndarray, *values: np.ndarray) -> tuple[np.ndarray, ...]:
    key, inverse = np.unique(code, return_inverse=True)
    return (key, *(np.bincount(inverse, weights=v, minlength=len(key)).astype(np.int64) for v in values))


def rank_pairs(atoms: DataFrame, cell: Cell, r_cut: float, ranks: Column, n_atoms: int, tiles: tuple[int, int, int] = (1, 1, 1), box_atoms: int = BOX_ATOMS) -> DataFrame:
    """(scheme, from_rank, to_rank, rows, messages) of many placements in one pass over the graph: :func:`.metrics.rank_pairs`
    without its joins.

    ranks: an array of ints for each atom, a rank for each scheme and, within the scheme, for each tile of a tiled
    structure, whose edges follow from the cell's."""
    n_tiles = math.prod(tiles)

    def kernel(frame, own, edges):
        held = np.stack(frame["_ranks"].to_numpy()).astype(np.int64) if len(frame) else np.zeros((0, 1), np.int64)
        shift = frame[[f"s{a}" for a in AXES]].to_numpy(np.int64)
        schemes = held.shape[1] // n_tiles
        shifts, kind = np.unique(shift, axis=0, return_inverse=True)
        kind = kind.ravel()
        found: list[list[tuple]] = [[] for _ in range(schemes)]
        everyone, parts, to_ranks = np.arange(len(frame)), [], []
        for s in range(schemes):
            block = held[:, s * n_tiles : (s + 1) * n_tiles]
            for t in range(n_tiles):
                seen = block[everyone, tile_of(t, shifts, tiles)[kind]]
                names, local = np.unique(seen, return_inverse=True)
                to_ranks.append((s, t, names, local.ravel()))
            parts.append(int(block.max()) + 1 if block.size else 1)
        for me, other in edges:
            who, at = np.unique(me, return_inverse=True)
            for s, t, names, local in to_ranks:
                k = np.bincount(at * len(names) + local[other], minlength=len(who) * len(names))
                hit = np.flatnonzero(k)
                code = held[who[hit // len(names)], s * n_tiles + t] * parts[s] + names[hit % len(names)]
                found[s].append(_summed(code, np.ones(len(hit)), k[hit]))
        out = []
        for s, several in enumerate(found):
            if several:
                code, rows, messages = _summed(np.concatenate([c for c, _, _ in several]), np.concatenate([r for _, r, _ in several]), np.concatenate([m for _, _, m in several]))
                out.append(pd.DataFrame({"scheme": s, "from_rank": code // parts[s], "to_rank": code % parts[s], "rows": rows, "messages": messages}))
        return pd.concat(out) if out else pd.DataFrame({c: [] for c in ("scheme", "from_rank", "to_rank", "rows", "messages")})

    placed = atoms.withColumn("_ranks", ranks)
    each = over(placed, cell, r_cut, ["_ranks"], kernel, "scheme int, from_rank int, to_rank int, rows long, messages long", n_atoms, "src", box_atoms)
    return each.groupBy("scheme", "from_rank", "to_rank").agg(F.sum("rows").alias("rows"), F.sum("messages").alias("messages"))
