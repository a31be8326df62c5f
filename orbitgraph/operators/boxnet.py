"""The network over boxes of space: edges and their rows live in one chunk of a task and are made again where they are
needed, so only atoms and their node rows move or are kept.

A box sees its own atoms, which own the edges that lead to them, and those within the cutoff. Chunks hold whole
neighbourhoods, so a block is the same kernel as on a rank (:mod:`.model`), and results are equal up to the order of sums.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import layers
from ..functions.layers import Shape
from . import boxes, model, partition
from .structure import AXES, Cell

CANDIDATES = 16_000  # pairs measured at once: about a quarter of them are edges
ATOMS = ("atom_id", "species", *AXES)
ATOMS_SCHEMA = "atom_id long, species int, x double, y double, z double"

Blocks = list[tuple[dict[str, np.ndarray], dict[str, np.ndarray]]]


def seeded(shape: Shape, n_layers: int, seed: int = 1) -> Blocks:
    """The parameters of :func:`.model.forward`: of the node and the edge block of every layer."""
    return [(layers.block_params(shape, seed * 1000 + 2 * k), layers.block_params(shape, seed * 1000 + 2 * k + 1)) for k in range(n_layers)]


@dataclass
class Piece:
    """Whole neighbourhoods of some atoms: ``here`` are the frame's atoms in it; src, dst and own point into ``here``."""

    here: np.ndarray
    src: np.ndarray
    dst: np.ndarray
    own: np.ndarray
    vectors: np.ndarray
    r: np.ndarray
    shift: np.ndarray


@dataclass(frozen=True)
class Space:
    """Atoms (atom_id, species, x, y, z) in a cell, and which pairs are edges: further apart than ``least``, up to the cutoff.

    ``parts``: ranks of contiguous ids; each gets its own atoms of a box and what it must receive, as a group of its own."""

    atoms: DataFrame
    cell: Cell
    r_cut: float
    n_atoms: int
    least: float = 0.0
    parts: int = 1
    box_atoms: int | None = None

    def over(self, atoms: DataFrame, columns: list[str], kernel: Callable[[pd.DataFrame, np.ndarray, Iterator[Piece]], pd.DataFrame], schema: str, own_only: tuple[str, ...] = ()) -> DataFrame:
        """kernel(frame, own, pieces) of every box; ``own_only``: columns that are null for atoms of other boxes."""
        size = self.box_atoms or int(min(max(self.n_atoms / 36, boxes.BOX_ATOMS), 12_000))
        copies = boxes._copies(atoms, self.cell, self.r_cut, ["species", *columns], self.n_atoms, size)
        keys = [f"b{a}" for a in AXES]
        if self.parts > 1:
            rank = partition.sequential_rank(self.parts, self.n_atoms)
            copies = copies.withColumn("rank", F.explode(F.sequence(F.lit(0), F.lit(self.parts - 1)))).withColumn("own", F.col("own") & (rank == F.col("rank")))
            keys = ["rank", *keys]
        copies = copies.withColumns({c: F.when(F.col("own"), F.col(c)) for c in own_only})
        space = (self.cell.lengths, self.r_cut, self.least)

        def run(frame: pd.DataFrame) -> pd.DataFrame:
            own = np.flatnonzero(frame["own"].to_numpy(bool))
            return kernel(frame, own, _pieces(frame, own, *space))

        # a box is a heavy group of few bytes: a stated number of partitions keeps AQE from merging them
        parts = int(atoms.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        return copies.repartition(max(parts, 48), *keys).groupBy(*keys).applyInPandas(run, schema)


def _pieces(frame: pd.DataFrame, own: np.ndarray, lengths: tuple, r_cut: float, least: float) -> Iterator[Piece]:
    if not len(own):
        return
    xyz, shift, side = frame[list(AXES)].to_numpy(float), frame[[f"s{a}" for a in AXES]].to_numpy(np.int64), np.asarray(lengths, float)
    near = np.floor((xyz[own] - xyz[own].min(0)) / (2 * r_cut)).astype(np.int64)
    own = own[np.lexsort((frame["atom_id"].to_numpy()[own], *near.T))]  # neighbours in space lie in one piece
    seen = np.zeros(len(frame), bool)
    for me, other in boxes.neighbourhoods(xyz, shift, own, lengths, r_cut, "dst", CANDIDATES):
        vectors = (xyz[me] + -shift[other] * side) - xyz[other]
        r = np.sqrt(vectors[:, 0] * vectors[:, 0] + vectors[:, 1] * vectors[:, 1] + vectors[:, 2] * vectors[:, 2])
        keep = r > least
        if not keep.all():
            me, other, vectors, r = me[keep], other[keep], vectors[keep], r[keep]
        if not len(me):
            continue
        here, at = np.unique(np.concatenate([me, other]), return_inverse=True)
        seen[me] = True
        yield Piece(here, at[len(me) :], at[: len(me)], np.unique(at[: len(me)]), vectors, r, -shift[other])
    alone, none = own[~seen[own]], np.zeros(0, np.int64)
    if len(alone):
        yield Piece(alone, none, none, np.arange(len(alone)), np.zeros((0, 3)), np.zeros(0), np.zeros((0, 3), np.int64))


class States:
    """Node rows of a frame before the first and after each of its kept layers (columns n1, n2, ..), and edge rows made of
    them for a piece."""

    def __init__(self, frame: pd.DataFrame, kept: int, table: dict[int, list[float]], blocks: Blocks, shape: Shape):
        self.shape, self.blocks = shape, blocks
        first = np.zeros((len(frame), shape.rows, shape.channels))
        z = frame["species"].to_numpy()
        for one in np.unique(z):
            first[z == one, 0] = table[int(one)]
        self.nodes = [first] + [rows(frame[f"n{k}"], shape) for k in range(1, kept + 1)]

    def edge(self, p: Piece, layer: int) -> np.ndarray:
        e = layers.radial(p.r, self.shape)
        for k in range(1, layer + 1):
            e = layers.edge_update(self.nodes[k][p.here], e, p.src, p.dst, p.vectors, self.blocks[k - 1][1], self.shape)
        return e


def rows(values: pd.Series, shape: Shape) -> np.ndarray:
    return np.stack(values.to_numpy()).reshape(len(values), shape.rows, shape.channels) if len(values) else np.zeros((0, shape.rows, shape.channels))


def listed(values: np.ndarray | list[np.ndarray]) -> np.ndarray:
    """A column of arrays, one that stays so where there are no rows."""
    out = np.empty(len(values), object)
    out[:] = list(values)
    return out


def node_rows(space: Space, shape: Shape, blocks: Blocks, species: list[int], seed: int = 1, settle: Callable[[DataFrame], DataFrame] | None = None, extra: Callable[[pd.DataFrame, Piece], np.ndarray] | None = None) -> DataFrame:
    """Atoms with their rows after every layer (n1, n2, ..): one pass over the boxes for each.

    ``extra``: numbers of each own atom of a piece, kept beside the first layer's rows in the column ``sums``."""
    settle = settle or (lambda df: df.checkpoint())
    table = model.species_rows(shape, species, seed)
    nodes, kept = space.atoms.select(*ATOMS), []
    schema = ATOMS_SCHEMA
    for k in range(1, len(blocks) + 1):

        def kernel(frame, own, pieces, k=k, kept=tuple(kept)):
            state = States(frame, k - 1, table, blocks, shape)
            new, more = np.zeros((len(frame), shape.rows * shape.channels)), None
            for p in pieces:
                mine = p.here[p.own]
                new[mine] = layers.node_update(state.nodes[k - 1][p.here], state.edge(p, k - 1), p.src, p.dst, p.vectors, p.own, blocks[k - 1][0], shape).reshape(len(mine), -1)
                if extra and k == 1:
                    values = extra(frame, p)
                    more = np.zeros((len(frame), values.shape[1])) if more is None else more
                    more[mine] = values
            out = frame.iloc[own][[*ATOMS, *kept]].assign(**{f"n{k}": listed(new[own])})
            if extra and k == 1:
                out["sums"] = listed(more[own] if more is not None else new[own])
            return out

        schema += f", n{k} array<double>" + (", sums array<double>" if extra and k == 1 else "")
        nodes = settle(space.over(nodes, kept, kernel, schema))
        kept += [f"n{k}", "sums"] if extra and k == 1 else [f"n{k}"]
    return nodes
