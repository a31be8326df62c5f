"""Atoms and periodic cells. Positions come from integer arithmetic on keys, so that every engine gets the same bits."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Fixed values: (multiplier, modulus) of the position hash of each axis.
SPREAD = ((7919, 10007), (104729, 20011), (1299709, 30011))
AXES = ("x", "y", "z")


@dataclass(frozen=True)
class Cell:
    """Edge lengths of an orthogonal box, and which axes are periodic."""

    lengths: tuple[float, float, float]
    periodic: tuple[bool, bool, bool] = (True, True, True)

    @staticmethod
    def cube(n_atoms: int, density: float) -> Cell:
        side = round((n_atoms / density) ** (1 / 3), 3)
        return Cell((side, side, side))

    def tiled(self, nx: int, ny: int, nz: int) -> Cell:
        return Cell(tuple(a * n for a, n in zip(self.lengths, (nx, ny, nz), strict=True)), self.periodic)


def species_rule(name: str, key: Column) -> Column:
    """Atomic numbers by key: oxide 1:2 of 72 and 8; pcm 1:2:4 of 32, 51, 52."""
    if name == "oxide":
        return F.when(key % 3 == 0, 72).otherwise(8)
    return F.when(key % 7 == 0, 32).when(key % 7 <= 2, 51).otherwise(52)


def atoms(df: DataFrame, key: str, cell: Cell, species: str = "oxide", skew_x: bool = False) -> DataFrame:
    """atom_id, species, x, y, z of every row. skew_x squares the first coordinate, for uneven density."""
    k = F.col(key).cast("long")
    unit = [((k * m) % p) / F.lit(float(p)) for m, p in SPREAD]
    if skew_x:
        unit[0] = unit[0] * unit[0]
    return df.select(k.alias("atom_id"), species_rule(species, k).alias("species"), *((u * F.lit(side)).alias(a) for u, side, a in zip(unit, cell.lengths, AXES, strict=True)))


def wrap(atoms_: DataFrame, cell: Cell) -> DataFrame:
    """Positions moved into the box along periodic axes."""
    moved = {a: F.col(a) - F.lit(side) * F.floor(F.col(a) / F.lit(side)) for a, side, p in zip(AXES, cell.lengths, cell.periodic, strict=True) if p}
    return atoms_.withColumns(moved)


def tile(atoms_: DataFrame, cell: Cell, n_atoms: int, nx: int, ny: int, nz: int, keep: tuple[str, ...] = ()) -> DataFrame:
    """Copies of the cell along the axes; ids continue as id + n_atoms * tile. Exploded in place: no join. keep: further
    columns of the atoms, or ``t``, the tile."""
    index = F.explode(F.sequence(F.lit(0), F.lit(nx * ny * nz - 1))).alias("t")
    t = F.col("t")
    at = ((t / (ny * nz)).cast("int"), (t / nz).cast("int") % ny, t % nz)
    lx, ly, lz = cell.lengths
    return atoms_.select("*", index).select(
        (F.col("atom_id") + t.cast("long") * n_atoms).alias("atom_id"),
        "species",
        *((F.col(a) + at[i] * F.lit(side)).alias(a) for i, (a, side) in enumerate(zip(AXES, (lx, ly, lz), strict=True))),
        *keep,
    )
