"""Shells of s, p and d orbitals: coupling of blocks in plans, and a two-centre stand-in for the exact matrix with them.

A block between shells of order l1 and l2 falls into components of order L = |l1 - l2| .. l1 + l2 (the coupled basis).
A two-centre block depends on the bond alone, so its component of order L is a number times the harmonics of order L of
the bond's direction; the stand-in is defined there, and its elements follow by the coupling coefficients.
"""

from __future__ import annotations

import math
from functools import lru_cache

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.so3 import clebsch, lm_index

# Orders of the shells of a species: ten orbitals for 72, four for 8, thirteen for 32, 51 and 52.
SHELLS = {72: (0, 0, 1, 2), 8: (0, 1), 32: (0, 0, 1, 1, 2), 51: (0, 0, 1, 1, 2), 52: (0, 0, 1, 1, 2)}
ENVIRONMENT = 0.05  # of the neighbours' share in a diagonal block
KEYS = ["src", "dst", "sx", "sy", "sz"]


def orbitals(species: int) -> int:
    return sum(2 * l + 1 for l in SHELLS[species])  # noqa: E741


@lru_cache(maxsize=8)
def harmonics_sql(l_max: int, x: str = "dx/r", y: str = "dy/r", z: str = "dz/r") -> tuple[str, ...]:
    """Expressions of the real spherical harmonics of a unit vector, row by row, for Spark and DuckDB alike."""
    cos, sin = ["1e0"], ["0e0"]
    for _ in range(l_max):
        cos, sin = [*cos, f"(({x})*{cos[-1]}-({y})*{sin[-1]})"], [*sin, f"(({x})*{sin[-1]}+({y})*{cos[-1]})"]
    out = [""] * (l_max + 1) ** 2
    for m in range(l_max + 1):
        p = {m: f"{float(math.prod(range(1, 2 * m, 2)) or 1)!r}e0"}
        if m < l_max:
            p[m + 1] = f"({2 * m + 1}e0*({z})*{p[m]})"
        for l in range(m + 2, l_max + 1):  # noqa: E741
            p[l] = f"(({2 * l - 1}e0*({z})*{p[l - 1]}-{l + m - 1}e0*{p[l - 2]})/{l - m}e0)"
        for l in range(m, l_max + 1):  # noqa: E741
            norm = math.sqrt((2 * l + 1) / (4 * math.pi) * math.factorial(l - m) / math.factorial(l + m)) * (math.sqrt(2) if m else 1)
            out[lm_index(l, m)] = f"({norm!r}e0*{p[l]}*{cos[m]})"
            if m:
                out[lm_index(l, -m)] = f"({norm!r}e0*{p[l]}*{sin[m]})"
    return tuple(out)


def strength(i: int, j: int, l1: int, l2: int, order: int) -> float:
    """Amplitude of a component between shell i of one end and j of the other; swapped ends give the transposed block."""
    if (l1 + l2 + order) % 2:
        return 0.0
    size = (1 + 0.1 * (i + j)) / (1 + order) * (-1) ** (order // 2)
    if (l1, i) > (l2, j) and l1 != l2:
        sign = np.sign((clebsch(l1, l2, order) * clebsch(l2, l1, order).transpose(0, 2, 1)).sum())
        return float(size * sign * (-1) ** order)
    return float(size)


@lru_cache(maxsize=4)
def components(species: tuple[int, ...]) -> list[tuple]:
    """(z1, z2, i, j, l1, l2, L, strength) of every component of natural parity between these species."""
    return [
        (z1, z2, i, j, l1, l2, order, strength(i, j, l1, l2, order))
        for z1 in species for z2 in species
        for i, l1 in enumerate(SHELLS[z1]) for j, l2 in enumerate(SHELLS[z2])
        for order in range(abs(l1 - l2), l1 + l2 + 1) if (l1 + l2 + order) % 2 == 0
    ]


@lru_cache(maxsize=1)
def coefficients(l_max: int = 2) -> list[tuple]:
    """(l1, l2, L, M, m1, m2, c): coupling coefficients that aren't zero, rows counted from 0."""
    out = []
    for l1 in range(l_max + 1):
        for l2 in range(l_max + 1):
            for order in range(abs(l1 - l2), l1 + l2 + 1):
                c = clebsch(l1, l2, order)
                out += [(l1, l2, order, int(m), int(a), int(b), float(c[m, a, b])) for m, a, b in zip(*np.nonzero(np.abs(c) > 1e-12), strict=True)]
    return out


def coefficient_table(spark: SparkSession) -> DataFrame:
    return F.broadcast(spark.createDataFrame(coefficients(), "l1 int, l2 int, L int, M int, m1 int, m2 int, c double"))


def component_table(spark: SparkSession, species: tuple[int, ...]) -> DataFrame:
    return F.broadcast(spark.createDataFrame(components(species), "z1 int, z2 int, i int, j int, l1 int, l2 int, L int, k double"))


def shell_table(spark: SparkSession, species: tuple[int, ...]) -> DataFrame:
    """(z, shell, l, m, a): which shell and row each orbital is."""
    rows = []
    for z in species:
        a = 0
        for s, l in enumerate(SHELLS[z]):  # noqa: E741
            rows += [(z, s, l, m, a + m) for m in range(2 * l + 1)]
            a += 2 * l + 1
    return F.broadcast(spark.createDataFrame(rows, "z int, shell int, l int, m int, a int"))


def decay_sql(rc: float) -> str:
    return f"(exp(-(r-2e0)/1.5e0)*0.5e0*(1e0+cos({math.pi!r}e0*r/{rc}e0))*(1e0+(z1+z2)/100e0))"


def _harmonics(order: Column, m: Column) -> Column:
    return F.get("ys", order * order + m)


def with_species(edges: DataFrame, atoms: DataFrame) -> DataFrame:
    one = atoms.select(F.col("atom_id").alias("src"), F.col("species").alias("z1"))
    return edges.join(one, "src").join(atoms.select(F.col("atom_id").alias("dst"), F.col("species").alias("z2")), "dst")


def coupled(edges: DataFrame, atoms: DataFrame, r_cut: float, species: tuple[int, ...]) -> DataFrame:
    """(keys, z1, z2, i, j, l1, l2, L, M, y): components of the off-diagonal blocks of the stand-in."""
    ends = with_species(edges, atoms).withColumns({"amp": F.expr(decay_sql(r_cut)), "ys": F.array(*map(F.expr, harmonics_sql(4)))})
    rows = ends.join(component_table(edges.sparkSession, species), ["z1", "z2"])
    rows = rows.withColumn("M", F.explode(F.sequence(F.lit(0), 2 * F.col("L"))))
    return rows.select(*KEYS, "z1", "z2", "i", "j", "l1", "l2", "L", "M", (F.col("amp") * F.col("k") * _harmonics(F.col("L"), F.col("M"))).alias("y"))


def coupled_onsite(edges: DataFrame, atoms: DataFrame, r_cut: float, species: tuple[int, ...]) -> DataFrame:
    """(atom_id, z, i, j, l1, l2, L, M, y): components of the diagonal blocks: a constant of species and shell, and a share
    of what the neighbours' directions add up to. One aggregate over the edges, before shells are joined."""
    ends = with_species(edges, atoms)
    sums = ends.groupBy(F.col("dst").alias("atom_id")).agg(F.array(*(F.sum(F.expr(f"{decay_sql(r_cut)}*{y}")) for y in harmonics_sql(4))).alias("ys"))
    rows = atoms.select("atom_id", F.col("species").alias("z1"), F.col("species").alias("z2")).join(sums, "atom_id", "left")
    rows = rows.join(component_table(edges.sparkSession, species), ["z1", "z2"]).withColumn("M", F.explode(F.sequence(F.lit(0), 2 * F.col("L"))))
    level = F.when((F.col("L") == 0) & (F.col("i") == F.col("j")), (F.col("z1") * F.lit(-0.05) + F.col("i") * F.lit(0.25)) * F.sqrt(2 * F.col("l1") + 1)).otherwise(0.0)
    y = level + F.lit(ENVIRONMENT) * F.col("k") * F.coalesce(_harmonics(F.col("L"), F.col("M")), F.lit(0.0))
    return rows.select("atom_id", F.col("z1").alias("z"), "i", "j", "l1", "l2", "L", "M", y.alias("y"))


def uncouple(rows: DataFrame, keys: list[str], value: str = "y") -> DataFrame:
    """(keys, i, j, m1, m2, val) of components (keys, i, j, l1, l2, L, M, value): a broadcast join and an aggregate."""
    both = rows.join(coefficient_table(rows.sparkSession), ["l1", "l2", "L", "M"])
    return both.groupBy(*keys, "i", "j", "m1", "m2").agg(F.sum(F.col("c") * F.col(value)).alias("val"))


def couple(elements: DataFrame, keys: list[str], value: str = "val") -> DataFrame:
    """(keys, i, j, l1, l2, L, M, y) of elements (keys, i, j, l1, l2, m1, m2, value): the inverse of :func:`uncouple`."""
    both = elements.join(coefficient_table(elements.sparkSession), ["l1", "l2", "m1", "m2"])
    return both.groupBy(*keys, "i", "j", "l1", "l2", "L", "M").agg(F.sum(F.col("c") * F.col(value)).alias("y"))


def elements(shell_elements: DataFrame, z1: str, z2: str, species: tuple[int, ...]) -> DataFrame:
    """Elements with the places a and b in their block, from those by shell and row; z1 and z2 name the species columns."""
    shells = shell_table(shell_elements.sparkSession, species)
    out = shell_elements
    for z, shell, row, place in ((z1, "i", "m1", "a"), (z2, "j", "m2", "b")):
        table = shells.select(F.col("z").alias("_z"), F.col("shell").alias("_s"), F.col("m").alias("_m"), F.col("a").alias(place))
        out = out.join(table, (F.col(z) == F.col("_z")) & (F.col(shell) == F.col("_s")) & (F.col(row) == F.col("_m"))).drop("_z", "_s", "_m")
    return out


def offsets(atoms: DataFrame) -> DataFrame:
    """atom_id, n_orb, first: where each atom's orbitals begin, for these shells."""
    from . import hamiltonian

    n = F.lit(None).cast("int")
    for z in SHELLS:
        n = F.when(F.col("species") == z, orbitals(z)).otherwise(n)
    return hamiltonian.offsets(atoms, n)
