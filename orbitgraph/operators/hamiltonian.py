"""Hamiltonian blocks: a two-centre stand-in for the exact matrix, splitting, coupling, assembling, symmetry, profiles."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

# orbitals of a species: one s, or s and three p; element order s, x, y, z
ORBITALS = {72: 4, 8: 1, 32: 4, 51: 4, 52: 4}
OFFSET_BLOCK = 4096


def n_orbitals(species: Column) -> Column:
    out = F.lit(None).cast("int")
    for z, n in ORBITALS.items():
        out = F.when(species == z, n).otherwise(out)
    return out


def offsets(atoms: DataFrame, n_orb: Column | None = None) -> DataFrame:
    """atom_id, n_orb, first: where the atom's orbitals begin. Prefix sums in two levels (within and over blocks of ids),
    so that no window runs over all atoms."""
    rows = atoms.select("atom_id", (n_orbitals(F.col("species")) if n_orb is None else n_orb).alias("n_orb"), F.floor(F.col("atom_id") / OFFSET_BLOCK).alias("b"))
    sums = rows.groupBy("b").agg(F.sum("n_orb").alias("s"))
    # the blocks are few (one for each 4,096 atoms); their own prefix is an aggregate over a range join of block rows
    upto = sums.alias("p").join(sums.alias("q"), F.col("q.b") < F.col("p.b"), "left").groupBy(F.col("p.b").alias("b")).agg(F.coalesce(F.sum("q.s"), F.lit(0)).alias("base"))
    inner = F.sum("n_orb").over(Window.partitionBy("b").orderBy("atom_id").rowsBetween(Window.unboundedPreceding, -1))
    return rows.withColumn("inner", F.coalesce(inner, F.lit(0))).join(upto, "b").select("atom_id", "n_orb", (F.col("base") + F.col("inner")).cast("long").alias("first"))


# the two-centre integrals as SQL text, shared with the DuckDB twin: (species pair) z1, z2, distance r, cutoff rc
def decay(rc: float) -> str:
    return f"exp(-(r-2e0)/1.5e0)*0.5e0*(1e0+cos({3.141592653589793}e0*r/{rc}e0))*(1e0+(z1+z2)/100e0)"


DIRECTION = "CASE {0} WHEN 1 THEN dx/r WHEN 2 THEN dy/r ELSE dz/r END"


def two_centre_value(rc: float) -> str:
    na, nb = DIRECTION.format("a"), DIRECTION.format("b")
    return f"""({decay(rc)})*CASE WHEN a=0 AND b=0 THEN -1e0 WHEN a=0 THEN 1.2e0*({nb}) WHEN b=0 THEN -1.2e0*({na})
 ELSE ({na})*({nb})*(1.6e0-(-0.5e0)) + CASE WHEN a=b THEN -0.5e0 ELSE 0e0 END END"""


def two_centre(edges: DataFrame, atoms: DataFrame, r_cut: float) -> DataFrame:
    """Off-diagonal elements (src, dst, sx, sy, sz, r, a, b, val) from distance and direction cosines."""
    one = atoms.select(F.col("atom_id").alias("src"), F.col("species").alias("z1"), n_orbitals(F.col("species")).alias("o1"))
    two = atoms.select(F.col("atom_id").alias("dst"), F.col("species").alias("z2"), n_orbitals(F.col("species")).alias("o2"))
    pairs = edges.join(one, "src").join(two, "dst")
    rows = pairs.withColumn("a", F.explode(F.sequence(F.lit(0), F.col("o1") - 1))).withColumn("b", F.explode(F.sequence(F.lit(0), F.col("o2") - 1)))
    return rows.select("src", "dst", "sx", "sy", "sz", "r", "z1", "z2", "a", "b", F.expr(two_centre_value(r_cut)).alias("val"))


def onsite(atoms: DataFrame) -> DataFrame:
    """Diagonal elements: a constant of the species and the orbital."""
    rows = atoms.withColumn("a", F.explode(F.sequence(F.lit(0), n_orbitals(F.col("species")) - 1)))
    return rows.select(F.col("atom_id").alias("src"), F.col("atom_id").alias("dst"), "a", F.col("a").alias("b"), (F.col("species") * F.lit(-0.05) + F.col("a") * F.lit(0.25)).alias("val"))


def to_coo(elements: DataFrame, offs: DataFrame) -> DataFrame:
    """Global (row, col, val), images of one pair folded by adding up."""
    one = offs.select(F.col("atom_id").alias("src"), F.col("first").alias("f1"))
    two = offs.select(F.col("atom_id").alias("dst"), F.col("first").alias("f2"))
    placed = elements.join(one, "src").join(two, "dst")
    return placed.groupBy((F.col("f1") + F.col("a")).alias("row"), (F.col("f2") + F.col("b")).alias("col")).agg(F.sum("val").alias("val"))


def orbital_map(offs: DataFrame) -> DataFrame:
    """(orbital, atom_id, k): which atom and element each global index is; the range join row -> atom as an equi-join."""
    return offs.select("atom_id", "first", F.explode(F.sequence(F.lit(0), F.col("n_orb") - 1)).alias("k")).select((F.col("first") + F.col("k")).alias("orbital"), "atom_id", "k")


def to_blocks(coo: DataFrame, offs: DataFrame) -> DataFrame:
    """Atom-pair blocks (i, j, ni, nj, kind, block row-major); node blocks on the diagonal, edge blocks off it."""
    m = orbital_map(offs)
    rows = coo.join(m.select(F.col("orbital").alias("row"), F.col("atom_id").alias("i"), F.col("k").alias("a")), "row").join(m.select(F.col("orbital").alias("col"), F.col("atom_id").alias("j"), F.col("k").alias("b")), "col")
    sizes = offs.select("atom_id", "n_orb")
    blocks = rows.groupBy("i", "j").agg(F.map_from_entries(F.collect_list(F.struct((F.col("a") * 64 + F.col("b")).alias("k"), "val"))).alias("m"))
    blocks = blocks.join(sizes.select(F.col("atom_id").alias("i"), F.col("n_orb").alias("ni")), "i").join(sizes.select(F.col("atom_id").alias("j"), F.col("n_orb").alias("nj")), "j")
    cells = F.flatten(F.transform(F.sequence(F.lit(0), F.col("ni") - 1), lambda a: F.transform(F.sequence(F.lit(0), F.col("nj") - 1), lambda b: F.coalesce(F.try_element_at(F.col("m"), a * 64 + b), F.lit(0.0)))))
    return blocks.select("i", "j", "ni", "nj", F.when(F.col("i") == F.col("j"), "node").otherwise("edge").alias("kind"), cells.alias("block"))


def assemble(blocks: DataFrame, offs: DataFrame) -> DataFrame:
    """Global (row, col, val) of blocks: the inverse of :func:`to_blocks`."""
    one = offs.select(F.col("atom_id").alias("i"), F.col("first").alias("f1"))
    two = offs.select(F.col("atom_id").alias("j"), F.col("first").alias("f2"))
    cells = blocks.join(one, "i").join(two, "j").select("f1", "f2", "nj", F.posexplode("block").alias("p", "val"))
    return cells.groupBy((F.col("f1") + F.floor(F.col("p") / F.col("nj"))).alias("row"), (F.col("f2") + F.col("p") % F.col("nj")).alias("col")).agg(F.sum("val").alias("val"))


def symmetrise(coo: DataFrame) -> DataFrame:
    """(H + Hᵀ)/2 without a self-join: both orders added up in one aggregate."""
    both = coo.select("row", "col", "val").unionAll(coo.select(F.col("col").alias("row"), F.col("row").alias("col"), "val"))
    return both.groupBy("row", "col").agg((F.sum("val") / 2).alias("val"))


def couple_pp(block: Column) -> Column:
    """A 3×3 block (row-major x, y, z) in the coupled basis: L=0 trace, L=1 antisymmetric, L=2 symmetric traceless."""
    g = lambda i, j: F.get(block, F.lit(3 * i + j))
    s2, s3, s6 = 2**0.5, 3**0.5, 6**0.5
    return F.array(
        (g(0, 0) + g(1, 1) + g(2, 2)) / F.lit(s3),
        (g(1, 2) - g(2, 1)) / F.lit(s2), (g(2, 0) - g(0, 2)) / F.lit(s2), (g(0, 1) - g(1, 0)) / F.lit(s2),
        (g(0, 1) + g(1, 0)) / F.lit(s2), (g(1, 2) + g(2, 1)) / F.lit(s2), (g(2, 2) * 2 - g(0, 0) - g(1, 1)) / F.lit(s6), (g(0, 2) + g(2, 0)) / F.lit(s2), (g(0, 0) - g(1, 1)) / F.lit(s2),
    )


def uncouple_pp(coupled: Column) -> Column:
    """Inverse of :func:`couple_pp` (the transform is orthogonal)."""
    c = lambda k: F.get(coupled, F.lit(k))
    s2, s3, s6 = 2**0.5, 3**0.5, 6**0.5
    xx = c(0) / F.lit(s3) - c(6) / F.lit(s6) + c(8) / F.lit(s2)
    yy = c(0) / F.lit(s3) - c(6) / F.lit(s6) - c(8) / F.lit(s2)
    zz = c(0) / F.lit(s3) + c(6) * 2 / F.lit(s6)
    half = lambda a, b: (a + b) / F.lit(s2)
    return F.array(xx, half(c(4), c(3)), half(c(7), -c(2)), half(c(4), -c(3)), yy, half(c(5), c(1)), half(c(7), c(2)), half(c(5), -c(1)), zz)


def magnitude_vs_distance(elements: DataFrame, width: float) -> DataFrame:
    """Largest magnitude and count by species pair and distance bin."""
    lo, hi = F.least("z1", "z2"), F.greatest("z1", "z2")
    return elements.groupBy(lo.alias("za"), hi.alias("zb"), F.floor(F.col("r") / F.lit(width)).cast("int").alias("bin")).agg(F.round(F.max(F.abs("val")), 6).alias("largest"), F.count(F.lit(1)).alias("n"))


def shape(coo: DataFrame, offs: DataFrame) -> DataFrame:
    """Size, stored elements and share of the full matrix."""
    size = offs.agg(F.sum("n_orb").cast("long").alias("size"))
    return coo.agg(F.count(F.lit(1)).alias("nnz")).crossJoin(size).select("size", "nnz", F.round(F.col("nnz") / (F.col("size") * F.col("size")), 6).alias("density"))
