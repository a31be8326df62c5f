"""Radius graphs with periodic images, and what is measured on them.

An edge is keyed by (src, dst, sx, sy, sz): src sends to dst's image shifted by s cells; (dx, dy, dz) leads from src to
that image.
"""

from __future__ import annotations

import math
from itertools import product

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .structure import AXES, Cell

EDGE_KEY = ("src", "dst", "sx", "sy", "sz")


def _bins(cell: Cell, r_cut: float) -> tuple[list[int], list[float], list[int]]:
    """Boxes along each axis (no thinner than the cutoff where the cell allows), their widths, and how far to look."""
    n = [max(1, int(side // r_cut)) for side in cell.lengths]
    widths = [side / k for side, k in zip(cell.lengths, n, strict=True)]
    return n, widths, [math.ceil(r_cut / w) for w in widths]


def _measured(pairs: DataFrame, cell: Cell, r_cut: float, extra: list[str]) -> DataFrame:
    out = pairs.withColumns({f"d{a}": (F.col(f"{a}2") + F.col(f"s{a}") * F.lit(side)) - F.col(f"{a}1") for a, side in zip(AXES, cell.lengths, strict=True)})
    r2 = F.col("dx") * F.col("dx") + F.col("dy") * F.col("dy") + F.col("dz") * F.col("dz")
    apart = (F.col("src") != F.col("dst")) | (F.col("sx") != 0) | (F.col("sy") != 0) | (F.col("sz") != 0)
    return out.where((r2 <= F.lit(r_cut * r_cut)) & apart).select(*extra, *EDGE_KEY, "dx", "dy", "dz", F.sqrt(r2).alias("r"))


def frame_edges(frames: DataFrame, cell: Cell, r_cut: float) -> DataFrame:
    """Edges of every frame of a trajectory (column frame_id) in one plan: the frame joins the key of the boxes."""
    return radius_edges(frames, cell, r_cut, by="frame_id")


def radius_edges(atoms: DataFrame, cell: Cell, r_cut: float, method: str = "cells", by: str | None = None, dense: int | None = None) -> DataFrame:
    """All directed pairs within ``r_cut``, every periodic image counted.

    cells: an equi-join on boxes of at least the cutoff's width; only (id, x, y, z) of the source side is copied to the
    neighbouring boxes, each copy with its image shift. brute: every pair and image, for checking small structures.
    Positions must lie inside the box along periodic axes (``structure.wrap``). ``by``: a column (frame or structure)
    within which atoms see each other. ``dense``: boxes of more atoms are split, their atoms dealt out over parts that each
    see all neighbours, so that no dense spot is a hot group; costs a count of the boxes."""
    extra = [by] if by else []
    one = atoms.select(*extra, F.col("atom_id").alias("src"), *(F.col(a).alias(f"{a}1") for a in AXES))
    two = atoms.select(*extra, F.col("atom_id").alias("dst"), *(F.col(a).alias(f"{a}2") for a in AXES))
    if method == "brute":
        reach = [math.ceil(r_cut / side) if p else 0 for side, p in zip(cell.lengths, cell.periodic, strict=True)]
        shifts = F.array(*(F.struct(*(F.lit(v).alias(f"s{a}") for v, a in zip(s, AXES, strict=True))) for s in product(*(range(-k, k + 1) for k in reach))))
        pairs = (one.join(two, by) if by else one.crossJoin(two)).withColumn("_s", F.explode(shifts)).select("*", "_s.*").drop("_s")
        return _measured(pairs, cell, r_cut, extra)
    n, widths, look = _bins(cell, r_cut)
    box = lambda a, i, end: F.least(F.greatest(F.floor(F.col(f"{a}{end}") / F.lit(widths[i])).cast("int"), F.lit(0)), F.lit(n[i] - 1)) if cell.periodic[i] else F.floor(F.col(f"{a}{end}") / F.lit(widths[i])).cast("int")
    offsets = F.array(*(F.struct(*(F.lit(v).alias(f"o{a}") for v, a in zip(o, AXES, strict=True))) for o in product(*(range(-k, k + 1) for k in look))))
    seen = one.withColumn("_o", F.explode(offsets))
    for i, a in enumerate(AXES):
        raw = box(a, i, 1) + F.col(f"_o.o{a}")
        shift = F.floor(raw / F.lit(n[i])).cast("int") if cell.periodic[i] else F.lit(0)
        seen = seen.withColumns({f"s{a}": shift, f"b{a}": raw - shift * n[i]})
    here = two.withColumns({f"b{a}": box(a, i, 2) for i, a in enumerate(AXES)})
    # few bytes in, many pairs out: a stated number of partitions keeps AQE from merging them by their small input
    keys, parts = [*extra, *(f"b{a}" for a in AXES)], int(atoms.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    seen = seen.drop("_o")
    if dense:
        crowded = here.groupBy(*keys).agg(F.ceil(F.count(F.lit(1)) / dense).cast("int").alias("_parts")).where("_parts > 1")
        pieces = F.coalesce("_parts", F.lit(1))
        here = here.join(crowded, keys, "left").withColumn("_piece", F.pmod(F.col("dst"), pieces).cast("int")).drop("_parts")
        seen = seen.join(crowded, keys, "left").withColumn("_piece", F.explode(F.sequence(F.lit(0), pieces - 1))).drop("_parts")
        keys = [*keys, "_piece"]
    seen, here = seen.repartition(parts, *keys), here.repartition(parts, *keys)
    return _measured(seen.join(here, keys), cell, r_cut, extra)


def tile_edges(edges: DataFrame, n_atoms: int, nx: int, ny: int, nz: int) -> DataFrame:
    """Edges of a tiled structure from those of its cell, without another join: the image shift becomes the tile of the
    destination, and what leaves the tiling its new shift."""
    counts = (nx, ny, nz)
    t = F.col("t")
    at = ((t / (ny * nz)).cast("int"), (t / nz).cast("int") % ny, t % nz)
    out = edges.withColumn("t", F.explode(F.sequence(F.lit(0), F.lit(nx * ny * nz - 1))))
    raw = [at[i] + F.col(f"s{a}") for i, a in enumerate(AXES)]
    home = [F.pmod(r, F.lit(c)) for r, c in zip(raw, counts, strict=True)]
    to = (home[0] * ny + home[1]) * nz + home[2]
    return out.select(
        (F.col("src") + t.cast("long") * n_atoms).alias("src"),
        (F.col("dst") + to.cast("long") * n_atoms).alias("dst"),
        *(F.floor(raw[i] / F.lit(counts[i])).cast("int").alias(f"s{a}") for i, a in enumerate(AXES)),
        "dx", "dy", "dz", "r",
    )


def degree(edges: DataFrame, atoms: DataFrame | None = None) -> DataFrame:
    """atom_id and number of incoming edges; with ``atoms``, atoms without any have 0."""
    counted = edges.groupBy(F.col("dst").alias("atom_id")).agg(F.count(F.lit(1)).alias("n_in"))
    if atoms is None:
        return counted
    return atoms.select("atom_id").join(counted, "atom_id", "left").select("atom_id", F.coalesce("n_in", F.lit(0)).alias("n_in"))


def stats(edges: DataFrame, atoms: DataFrame) -> DataFrame:
    """One row: atoms, edges, degrees."""
    d = degree(edges, atoms)
    return d.agg(F.count(F.lit(1)).alias("n_atoms"), F.sum("n_in").alias("n_edges"), F.min("n_in").alias("min_degree"), F.max("n_in").alias("max_degree"), F.round(F.avg("n_in"), 6).alias("mean_degree"))


def cutoff_coverage(h_edges: DataFrame, cutoffs: list[float], weight: Column, eps: float) -> DataFrame:
    """Share of the elements above ``eps`` (and of the squared weight) that each cutoff keeps, in one pass."""
    big = F.abs(weight) > eps
    kept = [F.struct(F.lit(c).alias("r_cut"), (F.sum(F.when(big & (F.col("r") <= c), 1).otherwise(0))).alias("kept"), F.sum(F.when(F.col("r") <= c, weight * weight).otherwise(0.0)).alias("w")) for c in cutoffs]
    one = h_edges.agg(F.sum(F.when(big, 1).otherwise(0)).alias("total"), F.sum(weight * weight).alias("total_w"), F.array(*kept).alias("k"))
    return one.select("total", "total_w", F.inline("k")).select("r_cut", F.col("kept").cast("long").alias("kept"), F.col("total").cast("long").alias("total"), F.round(F.col("kept") / F.col("total"), 6).alias("coverage"), F.round(F.col("w") / F.col("total_w"), 6).alias("weight_coverage"))


def choose_cutoff(coverage: DataFrame, target: float = 0.993) -> DataFrame:
    """The smallest cutoff that reaches the target coverage."""
    return coverage.where(F.col("coverage") >= target).agg(F.min("r_cut").alias("r_cut"))
