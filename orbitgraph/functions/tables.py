"""Python table functions for SQL users: image shifts of a cell, tiles, and the partition of one small structure."""

from __future__ import annotations

import math
from collections.abc import Iterator
from itertools import product

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="sx int, sy int, sz int")
class RadiusImages:
    """Image shifts that a cutoff can reach in a box."""

    def eval(self, lx: float, ly: float, lz: float, r_cut: float) -> Iterator[tuple[int, int, int]]:
        reach = [math.ceil(float(r_cut) / float(side)) for side in (lx, ly, lz)]
        yield from product(*(range(-k, k + 1) for k in reach))


@udtf(returnType="tile int, ix int, iy int, iz int")
class Tiles:
    def eval(self, nx: int, ny: int, nz: int) -> Iterator[tuple[int, int, int, int]]:
        for t, (x, y, z) in enumerate(product(range(nx), range(ny), range(nz))):
            yield t, x, y, z


@udtf(returnType="atom_id bigint, rank int")
class SmallBisection:
    """Longest-axis bisection of one small structure given as a table (atom_id, x, y, z, depth); large ones go through
    ``operators.partition``. Meant for PARTITION BY structure: a partition's rows are held together."""

    def __init__(self) -> None:
        self.rows: list[tuple[int, float, float, float]] = []
        self.depth = 0

    def eval(self, row) -> None:
        self.rows.append((row["atom_id"], row["x"], row["y"], row["z"]))
        self.depth = row["depth"]

    def terminate(self) -> Iterator[tuple[int, int]]:
        def split(rows: list, depth: int, code: int) -> Iterator[tuple[int, int]]:
            if depth == 0 or len(rows) < 2:
                yield from ((r[0], code << depth) for r in rows)
                return
            axis = max((1, 2, 3), key=lambda a: max(r[a] for r in rows) - min(r[a] for r in rows))
            rows = sorted(rows, key=lambda r: (r[axis], r[0]))
            half = (len(rows) + 1) // 2
            yield from split(rows[:half], depth - 1, 2 * code)
            yield from split(rows[half:], depth - 1, 2 * code + 1)

        yield from split(self.rows, self.depth, 0)


def register(spark: SparkSession) -> None:
    spark.udtf.register("og_radius_images", RadiusImages)
    spark.udtf.register("og_tiles", Tiles)
    spark.udtf.register("og_small_bisection", SmallBisection)
