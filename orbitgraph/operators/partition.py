"""Partitioners: few-neighbour bisection and the simpler placements it is compared with."""

from __future__ import annotations

import json
import math
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .structure import AXES, Cell

BINS = 4096


@dataclass
class Part:
    """What the driver keeps of one part: cuts so far by axis, and the choices made on the way."""

    code: int
    cuts: tuple[int, int, int]
    axes: str = ""
    leaves: int = 1


@dataclass
class Tree:
    """Opening origins and, for every level and code, the axis, coordinate and atom id of the cut."""

    origins: tuple[float | None, float | None, float | None]
    cell: Cell
    levels: list[dict[int, tuple[int, float, int]]] = field(default_factory=list)
    axes: dict[int, str] = field(default_factory=dict)
    table: DataFrame | None = None  # persisted: the ranks come from it


def choose_axis(extent: tuple[float, float, float], cuts: tuple[int, int, int], reach: float, tie: str = "index") -> int:
    """Axis whose cut brings the fewest neighbouring parts: one for an axis that was only opened so far, else the parts
    that a slab of this extent reaches on both sides. An axis that was neither opened nor cut goes first. Ties: the last
    axis, or the longest one."""

    never = [i for i in range(3) if cuts[i] == 0 and extent[i] > 0]
    if never:
        return never[0]

    def expected(i: int) -> float:
        if extent[i] <= 0:
            return math.inf
        return 1 if cuts[i] <= 1 else math.ceil(2 * reach / extent[i])

    cost = [expected(i) for i in range(3)]
    best = [i for i in range(3) if cost[i] == min(cost)]
    return max(best) if tie == "index" else max(best, key=lambda i: (extent[i], i))


def _crossing(state: DataFrame, value: Column, low: Column, span: Column, share: tuple[Column, Column] | None = None) -> list:
    """For each code the last atom of the shortest prefix, in (value, atom_id) order, with at least its share (numerator,
    denominator; half by default) of the weight.

    First a histogram of weights finds the bin where the share is reached, then only that bin's atoms are put in order; the
    driver gets a row for each part."""
    bin_ = F.when(span > 0, F.least(F.floor((value - low) / span * BINS), F.lit(BINS - 1))).otherwise(0).cast("int")
    num, den = share or (F.lit(1), F.lit(2))
    below = lambda upto, w, total: (upto - w) * den < total * num
    binned = state.select("code", "atom_id", "w", value.alias("v"), bin_.alias("bin"))
    sums = binned.groupBy("code", "bin").agg(F.sum("w").alias("bw"))
    run = Window.partitionBy("code").orderBy("bin")
    sums = sums.withColumns({"upto": F.sum("bw").over(run.rowsBetween(Window.unboundedPreceding, 0)), "total": F.sum("bw").over(Window.partitionBy("code"))})
    cross = sums.where(below(F.col("upto"), F.col("bw"), F.col("total"))).groupBy("code").agg(F.max(F.struct("bin", (F.col("upto") - F.col("bw")).alias("before"), "total")).alias("c"))
    inside = binned.join(F.broadcast(cross.select("code", F.col("c.bin").alias("bin"), F.col("c.before").alias("before"), F.col("c.total").alias("total"))), ["code", "bin"])
    order = Window.partitionBy("code").orderBy("v", "atom_id").rowsBetween(Window.unboundedPreceding, 0)
    inside = inside.withColumn("upto", F.col("before") + F.sum("w").over(order))
    last = inside.where(below(F.col("upto"), F.col("w"), F.col("total"))).groupBy("code").agg(F.max(F.struct("v", "atom_id")).alias("m"))
    return last.select("code", F.col("m.v").alias("v"), F.col("m.atom_id").alias("atom_id")).collect()


def _by_code(values: dict, kind: str, level: int) -> Column:
    """Value of the row's code, null where it has none: an array with a place for each code of the level, as a text of one
    literal, so that plans stay small however many parts there are."""
    if len(values) == 1 << level and len(set(map(repr, values.values()))) == 1 and not kind.startswith("struct"):
        return F.lit(values[0]).cast(kind)
    known = json.dumps([values.get(c) for c in range(1 << level)])
    return F.element_at(F.from_json(F.lit(known), f"array<{kind}>"), (F.col("code") + 1).cast("int"))


def along(axis: Column) -> Column:
    return F.when(axis == 0, F.col("x")).when(axis == 1, F.col("y")).otherwise(F.col("z"))


def few_neighbour(
    atoms: DataFrame, degree: DataFrame | None, cell: Cell, depth: int, reach: float, opening: str = "ring", tie: str = "index", weight: str = "degree", extent: str = "positions", parts_wanted: int | None = None, keep: tuple[str, ...] = ()
) -> tuple[DataFrame, Tree]:
    """Recursive, degree-balanced, periodicity-aware bisection into 2**depth parts, or into ``parts_wanted`` parts of
    equal weight (at most 2**depth), a part of k leaves being cut at ceil(k/2)/k of its weight.

    All parts of a level are cut together: a summary, a histogram and the order inside one bin, each an aggregate whose
    result has a row for each part. opening: "ring" moves the origin of every periodic axis to its weighted median
    before the first cut and spends no level; "split" counts the axes as never opened and cuts them right away.
    weight: "degree" or "unit". extent: of the "positions", or of the "box". degree: None if the atoms have their n_in. Returns
    (atom_id, rank, path), with the columns ``keep`` of the atoms, and the tree."""
    w = F.coalesce(F.col("n_in"), F.lit(0)).cast("long") if weight == "degree" else F.lit(1).cast("long")
    weighed = atoms if degree is None else atoms.join(degree, "atom_id", "left")
    state = weighed.select("atom_id", *AXES, *keep, w.alias("w"), F.lit(0).cast("long").alias("code")).persist()
    origins: list[float | None] = [None, None, None]
    if opening == "ring":
        # the three openings are one job: each axis is a part of its own here
        turned = [i for i in range(3) if cell.periodic[i]]
        each = state.select("atom_id", "w", F.inline(F.array(*(F.struct(F.lit(i).cast("long").alias("code"), F.col(AXES[i]).alias("at"), F.lit(cell.lengths[i]).alias("side")) for i in turned)))) if turned else None
        for r in _crossing(each, F.col("at"), F.lit(0.0), F.col("side")) if turned else ():
            origins[r.code] = r.v
        origins = [0.0 if i in turned and o is None else o for i, o in enumerate(origins)]
        state = state.withColumns({a: _rotated(a, origins[i], cell.lengths[i]) for i, a in enumerate(AXES) if origins[i] is not None})
    start = tuple(1 if opening == "ring" and p else 0 if p else 2 for p in cell.periodic)
    parts, tree = {0: Part(0, start, leaves=parts_wanted or 1 << depth)}, Tree(tuple(origins), cell)
    before = None
    for level in range(depth):
        rows = state.groupBy("code").agg(F.count(F.lit(1)).alias("n"), *(f(a).alias(f"{a}{e}") for a in AXES for f, e in ((F.min, "lo"), (F.max, "hi")))).collect()
        if before is not None:
            before.unpersist()  # the summary has read all of this level's table
        plan = {}
        for r in rows:
            if parts[r.code].leaves == 1:
                continue  # done: it stays as it is, on the left side of the levels to come
            box = tuple((r[f"{a}hi"] - r[f"{a}lo"]) if extent == "positions" else cell.lengths[i] for i, a in enumerate(AXES))
            axis = choose_axis(box, parts[r.code].cuts, reach, tie)
            plan[r.code] = (axis, r[f"{AXES[axis]}lo"], r[f"{AXES[axis]}hi"] - r[f"{AXES[axis]}lo"])
        leaves = {c: parts[c].leaves for c in plan}
        share = (_by_code({c: (k + 1) // 2 for c, k in leaves.items()}, "long", level), _by_code(leaves, "long", level))
        live = state.withColumn("_at", _by_code({c: dict(zip(("axis", "low", "span"), p, strict=True)) for c, p in plan.items()}, "struct<axis:int,low:double,span:double>", level))
        live = live.where(F.col("code").isin(*plan)) if len(plan) < len(parts) else live
        found = _crossing(live, along(F.col("_at.axis")), F.col("_at.low"), F.col("_at.span"), share)
        cut = {r.code: (plan[r.code][0], r.v, r.atom_id) for r in found}
        tree.levels.append(cut)
        value, at, ident = along(F.col("_cut.axis")), F.col("_cut.v"), F.col("_cut.id")
        right = F.coalesce((value > at) | ((value == at) & (F.col("atom_id") > ident)), F.lit(False))
        # each level reads the persisted table of the last one: a chain of all cuts would grow without bound in the optimizer
        # of the driver; one literal for a level's cuts keeps the nested plans short
        state = state.withColumn("_cut", _by_code({c: dict(zip(("axis", "v", "id"), v, strict=True)) for c, v in cut.items()}, "struct<axis:int,v:double,id:long>", level))
        before, state = state, state.withColumn("code", F.col("code") * 2 + F.when(right, 1).otherwise(0)).drop("_cut").persist()
        split: dict[int, Part] = {2 * c: Part(2 * c, p.cuts, p.axes) for c, p in parts.items() if c not in cut}
        for c, (axis, _, _) in cut.items():
            cuts = tuple(k + (2 if k == 0 else 1) * (i == axis) for i, k in enumerate(parts[c].cuts))
            k = parts[c].leaves
            for side, mine in ((0, (k + 1) // 2), (1, k // 2)):
                split[2 * c + side] = Part(2 * c + side, cuts, parts[c].axes + AXES[axis], mine)
        parts = split
    if before is not None:
        state.count()
        before.unpersist()
    tree.axes, tree.table = {c: p.axes for c, p in parts.items()}, state
    rank = F.col("code").cast("int")
    if parts_wanted:  # codes of leaves that ended early leave gaps: ranks count the leaves in order of code
        rank = F.element_at(F.create_map(*(x for i, c in enumerate(sorted(parts)) for x in (F.lit(c).cast("long"), F.lit(i)))), F.col("code"))
    return state.select("atom_id", *keep, rank.alias("rank"), F.lpad(F.bin("code"), depth, "0").alias("path")), tree


def coarser(ranks: DataFrame, levels: int) -> DataFrame:
    """Ranks of the same bisection, ended ``levels`` levels earlier: its parts nest, so nothing is partitioned anew."""
    return ranks.withColumn("rank", F.shiftright("rank", levels))


def _rotated(axis: str, origin: float | None, side: float) -> Column:
    """Coordinate counted from just behind the opening cut: what lay up to the cut comes last."""
    c = F.col(axis)
    return F.when(c > F.lit(origin), c - F.lit(origin)).otherwise(c - F.lit(origin) + F.lit(side))


def apply_tree(atoms: DataFrame, tree: Tree) -> DataFrame:
    """Ranks of atoms (of a later frame, say) by the cuts of a tree, without partitioning anew: no shuffle at all."""
    out = atoms.withColumn("code", F.lit(0).cast("long"))
    moved = {a: _rotated(a, tree.origins[i], tree.cell.lengths[i]) for i, a in enumerate(AXES) if tree.origins[i] is not None}
    out = out.withColumns(moved)
    for level in tree.levels:
        side = F.lit(0)
        for c, (axis, v, ident) in sorted(level.items()):
            x = F.col(AXES[axis])
            side = F.when(F.col("code") == c, F.when((x > v) | ((x == v) & (F.col("atom_id") > ident)), 1).otherwise(0)).otherwise(side)
        out = out.withColumn("code", F.col("code") * 2 + side)
    return out.select("atom_id", F.col("code").cast("int").alias("rank"))


def sequential_rank(parts: int, n_atoms: int) -> Column:
    return F.floor(F.col("atom_id") * parts / F.lit(n_atoms)).cast("int")


def sequential(atoms: DataFrame, parts: int, n_atoms: int) -> DataFrame:
    """Contiguous ranges of dense ids: arithmetic, no sort."""
    return atoms.select("atom_id", sequential_rank(parts, n_atoms).alias("rank"))


def random_rank(parts: int, multiplier: int = 48_271, offset: int = 12_345, modulus: int = 2_147_483_647) -> Column:
    once = ((F.col("atom_id") + 1) * multiplier + offset) % modulus
    return ((once * multiplier + offset) % modulus % parts).cast("int")


def random(atoms: DataFrame, parts: int, multiplier: int = 48_271, offset: int = 12_345, modulus: int = 2_147_483_647) -> DataFrame:
    """Placement by a linear congruence of the id, applied twice so that small ids are mixed as well."""
    return atoms.select("atom_id", random_rank(parts, multiplier, offset, modulus).alias("rank"))


def slabs(atoms: DataFrame, cell: Cell, parts: int, axis: str = "z") -> DataFrame:
    """Equal slabs of one axis."""
    side = cell.lengths[AXES.index(axis)]
    return atoms.select("atom_id", F.least(F.floor(F.col(axis) / F.lit(side) * parts), F.lit(parts - 1)).cast("int").alias("rank"))


def bricks_rank(cell: Cell, counts: tuple[int, int, int]) -> Column:
    at = [F.least(F.floor(F.col(a) / F.lit(side) * n), F.lit(n - 1)).cast("int") for a, side, n in zip(AXES, cell.lengths, counts, strict=True)]
    return (at[0] * counts[1] + at[1]) * counts[2] + at[2]


def bricks(atoms: DataFrame, cell: Cell, counts: tuple[int, int, int]) -> DataFrame:
    """Equal bricks of all three axes."""
    return atoms.select("atom_id", bricks_rank(cell, counts).alias("rank"))


def coordinate_bisection(atoms: DataFrame, degree: DataFrame, cell: Cell, depth: int) -> tuple[DataFrame, Tree]:
    """Longest-axis bisection that knows nothing of periodicity or reach: an ablation of the few-neighbour rule."""
    open_box = Cell(cell.lengths, (False, False, False))
    return few_neighbour(atoms, degree, open_box, depth, reach=1e-9, opening="split", tie="longest")
