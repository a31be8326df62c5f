"""The structures that stand for the published ones, built from the given tables, and their SQL twins."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession

from ..operators import graph, structure
from ..operators.structure import Cell


@dataclass(frozen=True)
class Kind:
    table: str
    key: str
    density: float
    species: str


KINDS = {
    "oxide": Kind("part", "p_partkey", 0.083, "oxide"),
    "pcm_a": Kind("customer", "c_custkey", 0.0314, "pcm"),
    "pcm_c": Kind("supplier", "s_suppkey", 0.0314, "pcm"),
    "small_box": Kind("supplier", "s_suppkey", 0.083, "oxide"),
}


def load(spark: SparkSession, sf_dir: str, name: str, skew_x: bool = False) -> tuple[DataFrame, Cell, int]:
    """Atoms, cell and number of atoms of a structure (the count is one number, read from the file's footer)."""
    kind = KINDS[name]
    rows = spark.read.parquet(f"{sf_dir}/{kind.table}.parquet").select(kind.key)
    n = rows.count()
    cell = Cell.cube(n, kind.density)
    return structure.atoms(rows, kind.key, cell, kind.species, skew_x), cell, n


def edges(spark: SparkSession, sf_dir: str, name: str, r_cut: float, skew_x: bool = False) -> tuple[DataFrame, DataFrame, Cell, int]:
    atoms, cell, n = load(spark, sf_dir, name, skew_x)
    return graph.radius_edges(atoms, cell, r_cut), atoms, cell, n


def atoms_sql(name: str, skew_x: bool = False) -> str:
    """CTEs ``cell`` (l, n) and ``atoms`` for DuckDB."""
    kind = KINDS[name]
    k = kind.key
    unit = [f"(({k}*{m})%{p})/{p}e0" for m, p in structure.SPREAD]
    x = f"({unit[0]}*({unit[0]}))" if skew_x else unit[0]
    species = f"CASE WHEN {k}%3=0 THEN 72 ELSE 8 END" if kind.species == "oxide" else f"CASE WHEN {k}%7=0 THEN 32 WHEN {k}%7<=2 THEN 51 ELSE 52 END"
    return f"""
cell AS (SELECT count(*) AS n, round(pow(count(*)/{kind.density}e0, 1e0/3e0), 3) AS l FROM {kind.table}),
atoms AS (SELECT CAST({k} AS BIGINT) AS atom_id, {species} AS species, {x}*l AS x, {unit[1]}*l AS y, {unit[2]}*l AS z FROM {kind.table}, cell)"""


def edges_sql(name: str, r_cut: float, skew_x: bool = False, images: int = 0) -> str:
    """CTE ``edges`` after those of :func:`atoms_sql`: the nearest image of each pair, or all of up to ``images`` cells."""
    if images:
        span = f"(SELECT unnest(range({-images}, {images + 1}))::INT"
        pairs = f"SELECT i.atom_id AS src, j.atom_id AS dst, a.s AS sx, b.s AS sy, c.s AS sz, (j.x+a.s*l)-i.x AS dx, (j.y+b.s*l)-i.y AS dy, (j.z+c.s*l)-i.z AS dz FROM atoms i, atoms j, cell, {span} AS s) a, {span} AS s) b, {span} AS s) c"
    else:
        near = "CAST(-round((j.{0}-i.{0})/l) AS INT)"
        pairs = f"""SELECT src, dst, sx, sy, sz, (x2+sx*l)-x1 AS dx, (y2+sy*l)-y1 AS dy, (z2+sz*l)-z1 AS dz FROM (
  SELECT i.atom_id AS src, j.atom_id AS dst, {near.format("x")} AS sx, {near.format("y")} AS sy, {near.format("z")} AS sz, i.x AS x1, i.y AS y1, i.z AS z1, j.x AS x2, j.y AS y2, j.z AS z2, l FROM atoms i, atoms j, cell)"""
    return f""",
edges AS (SELECT src, dst, sx, sy, sz, dx, dy, dz, sqrt(dx*dx+dy*dy+dz*dz) AS r FROM ({pairs}) WHERE dx*dx+dy*dy+dz*dz <= {r_cut * r_cut}e0 AND (src<>dst OR sx<>0 OR sy<>0 OR sz<>0))"""


def with_edges_sql(name: str, r_cut: float, skew_x: bool = False, images: int = 0) -> str:
    return "WITH " + atoms_sql(name, skew_x) + edges_sql(name, r_cut, skew_x, images)


def bisection_sql(depth: int, reach: float, opening: str = "ring", tie: str = "index", weight: str = "degree", sides: tuple[str, str, str] = ("l", "l", "l")) -> str:
    """CTEs ending in ``ranks`` (atom_id, rank), the few-neighbour bisection unrolled level by level, after ``edges``."""
    w = "coalesce(n_in, 0)" if weight == "degree" else "1"
    out = f""",
deg AS (SELECT dst AS atom_id, count(*) AS n_in FROM edges GROUP BY dst),
raw0 AS (SELECT atom_id, x, y, z, {w} AS w FROM atoms LEFT JOIN deg USING (atom_id))"""
    if opening == "ring":
        for a in "xyz":
            out += f""",
open_{a} AS (SELECT {a} AS o FROM (SELECT {a}, atom_id, sum(w) OVER (ORDER BY {a}, atom_id ROWS UNBOUNDED PRECEDING) - w AS before, sum(w) OVER () AS total FROM raw0) WHERE before*2 < total ORDER BY {a} DESC, atom_id DESC LIMIT 1)"""
        moved = ", ".join(f"CASE WHEN {a} > open_{a}.o THEN {a} - open_{a}.o ELSE {a} - open_{a}.o + {side} END AS {a}" for a, side in zip("xyz", sides, strict=True))
        out += f""",
lev0 AS (SELECT atom_id, w, {moved}, 0 AS code, 1 AS cx, 1 AS cy, 1 AS cz FROM raw0, cell, open_x, open_y, open_z)"""
    else:
        out += """,
lev0 AS (SELECT atom_id, w, x, y, z, 0 AS code, 0 AS cx, 0 AS cy, 0 AS cz FROM raw0)"""
    for i in range(depth):
        cost = {a: f"CASE WHEN c{a} <= 1 THEN 1 ELSE ceil({2 * reach}e0/e{a}) END" for a in "xyz"}
        if tie == "index":
            choice = "CASE WHEN kz <= ky AND kz <= kx THEN 2 WHEN ky <= kx THEN 1 ELSE 0 END"
        else:
            k = {a: f"CASE WHEN k{a} = least(kx, ky, kz) THEN e{a} ELSE -1e0 END" for a in "xyz"}
            choice = f"CASE WHEN {k['z']} >= {k['y']} AND {k['z']} >= {k['x']} THEN 2 WHEN {k['y']} >= {k['x']} THEN 1 ELSE 0 END"
        choice = f"CASE WHEN cx = 0 THEN 0 WHEN cy = 0 THEN 1 WHEN cz = 0 THEN 2 ELSE {choice} END"
        step = "CASE WHEN c{0} = 0 THEN 2 ELSE 1 END"
        out += f""",
ext{i} AS (SELECT code, any_value(cx) AS cx, any_value(cy) AS cy, any_value(cz) AS cz, max(x)-min(x) AS ex, max(y)-min(y) AS ey, max(z)-min(z) AS ez FROM lev{i} GROUP BY code),
axis{i} AS (SELECT code, {choice} AS axis FROM (SELECT *, {", ".join(f"{cost[a]} AS k{a}" for a in "xyz")} FROM ext{i})),
val{i} AS (SELECT t.*, axis, CASE axis WHEN 0 THEN x WHEN 1 THEN y ELSE z END AS v FROM lev{i} t JOIN axis{i} USING (code)),
cum{i} AS (SELECT *, sum(w) OVER (PARTITION BY code ORDER BY v, atom_id ROWS UNBOUNDED PRECEDING) - w AS before, sum(w) OVER (PARTITION BY code) AS total FROM val{i}),
lev{i + 1} AS (SELECT atom_id, w, x, y, z, code*2 + CASE WHEN before*2 < total THEN 0 ELSE 1 END AS code, {", ".join(f"c{a} + CASE WHEN axis = {j} THEN {step.format(a)} ELSE 0 END AS c{a}" for j, a in enumerate("xyz"))} FROM cum{i})"""
    return out + f""",
ranks AS (SELECT atom_id, CAST(code AS INT) AS rank FROM lev{depth})"""


PLAN_SQL = """,
both_ends AS (SELECT e.*, a.rank AS src_rank, b.rank AS dst_rank FROM edges e JOIN ranks a ON a.atom_id = e.src JOIN ranks b ON b.atom_id = e.dst),
plan AS (SELECT *, CAST(row_number() OVER (PARTITION BY from_rank, to_rank ORDER BY atom_id) - 1 AS INT) AS slot FROM (SELECT DISTINCT src_rank AS from_rank, dst_rank AS to_rank, src AS atom_id FROM both_ends WHERE src_rank <> dst_rank)),
all_ranks AS (SELECT CAST(unnest(range(8)) AS INT) AS rank)"""


def tiled_sql(name: str, r_cut: float, nx: int, ny: int, nz: int) -> str:
    """CTEs ``cell``, ``atoms`` and ``edges`` of a tiled structure, from those of its cell."""
    base = with_edges_sql(name, r_cut).replace("atoms AS (", "cell_atoms AS (").replace("atoms i, atoms j", "cell_atoms i, cell_atoms j").replace("edges AS (", "cell_edges AS (")
    home = lambda i, s, n: f"((({i}+{s})%{n}+{n})%{n})"
    return base + f""",
tl AS (SELECT t//{ny * nz} AS ix, t//{nz}%{ny} AS iy, t%{nz} AS iz, t FROM (SELECT unnest(range({nx * ny * nz})) AS t)),
atoms AS (SELECT atom_id + t*n AS atom_id, species, x + ix*l AS x, y + iy*l AS y, z + iz*l AS z FROM cell_atoms, cell, tl),
edges AS (SELECT src + t*n AS src, dst + (({home("ix", "sx", nx)}*{ny} + {home("iy", "sy", ny)})*{nz} + {home("iz", "sz", nz)})*n AS dst, r FROM cell_edges, cell, tl)"""
