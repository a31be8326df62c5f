import numpy as np
import pytest

from orbitgraph.functions import tables
from orbitgraph.operators import metrics, partition
from orbitgraph.operators.structure import Cell


@pytest.mark.parametrize("parts", [3, 5, 6, 8])
def test_any_number_of_parts(spark, parts):
    pos = np.random.default_rng(2).random((240, 3)) * 10
    atoms = spark.createDataFrame([(i, 8, *map(float, p)) for i, p in enumerate(pos)], "atom_id long, species int, x double, y double, z double")
    degree = spark.createDataFrame([(i, 1) for i in range(240)], "atom_id long, n_in long")
    ranks, _ = partition.few_neighbour(atoms, degree, Cell((10.0, 10.0, 10.0)), 3, 2.0, parts_wanted=parts)
    sizes = [r["count"] for r in ranks.groupBy("rank").count().orderBy("rank").collect()]
    assert len(sizes) == parts and max(sizes) - min(sizes) <= 3


def test_spring_layout_keeps_a_ring_together():
    ring = [(i, (i + 1) % 8, 1.0) for i in range(8)]
    p = metrics.spring_layout(ring, 8)
    near = np.mean([np.linalg.norm(p[a] - p[b]) for a, b, _ in ring])
    far = np.mean([np.linalg.norm(p[i] - p[(i + 4) % 8]) for i in range(8)])
    assert np.isfinite(p).all() and near < far


def test_table_functions(spark):
    tables.register(spark)
    assert spark.sql("SELECT * FROM og_radius_images(10.0D, 10.0D, 4.0D, 5.0D)").count() == 3 * 3 * 5
    assert spark.sql("SELECT max(tile) AS m FROM og_tiles(2, 3, 4)").first().m == 23
    spark.range(64).selectExpr("id % 2 AS s", "id AS atom_id", "double(id % 7) AS x", "double(id % 5) AS y", "double(id % 3) AS z", "2 AS depth").createOrReplaceTempView("og_small")
    got = spark.sql("SELECT rank, count(*) AS n FROM og_small_bisection(TABLE(og_small) PARTITION BY s) GROUP BY rank").collect()
    assert sorted((r.rank, r.n) for r in got) == [(i, 16) for i in range(4)]


def test_min_cut_contracts_on_executors(spark):
    """Two dense clusters with one bridge: found whether or not the first levels are contracted on the executors."""
    from orbitgraph.operators import mincut

    pairs = [(a, b) for base in (0, 20) for a in range(base, base + 20) for b in range(base, base + 20) if a != b] + [(3, 27), (27, 3)]
    edges = spark.createDataFrame(pairs, "src long, dst long")
    for most in (10_000, 150):
        ranks = {r.atom_id: r.rank for r in mincut.min_cut(edges, 2, max_edges=most).collect()}
        assert len(ranks) == 40 and len({ranks[i] for i in range(20)}) == 1 and ranks[0] != ranks[20]
