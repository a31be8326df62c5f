import numpy as np
import pytest
from pyspark.sql import functions as F

import ref
from orbitgraph.operators import exchange, graph, metrics, mincut, partition, structure
from orbitgraph.operators.structure import Cell
from orbitgraph.plans import structures


def frame(spark, pos):
    return spark.createDataFrame([(i, 8, *map(float, p)) for i, p in enumerate(pos)], "atom_id long, species int, x double, y double, z double")


@pytest.mark.parametrize(("lengths", "periodic", "r"), [((9.0, 11.0, 8.0), (True, True, True), 3.0), ((4.0, 9.0, 5.0), (True, False, True), 6.0), ((7.0, 7.0, 7.0), (False, False, False), 2.5)])
@pytest.mark.parametrize("method", ["cells", "brute"])
def test_radius_edges(spark, lengths, periodic, r, method):
    pos = np.random.default_rng(3).random((40, 3)) * np.array(lengths)
    e = graph.radius_edges(frame(spark, pos), Cell(lengths, periodic), r, method)
    got = {(x.src, x.dst, x.sx, x.sy, x.sz) for x in e.collect()}
    assert got == ref.edges(pos, lengths, r, periodic)
    assert {(b, a, -x, -y, -z) for a, b, x, y, z in got} == got


def test_translation_and_tiles(spark):
    cell = Cell((9.0, 9.0, 9.0))
    pos = np.random.default_rng(5).random((30, 3)) * 9
    atoms = frame(spark, pos)
    e = graph.radius_edges(atoms, cell, 3.0)
    moved = structure.wrap(atoms.withColumn("x", F.col("x") + 100.25), cell)
    assert graph.radius_edges(moved, cell, 3.0).count() == e.count()
    joined = graph.radius_edges(structure.tile(atoms, cell, 30, 2, 1, 3), cell.tiled(2, 1, 3), 3.0)
    derived = graph.tile_edges(e, 30, 2, 1, 3)
    key = list(graph.EDGE_KEY)
    assert derived.count() == 6 * e.count() and derived.select(*key).exceptAll(joined.select(*key)).count() == 0


@pytest.mark.parametrize("tie", ["index", "longest"])
def test_bisection_equals_recursion(spark, tie):
    cell = Cell((10.0, 12.0, 9.0))
    rng = np.random.default_rng(7)
    pos = np.round(rng.random((120, 3)) * np.array(cell.lengths), 1)  # rounded: many ties
    atoms = frame(spark, pos)
    weight = rng.integers(1, 9, 120)
    degree = spark.createDataFrame([(i, int(w)) for i, w in enumerate(weight)], "atom_id long, n_in long")
    ranks, tree = partition.few_neighbour(atoms, degree, cell, 4, 3.0, tie=tie)
    got = {r.atom_id: (r.rank, r.path) for r in ranks.collect()}
    want = ref.bisect(pos, weight, cell.lengths, 4, 3.0, tie)
    assert [got[i][0] for i in range(120)] == want.tolist()
    assert len(set(want)) == 16 and all(int(p, 2) == r and len(p) == 4 for r, p in got.values())
    again = {r.atom_id: r.rank for r in partition.apply_tree(atoms, tree).collect()}
    assert all(again[i] == got[i][0] for i in again)
    loads = np.bincount(want, weights=weight)
    assert loads.max() - loads.min() <= 4 * weight.max()


@pytest.mark.parametrize(
    ("extent", "cuts", "reach", "axis"),
    [((66, 66, 66), (1, 1, 1), 6, 2), ((66, 66, 16.5), (1, 1, 3), 6, 2), ((66, 66, 8.25), (1, 1, 4), 6, 1), ((9, 9, 9), (0, 1, 1), 6, 0), ((0, 5, 5), (1, 2, 2), 1, 2)],
)
def test_axis_rule(extent, cuts, reach, axis):
    assert partition.choose_axis(extent, cuts, reach) == axis


@pytest.mark.parametrize(("reach", "shape"), [(6.0, (2, 8, 8)), (12.0, (4, 4, 8))])
def test_axis_order_of_a_cube(reach, shape):
    """Cuts of a uniform cube at depth 7: slabs first with a short reach, bricks with a long one."""
    extent, cuts, parts = [66.0] * 3, [1, 1, 1], [1, 1, 1]
    for _ in range(7):
        a = partition.choose_axis(tuple(extent), tuple(cuts), reach)
        extent[a] /= 2
        cuts[a] += 1
        parts[a] *= 2
    assert tuple(parts) == shape


def test_three_atoms(spark):
    """Fully connected, one atom a rank: every rank receives two embeddings from two neighbours."""
    e = spark.createDataFrame([(a, b, 0, 0, 0) for a in range(3) for b in range(3) if a != b], "src long, dst long, sx int, sy int, sz int")
    ranks = spark.createDataFrame([(i, i) for i in range(3)], "atom_id long, rank int")
    plan = exchange.plan(e, ranks)
    assert [(r.receives_from, r.sends_to, r.either) for r in metrics.neighbours(plan, 3).collect()] == [(2, 2, 2)] * 3
    assert [(r.sent, r.received) for r in metrics.volume(plan, 4).orderBy("rank").collect()] == [(2, 2)] * 3 + [(0, 0)]
    assert exchange.missing_sources(e, ranks, plan).count() == 0
    assert metrics.is_ring(plan, 3).first().ring


def test_exchange_invariants(spark, sf):
    e, atoms, cell, n = structures.edges(spark, sf, "oxide", 6.0)
    e = e.persist()
    for ranks in (partition.few_neighbour(atoms, graph.degree(e), cell, 2, 6.0)[0], partition.random(atoms, 4)):
        plan = exchange.plan(e, ranks).persist()
        cut = metrics.edge_cut(e, ranks).first()
        volume = plan.count()
        assert plan.select("from_rank", "to_rank").distinct().count() <= volume <= cut.cut_edges
        assert exchange.missing_sources(e, ranks, plan).count() == 0
        assert exchange.place_edges(e, ranks).where("rank <> dst_rank").count() == 0
        order = exchange.local_order(ranks, plan)
        late = order.groupBy("rank").agg(F.max(F.when(F.col("sent") == 0, F.col("position"))).alias("a"), F.min(F.when(F.col("sent") == 1, F.col("position"))).alias("b"))
        assert late.where("a > b").count() == 0
        balance = metrics.imbalance(ranks, e, 4).first()
        assert balance.node_imbalance >= 1 and balance.edge_imbalance >= 1
        for r in metrics.approximate_volume(e, ranks).collect():
            assert abs(r.received - plan.where(F.col("to_rank") == r.rank).count()) <= 0.1 * volume


def test_minimum_cut_is_optimal_on_a_small_graph():
    """Two cliques joined by one edge."""
    pairs = [(i, j) for c in (0, 6) for i in range(c, c + 6) for j in range(i + 1, c + 6)] + [(5, 6)]
    a, b = map(np.array, zip(*pairs, strict=True))
    part = mincut.multilevel(a, b, np.ones(len(a)), np.ones(12), 2, small=4)
    assert len(set(part[:6])) == 1 and len(set(part[6:])) == 1 and part[0] != part[11]


def test_min_cut_beats_random_cut(spark, sf):
    e, atoms, _, n = structures.edges(spark, sf, "oxide", 6.0)
    e = e.persist()
    ranks = mincut.min_cut(e, 4)
    assert metrics.edge_cut(e, ranks).first().cut_edges < metrics.edge_cut(e, partition.random(atoms, 4)).first().cut_edges
    assert metrics.imbalance(ranks, e, 4).first().edge_imbalance < 1.2
    better = mincut.label_propagation(e, partition.sequential(atoms, 4, n), 4, rounds=3)
    assert metrics.edge_cut(e, better).first().cut_edges < metrics.edge_cut(e, partition.sequential(atoms, 4, n)).first().cut_edges


def test_plans(spark, sf):
    """The radius graph is an equi-join, scans are pruned and pushed down."""
    e, _, _, _ = structures.edges(spark, sf, "oxide", 6.0)
    text = e._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in text and "BroadcastNestedLoopJoin" not in text
    assert "ReadSchema: struct<p_partkey:bigint>" in text
    from orbitgraph import plans

    text = plans.queries()["pushed_scan"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_shipdate)" in text and "l_extendedprice" not in text


def test_dense_boxes_are_split(spark):
    rng = np.random.default_rng(6)
    points = np.concatenate([rng.random((60, 3)) * 2 + 1, rng.random((40, 3)) * 30])
    atoms = spark.createDataFrame([(i, 8, *map(float, p)) for i, p in enumerate(points)], "atom_id long, species int, x double, y double, z double")
    cell = structure.Cell((30.0, 30.0, 30.0))
    plain, split = (sorted(map(str, graph.radius_edges(atoms, cell, 5.0, dense=k).collect())) for k in (None, 7))
    assert plain == split and len(plain) > 3000
