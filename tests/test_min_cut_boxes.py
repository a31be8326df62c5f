import __spark_entry__ as entry
from orbitgraph.operators import metrics, mincut, partition
from orbitgraph.plans import structures


def test_min_cut_in_boxes(spark, sf):
    """Every atom gets a part, cuts beat random ones, atom by atom as well as by clusters of 16, and on tiles."""
    e, atoms, cell, n = structures.edges(spark, sf, "oxide", 3.0)
    e = e.persist()
    by_chance = metrics.edge_cut(e, partition.random(atoms, 4)).first().cut_edges
    for most in (500_000, 100):
        ranks = mincut.min_cut_boxes(atoms, cell, 3.0, n, (2, 4), most=most)
        ranks = ranks.selectExpr("atom_id", "ranks[1] AS rank").persist()
        assert ranks.count() == n and ranks.distinct().count() == n and ranks.select("rank").distinct().count() == 4
        assert metrics.edge_cut(e, ranks).first().cut_edges < 0.8 * by_chance
    rows = mincut.min_cut_boxes(atoms, cell, 3.0, n, (2, 4), (2, 1, 1)).collect()
    assert len(rows) == n and all(len(r.ranks) == 4 for r in rows) and {v for r in rows for v in r.ranks[2:]} == {0, 1, 2, 3}


def test_measures_of_the_cut_without_a_table_of_edges(spark, sf):
    df = entry.queries()["min_cut_p8"](spark, sf)
    assert "dx#" not in df._jdf.queryExecution().analyzed().toString()
    found = {r.scheme: r for r in df.collect()}
    e, atoms, cell, _ = structures.edges(spark, sf, "oxide", 6.0)
    from orbitgraph.operators import graph

    few = partition.few_neighbour(atoms, graph.degree(e), cell, 3, 6.0)[0]
    assert found["few_neighbour"].cut_edges == metrics.edge_cut(e, few).first().cut_edges
    assert found["few_neighbour"].asDict() | metrics.imbalance(few, e, 8).first().asDict() == found["few_neighbour"].asDict()
