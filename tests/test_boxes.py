from pyspark.sql import functions as F

import __spark_entry__ as entry
from orbitgraph.operators import boxes, graph, metrics, partition
from orbitgraph.plans import structures


def test_boxes_count_as_the_joined_graph_does(spark, sf):
    """Small boxes, several images of a pair, two placements at once."""
    for name, r_cut, box_atoms in (("oxide", 3.0, 10), ("oxide", 6.0, 2_000), ("small_box", 6.0, 2_000)):
        e, atoms, cell, n = structures.edges(spark, sf, name, r_cut)
        e = e.persist()
        want = sorted(map(tuple, graph.degree(e, atoms).collect()))
        assert sorted(map(tuple, boxes.degree(atoms, cell, r_cut, n, box_atoms).collect())) == want
        got = boxes.rank_pairs(atoms, cell, r_cut, F.array(partition.random_rank(8), partition.random_rank(3)), n, box_atoms=box_atoms).collect()
        for scheme, parts in enumerate((8, 3)):
            want = sorted(map(tuple, metrics.rank_pairs(e, partition.random(atoms, parts)).collect()))
            assert sorted(tuple(r)[1:] for r in got if r.scheme == scheme) == want


def test_tiles_count_as_the_tiled_graph_does(spark, sf):
    e, atoms, cell, n = structures.edges(spark, sf, "oxide", 6.0)
    want = metrics.rank_pairs(graph.tile_edges(e, n, 2, 1, 3), partition.random(spark.range(6 * n).withColumnRenamed("id", "atom_id"), 5))
    shifted = atoms.select("*", F.col("atom_id").alias("base"))
    for t in range(6):
        shifted = shifted.withColumn("atom_id", F.col("base") + t * n).withColumn(f"t{t}", partition.random_rank(5))
    of_tiles = F.array(*(f"t{t}" for t in range(6)))
    got = boxes.rank_pairs(shifted.withColumn("atom_id", F.col("base")), cell, 6.0, of_tiles, n, (2, 1, 3))
    assert sorted(tuple(r)[1:] for r in got.collect()) == sorted(map(tuple, want.collect()))


def test_no_placement_joins_the_edges(spark, sf):
    """Twelve placements are counted in one pass: nothing is joined by edge, and no table of edges is kept."""
    text = entry.queries()["overhead_decomposition"](spark, sf)._jdf.queryExecution().analyzed().toString()
    assert text.count("FlatMapGroupsInPandas") == 1 and "dx#" not in text


def test_tiled_placement_joins_nothing_as_long_as_the_tiles(spark, sf, monkeypatch):
    """Copies keep their degree, base and tile, so that only tables of the cell are joined; ranks are those of the tiled graph."""
    from orbitgraph.plans import workloads

    plans, few = [], partition.few_neighbour

    def seen(*args, **kwargs):
        ranks, tree = few(*args, **kwargs)
        plans.append((args[0]._jdf.queryExecution().optimizedPlan().toString(), ranks.columns))
        return ranks, tree

    want = {r.atom_id: r["rank"] for r in workloads.tiled(spark, sf, (2, 1, 1), 6.0)[3].collect()}
    monkeypatch.setattr(partition, "few_neighbour", seen)
    atoms, _, n, _ = workloads.placed(spark, sf, (2, 1, 1), 6.0)
    assert {r.atom_id + t * n: v for r in atoms.collect() for t, v in enumerate(r.ranks)} == want
    text, columns = plans[0]
    assert {"base", "t"} <= set(columns) and "Generate explode" not in text[text.index("Join") :].split("FlatMapGroupsInPandas")[0]
