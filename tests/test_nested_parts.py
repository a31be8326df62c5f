from orbitgraph.operators import graph, partition
from orbitgraph.plans import structures


def test_fewer_levels_are_prefixes(spark, sf):
    atoms, cell, _ = structures.load(spark, sf, "oxide")
    degree = graph.degree(graph.radius_edges(atoms, cell, 6.0)).persist()
    ranks = {depth: partition.few_neighbour(atoms, degree, cell, depth, 6.0)[0] for depth in (0, 2, 4)}
    for depth in (0, 2):
        assert sorted(partition.coarser(ranks[4], 4 - depth).select("atom_id", "rank").collect()) == sorted(ranks[depth].select("atom_id", "rank").collect())
