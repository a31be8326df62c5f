"""Queries run over their whole tables."""

from orbitgraph.plans import learning, structures

SF = "/root/testdata/sf0.01"


def test_network_queries_take_all_atoms(spark):
    atoms, e, cell, n = learning.supplier_graph(spark, SF)
    want, _, whole, _ = structures.edges(spark, SF, "pcm_c", learning.R_CUT)
    assert n == atoms.count() == 100 and cell == whole and e.count() == want.count()


def test_training_and_tiling_take_whole_structures(spark):
    atoms, cell, e, rows, _ = learning.structure_rows(spark, SF, "pcm_c")
    _, whole, n = structures.load(spark, SF, "pcm_c")
    assert atoms.count() == n == 100 and cell == whole and rows.count() == e.count()
