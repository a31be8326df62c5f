import __spark_entry__ as entry
from orbitgraph.plans import structures


def test_all_pairs_against_brute_force(spark):
    d = "/root/testdata/sf0.01"
    atoms, cell, n = structures.load(spark, d, "small_box")
    x, side = {r.atom_id: r.x for r in atoms.collect()}, cell.lengths[0]
    got = {(r.src, r.dst): r.dx for r in entry.queries()["min_image_pairs"](spark, d).collect()}
    assert set(got) == {(i, j) for i in x for j in x if i < j} and len(got) == n * (n - 1) // 2
    assert all(abs(v - min(abs(x[j] - x[i] + s * side) for s in (-1, 0, 1))) < 1e-6 for (i, j), v in got.items())
