import pytest

from orbitgraph.llm import linededup


@pytest.mark.parametrize("end", ["\u0085", "\u2028", "\u2029"])
def test_both_paths_agree_on_lines_that_end_in_a_separator(spark, end):
    line = "a line of more than forty characters that stands in many documents " + end
    docs = spark.createDataFrame([(i, f"first {i}\n{line}\nlast {i}") for i in range(6)], "doc_id long, text string")
    few, many = ({r.doc_id: (r.kept_text, r.n_dropped) for r in linededup.drop_lines(docs, broadcast_keys=n).collect()} for n in (10, 0))
    assert few == many and sum(n for _, n in many.values()) == 5
