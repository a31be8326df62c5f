from pyspark.sql import functions as F

from orbitgraph.llm import quality


def test_repeats_are_counted_alike_at_every_length(spark):
    """No switch by size remains, so the plan has one sort of windows that holds their words."""
    words = F.split(F.col("text"), " ")
    rows = spark.createDataFrame([(" ".join(f"w{i}" for i in range(50)) + " w3 w4 w5",), ("a b c a b c",), ("a b",)], "text string")
    assert [r[0] for r in rows.select(quality._repeat_words(words)).collect()] == [6, 6, 0]
    assert not hasattr(quality, "POSITION_BITS")
