from orbitgraph.llm import toxicity


def test_mined_units_do_not_depend_on_partitions(spark):
    rows = [(f"common word{i % 7} {'vragoid' if i % 3 == 0 else 'plain'}", int(i % 3 == 0)) for i in range(60)]
    sample = spark.createDataFrame(rows, "text string, y int")
    one = toxicity.mine_units(sample.coalesce(1), 20, 40)
    many = toxicity.mine_units(sample.repartition(30), 20, 40)
    assert one == many and "vragoid" in one and "common" not in one
