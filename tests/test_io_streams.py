import pytest
from pyspark.sql import functions as F

from orbitgraph.operators import exchange, graph, partition, telemetry
from orbitgraph.plans import structures
from orbitgraph.sources import xyz
from orbitgraph.streaming import phases


def run(stream, name, mode="append"):
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination(120)
    return stream.sparkSession.table(name)


@pytest.fixture(scope="module")
def folder(spark, sf, tmp_path_factory):
    """Events split by day, as files that arrive one after another."""
    path = str(tmp_path_factory.mktemp("events") / "days")
    spark.read.parquet(f"{sf}/events.parquet").repartitionByRange(4, "ts").sortWithinPartitions("ts").write.parquet(path)
    return path


def test_tumbling_equals_batch(spark, folder):
    got = run(phases.tumbling(phases.with_phases(phases.sample_stream(spark, folder), late="60 days")), "tumbling", "update").groupBy("rank", "phase", "w").agg(F.max("n").alias("n"))
    batch = telemetry.samples(spark.read.parquet(folder)).groupBy("rank", "phase", F.window("ts", "1 hour").alias("w")).count()
    assert got.count() == batch.count() and got.agg(F.sum("n")).first()[0] == batch.agg(F.sum("count")).first()[0]


def test_warmup_state(spark, folder):
    got = run(phases.after_warmup(phases.with_phases(phases.sample_stream(spark, folder, 100), late="60 days"), 20), "warm")
    want = telemetry.measured(telemetry.samples(spark.read.parquet(folder)), 20)
    assert {r.event_id for r in got.collect()} == {r.event_id for r in want.collect()}


def test_duplicates_and_late_rows_go(spark, folder, tmp_path):
    twice = str(tmp_path / "twice")
    rows = spark.read.parquet(folder)
    rows.unionAll(rows).coalesce(1).write.parquet(twice)
    assert run(phases.with_phases(phases.sample_stream(spark, twice), late="60 days"), "deduped").count() == rows.count()


def test_plateau_stream(spark, folder):
    got = run(phases.plateau(phases.with_phases(phases.sample_stream(spark, folder, 100), late="60 days")), "plateau")
    for rank in range(4):
        rows = sorted((r.ts, r.event_id, r.ms) for r in telemetry.samples(spark.read.parquet(folder)).where(F.col("rank") == rank).collect())
        s = telemetry.PlateauSchedule()
        want = {e: s.step(m) for _, e, m in rows}
        assert {r.event_id: r.lr for r in got.where(F.col("rank") == rank).collect()} == want


def test_restart_is_exactly_once(spark, folder, tmp_path):
    out, check = str(tmp_path / "out"), str(tmp_path / "check")
    for _ in range(2):
        q = phases.with_phases(phases.sample_stream(spark, folder), late="60 days").writeStream.format("parquet").option("path", out).option("checkpointLocation", check).trigger(availableNow=True).start()
        q.awaitTermination(120)
    assert spark.read.parquet(out).count() == spark.read.parquet(folder).count()


def test_interval_join(spark, folder):
    s = phases.with_phases(phases.sample_stream(spark, folder, 100), late="60 days")
    got = run(phases.pair_up(s.where("phase = 'pack'"), phases.with_phases(phases.sample_stream(spark, folder, 100), late="60 days").where("phase = 'unpack'")), "pairs")
    b = telemetry.samples(spark.read.parquet(folder))
    want = phases.pair_up(b.where("phase = 'pack'"), b.where("phase = 'unpack'"))
    assert got.exceptAll(want).count() == 0 == want.exceptAll(got).count()


def test_structure_files(spark, sf, tmp_path):
    atoms, cell, _ = structures.load(spark, sf, "oxide")
    rows = [(r.species, r.x, r.y, r.z) for r in atoms.orderBy("atom_id").collect()]
    (tmp_path / "a.xyz").write_text(xyz.render(rows, cell.lengths) + xyz.render(rows[:3], cell.lengths))
    spark.dataSource.register(xyz.XyzSource)
    for got in (xyz.read_structures(spark, f"{tmp_path}/*.xyz"), spark.read.format("xyz").load(str(tmp_path))):
        assert sorted((r.species, r.x, r.y, r.z) for r in got.where("structure_id = 'a.xyz#0'").collect()) == sorted(rows)
        assert got.where("structure_id = 'a.xyz#1'").count() == 3


def test_sinks(spark, sf, tmp_path):
    coo = spark.createDataFrame([(0, 0, 1.5), (250_000, 3, -2.0)], "row long, col long, val double")
    xyz.write_coo(coo, str(tmp_path / "coo"))
    assert spark.read.parquet(str(tmp_path / "coo")).where("row_block = 2").count() == 1
    xyz.write_matrix_market(coo, str(tmp_path / "mm"), 250_001)
    assert spark.read.text(str(tmp_path / "mm/body")).count() == 2
    e, atoms, _, n = structures.edges(spark, sf, "oxide", 6.0)
    placed = exchange.place_edges(e, partition.sequential(atoms, 4, n))
    spark.sql("DROP TABLE IF EXISTS og_edges")
    xyz.write_by_rank(placed, "og_edges", 4)
    text = spark.table("og_edges").groupBy("rank").count()._jdf.queryExecution().executedPlan().toString()
    assert "hashpartitioning(rank" not in text
    spark.sql("DROP TABLE og_edges")


def test_frames_under_a_frozen_tree(spark, sf):
    e, atoms, cell, _ = structures.edges(spark, sf, "oxide", 6.0)
    _, tree = partition.few_neighbour(atoms, graph.degree(e), cell, 2, 6.0)
    assert sum(r.n for r in phases.drift(atoms, tree).collect()) == atoms.count()
