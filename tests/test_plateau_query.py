import __spark_entry__ as entry
from orbitgraph.operators import telemetry


def test_schedule_runs_over_all_events(spark, sf):
    losses = [r.value for r in spark.read.parquet(f"{sf}/events.parquet").orderBy("event_id", "value").collect()]
    s = telemetry.PlateauSchedule()
    want = [(i, v, s.step(v)) for i, v in enumerate(losses)]
    got = sorted(tuple(r) for r in entry.queries()["plateau_schedule"](spark, sf).collect())
    assert len(want) > 200 and got == want
