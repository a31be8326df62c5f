"""Streams of runtime samples and structure frames."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators import partition
from ..operators.partition import Tree
from ..operators.telemetry import PHASES, PlateauSchedule

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"


def sample_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """Stream of recorded events in a folder of Parquet files."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def with_phases(stream: DataFrame, parts: int = 4, late: str = "1 hour") -> DataFrame:
    phase = F.lit(None).cast("string")
    for kind, name in PHASES.items():
        phase = F.when(F.col("event_type") == kind, name).otherwise(phase)
    rows = stream.select("event_id", "ts", (F.col("user_id") % parts).cast("int").alias("rank"), phase.alias("phase"), F.col("value").alias("ms"))
    return rows.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def tumbling(stream: DataFrame, every: str = "1 hour") -> DataFrame:
    return stream.groupBy("rank", "phase", F.window("ts", every).alias("w")).agg(F.count(F.lit(1)).alias("n"), F.sum("ms").alias("total"))


def sliding(stream: DataFrame, length: str = "2 hours", every: str = "1 hour") -> DataFrame:
    return stream.groupBy("rank", F.window("ts", length, every).alias("w")).agg(F.count(F.lit(1)).alias("n"))


def sessions(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    return stream.groupBy("rank", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n"))


def pair_up(sent: DataFrame, received: DataFrame, within: str = "10 minutes") -> DataFrame:
    """Interval join of send and receive samples of a rank; both sides need watermarks, which bound the state."""
    a, b = sent.alias("a"), received.alias("b")
    return a.join(b, F.expr(f"a.rank = b.rank AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL {within}")).select("a.rank", F.col("a.event_id").alias("sent_id"), F.col("b.event_id").alias("received_id"))


def after_warmup(stream: DataFrame, warmup: int = 20) -> DataFrame:
    """Drops the first samples of every (rank, phase); the state is one counter each."""

    def run(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        seen = state.get[0] if state.exists else 0
        for frame in frames:
            frame = frame.sort_values(["ts", "event_id"])
            yield frame.iloc[max(0, warmup - seen) :][["event_id", "ts", "rank", "phase", "ms"]]
            seen += len(frame)
        state.update((seen,))

    schema = "event_id long, ts timestamp, rank int, phase string, ms double"
    return stream.groupBy("rank", "phase").applyInPandasWithState(run, schema, "seen long", "append", GroupStateTimeout.NoTimeout)


def plateau(stream: DataFrame) -> DataFrame:
    """Learning rate along the stream of losses of each rank; the state is the schedule's four numbers."""

    def run(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        s = PlateauSchedule()
        if state.exists:
            s.lr, s.best, s.bad = state.get
        for frame in frames:
            frame = frame.sort_values(["ts", "event_id"])
            yield pd.DataFrame({"rank": key[0], "event_id": frame["event_id"], "lr": [s.step(v) for v in frame["ms"]]})
        state.update((s.lr, s.best, s.bad))

    return stream.groupBy("rank").applyInPandasWithState(run, "rank int, event_id long, lr double", "lr double, best double, bad int", "append", GroupStateTimeout.NoTimeout)


def frame_ranks(frames: DataFrame, tree: Tree) -> DataFrame:
    """Ranks of a stream of atoms under a frozen tree: a projection, so no state and no shuffle."""
    return partition.apply_tree(frames, tree)


def drift(frames: DataFrame, tree: Tree) -> DataFrame:
    """Atoms on each rank under the frozen tree, from which the imbalance of later frames follows."""
    return frame_ranks(frames, tree).groupBy("rank").agg(F.count(F.lit(1)).alias("n"))
