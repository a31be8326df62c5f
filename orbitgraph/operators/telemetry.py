"""Runtime samples: medians after a warm-up, phases, scaling ratios, knees, learning-rate schedules."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

# Which recorded event stands for which phase.
PHASES = {"click": "pack", "view": "send_recv", "purchase": "unpack", "signup": "transform", "error": "aggregate"}


def samples(events: DataFrame, parts: int = 4) -> DataFrame:
    """(ts, event_id, rank, phase, epoch, ms) of recorded events; epochs count within rank and phase."""
    phase = F.lit(None).cast("string")
    for kind, name in PHASES.items():
        phase = F.when(F.col("event_type") == kind, name).otherwise(phase)
    rows = events.select("ts", "event_id", (F.col("user_id") % parts).cast("int").alias("rank"), phase.alias("phase"), F.col("value").alias("ms"))
    epoch = F.row_number().over(Window.partitionBy("rank", "phase").orderBy("ts", "event_id"))
    return rows.withColumn("epoch", epoch.cast("int"))


def measured(rows: DataFrame, warmup: int = 20, keep: int | None = None) -> DataFrame:
    """Without the first ``warmup`` epochs, and only ``keep`` of the rest if given."""
    out = rows.where(F.col("epoch") > warmup)
    return out if keep is None else out.where(F.col("epoch") <= warmup + keep)


def boxes(rows: DataFrame, warmup: int = 20, keep: int | None = None) -> DataFrame:
    """Median of every rank and phase, then least, median and greatest over ranks."""
    each = measured(rows, warmup, keep).groupBy("rank", "phase").agg(F.percentile("ms", F.lit(0.5)).alias("m"))
    return each.groupBy("phase").agg(F.round(F.min("m"), 6).alias("low"), F.round(F.percentile("m", F.lit(0.5)), 6).alias("mid"), F.round(F.max("m"), 6).alias("high"))


def decompose(rows: DataFrame, warmup: int = 20) -> DataFrame:
    """Medians by rank with the share of the three exchange phases in all phases."""
    each = measured(rows, warmup).groupBy("rank", "phase").agg(F.percentile("ms", F.lit(0.5)).alias("m"))
    over = F.col("phase").isin("pack", "send_recv", "unpack")
    return each.groupBy("rank").agg(F.round(F.sum("m"), 6).alias("total"), F.round(F.sum(F.when(over, F.col("m")).otherwise(0.0)) / F.sum("m"), 6).alias("exchange_share"))


def strong(times: DataFrame, base_parts: int) -> DataFrame:
    """Speedup and efficiency against the best scheme at ``base_parts``, the ideal line, and gains over the worst scheme.

    times: scheme, parts, t."""
    base = F.min(F.when(F.col("parts") == base_parts, F.col("t"))).over(Window.partitionBy())
    worst = F.max("t").over(Window.partitionBy("parts"))
    speedup = base / F.col("t")
    return times.select(
        "scheme", "parts", F.round("t", 9).alias("t"), F.round(speedup, 6).alias("speedup"), F.round(F.col("parts") / F.lit(base_parts), 6).alias("ideal"),
        F.round(speedup * base_parts / F.col("parts"), 6).alias("efficiency"), F.round(worst / F.col("t") - 1, 6).alias("gain_over_worst"),
    )


def weak(times: DataFrame) -> DataFrame:
    """Efficiency and loss against the fewest parts. times: scheme, parts, t."""
    first = F.min_by("t", "parts").over(Window.partitionBy("scheme"))
    return times.select("scheme", "parts", F.round("t", 9).alias("t"), F.round(first / F.col("t"), 6).alias("efficiency"), F.round(1 - first / F.col("t"), 6).alias("loss"))


def knee(samples_: DataFrame, share: float = 0.9) -> DataFrame:
    """Smallest batch of every size of embedding that reaches the share of its best throughput. rows: channels, n, seconds."""
    rate = samples_.groupBy("channels", "n").agg((F.col("n") / F.percentile("seconds", F.lit(0.5))).alias("rate"))
    best = rate.withColumn("best", F.max("rate").over(Window.partitionBy("channels")))
    return best.where(F.col("rate") >= F.col("best") * share).groupBy("channels").agg(F.min("n").alias("knee"), F.round(F.max("best"), 6).alias("best_rate"))


def bandwidth(sent_bytes: Column, seconds: Column, peak: float) -> list[Column]:
    """GB/s of the slowest rank's time, and its share of the peak."""
    rate = F.sum(sent_bytes) / F.max(seconds) / 1e9
    return [F.round(rate, 6).alias("gb_per_s"), F.round(rate / peak, 6).alias("share_of_peak")]


@dataclass
class PlateauSchedule:
    """Learning rate that falls when the loss has not bettered by a relative threshold for over ``patience`` steps."""

    lr: float = 1e-3
    factor: float = 0.5
    patience: int = 5
    threshold: float = 1e-4
    min_lr: float = 1e-6
    best: float = float("inf")
    bad: int = 0

    def step(self, loss: float) -> float:
        if loss < self.best * (1 - self.threshold):
            self.best, self.bad = loss, 0
        else:
            self.bad += 1
            if self.bad > self.patience:
                self.lr, self.bad = max(self.lr * self.factor, self.min_lr), 0
        return self.lr


def dft_cost(n_iter: float, n_orb: Column) -> Column:
    """Growth of the exact method: iterations times the cube of the orbitals."""
    return n_orb * n_orb * n_orb * n_iter


def as_of(left: DataFrame, right: DataFrame, key: str, ts: str, value: str) -> DataFrame:
    """Latest value of ``right`` at or before each row of ``left``: one union and a running last, no range join."""
    a = left.select(key, ts, F.lit(1).alias("_side"), F.struct(*left.columns).alias("_row"), F.lit(None).cast(right.schema[value].dataType).alias("_v"))
    b = right.select(key, ts, F.lit(0).alias("_side"), F.lit(None).cast(a.schema["_row"].dataType).alias("_row"), F.col(value).alias("_v"))
    run = Window.partitionBy(key).orderBy(ts, "_side").rowsBetween(Window.unboundedPreceding, 0)
    out = a.unionByName(b).withColumn(f"{value}_as_of", F.last("_v", ignorenulls=True).over(run))
    return out.where("_side = 1").select("_row.*", f"{value}_as_of")
