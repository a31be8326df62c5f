"""Named queries of telemetry, scaling, and the relational operators around the methods."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from ..operators import metrics, telemetry

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(name, sql=None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def read(spark, d, table):
    return spark.read.parquet(f"{d}/{table}.parquet")


def recorded(spark, d):
    return telemetry.samples(read(spark, d, "events"))


def named():
    """Subtotal rows of rank and phase are named."""
    return {"rank": F.coalesce(F.col("rank").cast("string"), F.lit("all")), "phase": F.coalesce("phase", F.lit("all"))}


S = """s AS (SELECT ts, event_id, CAST(user_id % 4 AS INT) AS rank, CASE event_type WHEN 'click' THEN 'pack' WHEN 'view' THEN 'send_recv' WHEN 'purchase' THEN 'unpack' WHEN 'signup' THEN 'transform' WHEN 'error' THEN 'aggregate' END AS phase, value AS ms FROM events),
t AS (SELECT *, CAST(row_number() OVER (PARTITION BY rank, phase ORDER BY ts, event_id) AS INT) AS epoch FROM s),
m AS (SELECT rank, phase, quantile_cont(ms, 0.5) AS m FROM t WHERE epoch > 20 GROUP BY ALL)"""


@query("phase_samples", f"WITH {S} SELECT event_id, rank, phase, epoch, round(ms, 6) AS ms FROM t")
def _(spark, d):
    return recorded(spark, d).select("event_id", "rank", "phase", "epoch", F.round("ms", 6).alias("ms"))


@query("boxes", f"WITH {S} SELECT phase, round(min(m), 6) AS low, round(quantile_cont(m, 0.5), 6) AS mid, round(max(m), 6) AS high FROM m GROUP BY phase")
def _(spark, d):
    return telemetry.boxes(recorded(spark, d))


@query("decompose", f"WITH {S} SELECT rank, round(sum(m), 6) AS total, round(sum(CASE WHEN phase IN ('pack', 'send_recv', 'unpack') THEN m ELSE 0 END)/sum(m), 6) AS exchange_share FROM m GROUP BY rank")
def _(spark, d):
    return telemetry.decompose(recorded(spark, d))


@query("rollup_phase", f"WITH {S} SELECT coalesce(CAST(rank AS VARCHAR), 'all') AS rank, coalesce(phase, 'all') AS phase, count(*) AS n, round(avg(ms), 6) AS mean_ms, CAST(grouping(rank)*2 + grouping(phase) AS INT) AS level FROM t GROUP BY ROLLUP (rank, phase)")
def _(spark, d):
    return recorded(spark, d).rollup("rank", "phase").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("ms"), 6).alias("mean_ms"), F.grouping_id().cast("int").alias("level")).withColumns(named())


@query("cube_phase", f"WITH {S} SELECT coalesce(CAST(rank AS VARCHAR), 'all') AS rank, coalesce(phase, 'all') AS phase, count(*) AS n, round(max(ms), 6) AS top FROM t GROUP BY CUBE (rank, phase)")
def _(spark, d):
    return recorded(spark, d).cube("rank", "phase").agg(F.count(F.lit(1)).alias("n"), F.round(F.max("ms"), 6).alias("top")).withColumns(named())


PHASE_COLUMNS = ("aggregate", "pack", "send_recv", "transform", "unpack")


@query("pivot_phase", f"WITH {S} SELECT rank, " + ", ".join(f"count(*) FILTER (WHERE phase = '{p}') AS n_{p}" for p in PHASE_COLUMNS) + " FROM t GROUP BY rank")
def _(spark, d):
    out = recorded(spark, d).groupBy("rank").pivot("phase", list(PHASE_COLUMNS)).count()
    return out.select("rank", *(F.coalesce(p, F.lit(0)).alias(f"n_{p}") for p in PHASE_COLUMNS))


@query("rolling_ms", f"WITH {S} SELECT event_id, round(avg(ms) OVER (PARTITION BY rank, phase ORDER BY epoch ROWS BETWEEN 9 PRECEDING AND CURRENT ROW), 6) AS smooth, round(min(ms) OVER (PARTITION BY rank, phase ORDER BY epoch), 6) AS best, round(ms - lag(ms) OVER (PARTITION BY rank, phase ORDER BY epoch), 6) AS step FROM t")
def _(spark, d):
    w = Window.partitionBy("rank", "phase").orderBy("epoch")
    r = recorded(spark, d)
    return r.select("event_id", F.round(F.avg("ms").over(w.rowsBetween(-9, 0)), 6).alias("smooth"), F.round(F.min("ms").over(w.rowsBetween(Window.unboundedPreceding, 0)), 6).alias("best"), F.round(F.col("ms") - F.lag("ms").over(w), 6).alias("step"))


@query("rank_windows", f"WITH {S} SELECT event_id, CAST(rank() OVER w AS INT) AS rk, CAST(dense_rank() OVER w AS INT) AS dr, CAST(ntile(4) OVER w AS INT) AS quarter, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM t WINDOW w AS (PARTITION BY rank, phase ORDER BY ms, event_id)")
def _(spark, d):
    w = Window.partitionBy("rank", "phase").orderBy("ms", "event_id")
    return recorded(spark, d).select("event_id", F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(w).alias("quarter"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


@query("asof_lr", """WITH a AS (SELECT event_id, CAST(user_id % 4 AS INT) AS rank, ts FROM events WHERE event_type = 'view'), b AS (SELECT CAST(user_id % 4 AS INT) AS rank, ts, max(value) AS lr FROM events WHERE event_type = 'signup' GROUP BY ALL)
SELECT a.event_id, a.rank, round(b.lr, 6) AS lr_as_of FROM a ASOF LEFT JOIN b ON a.rank = b.rank AND a.ts >= b.ts""")
def _(spark, d):
    e = read(spark, d, "events").withColumn("rank", (F.col("user_id") % 4).cast("int"))
    right = e.where("event_type = 'signup'").groupBy("rank", "ts").agg(F.max("value").alias("lr"))
    left = e.where("event_type = 'view'").select("event_id", "rank", "ts")
    return telemetry.as_of(left, right, "rank", "ts", "lr").select("event_id", "rank", F.round("lr_as_of", 6).alias("lr_as_of"))


@query("tumbling_phases", f"WITH {S} SELECT rank, phase, CAST(epoch_us(time_bucket(INTERVAL 1 HOUR, ts))//1000000 AS BIGINT) AS start_s, count(*) AS n, round(sum(ms), 6) AS total FROM t GROUP BY ALL")
def _(spark, d):
    g = recorded(spark, d).groupBy("rank", "phase", F.window("ts", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("ms"), 6).alias("total"))
    return g.select("rank", "phase", F.unix_seconds(F.col("w.start").cast("timestamp")).alias("start_s"), "n", "total")


@query("sliding_phases", f"WITH {S} SELECT rank, CAST(epoch_us(time_bucket(INTERVAL 1 HOUR, ts))//1000000 - 3600*k AS BIGINT) AS start_s, count(*) AS n FROM t, (SELECT unnest([0, 1]) AS k) GROUP BY ALL")
def _(spark, d):
    g = recorded(spark, d).groupBy("rank", F.window("ts", "2 hours", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return g.select("rank", F.unix_seconds(F.col("w.start").cast("timestamp")).alias("start_s"), "n")


@query("session_phases", """WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events), g AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts RANGE UNBOUNDED PRECEDING) AS k FROM e)
SELECT user_id, CAST(epoch_us(min(ts))//1000000 AS BIGINT) AS start_s, count(*) AS n FROM g GROUP BY user_id, k""")
def _(spark, d):
    g = read(spark, d, "events").groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return g.select("user_id", F.unix_seconds(F.col("w.start").cast("timestamp")).alias("start_s"), "n")


@query("props_json", "SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")
def _(spark, d):
    return read(spark, d, "events").groupBy(F.from_json("props", "k long")["k"].alias("k")).agg(F.count(F.lit(1)).alias("n"))


@query("frames_by_month", "SELECT CAST(year(o_orderdate)*100 + month(o_orderdate) AS INT) AS frame, count(*) AS n_atoms, CAST(datediff('day', DATE '1992-01-01', CAST(min(o_orderdate) AS DATE)) AS INT) AS first_day FROM orders GROUP BY 1")
def _(spark, d):
    o = read(spark, d, "orders")
    return o.groupBy((F.year("o_orderdate") * 100 + F.month("o_orderdate")).alias("frame")).agg(F.count(F.lit(1)).alias("n_atoms"), F.datediff(F.min("o_orderdate"), F.lit("1992-01-01").cast("date")).alias("first_day"))


@query("lookup_regions", "SELECT r_name, count(*) AS n_suppliers, round(avg(s_acctbal), 4) AS mean_balance FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def _(spark, d):
    s = read(spark, d, "supplier").join(F.broadcast(read(spark, d, "nation")), F.col("s_nationkey") == F.col("n_nationkey"))
    return s.join(F.broadcast(read(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.count(F.lit(1)).alias("n_suppliers"), F.round(F.avg("s_acctbal"), 4).alias("mean_balance"))


@query("pushed_scan", "SELECT l_returnflag, l_linestatus, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS quantity, count(*) AS n FROM lineitem WHERE l_shipdate <= TIMESTAMP '1998-09-02' GROUP BY ALL")
def _(spark, d):
    rows = read(spark, d, "lineitem").where(F.col("l_shipdate") <= F.lit("1998-09-02").cast("timestamp"))
    return rows.groupBy("l_returnflag", "l_linestatus").agg(F.sum(F.col("l_quantity").cast("long")).alias("quantity"), F.count(F.lit(1)).alias("n"))


@query("semi_anti", "SELECT (SELECT count(*) FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem WHERE l_quantity >= 50)) AS needed, (SELECT count(*) FROM part WHERE p_partkey NOT IN (SELECT l_partkey FROM lineitem WHERE l_quantity >= 50)) AS interior")
def _(spark, d):
    part, used = read(spark, d, "part").select("p_partkey"), read(spark, d, "lineitem").where("l_quantity >= 50").select(F.col("l_partkey").alias("p_partkey"))
    flagged = part.join(used.distinct().withColumn("hit", F.lit(1)), "p_partkey", "left")
    return flagged.agg(F.count("hit").alias("needed"), F.sum(F.col("hit").isNull().cast("long")).alias("interior"))


@query("set_operations", "SELECT (SELECT count(*) FROM (SELECT l_suppkey FROM lineitem INTERSECT SELECT s_suppkey FROM supplier)) AS both_sides, (SELECT count(*) FROM (SELECT p_partkey FROM part EXCEPT SELECT l_partkey FROM lineitem)) AS only_parts")
def _(spark, d):
    li = read(spark, d, "lineitem")
    a = li.select("l_suppkey").intersect(read(spark, d, "supplier").select("s_suppkey")).agg(F.count(F.lit(1)).alias("both_sides"))
    b = read(spark, d, "part").select("p_partkey").subtract(li.select("l_partkey")).agg(F.count(F.lit(1)).alias("only_parts"))
    return a.crossJoin(b)


@query("top_pairs", "SELECT l_suppkey, l_partkey, CAST(n AS BIGINT) AS n FROM (SELECT l_suppkey, l_partkey, count(*) AS n FROM lineitem GROUP BY ALL) ORDER BY n DESC, l_suppkey, l_partkey LIMIT 20")
def _(spark, d):
    return read(spark, d, "lineitem").groupBy("l_suppkey", "l_partkey").agg(F.count(F.lit(1)).alias("n")).orderBy(F.desc("n"), "l_suppkey", "l_partkey").limit(20)


@query("page_hosts", r"SELECT host, count(*) AS n FROM (SELECT regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host FROM pages) GROUP BY host")
def _(spark, d):
    return read(spark, d, "pages").groupBy(F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1).alias("host")).agg(F.count(F.lit(1)).alias("n"))


# --- formulas of scaling, on recorded events as telemetry; modelled workloads are in workloads.py -------------------------------------------------------------------------------------------------------
TIMES = "(SELECT CASE WHEN user_id % 2 = 0 THEN 'few_neighbour' ELSE 'min_cut' END AS scheme, CAST(CASE user_id % 3 WHEN 0 THEN 32 WHEN 1 THEN 64 ELSE 128 END AS INT) AS parts, median(value) AS t FROM events GROUP BY ALL)"


def times(spark, d):
    e = read(spark, d, "events")
    scheme = F.when(F.col("user_id") % 2 == 0, "few_neighbour").otherwise("min_cut")
    parts = F.when(F.col("user_id") % 3 == 0, 32).when(F.col("user_id") % 3 == 1, 64).otherwise(128)
    return e.groupBy(scheme.alias("scheme"), parts.alias("parts")).agg(F.median("value").alias("t"))


@query("telemetry_strong", f"""SELECT scheme, parts, round(t, 9) AS t, round(base/t, 6) AS speedup, round(parts/32, 6) AS ideal, round(base/t*32/parts, 6) AS efficiency, round(worst/t-1, 6) AS gain_over_worst FROM (
 SELECT *, min(CASE WHEN parts = 32 THEN t END) OVER () AS base, max(t) OVER (PARTITION BY parts) AS worst FROM {TIMES})""")
def _(spark, d):
    return telemetry.strong(times(spark, d), 32)


@query("telemetry_weak", f"SELECT scheme, parts, round(t, 9) AS t, round(f/t, 6) AS efficiency, round(1-f/t, 6) AS loss FROM (SELECT *, first_value(t) OVER (PARTITION BY scheme ORDER BY parts) AS f FROM {TIMES})")
def _(spark, d):
    return telemetry.weak(times(spark, d))


@query("telemetry_knee", """WITH s AS (SELECT CAST(16*(1 + user_id % 3) AS INT) AS channels, CAST(pow(10, 2 + event_id % 4) AS BIGINT) AS n, (50 + pow(10, 2 + event_id % 4)/1000) * (1 + value/1e6) AS seconds FROM events),
r AS (SELECT channels, n, n/quantile_cont(seconds, 0.5) AS rate FROM s GROUP BY channels, n), b AS (SELECT *, max(rate) OVER (PARTITION BY channels) AS best FROM r)
SELECT channels, min(n) AS knee, round(max(best), 6) AS best_rate FROM b WHERE rate >= best*0.9 GROUP BY channels""")
def _(spark, d):
    n = F.pow(F.lit(10.0), 2 + F.col("event_id") % 4)
    rows = read(spark, d, "events").select((16 * (1 + F.col("user_id") % 3)).cast("int").alias("channels"), n.cast("long").alias("n"), ((50 + n / 1000) * (1 + F.col("value") / F.lit(1e6))).alias("seconds"))
    return telemetry.knee(rows)


@query("telemetry_bandwidth", "SELECT round(sum(value*1e6)/max(value)/1e9, 6) AS gb_per_s, round(sum(value*1e6)/max(value)/1e9/48.6, 6) AS share_of_peak FROM events")
def _(spark, d):
    return read(spark, d, "events").agg(*telemetry.bandwidth(F.col("value") * 1e6, F.col("value"), 48.6))


@query("message_bytes", "SELECT channels, CAST(3*25*channels*4 AS BIGINT) AS message_bytes, CAST(25*channels*4 AS BIGINT) AS embedding_bytes, count(*) AS n_messages, CAST(count(*)*3*25*channels*4 AS BIGINT) AS total_bytes FROM (SELECT CAST(16*pow(2, user_id % 4) AS INT) AS channels FROM events) GROUP BY channels")
def _(spark, d):
    """Bytes of a message and of an embedding by channels, and of all messages that the events stand for."""
    c, n = F.col("channels").cast("long"), F.count(F.lit(1))
    rows = read(spark, d, "events").select((16 * F.pow(F.lit(2.0), F.col("user_id") % 4)).cast("int").alias("channels")).groupBy("channels").agg(n.alias("n_messages"))
    return rows.select("channels", metrics.message_bytes(4, c).alias("message_bytes"), metrics.embedding_bytes(4, c).alias("embedding_bytes"), "n_messages", (F.col("n_messages") * metrics.message_bytes(4, c)).alias("total_bytes"))


@query("useful_ranks", "SELECT l_returnflag, l_linestatus, count(*) AS n_messages, CAST(greatest(1, floor(count(*)/2e5)) AS BIGINT) AS ranks_2e5, CAST(greatest(1, floor(count(*)/1e5)) AS BIGINT) AS ranks_1e5 FROM lineitem GROUP BY ALL")
def _(spark, d):
    """Ranks that the messages of each part of the trade graph keep busy: a line is an edge, an edge sends a message."""
    useful = lambda floor: F.greatest(F.lit(1), F.floor(F.col("n_messages") / F.lit(floor))).cast("long")
    rows = read(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n_messages"))
    return rows.select("*", useful(2e5).alias("ranks_2e5"), useful(1e5).alias("ranks_1e5"))


@query("memory_model", "SELECT count(*)*1600 AS nodes, count(*)*76*1600 AS edges, count(*)*76*4800 AS messages, count(*)*1600 + 4*count(*)*76*1600 AS total FROM part")
def _(spark, d):
    """Rows are counted by their keys, which tasks read, null ones included."""
    n = F.count("p_partkey") + F.count_if(F.col("p_partkey").isNull())
    m = metrics.memory_model(F.col("n"), 76 * F.col("n"), 4, 16)
    return read(spark, d, "part").agg(n.alias("n")).select(*(m[k].alias(k) for k in ("nodes", "edges", "messages", "total")))


@query("cost_growth", """WITH o AS (SELECT p_size, sum(CASE WHEN p_partkey % 3 = 0 THEN 10 ELSE 4 END) AS k FROM part GROUP BY p_size), g AS (SELECT p_size, CAST(sum(k) OVER (ORDER BY p_size) AS BIGINT) AS n_orb FROM o)
SELECT p_size, n_orb, CAST(n_orb AS DOUBLE)*CAST(n_orb AS DOUBLE)*CAST(n_orb AS DOUBLE)*20e0 AS exact_cost, CAST(n_orb AS DOUBLE) AS inferred_cost FROM g""")
def _(spark, d):
    """Costs of the exact method and of inference as the oxide grows, part size by part size: 10 orbitals for each 72, 4 for
    each 8. The running sum has a row for each size."""
    orbitals = read(spark, d, "part").groupBy("p_size").agg(F.sum(F.when(F.col("p_partkey") % 3 == 0, 10).otherwise(4)).alias("k"))
    n = orbitals.select("p_size", F.sum("k").over(Window.orderBy("p_size")).cast("long").alias("n_orb"))
    return n.select("p_size", "n_orb", telemetry.dft_cost(20.0, F.col("n_orb").cast("double")).alias("exact_cost"), F.col("n_orb").cast("double").alias("inferred_cost"))


@query("plateau_schedule")
def _(spark, d):
    """Learning rates along all recorded losses: rows only, as each step depends on the one before (tested in Python).

    One ordered stream of thin rows; the task keeps the state of the schedule and the number of the step."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        s, done = telemetry.PlateauSchedule(), 0
        for frame in frames:
            losses = frame["loss"].tolist()
            yield pd.DataFrame({"step": range(done, done + len(losses)), "loss": losses, "lr": [s.step(v) for v in losses]})
            done += len(losses)

    losses = read(spark, d, "events").select("event_id", F.col("value").cast("double").alias("loss"))
    return losses.repartition(1).sortWithinPartitions("event_id", "loss").mapInPandas(run, "step long, loss double, lr double")
