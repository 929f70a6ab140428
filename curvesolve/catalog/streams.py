"""Streams over the heartbeat log, each held against the same question over the stored table."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import SolveConfig
from ..plans import distributed
from ..runtime import checkpoint, shared_folder
from ..sources import tables
from .shared import SCALE
from ..streaming import heartbeats as hb

Spark = SparkSession
P = 10
UTC = "UTC"


def _beats(spark: Spark, sf_dir: str) -> DataFrame:
    return hb.heartbeats(hb.stream(spark, f"{sf_dir}/events.parquet*", 1000), P)


def _table(df: DataFrame, mode: str) -> DataFrame:
    return hb.to_table(df, f"s{uuid.uuid4().hex}", mode)


def _hours(col: str):
    return F.floor(F.unix_seconds(F.col(col)) / F.lit(3600)).cast("long").alias(col)


def s02_cycles(spark: Spark, sf_dir: str) -> DataFrame:
    return _table(hb.cycles(_beats(spark, sf_dir)), "complete").select(_hours("cycle"), "sub", "beats", "failed")


def s03_failure_rate(spark: Spark, sf_dir: str) -> DataFrame:
    return _table(hb.failure_rate(_beats(spark, sf_dir)), "complete").select(_hours("start"), "beats", F.round("rate", 9).alias("rate"))


def s04_outages(spark: Spark, sf_dir: str) -> DataFrame:
    out = _table(hb.outages(_beats(spark, sf_dir)), "complete")
    return out.groupBy("sub").agg(F.count("*").alias("outages"), F.max("errors").alias("longest"))


def s05_late(spark: Spark, sf_dir: str) -> DataFrame:
    """Closed cycles only: what the watermark lets through, as counts per slice."""
    out = _table(hb.cycles(_beats(spark, sf_dir)), "append")
    return out.groupBy("sub").agg(F.count("*").alias("closed"))


def s06_states(spark: Spark, sf_dir: str) -> DataFrame:
    """Stateful machine per slice; its state store must be the one that keeps typed state."""
    name = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(name)
    spark.conf.set(name, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        out = _table(hb.slice_states(_beats(spark, sf_dir)), "append")
    finally:
        spark.conf.set(name, before)
    return out.groupBy("sub", "state").agg(F.count("*").alias("beats"))


def s06_states_batch(spark: Spark, sf_dir: str) -> DataFrame:
    """The batch twin: a lag over each slice's heartbeats."""
    from pyspark.sql import Window

    beats = hb.heartbeats(tables.table(spark, sf_dir, "events"), P)
    before = F.lag("failed", 1, False).over(Window.partitionBy("sub").orderBy("ts", "event_id"))
    state = F.when(F.col("failed"), "failed").when(before, "returning").otherwise("active")
    return beats.select("sub", state.alias("state")).groupBy("sub", "state").agg(F.count("*").alias("beats"))


def s07_once(spark: Spark, sf_dir: str) -> DataFrame:
    out = _table(hb.first_results(_beats(spark, sf_dir)), "append")
    return out.groupBy("sub").agg(F.count("*").alias("results"))


def s08_deadline(spark: Spark, sf_dir: str) -> DataFrame:
    """Assigned work joined to returns of the same event within the hour; batch form."""
    beats = hb.heartbeats(tables.table(spark, sf_dir, "events"), P)
    assigned = beats.select(F.col("event_id").alias("work_id"), "sub", (F.col("ts") - F.expr("INTERVAL 10 MINUTES")).alias("at"))
    returned = beats.where("not failed").select(F.col("event_id").alias("result_id"), "ts")
    return hb.unreturned(assigned, returned).groupBy("sub").agg(F.count_if(F.col("back").isNull()).alias("unreturned"), F.count("*").alias("assigned"))


def s08_deadline_stream(spark: Spark, sf_dir: str) -> DataFrame:
    """The same as a join of two streams, inner part only, as unmatched rows wait for the watermark."""
    def beats(name: str) -> DataFrame:
        plain = hb.stream(spark, f"{sf_dir}/events.parquet*", 1000).select(
            F.col("ts").cast("timestamp").alias(name), F.pmod("user_id", F.lit(P)).cast("int").alias("sub"), "event_type", "event_id")
        return plain.withWatermark(name, "1 hour")

    assigned = beats("at").select(F.col("event_id").alias("work_id"), "sub", "at")
    returned = beats("ts").where("event_type <> 'error'").select(F.col("event_id").alias("result_id"), "ts")
    out = _table(assigned.join(returned, F.expr("result_id = work_id AND ts >= at AND ts <= at + INTERVAL 1 HOUR")), "append")
    return out.groupBy("sub").agg(F.count("*").alias("returned"))


LINE = SolveConfig((P,), 3, 2, 0.5, tol=1e-11)


def s09_updates(spark: Spark, sf_dir: str) -> DataFrame:
    """The solution for running sums per slice: every micro-batch adds to the right-hand side and starts from the last solution."""
    total, last = dict.fromkeys(range(P), 0), {"x": None}
    system = distributed.setup(spark, LINE)

    def update(batch: DataFrame, epoch: int) -> None:
        for r in batch.groupBy("sub").agg(F.sum(F.round(F.col("value") * 100).cast("long")).alias("v")).collect():  # one row per slice
            total[r["sub"]] += r["v"] or 0
        b = spark.createDataFrame([(i, v / SCALE) for i, v in sorted(total.items())], "pos long, v double")
        out = distributed.run(system, b, x0=last["x"])
        last["x"] = checkpoint(distributed.solution(system, out.state))

    folder = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    for part in (0, 1):  # the table is one file, hence two streams for two micro-batches
        hb.solve_updates(_beats(spark, sf_dir).where(F.pmod("event_id", F.lit(2)) == part), update, f"{folder}/{part}").awaitTermination()
    return last["x"].select(F.col("pos").alias("id"), (F.round("v", 6) + 0.0).alias("u"))


def s10_update_mode(spark: Spark, sf_dir: str) -> DataFrame:
    """Cycles written as updates; the last one of each key is the result."""
    rows = hb.latest(_table(hb.cycles(_beats(spark, sf_dir)), "update"), ["cycle", "sub"])
    return rows.select(_hours("cycle"), "sub", "beats", "failed")


QUERIES = {f.__name__: f for f in (s02_cycles, s03_failure_rate, s04_outages, s05_late, s06_states, s06_states_batch, s07_once, s08_deadline, s08_deadline_stream, s09_updates, s10_update_mode)}
_B = f"SELECT *, CAST(user_id % {P} AS INTEGER) AS sub, event_type = 'error' AS failed FROM events"
_ST = ("SELECT sub, state, CAST(count(*) AS BIGINT) AS beats FROM (SELECT sub, CASE WHEN failed THEN 'failed' WHEN lag(failed, 1, false) OVER (PARTITION BY sub ORDER BY ts, event_id) THEN 'returning' ELSE 'active' END AS state "
       f"FROM ({_B})) GROUP BY 1, 2")
_CYCLES = f"SELECT CAST(floor(epoch(ts) / 3600) AS BIGINT) AS cycle, sub, CAST(count(*) AS BIGINT) AS beats, bool_or(failed) AS failed FROM ({_B}) GROUP BY 1, 2"
SQL = {
    "s10_update_mode": _CYCLES,
    "s02_cycles": f"SELECT CAST(floor(epoch(ts) / 3600) AS BIGINT) AS cycle, sub, CAST(count(*) AS BIGINT) AS beats, bool_or(failed) AS failed FROM ({_B}) GROUP BY 1, 2",
    "s03_failure_rate": f"SELECT CAST(floor(epoch(ts) / 3600) - o AS BIGINT) AS start, CAST(count(*) AS BIGINT) AS beats, round(avg(CAST(failed AS DOUBLE)), 9) AS rate FROM ({_B}), range(6) r(o) GROUP BY 1",
    "s04_outages": f"WITH e AS (SELECT sub, ts FROM ({_B}) WHERE failed), g AS (SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 2 HOUR THEN 0 ELSE 1 END AS new FROM e WINDOW w AS (PARTITION BY sub ORDER BY ts)), "
                   "s AS (SELECT sub, sum(new) OVER (PARTITION BY sub ORDER BY ts ROWS UNBOUNDED PRECEDING) AS n FROM g), c AS (SELECT sub, n, count(*) AS k FROM s GROUP BY 1, 2) SELECT sub, CAST(count(*) AS BIGINT) AS outages, CAST(max(k) AS BIGINT) AS longest FROM c GROUP BY sub",
    "s06_states": _ST, "s06_states_batch": _ST,
    "s07_once": f"SELECT sub, CAST(count(DISTINCT event_id) AS BIGINT) AS results FROM ({_B}) GROUP BY sub",
    "s08_deadline": f"SELECT sub, CAST(count(*) FILTER (WHERE failed) AS BIGINT) AS unreturned, CAST(count(*) AS BIGINT) AS assigned FROM ({_B}) GROUP BY sub",
    "s08_deadline_stream": f"SELECT sub, CAST(count(*) AS BIGINT) AS returned FROM ({_B}) WHERE NOT failed GROUP BY sub",
    "s09_updates": f"WITH b AS (SELECT sub AS id, sum(CAST(round(value * 100) AS BIGINT)) / {SCALE!r} AS v FROM ({_B}) GROUP BY sub) SELECT CAST(x.i AS BIGINT) AS id, "
                   f"round(sum({(1 / (P + 1)) ** 2!r} * (least(x.i, b.id) + 1) * ({P} - greatest(x.i, b.id)) / {P + 1}.0 * b.v), 6) + 0.0 AS u FROM range({P}) x(i), b GROUP BY x.i",
    "s05_late": f"SELECT sub, CAST(count(*) AS BIGINT) AS closed FROM (SELECT DISTINCT sub, floor(epoch(ts) / 3600) AS c FROM ({_B})) WHERE c * 3600 + 3600 <= (SELECT epoch(max(ts)) - 3600 FROM events) GROUP BY sub",
}
