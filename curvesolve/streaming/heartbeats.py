"""Stream operators over a heartbeat log (ts, user_id, event_type, value).

A slice is pmod(user_id, P); an error event is a fault. Each function takes a streaming or a batch
frame, so that a stream's result can be held against the same query over the stored table.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..runtime import shared_folder
from ..sources.tables import SCHEMAS

#: Rows of an answer that a stateful processor hands on together.
CHUNK = 10_000


def stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """Heartbeats of a folder or glob of Parquet files, as they arrive."""
    return spark.readStream.schema(SCHEMAS["events"]).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def heartbeats(events: DataFrame, p: int, delay: str = "1 hour") -> DataFrame:
    """(ts, sub, failed, value, event_id) with a watermark if it streams."""
    out = events.select(F.col("ts").cast("timestamp").alias("ts"), F.pmod("user_id", F.lit(p)).cast("int").alias("sub"), (F.col("event_type") == "error").alias("failed"), "value", "event_id")
    return out.withWatermark("ts", delay)


def cycles(beats: DataFrame, length: str = "1 hour") -> DataFrame:
    """(cycle, sub, beats, failed): tumbling windows; any error fails the slice."""
    return beats.groupBy(F.window("ts", length).alias("w"), "sub").agg(F.count("*").alias("beats"), F.max(F.col("failed").cast("int")).alias("f")).select(
        F.col("w.start").alias("cycle"), "sub", "beats", (F.col("f") == 1).alias("failed"))


def failure_rate(beats: DataFrame, length: str = "6 hours", step: str = "1 hour") -> DataFrame:
    """(start, rate): share of errors in sliding windows."""
    return beats.groupBy(F.window("ts", length, step).alias("w")).agg(F.avg(F.col("failed").cast("double")).alias("rate"), F.count("*").alias("beats")).select(
        F.col("w.start").alias("start"), "beats", "rate")


def outages(beats: DataFrame, gap: str = "2 hours") -> DataFrame:
    """(sub, start, end, errors): errors of a slice within a gap are one outage."""
    return beats.where("failed").groupBy("sub", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("errors")).select(
        "sub", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "errors")


def first_results(beats: DataFrame) -> DataFrame:
    """Each result once, repeats within the watermark dropped."""
    return beats.dropDuplicatesWithinWatermark(["event_id"]) if beats.isStreaming else beats.dropDuplicates(["event_id"])


def unreturned(assigned: DataFrame, returned: DataFrame, deadline: str = "1 hour") -> DataFrame:
    """(work_id, sub, at, back): assigned work left-joined to results within its deadline; back is null for a fault.

    ``assigned`` is (work_id, sub, at), ``returned`` (result_id, ts), both with watermarks if they stream.
    """
    on = F.expr(f"result_id = work_id AND ts >= at AND ts <= at + INTERVAL {deadline}")
    return assigned.join(returned, on, "leftOuter").select("work_id", "sub", "at", F.col("ts").alias("back"))


class SliceStates(StatefulProcessor):
    """Per slice, the state after each heartbeat: failed, returning (first sound one after a failure), active."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.last = handle.getValueState("last", "failed boolean")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:  # noqa: N802, N803
        # A slice's rows come in several batches, of no order between them: all are put in order before any state is told.
        every = pd.concat([pdf[["ts", "event_id", "failed"]].assign(failed=pdf["failed"].fillna(False).astype(bool)) for pdf in rows], ignore_index=True).sort_values(["ts", "event_id"])
        failed = every["failed"].to_numpy()
        before = np.r_[bool(self.last.get()[0]) if self.last.exists() else False, failed[:-1]]
        state = np.where(failed, "failed", np.where(before, "returning", "active"))
        self.last.update((bool(failed[-1]),))
        ids = every["event_id"].to_numpy()
        for at in range(0, len(ids), CHUNK):
            part = slice(at, at + CHUNK)
            yield pd.DataFrame({"sub": [key[0]] * len(ids[part]), "event_id": ids[part], "state": state[part]})

    def close(self) -> None:
        pass


def slice_states(beats: DataFrame) -> DataFrame:
    """(sub, event_id, state) of a stream; all rows of one trigger are taken in time order, for which a task holds a slice's three columns of it."""
    return beats.groupBy("sub").transformWithStateInPandas(
        statefulProcessor=SliceStates(), outputStructType="sub int, event_id long, state string", outputMode="Append", timeMode="None")


def to_table(df: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run an available-now query to Parquet in the shared folder and read its rows; that of any mode.

    Appended rows go through the file sink. A complete result replaces the one before; updates of each
    micro-batch go to a folder of their own (column epoch), see ``latest``.
    """
    spark = df.sparkSession
    folder = f"{shared_folder(spark)}/{name}"
    writer = df.writeStream.queryName(name).outputMode(mode).option("checkpointLocation", f"{folder}/log").trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").start(f"{folder}/rows").awaitTermination()
        return spark.read.schema(df.schema).parquet(f"{folder}/rows")

    def put(batch: DataFrame, epoch: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/rows" + ("" if mode == "complete" else f"/epoch={epoch}"))

    writer.foreachBatch(put).start().awaitTermination()
    return spark.read.option("basePath", f"{folder}/rows").parquet(f"{folder}/rows")


def latest(rows: DataFrame, keys: list[str]) -> DataFrame:
    """Of rows written batch by batch (column epoch) the last one of each key."""
    values = [c for c in rows.columns if c not in (*keys, "epoch")]
    return rows.groupBy(*keys).agg(F.max(F.struct("epoch", *values)).alias("x")).select(*keys, *[f"x.{v}" for v in values])


def solve_updates(events: DataFrame, update, checkpoint_dir: str):
    """Hand each micro-batch of new facts to ``update(batch, epoch)``, which solves anew from its last result."""
    return events.writeStream.foreachBatch(update).option("checkpointLocation", checkpoint_dir).trigger(availableNow=True).start()
