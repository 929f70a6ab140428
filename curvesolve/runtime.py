"""Checkpoints, partition counts and frame caching."""

from __future__ import annotations

import tempfile

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The checkpoint folder that the session names; a temporary one only on a single machine where it names none."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not sc.master.startswith("local"):
            raise ValueError("name a folder that all machines share in spark.checkpoint.dir")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="checkpoint-"))
    return sc._jsc.sc().getCheckpointDir().get()


def checkpoint(df: DataFrame) -> DataFrame:
    """Reliable checkpoint in the shared folder; the frame made of it carries no size estimate of its plan's joins along."""
    spark = df.sparkSession
    shared_folder(spark)
    done = df.checkpoint()._jdf
    return DataFrame(spark._jsparkSession.internalCreateDataFrame(done.queryExecution().toRdd(), done.schema(), False), spark)


def flat(df: DataFrame) -> DataFrame:
    """The same rows under a plan of one step; lost ones are still computed again from lineage. For kept frames of long loops."""
    spark, made = df.sparkSession, df.select("*")._jdf
    return DataFrame(spark._jsparkSession.internalCreateDataFrame(made.queryExecution().toRdd(), made.schema(), False), spark)


def keep(df: DataFrame) -> DataFrame:
    """Cached with spilling; lost blocks are computed again from their lineage."""
    return df.persist(StorageLevel.MEMORY_AND_DISK)


def release(*frames: DataFrame) -> None:
    for df in frames:
        df.unpersist()


def one_task_frame(spark: SparkSession, rows: list[dict], schema: str, partitions: int) -> DataFrame:
    """A small frame of run parameters, one row per task."""
    names = [c.strip().split(" ")[0] for c in schema.split(",")]
    return spark.createDataFrame([tuple(r[n] for n in names) for r in rows], schema).repartition(max(1, min(partitions, len(rows))))
