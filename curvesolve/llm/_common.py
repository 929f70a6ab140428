"""Helpers shared by the corpus operators: checkpoints, skew-safe joins, components, spans."""

from __future__ import annotations

import gc
import tempfile
from collections.abc import Iterator

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space, the separator of words in all operators here.
WORD = r"[^\x20\x09-\x0D]+"


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Use the folder the session names in spark.checkpoint.dir; on a single machine make one where it names none."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not sc.master.startswith("local"):
            raise ValueError("name a folder that all machines share in spark.checkpoint.dir")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="checkpoint-"))


def cut(df: DataFrame) -> DataFrame:
    """Reliable checkpoint: the rows are written once to the shared folder and read from there afterwards.

    The frame made of them has no size estimate: a checkpoint inherits that of its plan, a join the
    product of its sides', so that after many rounds planning would do nothing but multiply.
    """
    ensure_checkpoint_dir(df.sparkSession)
    spark, done = df.sparkSession, df.checkpoint()._jdf
    return DataFrame(spark._jsparkSession.internalCreateDataFrame(done.queryExecution().toRdd(), done.schema(), False), spark)


def tidy(df: DataFrame) -> None:
    """Have Spark remove the shuffle files, and where the session cleans them the checkpoints, of frames that nothing names any more.

    It does so as the driver collects its garbage, for which a driver with little to do has no cause of its own.
    """
    gc.collect()
    df.sparkSession._jvm.System.gc()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def keyed_min(df: DataFrame, key: str, value: str, out: str) -> DataFrame:
    """(key, min value) whose partitioning is hidden from later joins on ``key``.

    Grouping happens on the complemented key, so a join on ``key`` gets a fresh exchange on both
    sides; adaptive execution can then split the partition of a hot key on the other side.
    """
    grouped = df.groupBy(F.bitwise_not(F.col(key)).alias("_k")).agg(F.min(value).alias(out))
    return grouped.select(F.bitwise_not(F.col("_k")).alias(key), out)


def components(edges: DataFrame) -> DataFrame:
    """Connected components of edges (u, v) of longs: rows (node, root), root the smallest node.

    Alternating large-star and small-star rounds, each a pre-aggregated minimum and one join, with a
    checkpoint per round. Null ends and loops are ignored; nodes without an edge do not appear.
    """
    e = cut(edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct())
    seen = None
    while True:
        mark = e.agg(F.count("*").alias("n"), F.bit_xor(F.xxhash64("u", "v")).alias("x")).first()
        if mark["n"] == 0 or mark == seen:
            return e.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(
                e.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
        seen = mark
        both = e.select(F.col("u").alias("x"), F.col("v").alias("y")).unionByName(
            e.select(F.col("v").alias("x"), F.col("u").alias("y")))
        low = keyed_min(both, "x", "y", "m").select("x", F.least("x", "m").alias("m"))
        large = both.join(low, "x").where("y > x").select(F.col("y").alias("u"), F.col("m").alias("v"))
        low = keyed_min(large, "u", "v", "m")
        small = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        e = cut(small.unionByName(low.select("u", F.col("m").alias("v"))).distinct())


def spanning(n: int, edges: Iterator[np.ndarray]) -> np.ndarray:
    """For 0..n-1, the smallest member each is connected to."""
    root = list(range(n))

    def find(x: int) -> int:
        while root[x] != x:
            root[x] = x = root[root[x]]
        return x

    for part in edges:
        for a, b in part.tolist():
            a, b = find(a), find(b)
            if a != b:
                root[max(a, b)] = min(a, b)
    return np.array([find(x) for x in range(n)], np.int64)


def let(value: Column, body) -> Column:
    """body(value) with the value computed once per row, also where body uses it within lambdas."""
    return F.element_at(F.transform(F.array(value), body), 1)


def _running(items: Column, zero: Column) -> Column:
    """Spans of items (gap, hit) laid one after the other, beginning at ``zero``."""
    def step(acc: Column, x: Column) -> Column:
        start = acc["at"] + F.length(x["gap"])
        end = start + F.length(x["hit"])
        return F.struct(end.alias("at"), F.concat(acc["out"], F.array(
            F.struct(start.alias("s"), end.alias("e"), x["hit"].alias("t")))).alias("out"))
    empty = F.array().cast("array<struct<s:int,e:int,t:string>>")
    return F.aggregate(items, F.struct(zero.alias("at"), empty.alias("out")), step, lambda acc: acc["out"])


def spans(text: Column, pattern: str, chunk: int = 512) -> Column:
    """All leftmost non-overlapping matches as array<struct<s, e, t>>; code points, end exclusive.

    Position arithmetic on the gaps and hits of one pattern, chunk by chunk, so that its cost stays
    near linear in the number of matches. No match: an empty array.
    """
    items = F.zip_with(F.split(text, pattern, -1), F.regexp_extract_all(text, F.lit(pattern), F.lit(0)),
                       lambda g, h: F.struct(g.alias("gap"), h.alias("hit")))
    items = F.filter(items, lambda x: x["hit"].isNotNull())

    def lay(blocks: Column) -> Column:
        lengths = F.transform(blocks, lambda b: F.aggregate(
            b, F.lit(0), lambda acc, x: acc + F.length(x["gap"]) + F.length(x["hit"])))
        offsets = F.aggregate(lengths, F.array(F.lit(0)), lambda acc, n: F.concat(acc, F.array(F.element_at(acc, -1) + n)))
        return F.flatten(F.zip_with(blocks, F.slice(offsets, 1, F.size(blocks)), _running))

    return let(items, lambda it: let(F.transform(
        F.sequence(F.lit(0), F.greatest(F.lit(0), F.ceil(F.size(it) / F.lit(chunk)).cast("int") - 1)),
        lambda c: F.slice(it, c * chunk + 1, chunk)), lay))


def span_text(marks: Column) -> Column:
    """Comma-joined kind:start:end of array<struct<s, k, e, kind>>, by start, then by the kind's number k."""
    return F.array_join(F.transform(F.array_sort(marks), lambda x: F.concat_ws(
        ":", x["kind"], x["s"].cast("string"), x["e"].cast("string"))), ",")


def marks_of(kind: str, order: int, found: Column) -> Column:
    return F.transform(found, lambda x: F.struct(
        x["s"].alias("s"), F.lit(order).alias("k"), x["e"].alias("e"), F.lit(kind).alias("kind")))
