"""Blocked layout: one row per slice with its values as an array; only boundary values move.

A block vector is (sub, lo, vs). The matrix is kept as (sub, rows array<struct<r, entries>>) for entries
within the slice and (sub, from_sub, entries array<struct<r, c, v>>) for entries to other slices, so a
product moves one row per pair of touching slices instead of one per matrix entry.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .partition import lo_of, sub_of


def vector(x: DataFrame, n: int, p: int) -> DataFrame:
    """(sub, lo, vs) of (i, v) with a value at every position."""
    sub = sub_of(F.col("i"), n, p)
    rows = x.groupBy(sub.alias("sub")).agg(F.sort_array(F.collect_list(F.struct("i", "v"))).alias("e"))
    return rows.select("sub", lo_of(F.col("sub").cast("long"), n, p).cast("long").alias("lo"), F.transform("e", lambda e: e["v"]).alias("vs"))


def matrix(a: DataFrame, n: int, p: int) -> DataFrame:
    """(sub, from_sub, entries) with offsets within the slices."""
    si, sj = sub_of(F.col("i"), n, p), sub_of(F.col("j"), n, p)
    local = a.select(si.alias("sub"), sj.alias("from_sub"), "i", "j", "v").select(
        "sub", "from_sub", F.struct((F.col("i") - lo_of(F.col("sub").cast("long"), n, p)).cast("int").alias("r"),
                                    (F.col("j") - lo_of(F.col("from_sub").cast("long"), n, p)).cast("int").alias("c"), "v").alias("e"))
    return local.groupBy("sub", "from_sub").agg(F.sort_array(F.collect_list("e")).alias("entries"))


def spmv(m: DataFrame, x: DataFrame) -> DataFrame:
    """(sub, lo, vs): products of touching slices, added per slice; all in expressions."""
    got = m.join(x.select(F.col("sub").alias("from_sub"), F.col("vs").alias("xs")), "from_sub")
    terms = got.select("sub", F.explode(F.transform("entries", lambda e: F.struct(e["r"].alias("r"), (e["v"] * F.get("xs", e["c"])).alias("v")))).alias("t"))
    summed = terms.groupBy("sub", "t.r").agg(F.sum("t.v").alias("v"))
    packed = summed.groupBy("sub").agg(F.sort_array(F.collect_list(F.struct("r", "v"))).alias("e"))
    return packed.join(x.select("sub", "lo"), "sub").select("sub", "lo", F.transform("e", lambda e: e["v"]).alias("vs"))


def rows(x: DataFrame) -> DataFrame:
    """(i, v) of a block vector."""
    return x.select("lo", F.posexplode("vs").alias("k", "v")).select((F.col("lo") + F.col("k")).alias("i"), "v")
