"""Curve order of cells: dense positions without a global window, locality, and slice shape."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.curves import key as curve_key
from ..runtime import checkpoint


def with_key(df: DataFrame, curve: str, d: int, bits: int, first: int = 1) -> DataFrame:
    """Adds ``key``; ``first`` is the smallest coordinate."""
    return df.withColumn("key", curve_key(curve, [F.col(f"k{j + 1}") - first + (1 if curve in ("hilbert", "lebesgue") and first else 0) for j in range(d)], bits))


def positions(df: DataFrame, keys: list[str], partitions: int | None = None) -> DataFrame:
    """Adds ``pos`` 0..N-1 by ascending keys, which must be unique together.

    Range partitions are numbered on their own and shifted by the counts before them: one range
    exchange, and a table of one row per partition that is broadcast.
    """
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = checkpoint(df.repartitionByRange(n, *keys).withColumn("_p", F.spark_partition_id()))
    sizes = dealt.groupBy("_p").agg(F.count("*").alias("_n"))
    before = Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)  # one row per partition
    starts = sizes.select("_p", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_at"))
    rank = F.row_number().over(Window.partitionBy("_p").orderBy(*keys)) - 1
    return dealt.withColumn("_r", rank).join(F.broadcast(starts), "_p").withColumn("pos", (F.col("_at") + F.col("_r")).cast("long")).drop("_p", "_r", "_at")


def adaptive_prefix(df: DataFrame, d: int, bits: int) -> DataFrame:
    """Bit-interleaved order with no more digits than needed: (.., prefix, depth) of each cell.

    Rounds lengthen the prefix by a level only for cells that still share it with another cell.
    """
    from ..functions.curves import interleave

    todo, done = df, None
    for depth in range(1, bits + 1):
        cols = [F.shiftright(F.col(f"k{j + 1}").cast("long"), bits - depth) for j in range(d)]
        marked = todo.withColumn("prefix", F.shiftleft(interleave(cols, depth), d * (bits - depth))).withColumn("depth", F.lit(depth))
        ties = marked.groupBy("prefix").count().where("count > 1").select("prefix")
        last = depth == bits
        alone = marked if last else marked.join(ties, "prefix", "left_anti")
        done = alone if done is None else done.unionByName(alone.select(*done.columns))
        if last:
            break
        todo = checkpoint(marked.join(ties, "prefix", "left_semi").select(*df.columns))
        if todo.isEmpty():
            break
    return done


def lagged(order: DataFrame, d: int, lag: int) -> DataFrame:
    """(pos, lag, dist): Euclidean distance of cells ``lag`` positions apart; an equi-join on shifted positions."""
    ahead = order.select((F.col("pos") - lag).alias("pos"), *[F.col(f"k{j + 1}").alias(f"m{j + 1}") for j in range(d)])
    gap = sum((F.col(f"k{j + 1}") - F.col(f"m{j + 1}")) * (F.col(f"k{j + 1}") - F.col(f"m{j + 1}")) for j in range(d))
    return order.join(ahead, "pos").select("pos", F.lit(lag).alias("lag"), F.sqrt(gap.cast("double")).alias("dist"))


def holder(order: DataFrame, d: int, lags: list[int]) -> DataFrame:
    """Per lag, the largest distance over lag^(1/d), beside the bound 2 sqrt(d + 3)."""
    parts = None
    for lag in lags:
        part = lagged(order, d, lag)
        parts = part if parts is None else parts.unionByName(part)
    return parts.groupBy("lag").agg(F.max(F.col("dist") / F.pow(F.col("lag"), F.lit(1.0 / d))).alias("ratio")).withColumn("bound", F.lit(2 * (d + 3) ** 0.5))


def slice_shape(a: DataFrame, subs: DataFrame) -> DataFrame:
    """(sub, cells, cut_edges, neighbours): the surface of each slice; ``subs`` is (pos, sub), ``a`` in positions."""
    near = a.where("i <> j").join(subs.select(F.col("pos").alias("i"), "sub"), "i").join(subs.select(F.col("pos").alias("j"), F.col("sub").alias("other")), "j")
    edges = near.where("sub <> other").groupBy("sub").agg(F.count("*").alias("cut_edges"), F.count_distinct("other").alias("neighbours"))
    return subs.groupBy("sub").agg(F.count("*").alias("cells")).join(edges, "sub", "left").select(
        "sub", "cells", F.coalesce("cut_edges", F.lit(0)).alias("cut_edges"), F.coalesce("neighbours", F.lit(0)).alias("neighbours"))


def slice_components(a: DataFrame, subs: DataFrame) -> DataFrame:
    """(sub, components): connected parts of each slice, by spreading the smallest label until nothing changes."""
    inner = a.where("i <> j").join(subs.select(F.col("pos").alias("i"), "sub"), "i").join(subs.select(F.col("pos").alias("j"), F.col("sub").alias("other")), "j").where("sub = other").select("i", "j")
    inner = checkpoint(inner)
    label = checkpoint(subs.select("pos", "sub", F.col("pos").alias("label")))
    while True:
        seen = inner.join(label.select(F.col("pos").alias("j"), "label"), "j").groupBy(F.col("i").alias("pos")).agg(F.min("label").alias("m"))
        new = label.join(seen, "pos", "left").select("pos", "sub", F.least("label", F.coalesce("m", "label")).alias("near"), "label")
        # Jump to the label's own label, which halves the rounds.
        hop = new.select(F.col("pos").alias("near"), F.col("near").alias("far"))
        new = checkpoint(new.join(hop, "near").select("pos", "sub", F.least("near", "far").alias("new"), "label"))
        moved = new.where("new < label").limit(1).count()
        label = new.select("pos", "sub", F.col("new").alias("label"))
        if not moved:
            return label.groupBy("sub").agg(F.count_distinct("label").alias("components"))
