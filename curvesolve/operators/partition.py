"""Slices of an order, their cyclic overlaps, covers and weights, in closed form."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def _div(a: Column, b: Column | int) -> Column:
    return F.floor(a / (b if isinstance(b, Column) else F.lit(b))).cast("long")


def lo_of(sub: Column, n: int, p: int) -> Column:
    return sub * (n // p) + F.least(sub, F.lit(n % p))


def size_of(sub: Column, n: int, p: int) -> Column:
    return F.lit(n // p) + F.when(sub < n % p, 1).otherwise(0)


def slices(spark: SparkSession, n: int, p: int) -> DataFrame:
    """(sub, lo, size): the first n mod p slices are one longer."""
    if not 1 <= p <= n:
        raise ValueError("there must be between one and N slices")
    s = F.col("id")
    return spark.range(p).select(s.cast("int").alias("sub"), lo_of(s, n, p).cast("long").alias("lo"), size_of(s, n, p).cast("long").alias("size"))


def sub_of(pos: Column, n: int, p: int) -> Column:
    w, r = n // p, n % p
    edge = r * (w + 1)
    return F.when(pos < edge, _div(pos, w + 1)).otherwise(r + _div(pos - edge, w)).cast("int")


def _milli(gamma: float) -> tuple[int, int]:
    if gamma <= 0:
        raise ValueError("the overlap must be positive")
    thousand = round(gamma * 1000)
    return thousand // 1000, thousand % 1000


def members(order: DataFrame, n: int, p: int, gamma: float) -> DataFrame:
    """(sub, pos, owner): every position with each grown slice that holds it; an explode, no join.

    A position belongs to its owner, to the owners' whole neighbours, and to one more slice on either
    side if it lies in the part of its slice that faces that side: the rounded-up tail for the slice
    after, the rounded-down head for the slice before.
    """
    whole, milli = _milli(gamma)
    owner = sub_of(F.col("pos"), n, p).cast("long")
    rank = F.col("pos") - lo_of(owner, n, p)
    size = size_of(owner, n, p)
    steps = [F.lit(k) for k in range(-whole, whole + 1)]
    if milli:
        tail = -_div(-(size * milli), 1000)
        steps += [F.when(rank >= size - tail, F.lit(whole + 1)), F.when(rank < _div(size * milli, 1000), F.lit(-whole - 1))]
    made = F.filter(F.array(*[s.cast("int") for s in steps]), lambda s: s.isNotNull())
    out = order.select("pos", owner.cast("int").alias("owner"), F.explode(made).alias("step")).select(
        F.pmod(F.col("owner") + F.col("step"), F.lit(p)).cast("int").alias("sub"), "pos", "owner")
    return out.distinct() if 2 * (whole + 1) + 1 > p else out


def bounds(spark: SparkSession, n: int, p: int, gamma: float) -> DataFrame:
    """(sub, lo, size, ov_lo, ov_len): a grown slice as a cyclic interval of positions."""
    whole, milli = _milli(gamma)
    base = slices(spark, n, p)
    s = F.col("sub").cast("long")
    before = F.lit(0).cast("long")
    after = F.lit(0).cast("long")
    for k in range(1, whole + 1):
        before = before + size_of(F.pmod(s - k, F.lit(p)), n, p)
        after = after + size_of(F.pmod(s + k, F.lit(p)), n, p)
    if milli:
        before = before - _div(-(size_of(F.pmod(s - whole - 1, F.lit(p)), n, p) * milli), 1000)
        after = after + _div(size_of(F.pmod(s + whole + 1, F.lit(p)), n, p) * milli, 1000)
    length = F.least(F.lit(n).cast("long"), F.col("size") + before + after)
    return base.select("sub", "lo", "size", F.pmod(F.col("lo") - before, F.lit(n)).cast("long").alias("ov_lo"), length.cast("long").alias("ov_len"))


def cover(held: DataFrame) -> DataFrame:
    return held.groupBy("pos").agg(F.count("*").alias("cover"))


def weights(held: DataFrame, kind: str, gamma: float, p: int) -> DataFrame:
    """Adds ``w`` to members: none 1, unity 1 / cover, omega the largest 1 / cover of a slice.

    For half-integer overlaps with 2 gamma <= p - 1 every cover is 2 gamma + 1, so the weight is a
    literal and no join is made.
    """
    if kind == "none":
        return held.withColumn("w", F.lit(1.0))
    if kind not in ("unity", "omega"):
        raise ValueError(f"unknown weight {kind!r}")
    twice = 2 * gamma
    if twice == int(twice) and twice <= p - 1:
        return held.withColumn("w", F.lit(1.0 / (twice + 1)))
    unity = held.join(cover(held), "pos").withColumn("w", 1.0 / F.col("cover")).drop("cover")
    if kind == "unity":
        return unity
    top = unity.groupBy("sub").agg(F.max("w").alias("w"))
    return held.join(top, "sub")


def check_uniform(held: DataFrame) -> DataFrame:
    """(lowest, highest) cover; equal where all weights coincide."""
    return cover(held).agg(F.min("cover").alias("lowest"), F.max("cover").alias("highest"))


def tolerance(gamma: float) -> int:
    """So many adjacent slices may fail in one cycle without loss."""
    return int(2 * gamma)


def agg_id(pos: Column, n: int, p: int, q: int) -> Column:
    """Coarse piece of a position: its slice cut in q near-equal pieces."""
    if not 1 <= q <= n // p:
        raise ValueError("a slice has room for at most floor(N / P) coarse pieces")
    sub = sub_of(pos, n, p).cast("long")
    rank, size = pos - lo_of(sub, n, p), size_of(sub, n, p)
    w, r = _div(size, q), size % q
    edge = r * (w + 1)
    piece = F.when(rank < edge, _div(rank, w + 1)).otherwise(r + _div(rank - edge, w))
    return (sub * q + piece).cast("long")


def agg_id_var(pos: Column, n: int, p: int, pieces: list[int]) -> Column:
    """The same with a number of pieces per slice; the table of p numbers is a literal."""
    sub = sub_of(pos, n, p).cast("long")
    first, total = [], 0
    for k in pieces:
        first.append(total)
        total += k
    q = F.element_at(F.lit(pieces), sub.cast("int") + 1).cast("long")
    rank, size = pos - lo_of(sub, n, p), size_of(sub, n, p)
    w, r = _div(size, q), size % q
    edge = r * (w + 1)
    piece = F.when(rank < edge, _div(rank, w + 1)).otherwise(r + _div(rank - edge, w))
    return (F.element_at(F.lit(first), sub.cast("int") + 1).cast("long") + piece).cast("long")


def restrict(v: DataFrame, agg: Column) -> DataFrame:
    """R0 v: sums over pieces; ``v`` is (i, v) in positions, ``agg`` over ``i``."""
    return v.groupBy(agg.alias("agg")).agg(F.sum("v").alias("v"))


def extend(c: DataFrame, order: DataFrame, agg: Column) -> DataFrame:
    """R0^T c: each position takes its piece's value."""
    return order.withColumn("agg", agg).join(c, "agg").select(F.col("pos").alias("i"), "v")


def coarse_matrix(a: DataFrame, agg_i: Column, agg_j: Column) -> DataFrame:
    """R0 A R0^T as one grouping of the entries."""
    return a.groupBy(agg_i.alias("i"), agg_j.alias("j")).agg(F.sum("v").alias("v"))


def q_rule(rule: str, s: int = 8, level: int = 0, n: int = 0, p: int = 1) -> int:
    """Coarse pieces per slice: "fixed" 16, "s" 2^(S-4), "level" 2^(L-12), "np" 2^(floor(log2(N/P)) - 4)."""
    power = {"fixed": 4, "s": s - 4, "level": level - 12, "np": (n // p).bit_length() - 1 - 4}[rule]
    return 2 ** max(0, power)
