"""Mixing sources to target weights by hierarchical budgets, in DataFrame expressions only.

A tree of domains, languages and sources carries weights. A node can supply the tokens below it times
the most epochs allowed. The token budget is poured from the root down: among siblings by weight, and
what a sibling cannot supply goes to the other siblings first; as a node's own budget never exceeds
what lies below it, only a shortage of a whole node reaches its parent's siblings. Each leaf then
takes whole seeded epochs and, for the rest, the longest token prefix of the next epoch's order.

The order within a leaf and epoch is that of a seeded hash of doc_id, so a prefix is a hash cutoff.
It is found by radix selection: token sums per 8-bit digit, then within the digit that the budget
ends in, and so on; no task orders a whole leaf.

Defined results: documents without a token, such as null and empty texts, are not taken; null names are the name ""; rows with equal
order keys (repeated rows, null ids) enter or stay out together; a budget beyond what all leaves can
supply is cut to it; an empty table gives an empty result; other columns pass through.
"""

from __future__ import annotations

import math
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ._common import WORD, cut

LEVELS = ("domain", "lang", "source")
#: Leaves up to which a table of leaves is broadcast; beyond that it is joined by shuffle.
FEW = 50_000
MILLION = 1_000_000
#: Target weights of the registered query and the pipeline: languages, and the stand-in domains; sources share alike.
TARGETS = {"domain": {"domain0": 4.0, "domain1": 3.0, "domain2": 2.0, "domain3": 1.0}, "lang": {"en": 5.0, "de": 2.0, "fr": 2.0, "es": 1.0}}
#: Rows of the last radix bucket to aim at.
BUCKET = 64


def default_domain(domains: int = 4) -> Column:
    """A stand-in domain for tables without one: sources dealt to a few domains by hash."""
    return F.concat(F.lit("domain"), F.pmod(F.crc32(F.coalesce(F.col("source"), F.lit("")).cast("binary")), F.lit(domains)).cast("string"))


def order_key(seed: int, epoch: Column) -> Column:
    return F.xxhash64(F.lit(seed), epoch.cast("int"), F.col("doc_id")).bitwiseXOR(F.lit(-(1 << 63)))


def digit(key: Column, level: int) -> Column:
    """The level-th 8-bit digit of a key, most significant first; keys compare as unsigned numbers."""
    return F.shiftrightunsigned(key, 56 - 8 * level).bitwiseAND(F.lit(255)).cast("int")


def leaves(docs: DataFrame, domain: Column | None, path: tuple[str, ...]) -> list[Column]:
    names = {"domain": domain if domain is not None else default_domain()}
    return [F.coalesce(names.get(p, F.col(p)).cast("string"), F.lit("")).alias(f"_{p}") for p in path]


def weight_of(name: str, weights: dict[str, float]) -> Column:
    """A child's weight in millionths, as a whole number, so that sums do not depend on their order; 1 unless given."""
    w = F.lit(MILLION)
    for k, v in weights.items():
        w = F.when(F.col(name) == k, F.lit(round(v * MILLION))).otherwise(w)
    return w.cast("decimal(38,0)")


def pour(nodes: DataFrame, parent: list[str], name: str, weights: dict[str, float], few: bool = False) -> DataFrame:
    """Share each parent's ``budget`` among its children: by weight, none beyond its supply ``cap``.

    Children whose supply is no more than their share are filled; what they leave is shared among the
    rest, until none is filled any more. Each round is one sum by parent, pre-aggregated before its
    exchange, so a parent may have any number of children; ``few`` nodes go through one task without
    exchanges. Adds the column ``given``; shares are whole tokens, rounded down.
    """
    def together(df: DataFrame) -> DataFrame:
        return df.coalesce(1) if few else df

    rows = cut(together(nodes.withColumn("_w", weight_of(name, weights)).withColumn("_full", F.col("_w") < 0).withColumn("_all", F.lit(0))))
    keys = [*parent, "_all"]
    while True:
        rows = together(rows)
        sums = rows.groupBy(*[F.col(p).alias(f"_of{p}") for p in keys]).agg(
            F.sum(F.when(F.col("_full"), F.col("cap")).otherwise(0)).cast("decimal(38,0)").alias("_used"),
            F.sum(F.when(~F.col("_full"), F.col("_w")).otherwise(0)).cast("decimal(38,0)").alias("_left"))
        shared = rows.join(sums, [F.col(p) == F.col(f"_of{p}") for p in keys])
        room = F.greatest(F.col("budget").cast("decimal(38,0)") - F.col("_used"), F.lit(0)).cast("decimal(19,0)")
        share = F.col("_w").cast("decimal(19,0)") * room
        fills = ~F.col("_full") & (F.col("_w") > 0) & (F.col("cap").cast("decimal(19,0)") * F.col("_left").cast("decimal(19,0)") <= share)
        shared = cut(shared.select(*rows.columns, fills.alias("_fills"), F.when(F.col("_full"), F.col("cap")).when(
            F.col("_left") > 0, F.call_function("div", share, F.col("_left"))).otherwise(0).cast("long").alias("given")))
        if shared.where("_fills").isEmpty():
            return shared.drop("_w", "_full", "_fills", "_all")
        rows = shared.withColumn("_full", F.col("_full") | F.col("_fills")).select(*rows.columns)


def budgets(sums: DataFrame, total: Column, weights: dict[str, dict[str, float]], epochs: int, path: tuple[str, ...], few: bool = False) -> DataFrame:
    """(leaf names, tokens, given) of leaf token sums; ``total`` is an expression over ``tokens``, all tokens."""
    cols = [f"_{p}" for p in path]
    nodes = (sums.coalesce(1) if few else sums).withColumn("cap", F.col("tokens") * epochs)
    whole = nodes.agg(F.coalesce(F.sum("tokens"), F.lit(0)).alias("tokens"), F.coalesce(F.sum("cap"), F.lit(0)).alias("cap")).select(
        F.least(total.cast("long"), F.col("cap")).alias("budget")).first()["budget"]
    above = None
    for depth, name in enumerate(cols):
        parent = cols[:depth]
        level = nodes.groupBy(*cols[:depth + 1]).agg(F.sum("cap").alias("cap"))
        level = level.withColumn("budget", F.lit(whole)) if above is None else level.join(above, parent)
        above = pour(level, parent, name, weights.get(path[depth], {}), few).select(*cols[:depth + 1], F.col("given").alias("budget"))
    return nodes.join(above.withColumnRenamed("budget", "given"), cols).select(*cols, "tokens", "given")


def leaf_cutoffs(docs: DataFrame, share: float = 0.8, weights: dict[str, dict[str, float]] | None = None, epochs: int = 3,
                 seed: int = 11, domain: Column | None = None, path: tuple[str, ...] = LEVELS, tokens: Column | None = None) -> DataFrame:
    """Per leaf: names, tokens, given, whole epochs, and the cutoff key of the epoch cut short (null: none of it)."""
    cols = [f"_{p}" for p in path]
    count = tokens if tokens is not None else F.regexp_count(F.coalesce(F.col("text"), F.lit("")), F.lit(WORD))
    narrow = cut(docs.select("doc_id", *leaves(docs, domain, path), count.cast("long").alias("n")))
    sums = cut(narrow.groupBy(*cols).agg(F.sum("n").alias("tokens"), F.count("*").alias("docs")))
    size = sums.agg(F.max("docs").alias("most"), F.count("*").alias("n")).first()
    most, small = size["most"] or 0, F.broadcast if size["n"] <= FEW else (lambda df: df)
    given = cut(budgets(sums.drop("docs"), F.col("tokens") * F.lit(float(share)), weights or {}, epochs, path, size["n"] <= FEW).select(
        *cols, "tokens", "given", F.when(F.col("tokens") > 0, F.call_function("div", F.col("given"), F.col("tokens"))).otherwise(0).cast("int").alias("full")))
    at = given.select(*cols, "full", (F.col("given") - F.col("full") * F.col("tokens")).alias("room"), F.lit(0).cast("long").alias("prefix"), F.lit(None).cast("long").alias("cutoff"))
    levels = 1 + max(0, math.ceil(math.log2(max(1, most) / BUCKET) / 8))
    by = Window.partitionBy(*cols).orderBy("d")
    for level in range(levels):
        shift = 64 - 8 * level
        inside = F.lit(True) if level == 0 else F.shiftrightunsigned("key", shift) == F.col("prefix")
        # Few rows: a leaf has one row, and only the digit its budget ends in is looked into further.
        keyed = narrow.where("n > 0").join(small(at.where("room > 0")), cols).withColumn("key", order_key(seed, F.col("full"))).where(inside)
        d = digit(F.col("key"), level)
        last = level == levels - 1
        cells = keyed.groupBy(*cols, "room", "prefix", "cutoff", (F.col("key").bitwiseXOR(F.lit(-(1 << 63))) if last else d).alias("d")).agg(
            F.sum("n").alias("n"), F.max(F.col("key").bitwiseXOR(F.lit(-(1 << 63)))).alias("top"))
        cells = cells.withColumn("upto", F.sum("n").over(by))
        fits = F.col("upto") <= F.col("room")
        found = cells.groupBy(*cols).agg(
            F.max(F.when(fits, F.col("top"))).alias("_top"), F.max(F.when(fits, F.col("upto"))).alias("_used"), F.min(F.when(~fits, F.col("d"))).alias("_d"))
        at = cut(at.join(found, cols, "left").select(
            *cols, "full", F.when(F.col("_d").isNull(), F.lit(0)).otherwise(F.col("room") - F.coalesce("_used", F.lit(0))).alias("room"),
            F.shiftleft("prefix", 8).bitwiseOR(F.coalesce("_d", F.lit(0)).cast("long")).alias("prefix"), F.coalesce("_top", "cutoff").alias("cutoff")))
    return cut(given.join(at.select(*cols, "cutoff"), cols))


def _taken(docs: DataFrame, seed: int = 11, domain: Column | None = None, path: tuple[str, ...] = LEVELS, **options) -> DataFrame:
    """(row, leaf, copies): the documents taken, packed, so that names inside and outside cannot clash."""
    cols = [f"_{p}" for p in path]
    plan = leaf_cutoffs(docs, seed=seed, domain=domain, path=path, **options)
    few = plan.count() <= FEW
    plan = plan.where("tokens > 0").drop("tokens", "given")
    count = options.get("tokens")
    worded = F.rlike(F.coalesce(F.col("text"), F.lit("")), F.lit(r"[^\x20\x09-\x0D]")) if count is None else count > 0
    rows = docs.where(worded).select(F.struct("*").alias("row"), F.col("doc_id"), *leaves(docs, domain, path)).select("row", "doc_id", *cols)
    both = rows.join(F.broadcast(plan) if few else plan, cols)
    signed = order_key(seed, F.col("full")).bitwiseXOR(F.lit(-(1 << 63)))
    copies = F.col("full") + F.coalesce((signed <= F.col("cutoff")).cast("int"), F.lit(0))
    return both.select("row", F.concat_ws("/", *cols).alias("leaf"), copies.alias("copies")).where("copies > 0")


def mix(docs: DataFrame, **options) -> DataFrame:
    """The documents with their leaf and the number of copies the mixture takes; none taken: not returned."""
    return _taken(docs, **options).select(*[F.col("row").getField(c).alias(c) for c in docs.columns], "leaf", "copies")


def mixed_documents(docs: DataFrame, **options) -> DataFrame:
    """The mixture itself: each document as many times as the mixture takes it, columns unchanged."""
    taken = _taken(docs, **options).select("row", F.explode(F.sequence(F.lit(1), F.col("copies"))))
    return taken.select(*[F.col("row").getField(c).alias(c) for c in docs.columns])
