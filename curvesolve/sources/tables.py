"""The given tables with declared schemas, readers and writers of common formats, and grid bindings.

A binding turns facts into a right-hand side: integer axis codes are binned to cells, amounts are
summed as whole cents, and cells without facts hold zero. Codes that are null or out of range are not
clipped; ``rejected`` counts them.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.grid import GridSpec, axis_cell, cells, lex_id

#: The schemas of the given tables.
SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey bigint, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey bigint, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey bigint, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey bigint, o_custkey bigint, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey bigint, l_partkey bigint, l_suppkey bigint, l_linenumber int, l_quantity double, l_extendedprice double, "
                "l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string",
    "documents": "doc_id bigint, text string, lang string, source string, n_chars bigint",
    "embeddings": "vec_id bigint, embedding array<float>, label int",
    "labels": "doc_id bigint, quality int, toxic int",
    "pages": "page_id bigint, url string, html string",
    "benchmark": "item_id bigint, text string",
    "conversations": "conv_id bigint, turn bigint, role string, text string",
}
DAYS = 2405


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.schema(SCHEMAS[name]).parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """Parquet, ORC, CSV, JSON or text; formats without a schema of their own need one."""
    if fmt in ("csv", "json") and schema is None:
        raise ValueError("declare a schema; it is not inferred")
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write(df: DataFrame, path: str, fmt: str = "parquet", by: list[str] | None = None, mode: str = "errorifexists") -> None:
    """Partitioned by columns if named; mode "dynamic" replaces the partitions that occur."""
    w = df.write.format(fmt)
    if mode == "dynamic":
        w = w.option("partitionOverwriteMode", "dynamic").mode("overwrite")
    else:
        w = w.mode(mode)
    (w.partitionBy(*by) if by else w).save(path)


def write_bucketed(df: DataFrame, name: str, key: str, buckets: int) -> None:
    """A table bucketed and sorted by key: later joins on it need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def cents(amount: Column) -> Column:
    return F.round(amount * 100).cast("long")


def day(ts: Column) -> Column:
    return F.datediff(ts.cast("date"), F.to_date(F.lit("1995-01-01")))


def axes(name: str) -> list[tuple[Column, int]]:
    """(integer code, number of codes) per axis of a binding over lineitem, in order."""
    every = [(F.col("l_quantity").cast("int") - 1, 50), (F.round(F.col("l_discount") * 100).cast("int"), 11), (F.round(F.col("l_tax") * 100).cast("int"), 9),
             (F.col("l_linenumber") - 1, 7), (F.year("l_shipdate") - 1995, 7), (F.array_position(F.lit(["A", "N", "R"]), F.col("l_returnflag")).cast("int") - 1, 3)]
    return every[:int(name[1:])]


def bind(facts: DataFrame, codes: list[tuple[Column, int]], amount: Column, spec: GridSpec) -> DataFrame:
    """(id, cents) of the cells that have facts."""
    coords = [axis_cell(c, m, n) for (c, m), n in zip(codes, spec.extents)]
    known = facts.select(lex_id(coords, spec).alias("id"), amount.alias("amount")).where("id is not null")
    return known.groupBy("id").agg(F.sum("amount").alias("cents"))


def rejected(facts: DataFrame, codes: list[tuple[Column, int]], spec: GridSpec) -> DataFrame:
    """(n_facts, n_rejected)."""
    coords = [axis_cell(c, m, n) for (c, m), n in zip(codes, spec.extents)]
    return facts.agg(F.count("*").alias("n_facts"), F.count_if(lex_id(coords, spec).isNull()).alias("n_rejected"))


def rhs(spark: SparkSession, sf_dir: str, name: str, spec: GridSpec) -> DataFrame:
    """(id, cents) on every cell: B1 orders by day; B2..B6 lineitem; B7 events by hour."""
    if name == "B1":
        facts, codes, amount = table(spark, sf_dir, "orders"), [(day(F.col("o_orderdate")), DAYS)], cents(F.col("o_totalprice"))
    elif name == "B7":
        facts = table(spark, sf_dir, "events")
        hour = F.floor((F.unix_micros(F.col("ts").cast("timestamp")) - F.unix_micros(F.to_timestamp(F.lit("2024-01-01")))) / F.lit(3_600_000_000)).cast("int")
        codes, amount = [(hour, 720), (F.col("user_id").cast("int"), 150)][:spec.d], cents(F.col("value"))
    else:
        facts, codes, amount = table(spark, sf_dir, "lineitem"), axes(name), cents(F.col("l_extendedprice"))
    got = bind(facts, codes, amount, spec)
    return cells(spark, spec).select("id").join(got, "id", "left").select("id", F.coalesce("cents", F.lit(0)).alias("cents"))


def trade_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(a, b, w): shipped value between supplier and customer nations, a < b."""
    li, o = table(spark, sf_dir, "lineitem"), table(spark, sf_dir, "orders")
    c, s = table(spark, sf_dir, "customer"), table(spark, sf_dir, "supplier")
    moved = li.join(o, li["l_orderkey"] == o["o_orderkey"]).join(c, F.col("o_custkey") == c["c_custkey"]).join(s, F.col("l_suppkey") == s["s_suppkey"])
    pair = moved.select(F.least("c_nationkey", "s_nationkey").cast("long").alias("a"), F.greatest("c_nationkey", "s_nationkey").cast("long").alias("b"), cents(F.col("l_extendedprice")).alias("v"))
    return pair.where("a < b").groupBy("a", "b").agg(F.sum("v").alias("w"))


def points(spark: SparkSession, sf_dir: str, bits: int = 5) -> DataFrame:
    """Documents as points: (id, k1, k2) from their length class and language rank."""
    docs = table(spark, sf_dir, "documents")
    size = F.least(F.lit((1 << bits) - 1), F.floor(F.log2(F.greatest(F.col("n_chars"), F.lit(1)).cast("double"))).cast("int"))
    rank = F.coalesce(F.array_position(F.lit(["de", "en", "es", "fr"]), F.col("lang")).cast("int"), F.lit(0))
    return docs.select(F.col("doc_id").alias("id"), size.alias("k1"), rank.alias("k2"))


def vector_points(spark: SparkSession, sf_dir: str, d: int, bits: int) -> DataFrame:
    """Embeddings as points: (id, k1..kd), the first components quantised."""
    top = (1 << bits) - 1
    cells_ = [F.greatest(F.lit(0), F.least(F.lit(top), F.floor((F.col("embedding")[j].cast("double") + 0.6) / 1.2 * (1 << bits)).cast("int"))).alias(f"k{j + 1}") for j in range(d)]
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), *cells_)
