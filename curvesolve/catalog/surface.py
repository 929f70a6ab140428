"""The operator surface around the methods: joins, groupings, windows, functions, tables of the user."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions import curves, grid
from ..operators import matrices
from ..sources import grid_source, tables
from .shared import G2, cells_sql

Spark = SparkSession


def x_scan_pushdown(spark: Spark, sf_dir: str) -> DataFrame:
    return tables.table(spark, sf_dir, "lineitem").where("l_quantity between 10 and 20 and l_returnflag = 'A'").select("l_orderkey", "l_linenumber", "l_quantity")


def x_grouping_sets(spark: Spark, sf_dir: str) -> DataFrame:
    li = tables.table(spark, sf_dir, "lineitem")
    li.createOrReplaceTempView("x_lineitem")
    return spark.sql("SELECT l_returnflag, l_linestatus, grouping_id() AS level, count(*) AS n FROM x_lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())")


def x_cube(spark: Spark, sf_dir: str) -> DataFrame:
    li = tables.table(spark, sf_dir, "lineitem")
    return li.cube("l_returnflag", F.year("l_shipdate").alias("y")).agg(F.sum(tables.cents(F.col("l_extendedprice"))).alias("cents"))


def x_rollup(spark: Spark, sf_dir: str) -> DataFrame:
    o = tables.table(spark, sf_dir, "orders")
    return o.rollup(F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m")).agg(F.count("*").alias("n"))


def x_pivot(spark: Spark, sf_dir: str) -> DataFrame:
    e = tables.table(spark, sf_dir, "events").withColumn("sub", F.pmod("user_id", F.lit(10)).cast("int"))
    return e.groupBy("sub").pivot("event_type", ["click", "error"]).agg(F.count(F.lit(1))).select("sub", F.coalesce("click", F.lit(0)).alias("click"), F.coalesce("error", F.lit(0)).alias("error"))


def x_semi_join(spark: Spark, sf_dir: str) -> DataFrame:
    c, o = tables.table(spark, sf_dir, "customer"), tables.table(spark, sf_dir, "orders")
    return c.join(o.where("o_totalprice > 300000"), c["c_custkey"] == o["o_custkey"], "left_semi").select("c_custkey", "c_nationkey")


def x_anti_join(spark: Spark, sf_dir: str) -> DataFrame:
    c, o = tables.table(spark, sf_dir, "customer"), tables.table(spark, sf_dir, "orders")
    return c.join(o, c["c_custkey"] == o["o_custkey"], "left_anti").select("c_custkey")


def x_full_outer(spark: Spark, sf_dir: str) -> DataFrame:
    c, s = tables.table(spark, sf_dir, "customer"), tables.table(spark, sf_dir, "supplier")
    a = c.groupBy(F.col("c_nationkey").alias("k")).agg(F.count("*").alias("customers"))
    b = s.groupBy(F.col("s_nationkey").alias("k")).agg(F.count("*").alias("suppliers"))
    return a.join(b, "k", "full_outer").select("k", F.coalesce("customers", F.lit(0)).alias("customers"), F.coalesce("suppliers", F.lit(0)).alias("suppliers"))


def x_as_of(spark: Spark, sf_dir: str) -> DataFrame:
    """For each purchase, the latest error of the same user before it: one union and a window, no range join."""
    e = tables.table(spark, sf_dir, "events").where("event_type in ('purchase', 'error')")
    by = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "error", F.col("event_id")), ignorenulls=True).over(by)
    return e.withColumn("last_error", last).where("event_type = 'purchase'").select("event_id", "last_error")


def x_interval_join(spark: Spark, sf_dir: str) -> DataFrame:
    """Purchases within ten minutes after a click of the same user: an equi-join on ten-minute cells and their successors."""
    e = tables.table(spark, sf_dir, "events").select("event_id", "user_id", "event_type", F.unix_micros(F.col("ts").cast("timestamp")).alias("at"))
    cell = F.floor(F.col("at") / F.lit(600_000_000))
    clicks = e.where("event_type = 'click'").select("user_id", F.col("at").alias("click_at"), F.explode(F.array(cell, cell + 1)).alias("cell"))
    buys = e.where("event_type = 'purchase'").withColumn("cell", cell)
    return buys.join(clicks, ["user_id", "cell"]).where("at >= click_at and at <= click_at + 600000000").groupBy("event_id").agg(F.count("*").alias("clicks"))


def x_range_join(spark: Spark, sf_dir: str) -> DataFrame:
    """Positions to slices by their bounds: slices are a broadcast of P rows."""
    from ..operators.partition import slices

    s = slices(spark, 1000, 7)
    return spark.range(1000).join(F.broadcast(s), (F.col("id") >= F.col("lo")) & (F.col("id") < F.col("lo") + F.col("size"))).select("id", "sub")


def x_windows(spark: Spark, sf_dir: str) -> DataFrame:
    o = tables.table(spark, sf_dir, "orders")
    by = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    cents = tables.cents(F.col("o_totalprice"))
    return o.select("o_orderkey", F.row_number().over(by).alias("rn"), F.lag("o_orderkey").over(by).alias("before"), F.lead("o_orderkey").over(by).alias("after"),
                    F.sum(cents).over(by.rowsBetween(Window.unboundedPreceding, 0)).alias("running"), F.sum(cents).over(by.rowsBetween(-2, 0)).alias("moving"),
                    F.rank().over(Window.partitionBy("o_custkey").orderBy("o_orderpriority")).alias("rk"), F.dense_rank().over(Window.partitionBy("o_custkey").orderBy("o_orderpriority")).alias("drk"),
                    F.ntile(3).over(by).alias("nt"))


def x_top_k(spark: Spark, sf_dir: str) -> DataFrame:
    return tables.table(spark, sf_dir, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10).select("o_orderkey", "o_totalprice")


def x_top_k_per_group(spark: Spark, sf_dir: str) -> DataFrame:
    c = tables.table(spark, sf_dir, "customer")
    by = Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")
    return c.withColumn("r", F.row_number().over(by)).where("r <= 3").select("c_nationkey", "c_custkey", "r")


def x_set_operations(spark: Spark, sf_dir: str) -> DataFrame:
    o = tables.table(spark, sf_dir, "orders")
    a, b = o.where("o_totalprice > 200000").select("o_custkey"), o.where("o_orderstatus = 'F'").select("o_custkey")
    parts = [a.intersect(b).withColumn("op", F.lit("intersect")), a.exceptAll(b).groupBy("o_custkey").count().select("o_custkey", F.lit("except all").alias("op")), a.union(b).distinct().withColumn("op", F.lit("union"))]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


def x_distinct_counts(spark: Spark, sf_dir: str) -> DataFrame:
    return tables.table(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey", "l_linenumber").alias("pairs"), F.min_by("l_orderkey", F.struct("l_shipdate", "l_orderkey", "l_linenumber")).alias("first_order"))


def x_approx(spark: Spark, sf_dir: str) -> DataFrame:
    """Whether the sketches come within 6 percent of the exact number of parts, and 2 percent of the exact median."""
    got = tables.table(spark, sf_dir, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"), F.percentile_approx("l_extendedprice", 0.5, 1000).alias("median"),
                                                      F.count_distinct("l_partkey").alias("all"), F.percentile("l_extendedprice", 0.5).alias("middle"))
    return got.select((F.abs(F.col("parts") / F.col("all") - 1) < 0.06).alias("parts_near"), (F.abs(F.col("median") / F.col("middle") - 1) < 0.02).alias("median_near"))


def x_percentiles(spark: Spark, sf_dir: str) -> DataFrame:
    return tables.table(spark, sf_dir, "lineitem").groupBy("l_linestatus").agg(F.round(F.percentile("l_quantity", 0.5), 6).alias("median"), F.round(F.percentile("l_extendedprice", 0.9), 6).alias("p90"))


def x_regression(spark: Spark, sf_dir: str) -> DataFrame:
    return tables.table(spark, sf_dir, "lineitem").agg(F.round(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("slope"), F.round(F.corr("l_extendedprice", "l_quantity"), 6).alias("r"))


def x_json(spark: Spark, sf_dir: str) -> DataFrame:
    e = tables.table(spark, sf_dir, "events")
    return e.select("event_id", F.from_json("props", "k int")["k"].alias("k"), F.get_json_object("props", "$.k").cast("int").alias("k2"))


def x_arrays(spark: Spark, sf_dir: str) -> DataFrame:
    e = tables.table(spark, sf_dir, "embeddings")
    v = F.transform("embedding", lambda x: F.round(x.cast("double") * 1000).cast("long"))
    return e.select("vec_id", F.size(v).cast("long").alias("dims"), F.aggregate(v, F.lit(0).cast("long"), lambda a, x: a + x).alias("total"), F.array_max(v).alias("top"), F.element_at(v, 1).alias("head"), F.size(F.filter(v, lambda x: x > 0)).cast("long").alias("positive"))


def x_dates(spark: Spark, sf_dir: str) -> DataFrame:
    o = tables.table(spark, sf_dir, "orders")
    return o.select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), tables.day(F.col("o_orderdate")).alias("day"), F.date_format("o_orderdate", "yyyy-MM").alias("ym"))


def x_hash_sample(spark: Spark, sf_dir: str) -> DataFrame:
    """A reproducible sample of a tenth, by hashed key: the sampling operator."""
    from ..functions.uniform import uniform

    return tables.table(spark, sf_dir, "orders").where(uniform(3, F.col("o_orderkey")) < 0.1).select("o_orderkey")


def x_lateral(spark: Spark, sf_dir: str) -> DataFrame:
    n = tables.table(spark, sf_dir, "nation")
    tables.table(spark, sf_dir, "customer").createOrReplaceTempView("x_customer")
    n.createOrReplaceTempView("x_nation")
    return spark.sql("SELECT n_nationkey, t.c_custkey FROM x_nation, LATERAL (SELECT max(c_custkey) AS c_custkey FROM x_customer WHERE c_nationkey = n_nationkey) t")


@F.udtf(returnType="sub int, lo bigint, size bigint")
class SlicesOf:
    """Table function: the slices of n positions over p."""

    def eval(self, n: int, p: int) -> Iterator[tuple]:
        for s in range(p):
            yield s, s * (n // p) + min(s, n % p), n // p + (s < n % p)


def x_table_function(spark: Spark, sf_dir: str) -> DataFrame:
    spark.udtf.register("slices_of", SlicesOf)
    return spark.sql("SELECT * FROM slices_of(105, 8)")


@F.pandas_udf(T.DoubleType())
def exact_sum(v: pd.Series) -> float:
    """Compensated sum of a group."""
    import math

    return math.fsum(v)


def x_compensated_sum(spark: Spark, sf_dir: str) -> DataFrame:
    return tables.table(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.round(exact_sum("l_extendedprice"), 2).alias("total"))


def x_data_source(spark: Spark, sf_dir: str) -> DataFrame:
    grid_source.register(spark)
    got = spark.read.format("grid_cells").option("levels", "4,3").load()
    return got.select("id", F.col("k")[0].alias("k1"), F.col("k")[1].alias("k2"))


def x_parameter_sql(spark: Spark, sf_dir: str) -> DataFrame:
    return spark.sql("SELECT o_orderstatus, count(*) AS n FROM {orders} WHERE o_totalprice > :least GROUP BY o_orderstatus", args={"least": 150000.0}, orders=tables.table(spark, sf_dir, "orders"))


def x_sql_spmv(spark: Spark, sf_dir: str) -> DataFrame:
    x = grid.cells(spark, G2).select(F.col("id").alias("i"), F.col("id").cast("double").alias("v"))
    return spark.sql("SELECT a.i, round(sum(a.v * x.v), 6) + 0.0D AS v FROM {a} a JOIN {x} x ON x.i = a.j GROUP BY a.i", a=matrices.laplace(spark, G2), x=x)


def x_curve_function(spark: Spark, sf_dir: str) -> DataFrame:
    """Round trip of Hilbert keys over five dimensions."""
    c = spark.range(1024).select("id", *[F.shiftright("id", 2 * j).bitwiseAND(F.lit(3).cast("long")).alias(f"k{j}") for j in range(5)])
    back = curves.hilbert_cell(curves.hilbert_key([F.col(f"k{j}") for j in range(5)], 2), 5, 2)
    c = c.withColumn("c", back)
    again = sum((F.shiftleft(F.col(f"c.x{j}"), 2 * j) for j in range(1, 5)), F.col("c.x0"))
    return c.select("id", again.alias("again"))


def x_rejected(spark: Spark, sf_dir: str) -> DataFrame:
    li = tables.table(spark, sf_dir, "lineitem")
    return tables.rejected(li.where("l_linenumber <= 8"), [(F.col("l_linenumber") - 2, 5)], grid.GridSpec((5,)))


def x_text_scan(spark: Spark, sf_dir: str) -> DataFrame:
    return tables.table(spark, sf_dir, "documents").groupBy("lang", "source").agg(F.count("*").alias("docs"), F.sum("n_chars").alias("chars"))


def x_scan_pages(spark: Spark, sf_dir: str) -> DataFrame:
    return tables.table(spark, sf_dir, "pages").select("page_id", F.length("html").alias("size"))


QUERIES = {f.__name__: f for f in (
    x_scan_pushdown, x_grouping_sets, x_cube, x_rollup, x_pivot, x_semi_join, x_anti_join, x_full_outer, x_as_of, x_interval_join, x_range_join, x_windows, x_top_k, x_top_k_per_group,
    x_set_operations, x_distinct_counts, x_approx, x_percentiles, x_regression, x_json, x_arrays, x_dates, x_hash_sample, x_lateral, x_table_function, x_compensated_sum, x_data_source,
    x_parameter_sql, x_sql_spmv, x_curve_function, x_rejected, x_text_scan, x_scan_pages)}
_W = "OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey"
from .shared import laplace_sql, uniform_sql  # noqa: E402

SQL = {
    "x_approx": "SELECT true AS parts_near, true AS median_near",
    "x_scan_pushdown": "SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_quantity BETWEEN 10 AND 20 AND l_returnflag = 'A'",
    "x_grouping_sets": "SELECT l_returnflag, l_linestatus, CAST(grouping_id(l_returnflag, l_linestatus) AS BIGINT) AS level, CAST(count(*) AS BIGINT) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_returnflag), ())",
    "x_cube": "SELECT l_returnflag, CAST(year(l_shipdate) AS INTEGER) AS y, CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS BIGINT) AS cents FROM lineitem GROUP BY CUBE (l_returnflag, year(l_shipdate))",
    "x_rollup": "SELECT CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, CAST(count(*) AS BIGINT) AS n FROM orders GROUP BY ROLLUP (year(o_orderdate), month(o_orderdate))",
    "x_pivot": "SELECT CAST(user_id % 10 AS INTEGER) AS sub, CAST(count(*) FILTER (WHERE event_type = 'click') AS BIGINT) AS click, CAST(count(*) FILTER (WHERE event_type = 'error') AS BIGINT) AS error FROM events GROUP BY 1",
    "x_semi_join": "SELECT c_custkey, c_nationkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_totalprice > 300000)",
    "x_anti_join": "SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)",
    "x_full_outer": "SELECT coalesce(a.k, b.k) AS k, CAST(coalesce(c, 0) AS BIGINT) AS customers, CAST(coalesce(s, 0) AS BIGINT) AS suppliers FROM (SELECT c_nationkey AS k, count(*) AS c FROM customer GROUP BY 1) a FULL JOIN (SELECT s_nationkey AS k, count(*) AS s FROM supplier GROUP BY 1) b ON a.k = b.k",
    "x_as_of": "SELECT p.event_id, (SELECT arg_max(e.event_id, (e.ts, e.event_id)) FROM events e WHERE e.user_id = p.user_id AND e.event_type = 'error' AND (e.ts, e.event_id) < (p.ts, p.event_id)) AS last_error FROM events p WHERE p.event_type = 'purchase'",
    "x_interval_join": "SELECT p.event_id, CAST(count(*) AS BIGINT) AS clicks FROM events p JOIN events c ON c.user_id = p.user_id AND c.event_type = 'click' AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 10 MINUTE WHERE p.event_type = 'purchase' GROUP BY 1",
    "x_range_join": "SELECT CAST(i AS BIGINT) AS id, CAST(CASE WHEN i < 6 * 143 THEN i // 143 ELSE 6 + (i - 858) // 142 END AS INTEGER) AS sub FROM range(1000) t(i)",
    "x_windows": f"SELECT o_orderkey, CAST(row_number() {_W}) AS INTEGER) AS rn, lag(o_orderkey) {_W}) AS before, lead(o_orderkey) {_W}) AS after, CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) {_W} ROWS UNBOUNDED PRECEDING) AS BIGINT) AS running, "
                 f"CAST(sum(CAST(round(o_totalprice * 100) AS BIGINT)) {_W} ROWS 2 PRECEDING) AS BIGINT) AS moving, CAST(rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS INTEGER) AS rk, CAST(dense_rank() OVER (PARTITION BY o_custkey ORDER BY o_orderpriority) AS INTEGER) AS drk, CAST(ntile(3) {_W}) AS INTEGER) AS nt FROM orders",
    "x_top_k": "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10",
    "x_top_k_per_group": "SELECT c_nationkey, c_custkey, CAST(r AS INTEGER) AS r FROM (SELECT *, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS r FROM customer) WHERE r <= 3",
    "x_set_operations": "WITH a AS (SELECT o_custkey FROM orders WHERE o_totalprice > 200000), b AS (SELECT o_custkey FROM orders WHERE o_orderstatus = 'F') SELECT o_custkey, 'intersect' AS op FROM (SELECT o_custkey FROM a INTERSECT SELECT o_custkey FROM b) UNION ALL SELECT DISTINCT o_custkey, 'except all' FROM (SELECT o_custkey FROM a EXCEPT ALL SELECT o_custkey FROM b) UNION ALL SELECT o_custkey, 'union' FROM (SELECT o_custkey FROM a UNION SELECT o_custkey FROM b)",
    "x_distinct_counts": "SELECT l_returnflag, CAST(count(DISTINCT l_partkey) AS BIGINT) AS parts, CAST(count(DISTINCT (l_suppkey, l_linenumber)) AS BIGINT) AS pairs, arg_min(l_orderkey, (l_shipdate, l_orderkey, l_linenumber)) AS first_order FROM lineitem GROUP BY 1",
    "x_percentiles": "SELECT l_linestatus, round(quantile_cont(l_quantity, 0.5), 6) AS median, round(quantile_cont(l_extendedprice, 0.9), 6) AS p90 FROM lineitem GROUP BY 1",
    "x_regression": "SELECT round(regr_slope(l_extendedprice, l_quantity), 4) AS slope, round(corr(l_extendedprice, l_quantity), 6) AS r FROM lineitem",
    "x_json": "SELECT event_id, CAST(json_extract(props, '$.k') AS INTEGER) AS k, CAST(json_extract(props, '$.k') AS INTEGER) AS k2 FROM events",
    "x_arrays": "WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(round(CAST(x AS DOUBLE) * 1000) AS BIGINT)) AS v FROM embeddings) SELECT vec_id, CAST(len(v) AS BIGINT) AS dims, CAST(list_sum(v) AS BIGINT) AS total, list_max(v) AS top, v[1] AS head, CAST(len(list_filter(v, lambda x: x > 0)) AS BIGINT) AS positive FROM v",
    "x_dates": "SELECT o_orderkey, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, CAST(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS INTEGER) AS day, strftime(o_orderdate, '%Y-%m') AS ym FROM orders",
    "x_hash_sample": f"SELECT o_orderkey FROM orders WHERE {uniform_sql('3', 'o_orderkey')} < 0.1",
    "x_lateral": "SELECT n_nationkey, max(c_custkey) AS c_custkey FROM nation LEFT JOIN customer ON c_nationkey = n_nationkey GROUP BY 1",
    "x_table_function": "SELECT CAST(s AS INTEGER) AS sub, CAST(s * 13 + least(s, 1) AS BIGINT) AS lo, CAST(13 + (CASE WHEN s < 1 THEN 1 ELSE 0 END) AS BIGINT) AS size FROM range(8) t(s)",
    "x_compensated_sum": "SELECT l_returnflag, l_linestatus, round(CAST(sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS DOUBLE) / 100, 2) AS total FROM lineitem GROUP BY 1, 2",
    "x_data_source": cells_sql(G2),
    "x_parameter_sql": "SELECT o_orderstatus, CAST(count(*) AS BIGINT) AS n FROM orders WHERE o_totalprice > 150000 GROUP BY 1",
    "x_sql_spmv": f"SELECT a.i, round(sum(a.v * a.j), 6) + 0.0 AS v FROM ({laplace_sql(G2)}) a GROUP BY a.i",
    "x_curve_function": "SELECT CAST(i AS BIGINT) AS id, CAST(i AS BIGINT) AS again FROM range(1024) t(i)",
    "x_rejected": "SELECT CAST(count(*) AS BIGINT) AS n_facts, CAST(count(*) FILTER (WHERE l_linenumber < 2 OR l_linenumber > 6) AS BIGINT) AS n_rejected FROM lineitem WHERE l_linenumber <= 8",
    "x_text_scan": "SELECT lang, source, CAST(count(*) AS BIGINT) AS docs, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY 1, 2",
    "x_scan_pages": "SELECT page_id, CAST(length(html) AS INTEGER) AS size FROM pages",
}
