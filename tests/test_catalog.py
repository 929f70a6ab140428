"""Every registered query of the library with SQL, against DuckDB on the smallest tables."""

import os

import pytest
from compare import connect, differ
from pyspark.sql import functions as F

from curvesolve import catalog
from curvesolve.functions import grid

#: Experiments at full size and the flagship solve take up to a minute each; RUN_SLOW=1 holds them against their SQL here too.
SLOW = {f"w{k}" for k in ("05", "08", "09", "10", "13", "18", "19", "20", "21", "22", "24", "25")} | {"m70_balanced_pcg"}
SQL = catalog.oracle_sql()


@pytest.fixture(scope="module")
def con(sf):
    return connect(sf)


@pytest.mark.parametrize("name", [n for n in SQL if not {n, n[:3]} & SLOW or os.environ.get("RUN_SLOW")])
def test_query_equals_sql(spark, sf, con, name):
    assert differ(spark, con, sf, catalog.queries()[name], SQL[name]) is None


#: Queries that once made up their data.
TABLED = ("m01_unknowns", "m02_cells", "m03_lex_round_trip", "m04_levels", "m05_extents", "m06_needle", "m07_laplace", "m08_fem", "m100_expected_bound", "m101_mean_rate", "m102_one_step", "m103_fault_bound")


@pytest.mark.parametrize("name", TABLED)
def test_query_reads_a_table(spark, sf, name):
    assert any(f.endswith(".parquet") for f in catalog.queries()[name](spark, sf).inputFiles())


def test_level_column_agrees(spark):
    every = spark.range(1, 300).selectExpr("id AS p", "explode(array(1, 2, 3, 6)) AS d").withColumn("level", grid.level_column(F.col("d"), 8, F.col("p")))
    assert all(grid.levels_for(r["d"], 8, r["p"]) == (r["level"],) * r["d"] for r in every.collect())


def test_every_sql_has_a_query():
    assert set(SQL) <= set(catalog.queries())
