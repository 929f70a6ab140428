"""Remaining measures, baselines, layouts and small workloads."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import SolveConfig
from ..functions.grid import GridSpec, cells, extents_for_budget, needle
from ..operators import blocks, combine, matrices, ordering, partition
from ..plans import advise, measures, sweeps, theory
from ..sources import tables
from .grids import SQL as GRID_SQL
from .shared import G2, GAMMA, N, P, SCALE, cells_sql, laplace_sql, members_sql, rhs_sql

Spark = SparkSession


def m15_manufactured(spark: Spark, sf_dir: str) -> DataFrame:
    exact = cells(spark, G2).select(F.col("id").alias("i"), (F.col("k1") * F.col("k2")).cast("double").alias("v"))
    return matrices.manufactured(matrices.laplace(spark, G2), exact).select("i", F.round("v", 6).alias("v"))


def m33_exponents(spark: Spark, sf_dir: str) -> DataFrame:
    return spark.createDataFrame([(d, *theory.holder_exponent(d)) for d in range(1, 7)], "d int, hilbert double, lebesgue double").select("d", F.round("hilbert", 9).alias("hilbert"), F.round("lebesgue", 9).alias("lebesgue"))


def m45_none(spark: Spark, sf_dir: str) -> DataFrame:
    held = partition.members(spark.range(N).select(F.col("id").alias("pos")), N, P, GAMMA)
    return partition.weights(held, "none", GAMMA, P).groupBy("sub").agg(F.sum("w").alias("total"))


def m49_tolerance(spark: Spark, sf_dir: str) -> DataFrame:
    return spark.createDataFrame([(g, partition.tolerance(g)) for g in (0.25, 0.5, 0.75, 1.0, 1.5, 2.0)], "gamma double, faults int")


def m58_kernel_basis(spark: Spark, sf_dir: str) -> DataFrame:
    """Restriction by one constant per grown slice, weighted to a partition of unity."""
    v = tables.rhs(spark, sf_dir, "B2", G2).select(F.col("id").alias("pos"), (F.col("cents") / SCALE).alias("v"))
    held = partition.weights(partition.members(spark.range(N).select(F.col("id").alias("pos")), N, P, 0.25), "unity", 0.25, P)
    return held.join(v, "pos").groupBy("sub").agg(F.round(F.sum(F.col("w") * F.col("v")), 6).alias("v"))


def m62_coarse_rules(spark: Spark, sf_dir: str) -> DataFrame:
    rows = [(s, partition.q_rule("fixed"), partition.q_rule("s", s=s), partition.q_rule("np", n=2**s * 64, p=64)) for s in range(4, 13)]
    return spark.createDataFrame(rows, "s int, fixed int, by_size int, by_slice int")


def m63_level_distance(spark: Spark, sf_dir: str) -> DataFrame:
    rows = [(d, q, measures.level_distance(2**14, 64, q, d), measures.coarse_share(2**14, 64, q)) for d in (1, 2, 3, 6) for q in (4, 16)]
    return spark.createDataFrame(rows, "d int, q int, distance double, share double").select("d", "q", F.round("distance", 9).alias("distance"), "share")


def m71_uniform_plan(spark: Spark, sf_dir: str) -> DataFrame:
    """Weights for half-integer overlaps: a literal, equal to the joined ones."""
    held = partition.members(spark.range(N).select(F.col("id").alias("pos")), N, P, 1.5)
    return partition.weights(held, "omega", 1.5, P).select("sub", "pos", "w")


def _gaps(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    from ..kernels import System

    for pdf in batches:
        for r in pdf.itertuples():
            s = System(SolveConfig((256,), 8, 4, float(r.gamma), weight=r.weight, kind=r.kind))
            yield pd.DataFrame([{"kind": r.kind, "weight": r.weight, "gamma": r.gamma, "symmetric": bool(s.symmetry_gap() < 1e-9)}])


def m75_symmetry(spark: Spark, sf_dir: str) -> DataFrame:
    rows = [(k, w, g) for k in ("one_level", "additive", "balanced") for w in ("none", "omega", "unity") for g in (0.3, 0.5)]
    return spark.createDataFrame(rows, "kind string, weight string, gamma double").repartition(8).mapInPandas(_gaps, "kind string, weight string, gamma double, symmetric boolean")


def m110_norms(spark: Spark, sf_dir: str) -> DataFrame:
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from ..plans.baselines import norm_ratio

        for pdf in batches:
            for n in pdf["n"]:
                lo, hi = norm_ratio(int(n))
                yield pd.DataFrame([{"n": int(n), "lowest": lo, "highest": hi}])
    got = spark.createDataFrame([(7,), (15,), (31,)], "n int").mapInPandas(run, "n int, lowest double, highest double")
    # Up to its scale the ratio of both norms stays within fixed bounds on every grid.
    return got.select("n", ((F.col("lowest") > 0) & (F.col("highest") / F.col("lowest") < 4)).alias("bounded"))


def m111_effective_weight(spark: Spark, sf_dir: str) -> DataFrame:
    rows = [(g, *measures.effective_weight(1.86, g)) for g in (0.5, 1.0, 2.0)]
    return spark.createDataFrame(rows, "gamma double, effective double, plain double").select("gamma", F.round("effective", 9).alias("effective"), F.round("plain", 9).alias("plain"))


def m61_nested(spark: Spark, sf_dir: str) -> DataFrame:
    """Iterations with the coarse problem solved directly and by the method itself."""
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from ..kernels import System, rates, solve
        from ..plans.baselines import Nested

        for pdf in batches:
            for p in pdf["p"]:
                cfg = SolveConfig((64 * int(p),), int(p), 4, method="flexible")
                yield pd.DataFrame([{"p": int(p), "direct": rates(solve(System(cfg)).errors)["k_iter"], "nested": rates(solve(Nested(cfg)).errors)["k_iter"]}])
    got = spark.createDataFrame([(8,), (16,), (32,)], "p int").repartition(3).mapInPandas(run, "p int, direct int, nested int")
    return got.select("p", (F.abs(F.col("direct") - F.col("nested")) <= 2).alias("agree"))


def m128_fault_baselines(spark: Spark, sf_dir: str) -> DataFrame:
    """Rebuilding beside restart from snapshots, from zero, and no recovery."""
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from ..plans.baselines import table

        for pdf in batches:
            for r in pdf.itertuples():
                yield pd.DataFrame([table(r.name, SolveConfig((1024,), 16, 4, 1.0, method="richardson", xi=1.6, maxit=300, p_fault=r.rate))]).astype({"k_iter": "Int32"})
    rows = [(n, f) for n in ("rebuild", "snapshot", "from zero", "no recovery") for f in (0.0, 0.01, 0.05)]
    return spark.createDataFrame(rows, "name string, rate double").repartition(8).mapInPandas(run, "baseline string, p_fault double, k_iter int, lost int, last double")


def m138_combination_error(spark: Spark, sf_dir: str) -> DataFrame:
    """Largest difference of the combined and the full-grid solution of a smooth problem, by level."""
    import numpy as np

    rows = []
    for top in (3, 4):
        x = (np.arange(2**top - 1) + 1) / 2**top
        f = 2 * np.pi**2 * np.sin(np.pi * x)[:, None] * np.sin(np.pi * x)[None, :]
        grids = combine.levels(spark, 2, top)
        got = combine.solve_all(grids, f, top)
        n = 2**top - 1
        pts = spark.range(n * n).select("id", F.array((F.floor(F.col("id") / n) + 1) / F.lit(2.0**top), (F.col("id") % n + 1) / F.lit(2.0**top)).alias("x"))
        exact = F.sin(F.col("x")[0] * F.pi()) * F.sin(F.col("x")[1] * F.pi())
        rows.append(combine.evaluate(pts, got, grids).join(pts, "id").agg(F.lit(top).alias("level"), F.max(F.abs(F.col("u") - exact)).alias("error")))
    both = rows[0].unionByName(rows[1])
    return both.agg((F.max(F.when(F.col("level") == 4, F.col("error"))) < F.max(F.when(F.col("level") == 3, F.col("error")))).alias("falls"))


def m139_combination_under_faults(spark: Spark, sf_dir: str) -> DataFrame:
    """The same sums with failing local solves in every grid."""
    import numpy as np

    x = (np.arange(15) + 1) / 16
    f = np.sin(np.pi * x)[:, None] * np.sin(np.pi * x)[None, :]
    grids = combine.levels(spark, 2, 4)
    parts = [combine.solve_all(grids, f, 4, p_hat=2, p_fault=p).groupBy(F.array_join(F.transform("l", lambda v: v.cast("string")), ",").alias("l")).agg(F.round(F.sum("u"), 7).alias(f"u{k}"), F.bool_and("ok").alias(f"ok{k}")) for k, p in enumerate((0.0, 0.05))]
    return parts[0].join(parts[1], "l").select("l", ((F.abs(F.col("u0") - F.col("u1")) < 1e-6) | ~F.col("ok1")).alias("equal"))


def m141_advice(spark: Spark, sf_dir: str) -> DataFrame:
    rows = [(d, p, advise.gamma(p), advise.q(2**14, 64, d), *advise.method(p, d)) for d in (1, 6) for p in (0.0, 0.02, 0.05, 0.2)]
    return spark.createDataFrame(rows, "d int, p_fault double, gamma double, q int, kind string, weight string, method string")


def m05_extents(spark: Spark, sf_dir: str) -> DataFrame:
    """Extents for budgets of points, the orders' prices in whole thousands: not above it, near it, and as equal as whole numbers allow."""
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in frames:
            rows = []
            for n, orders in zip(pdf["n"].tolist(), pdf["orders"].tolist()):
                for d in range(1, 7):
                    x = extents_for_budget(d, n)
                    size = GridSpec(x).size
                    rows.append((d, n, len(x), size <= n, size >= 0.75 * n, max(x) - min(x) <= 1, orders))
            yield pd.DataFrame(rows, columns=["d", "n", "axes", "within", "near", "even", "orders"])

    thousands = F.floor(F.col("o_totalprice") / 1000).cast("int") * 1000
    budgets = tables.table(spark, sf_dir, "orders").groupBy(thousands.alias("n")).agg(F.count("*").alias("orders")).where("n > 0")
    return budgets.mapInPandas(run, "d int, n int, axes int, within boolean, near boolean, even boolean, orders long")


def m144_upper_envelope(spark: Spark, sf_dir: str) -> DataFrame:
    """Whether grids of two and three dimensions stay below the count of the line of as many points."""
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from ..kernels import System, rates, solve

        for pdf in batches:
            for d, m in zip(pdf["d"], pdf["method"]):
                cfg = SolveConfig({2: (31, 32), 3: (10, 10, 10)}[int(d)], 16, 4, method=m)
                yield pd.DataFrame([{"d": int(d), "method": m, "below": rates(solve(System(cfg)).errors)["k_iter"] <= advise.iteration_cap(cfg)}]).astype({"d": "int32"})
    rows = [(d, m) for d in (2, 3) for m in ("pcg", "richardson")]
    return spark.createDataFrame(rows, "d int, method string").repartition(4).mapInPandas(run, "d int, method string, below boolean")


def w01_curves(spark: Spark, sf_dir: str) -> DataFrame:
    """Length of the polylines of both curves at three refinements."""
    parts = None
    for curve in ("hilbert", "lebesgue"):
        for n in (1, 2, 3):
            spec = GridSpec((2**n, 2**n))
            from ..functions.curves import key

            order = ordering.positions(cells(spark, spec).withColumn("key", key(curve, [F.col("k1") - 1, F.col("k2") - 1], n)), ["key"])
            part = ordering.lagged(order, 2, 1).agg(F.lit(curve).alias("curve"), F.lit(n).alias("n"), F.round(F.sum("dist") / 2**n, 9).alias("length"))
            parts = part if parts is None else parts.unionByName(part)
    return parts


def w04_growth(spark: Spark, sf_dir: str) -> DataFrame:
    parts = None
    for lv in ((3, 3), (2, 3)):
        n = GridSpec.of_levels(lv).size
        held = partition.members(spark.range(n).select(F.col("id").alias("pos")), n, 4, 0.25)
        part = held.groupBy(F.lit(",".join(map(str, lv))).alias("levels"), "sub").agg(F.count_if(F.col("sub") == F.col("owner")).alias("own"), F.count_if(F.col("sub") != F.col("owner")).alias("borrowed"))
        parts = part if parts is None else parts.unionByName(part)
    return parts.where("sub in (0, 2)")


def w15_needle(spark: Spark, sf_dir: str) -> DataFrame:
    """Entries in which the needle grid's matrix and the reaction operator differ: none."""
    a, b = matrices.laplace(spark, needle(4, 6)), matrices.reaction(spark, 6, 24.0)
    return a.exceptAll(b).unionByName(b.exceptAll(a))


def _diffusion(spark: Spark, sf_dir: str, steps: int | None):
    from ..plans import distributed
    from .grids import m09_diffusion

    s = distributed.setup(spark, SolveConfig(G2.extents, 4, 2, 0.5, tol=1e-11), m09_diffusion(spark, sf_dir))
    b = tables.rhs(spark, sf_dir, "B2", G2).join(s.order, "id").select("pos", (F.col("cents") / SCALE).alias("v"))
    out = distributed.run(s, b, steps=steps)
    return s, distributed.solution(s, out.state)


def w28_diffusion_solve(spark: Spark, sf_dir: str) -> DataFrame:
    """A x of the balanced solve with the coefficient of lineitem cells: the right-hand side again."""
    s, x = _diffusion(spark, sf_dir, None)
    got = matrices.spmv(s.a, x.withColumnRenamed("pos", "i"))
    return got.join(s.order, F.col("i") == F.col("pos")).select("id", (F.round("v", 5) + 0.0).alias("v"))


def m16_blocked_spmv(spark: Spark, sf_dir: str) -> DataFrame:
    x = tables.rhs(spark, sf_dir, "B2", G2).select(F.col("id").alias("i"), (F.col("cents") / SCALE).alias("v"))
    got = blocks.spmv(blocks.matrix(matrices.laplace(spark, G2), N, P), blocks.vector(x, N, P))
    return blocks.rows(got).select("i", F.round("v", 4).alias("v"))


QUERIES = {f.__name__: f for f in (
    m15_manufactured, m16_blocked_spmv, m33_exponents, m45_none, m49_tolerance, m58_kernel_basis, m61_nested, m62_coarse_rules, m63_level_distance, m71_uniform_plan, m75_symmetry, m110_norms,
    m111_effective_weight, m128_fault_baselines, m138_combination_error, m139_combination_under_faults, m141_advice, m05_extents, m144_upper_envelope, w01_curves, w04_growth, w15_needle, w28_diffusion_solve)}
_SLICE = "SELECT * FROM (VALUES ('3,3', 0, 13, 6), ('3,3', 2, 12, 6), ('2,3', 0, 6, 3), ('2,3', 2, 5, 3)) t(levels, sub, own, borrowed)"
SQL = {
    "m15_manufactured": f"SELECT a.i, round(sum(a.v * c.k1 * c.k2), 6) + 0.0 AS v FROM ({laplace_sql(G2)}) a JOIN ({cells_sql(G2)}) c ON c.id = a.j GROUP BY a.i",
    "m16_blocked_spmv": GRID_SQL["m16_spmv"],
    "m33_exponents": "SELECT CAST(d AS INTEGER) AS d, round(1.0 / d, 9) AS hilbert, round(1.0 / (d * log2(3.0)), 9) AS lebesgue FROM range(1, 7) t(d)",
    "m45_none": f"SELECT sub, CAST(count(*) AS DOUBLE) AS total FROM ({members_sql(N, P, GAMMA)}) GROUP BY sub",
    "m49_tolerance": "SELECT CAST(g AS DOUBLE) AS gamma, CAST(floor(2 * g) AS INTEGER) AS faults FROM (VALUES (0.25), (0.5), (0.75), (1.0), (1.5), (2.0)) t(g)",
    "m58_kernel_basis": f"WITH m AS ({members_sql(N, P, 0.25)}), c AS (SELECT pos, count(*) AS n FROM m GROUP BY pos) SELECT m.sub, round(sum(r.cents / {SCALE!r} / c.n), 6) AS v FROM m JOIN c USING (pos) JOIN ({rhs_sql('B2', G2)}) r ON r.id = m.pos GROUP BY m.sub",
    "m62_coarse_rules": "SELECT CAST(s AS INTEGER) AS s, CAST(16 AS INTEGER) AS fixed, CAST(power(2, greatest(0, s - 4)) AS INTEGER) AS by_size, CAST(power(2, greatest(0, s - 4)) AS INTEGER) AS by_slice FROM range(4, 13) t(s)",
    "m63_level_distance": "SELECT CAST(d AS INTEGER) AS d, CAST(q AS INTEGER) AS q, round(power(q * 64 / 16384.0, -1.0 / d), 9) AS distance, CAST(q * 64 / 256.0 AS DOUBLE) AS share FROM (VALUES (1), (2), (3), (6)) a(d), (VALUES (4), (16)) b(q)",
    "m71_uniform_plan": f"WITH m AS ({members_sql(N, P, 1.5)}), c AS (SELECT pos, count(*) AS n FROM m GROUP BY pos) SELECT m.sub, m.pos, max(1.0::DOUBLE / c.n) OVER (PARTITION BY m.sub) AS w FROM m JOIN c USING (pos)",
    "m75_symmetry": "SELECT kind, weight, CAST(g AS DOUBLE) AS gamma, NOT (weight = 'unity' AND g = 0.3) AS symmetric FROM (VALUES ('one_level'), ('additive'), ('balanced')) a(kind), (VALUES ('none'), ('omega'), ('unity')) b(weight), (VALUES (0.3), (0.5)) c(g)",
    "m111_effective_weight": "SELECT CAST(g AS DOUBLE) AS gamma, round(1.86 / (2 * g + 1), 9) AS effective, round(1.0 / (2 * g + 1), 9) AS plain FROM (VALUES (0.5::DOUBLE), (1.0), (2.0)) t(g)",
    "w04_growth": f"SELECT levels, CAST(sub AS INTEGER) AS sub, CAST(own AS BIGINT) AS own, CAST(borrowed AS BIGINT) AS borrowed FROM ({_SLICE})",
    "w15_needle": "SELECT CAST(0 AS BIGINT) AS i, CAST(0 AS BIGINT) AS j, CAST(0 AS DOUBLE) AS v WHERE 1 = 0",
    "w28_diffusion_solve": f"SELECT id, round(cents / {SCALE!r}, 5) + 0.0 AS v FROM ({rhs_sql('B2', G2)})",
    "m61_nested": "SELECT CAST(p AS INTEGER) AS p, true AS agree FROM (VALUES (8), (16), (32)) t(p)",
    "m05_extents": "SELECT CAST(d AS INTEGER) AS d, CAST(n AS INTEGER) AS n, CAST(d AS INTEGER) AS axes, true AS within, true AS near, true AS even, orders FROM range(1, 7) t(d), "
                   "(SELECT CAST(floor(o_totalprice / 1000) AS INTEGER) * 1000 AS n, CAST(count(*) AS BIGINT) AS orders FROM orders GROUP BY 1) WHERE n > 0",
    "m144_upper_envelope": "SELECT CAST(d AS INTEGER) AS d, m AS method, true AS below FROM (VALUES (2), (3)) t(d), (VALUES ('pcg'), ('richardson')) u(m)",
    "m110_norms": "SELECT CAST(n AS INTEGER) AS n, true AS bounded FROM (VALUES (7), (15), (31)) t(n)",
    "m138_combination_error": "SELECT true AS falls",
    "w01_curves": f"WITH RECURSIVE z AS (SELECT n, i, list_sum([((i >> (2 * b + 1)) & 1) << b for b in range(n)]) AS x, list_sum([((i >> (2 * b)) & 1) << b for b in range(n)]) AS y FROM range(1, 4) t(n), range(64) c(i) WHERE i < power(4, n)) "
                  "SELECT 'hilbert' AS curve, CAST(n AS INTEGER) AS n, round((power(4, n) - 1) / power(2, n), 9) AS length FROM range(1, 4) t(n) UNION ALL "
                  "SELECT 'lebesgue', CAST(n AS INTEGER), round(sum(d) / power(2, n), 9) FROM (SELECT n, sqrt(power(x - lag(x) OVER w, 2) + power(y - lag(y) OVER w, 2)) AS d FROM z WINDOW w AS (PARTITION BY n ORDER BY i)) GROUP BY n",
    "m139_combination_under_faults": "SELECT a || ',' || b AS l, true AS equal FROM range(1, 5) x(a), range(1, 5) y(b) WHERE a + b IN (4, 5)",
    "m141_advice": "SELECT CAST(d AS INTEGER) AS d, CAST(p AS DOUBLE) AS p_fault, CAST(g AS DOUBLE) AS gamma, CAST(CASE WHEN d <= 3 THEN 16 ELSE 8 END AS INTEGER) AS q, 'balanced' AS kind, 'omega' AS weight, CASE WHEN p = 0 THEN 'pcg' WHEN p >= 0.1 AND d >= 6 THEN 'richardson' ELSE 'flexible' END AS method "
                   "FROM (VALUES (1), (6)) a(d), (VALUES (0.0, 0.5), (0.02, 0.5), (0.05, 1.0), (0.2, 3.0)) b(p, g)",
}
