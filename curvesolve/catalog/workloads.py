"""The experiments: convergence tables over generated grids, and combinations on table data."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import SolveConfig
from ..functions.grid import GridSpec, extents_for_budget
from ..kernels import System
from ..operators import combine, faults
from ..operators.partition import q_rule
from ..plans import measures, spectra, sweeps
from ..sources import tables
from . import claims as claims_of
from .shared import SCALE, rhs_sql

Spark = SparkSession
#: Sizes of the experiments: points per slice as a power of two, coarse pieces, and numbers of slices.
POINTS, PIECES, SLICES = 8, 16, (16, 64, 256)
BOTH = ("richardson", "pcg")


def weak(p: int, s: int = POINTS, q: int = PIECES, d: int = 1, **options) -> SolveConfig:
    """A grid of about 2^s points for each of p slices."""
    extents = (2**s * p,) if d == 1 else extents_for_budget(d, 2**s * p)
    n = GridSpec(extents).size
    return SolveConfig(extents, p, min(q, n // p), **options)


def w05_plain(slices=SLICES, **o) -> list[SolveConfig]:
    return [weak(p, kind="additive", weight=w, method=m, **o) for p in slices for w in ("none", "omega", "unity") for m in BOTH]


def w06_balanced(slices=SLICES, **o) -> list[SolveConfig]:
    return [weak(p, weight=w, method=m, **o) for p in slices for w in ("none", "omega", "unity") for m in BOTH]


def w07_kinds(slices=(64, 256), **o) -> list[SolveConfig]:
    return [weak(p, kind=k, method=m, maxit=4000, **o) for p in slices for k in ("one_level", "kernel", "additive", "deflated", "balanced") for m in ("pcg",)]


GAMMAS = (0.2, 0.5, 0.75, 1.0, 1.5, 2.0, 3.0, 4.0, 5.0)


def w08_gamma(weight: str = "none", slices=(128,), d: int = 1, gammas=GAMMAS, **o) -> list[SolveConfig]:
    return [weak(p, d=d, gamma=g, weight=weight, method=m, **o) for p in slices for g in gammas for m in BOTH]


def w11_asymmetric(p: int = 64) -> list[SolveConfig]:
    return [weak(p, gamma=0.3, weight="unity", method=m, maxit=400) for m in ("pcg", "flexible")] + [weak(p, gamma=0.3, weight="omega", method="pcg")]


def w12_size(points=(6, 8, 10), p: int = 64) -> list[SolveConfig]:
    return [weak(p, s=s, method=m, maxit=4000) for s in points for m in BOTH] + [weak(p, s=12, method="pcg")]


def w13_size_q(points=(6, 8, 10, 12), p: int = 64) -> list[SolveConfig]:
    return [weak(p, s=s, q=q_rule("s", s=s), method=m) for s in points for m in BOTH]


def w13_quadrupled(points=(6, 7, 8), p: int = 64) -> list[SolveConfig]:
    """q grows fourfold where a slice doubles."""
    return [weak(p, s=s, q=4 ** (s - 5), method=m) for s in points for m in BOTH]


def w14_dimension(p: int = 64, s: int = POINTS) -> list[SolveConfig]:
    return [weak(p, s=s, q=q_rule("s", s=s), d=d, method=m) for d in (1, 2, 3, 4, 5, 6) for m in BOTH]


def w16_strong(level: int = 16, slices=(16, 32, 64, 100, 128, 200, 256, 400, 512, 1024), by_p: bool = False, methods=("pcg",)) -> list[SolveConfig]:
    n = 2**level
    return [SolveConfig((n,), p, min(n // p, q_rule("np", n=n, p=p) if by_p else q_rule("level", level=level)), method=m) for p in slices for m in methods]


def w18_pairs(p: int = 256) -> list[tuple[str, SolveConfig]]:
    """Each side by its own rule: N and q from the level, or from the points per slice."""
    out = []
    for level, s in ((16, 8), (18, 10), (20, 12)):
        out += [(f"strong {level}", w16_strong(level, (p,))[0]), (f"weak {s}", weak(p, s=s, q=q_rule("s", s=s), method="pcg"))]
    return out


RATES = (0.0, 0.01, 0.02, 0.05, 0.1, 0.2)


def w19_faults(p: int = 100, d: int = 1, rates=RATES, gammas=(0.5, 1.0, 1.5, 2.0), runs: int = 10, methods=BOTH, **o) -> list[SolveConfig]:
    return [weak(p, d=d, gamma=g, method=m, p_fault=f, run=r, maxit=600, **o) for g in gammas for f in rates for m in methods for r in range(runs)]


def w23_switch(p: int = 64) -> list[SolveConfig]:
    return [weak(p, gamma=2.0, method="richardson", spectrum=True, switch=k) for k in (0, 5, 10)]


#: Experiments of which each configuration is one row. d = 6 under faults: fewer slices, overlaps and runs, as a slice's dense inverse grows with the sixth of its width.
TABLES = {
    "w05": [("w05", c) for c in w05_plain()], "w06": [("w06", c) for c in w06_balanced()], "w07": [("w07", c) for c in w07_kinds()],
    "w08": [("w08", c) for c in w08_gamma("none")], "w09": [("w09", c) for c in w08_gamma("omega")],
    "w10": [("w10", c) for w in ("none", "omega") for c in w08_gamma(w, (128,), 3, (0.2, 0.5, 1.0))], "w11": [("w11", c) for c in w11_asymmetric()],
    "w12": [("w12", c) for c in w12_size()], "w13": [("w13", c) for c in w13_size_q()] + [("w13 quadrupled", c) for c in w13_quadrupled()],
    "w14": [("w14", c) for c in w14_dimension()], "w16": [("w16", c) for c in w16_strong()], "w17": [("w17", c) for c in w16_strong(by_p=True)], "w18": w18_pairs(),
    "w19": [("w19", c) for c in w19_faults()], "w20": [("w20", c) for c in w19_faults(50, 6, (0.0, 0.1, 0.2), (0.5, 2.0), 3)],
    "w21": [("w21", c) for p in (32, 64, 128) for c in w19_faults(p, gammas=(3.0,), runs=4)],
    "w22": [("w22", c) for p in (16, 32) for c in w19_faults(p, 6, (0.0, 0.05, 0.1, 0.2), (3.0,), 3)],
    "w23": [("w23", c) for c in w23_switch()], "w24": [("w24", c) for c in w19_faults(200, gammas=(2.0,), rates=(0.0, 0.02, 0.05, 0.1), runs=4, methods=("pcg",))],
    "w25": [("w25", c) for c in w19_faults(kind="additive", gammas=(2.0,), rates=(0.0, 0.05), runs=3, methods=("richardson",))],
}


def rows(spark: Spark, name: str) -> DataFrame:
    """All rows of an experiment: iterations, rates, spectrum and survival of each run."""
    return sweeps.sweep(spark, TABLES[name])


def _held(name: str, claims: list[claims_of.Claim]):
    def run(spark: Spark, sf_dir: str) -> DataFrame:
        return claims_of.held(rows(spark, name), claims)
    return run


def w03_levels_split(spark: Spark, sf_dir: str) -> DataFrame:
    """Cells of the grids (3,3) and (2,3) by slice, in Hilbert order, for two to eight slices."""
    from ..functions.curves import hilbert_key
    from ..functions.grid import cells
    from ..operators.ordering import positions
    from ..operators.partition import sub_of

    parts = None
    for lv in ((3, 3), (2, 3)):
        spec = GridSpec.of_levels(lv)
        order = positions(cells(spark, spec).withColumn("key", hilbert_key([F.col("k1"), F.col("k2")], spec.bits)), ["key"])
        for p in range(2, 9):
            part = order.groupBy(F.lit(",".join(map(str, lv))).alias("levels"), F.lit(p).alias("p"), sub_of(F.col("pos"), spec.size, p).alias("sub")).agg(F.count("*").alias("cells"))
            parts = part if parts is None else parts.unionByName(part)
    return parts


def w26_combination(spark: Spark, sf_dir: str) -> DataFrame:
    """Combined solution at the points of the finest grid, right-hand side from lineitem."""
    top = 3
    full = GridSpec.of_levels((top, top))
    got = tables.rhs(spark, sf_dir, "B2", full).toPandas()  # the 49 cells of the full grid
    f = np.zeros(full.size)
    f[got["id"]] = got["cents"] / SCALE
    grids = combine.levels(spark, 2, top)
    solved = combine.solve_all(grids, f.reshape(full.extents), top)
    points = spark.range(full.size).select("id", F.array(((F.floor(F.col("id") / 7) + 1) / 8.0), ((F.col("id") % 7 + 1) / 8.0)).alias("x"))
    return combine.evaluate(points, solved, grids).select("id", (F.round("u", 6) + 0.0).alias("u"))


def m131_levels(spark: Spark, sf_dir: str) -> DataFrame:
    return combine.levels(spark, 3, 5).select("layer", F.array_join(F.transform("l", lambda x: x.cast("string")), ",").alias("l"), "coef")


def m133_counts(spark: Spark, sf_dir: str) -> DataFrame:
    return combine.counts(spark, 4, 6, 8)


def w27_totals(spark: Spark, sf_dir: str) -> DataFrame:
    return spark.createDataFrame([(d, combine.total_subdomains(d, 20, 1)) for d in range(1, 7)], "d int, total long")


def w30_cost(spark: Spark, sf_dir: str) -> DataFrame:
    """Operations that one application is seen to take, from the kernel's counters."""
    rows = []
    for kind in ("one_level", "additive", "deflated", "balanced"):
        system = System(SolveConfig((64,), 8, 2, kind=kind))
        system.apply(np.ones(64))
        rows.append((kind, *(system.counts[n] for n in ("matvec", "axpy", "coarse", "local"))))
    return spark.createDataFrame(rows, "kind string, matvec int, axpy int, coarse int, local int")


def w29_log(spark: Spark, sf_dir: str) -> DataFrame:
    """Share of failing (cycle, slice) pairs in the log beside that of a drawn schedule of the same rate."""
    log = faults.from_events(tables.table(spark, sf_dir, "events"), 10)
    return log.groupBy("sub").agg(F.count("*").alias("cycles"), F.count_if("failed").alias("failed"))


def w99_scaling(spark: Spark, sf_dir: str) -> DataFrame:
    """Slope of log K over log P: none for two levels, a large one for one level."""
    got = sweeps.sweep(spark, [("w99", c) for c in w07_kinds((64, 128, 256))]).where("ok and kind in ('one_level', 'balanced')")
    return measures.scaling(got).select("kind", (F.abs("slope") < 0.1).alias("scales"))


def m51_spectrum(spark: Spark, sf_dir: str) -> DataFrame:
    """Whether extreme eigenvalues by conjugate-gradient coefficients and by restarts agree with the dense ones."""
    def near(a: str, b: str, share: float):
        return F.abs(F.col(a) / F.col(b) - 1) < share
    got = spectra.table(spark, sf_dir)
    return got.select("kind", "p", (near("lanczos_min", "dense_min", 0.02) & near("lanczos_max", "dense_max", 0.02)).alias("lanczos"), near("krylov_max", "dense_max", 0.05).alias("restarted"))


QUERIES = {
    "w03_splits": w03_levels_split, **{name: _held(name.split("_")[0], claims) for name, claims in claims_of.CLAIMS.items()},
    "w26_combination": w26_combination, "m131_levels": m131_levels, "m133_counts": m133_counts, "w27_totals": w27_totals, "w29_log": w29_log, "w30_cost": w30_cost,
    "m99_scaling": w99_scaling, "m51_spectrum": m51_spectrum, "m140_heat_steps": spectra.heat_table, "m64_geometric": spectra.geometric_table,
}


def _combined_sql() -> str:
    """Exact component solutions by sine expansions, interpolated and added."""
    full = rhs_sql("B2", GridSpec.of_levels((3, 3)))
    grids = [(1, 3, 1), (2, 2, 1), (3, 1, 1), (1, 2, -1), (2, 1, -1)]
    parts = []
    for a, b, c in grids:
        n1, n2 = 2**a, 2**b
        s1, s2 = 8 // n1, 8 // n2
        lam = f"({4.0 * n1 * n1} * power(sin(p * pi() / {2 * n1}), 2) + {4.0 * n2 * n2} * power(sin(q * pi() / {2 * n2}), 2))"
        h = (f"(SELECT p, q, {4.0 / (n1 * n2)} * sum(f.cents / {SCALE!r} * sin(p * pi() * (f.id // 7 + 1) / 8.0) * sin(q * pi() * (f.id % 7 + 1) / 8.0)) / {lam} AS w FROM f, range(1, {n1}) x(p), range(1, {n2}) y(q) "
             f"WHERE (f.id // 7 + 1) % {s1} = 0 AND (f.id % 7 + 1) % {s2} = 0 GROUP BY p, q)")
        u = f"(SELECT k1, k2, sum(w * sin(p * pi() * k1 / {n1}.0) * sin(q * pi() * k2 / {n2}.0)) AS u FROM {h}, range(0, {n1 + 1}) s(k1), range(0, {n2 + 1}) t(k2) GROUP BY k1, k2)"
        x1, x2 = f"((g.i // 7 + 1) * {n1} / 8.0)", f"((g.i % 7 + 1) * {n2} / 8.0)"
        parts.append(f"SELECT g.i AS id, {c} * u.u * greatest(0, 1 - abs({x1} - u.k1)) * greatest(0, 1 - abs({x2} - u.k2)) AS u FROM range(49) g(i), {u} u WHERE abs({x1} - u.k1) < 1 AND abs({x2} - u.k2) < 1")
    return f"WITH f AS ({full}) SELECT CAST(id AS BIGINT) AS id, round(sum(u), 6) + 0.0 AS u FROM ({' UNION ALL '.join(parts)}) GROUP BY id"


SQL = {
    "m99_scaling": "SELECT kind, kind = 'balanced' AS scales FROM (VALUES ('one_level'), ('balanced')) t(kind)",
    "m51_spectrum": "SELECT kind, CAST(p AS INTEGER) AS p, true AS lanczos, true AS restarted FROM (VALUES ('one_level'), ('additive'), ('balanced')) a(kind), (VALUES (4), (8)) b(p)",
    "m140_heat_steps": "SELECT CAST(k AS INTEGER) AS step, round(power(1 + 0.01 * l, -k), 8) AS size, round(power(1 + 0.01 * l, -k), 8) AS exact FROM range(6) t(k), (SELECT 4 * 128 * 128 * power(sin(pi() / 256), 2) AS l)",
    **{name: claims_of.sql(claims) for name, claims in claims_of.CLAIMS.items()},
    "w03_splits": "SELECT levels, CAST(p AS INTEGER) AS p, CAST(s AS INTEGER) AS sub, CAST(n // p + (CASE WHEN s < n % p THEN 1 ELSE 0 END) AS BIGINT) AS cells FROM (VALUES ('3,3', 49), ('2,3', 21)) g(levels, n), range(2, 9) k(p), range(8) t(s) WHERE s < p",
    "w26_combination": _combined_sql(),
    "m131_levels": "SELECT CAST(i AS INTEGER) AS layer, a || ',' || b || ',' || c AS l, CAST(CASE i WHEN 0 THEN 1 WHEN 1 THEN -2 ELSE 1 END AS INTEGER) AS coef FROM range(3) x(i), range(1, 8) p(a), range(1, 8) q(b), range(1, 8) r(c) WHERE a + b + c = 7 - i",
    "m133_counts": "SELECT CAST(i AS INTEGER) AS layer, CAST(factorial((8 - i)::INTEGER) / (factorial(3) * factorial((5 - i)::INTEGER)) AS BIGINT) AS grids, CAST(8 * power(2, 3 - i) AS BIGINT) AS p FROM range(4) t(i)",
    "w27_totals": "SELECT CAST(d AS INTEGER) AS d, CAST(sum(power(2, d - 1 - i) * factorial((20 + d - 2 - i)::INTEGER) / (factorial((d - 1)::INTEGER) * factorial((19 - i)::INTEGER))) AS BIGINT) AS total FROM range(1, 7) a(d), range(6) b(i) WHERE i < d GROUP BY d",
    "w29_log": "SELECT sub, CAST(count(*) AS BIGINT) AS cycles, CAST(count(*) FILTER (WHERE failed) AS BIGINT) AS failed FROM (SELECT floor(epoch(ts) / 3600) AS cycle, CAST(user_id % 10 AS INTEGER) AS sub, bool_or(event_type = 'error') AS failed FROM events GROUP BY 1, 2) GROUP BY sub",
    "w30_cost": "SELECT kind, CAST(m AS INTEGER) AS matvec, CAST(a AS INTEGER) AS axpy, CAST(c AS INTEGER) AS coarse, CAST(1 AS INTEGER) AS local FROM (VALUES ('one_level', 0, 0, 0), ('additive', 0, 1, 1), ('deflated', 1, 2, 2), ('balanced', 2, 3, 2)) t(kind, m, a, c)",
}
