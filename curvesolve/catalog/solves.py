"""Operators and iterations on table data, all by the distributed solver.

Single applications and the iterates after a few steps are held against SQL built from closed forms, so
that another method, weight or overlap in their place would show; whole solves against exact solutions.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import SolveConfig
from ..functions.grid import GridSpec
from ..functions.uniform import py_uniform
from ..plans import distributed, sweeps
from ..runtime import checkpoint
from ..sources import tables
from .shared import G1, SCALE, exact1_sql, exact2_sql, members_sql
from .steps_sql import application, iterate

G2S = GridSpec.of_levels((3, 3))
BASE1 = SolveConfig(G1.extents, p=6, q=3, gamma=0.5, tol=1e-12, maxit=400)
BASE2 = SolveConfig(G2S.extents, p=5, q=3, gamma=0.5, tol=1e-11, maxit=400)
#: Every day of the orders, in 64 slices.
DAYS = SolveConfig((2405,), p=64, q=4, gamma=0.5, tol=1e-10)
#: Spectral bounds given to the damped and two-step iterations, and steps whose iterate is compared.
BOUNDS, STEPS = (0.3, 1.9), 3


def _rounded(df: DataFrame) -> DataFrame:
    return df.select("id", (F.round("u", 6) + 0.0).alias("u"))


def _solved(cfg: SolveConfig, binding: str = "B1", **options):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return _rounded(distributed.solve_table(spark, tables.rhs(spark, sf_dir, binding, GridSpec(cfg.extents)), cfg, SCALE, **options))
    return run


def _applied(cfg: SolveConfig):
    """C b: the first damped step from zero with factor one."""
    return _solved(cfg.but(method="richardson", xi=1.0), steps=1)


def _direct(cfg: SolveConfig):
    """The baseline that solves a system within one task; it must fit there."""
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return _rounded(sweeps.solve_rhs(tables.rhs(spark, sf_dir, "B1", GridSpec(cfg.extents)), cfg, SCALE))
    return run


def drawn(p: int, rate: float, seed: int):
    """Failing slices of a cycle from counter-based uniforms."""
    return lambda k: {i for i in range(p) if py_uniform(seed, 0, k, i) < rate}


FT = BASE1.but(p=8, q=3, gamma=2.0, tol=1e-10)
FAILS = drawn(8, 0.1, 3)


def b1_solution_extremes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The days of largest and smallest solution of the balanced solve."""
    u = _solved(BASE1)(spark, sf_dir)
    return u.orderBy(F.desc("u"), "id").limit(5)


def _rebuilt(spark: SparkSession, sf_dir: str):
    """A solve that loses slices 1 and 4 before the third cycle; (setup before, rows before, outcome)."""
    s = distributed.setup(spark, FT.but(gamma=1.0))
    before = checkpoint(distributed.rows_held(s))
    entries = s.a0
    b = checkpoint(tables.rhs(spark, sf_dir, "B1", GridSpec(FT.extents)).join(s.order, "id").select("pos", (F.col("cents") / F.lit(SCALE)).alias("v")))
    out = distributed.run(s, b, lost=lambda k: {1, 4} if k == 2 else set())
    return s, before, entries, out


def m120_lost_slices(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The solution of a run in which two slices lose matrix rows, factor and vectors and are built anew."""
    s, _, _, out = _rebuilt(spark, sf_dir)
    return _rounded(distributed.solution(s, out.state).join(s.order, "pos").select("id", F.col("v").alias("u")))


def m119_rebuilt_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of the matrix per rebuilt slice, and those that differ from the lost ones."""
    s, before, _, _ = _rebuilt(spark, sf_dir)
    after = checkpoint(distributed.rows_held(s))
    wrong = before.exceptAll(after).unionByName(after.exceptAll(before)).groupBy("sub").agg(F.count("*").alias("differing"))
    return after.where("sub in (1, 4)").groupBy("sub").agg(F.count("*").alias("entries")).join(wrong, "sub", "left").select("sub", "entries", F.coalesce("differing", F.lit(0)).alias("differing"))


def m121_coarse_copy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The coarse matrix added up again from the parts after rebuilding."""
    s, _, _, _ = _rebuilt(spark, sf_dir)
    return distributed.coarse_entries(s).select("i", "j", F.round("v", 4).alias("v")).where("v <> 0")


def m118_copies_agree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Copies of the residual that differ between the slices that hold a position, after a run with failures and a loss."""
    s, _, _, out = _rebuilt(spark, sf_dir)
    held = distributed.copies(s, out.state, "x").groupBy("pos").agg(F.count("*").alias("holders"), (F.max("v") - F.min("v")).alias("gap"))
    return held.select("pos", "holders", (F.col("gap") < 1e-9).alias("agree"))


STEPPED = {
    "m65_one_level": BASE1.but(kind="one_level"),
    "m66_weighted_one_level": BASE1.but(kind="one_level", weight="unity", gamma=0.3, method="flexible"),
    "m67_additive": BASE1.but(kind="additive"),
    "m69_deflated": BASE1.but(kind="deflated"),
    "m72_coarse_weight": BASE1.but(kind="additive", coarse_weight=0.8),
    "m77_richardson": BASE1.but(method="richardson", xi=0.9),
    "m79_damping_low": BASE1.but(method="richardson", xi=1 / BOUNDS[1]),
    "m79_damping_over": BASE1.but(method="richardson", xi=1.5),
    "m80_switched_damping": BASE1.but(method="richardson", xi=0.9, switch=2),
    "m81_pcg": BASE1,
    "m82_flexible": BASE1.but(method="flexible", weight="unity", gamma=0.3),
    "m83_steepest": BASE1.but(method="steepest"),
    "m85_sequential": BASE1.but(method="sequential", kind="additive"),
    "m86_all_at_once": BASE1.but(method="all", kind="additive", xi=0.6),
    "m87_colored": BASE1.but(method="colored", kind="additive"),
    "m88_random_subsets": BASE1.but(method="random", kind="additive", xi=0.5, p_fault=0.4),
    "m89_coarse_plus_random": BASE1.but(method="coarse_random", kind="additive", xi=0.5, p_fault=0.4),
    "m90_two_step": BASE1.but(method="two_step"),
    "m92_cg_plain": BASE1.but(method="cg"),
    "m92_jacobi": BASE1.but(method="jacobi"),
}
FAULTY = {"m124_ft_linear": FT.but(method="richardson", xi=0.4), "m125_ft_pcg": FT, "m125_ft_flexible": FT.but(method="flexible")}
APPLIED = {f"c_{k}_{w}": BASE1.but(kind=k, weight=w, gamma=0.7) for k in ("one_level", "additive", "deflated", "balanced") for w in ("none", "omega", "unity")}
APPLIED |= {"c_balanced_wide": BASE1.but(gamma=1.5, p=7, q=2), "c_balanced_closed": BASE1.but(gamma=2.0, p=4, q=5)}
SHORT = ("sequential", "colored")


def _groups(cfg: SolveConfig):
    return (lambda k: distributed._order_of(cfg, k)) if cfg.method in distributed.SUBSPACE else None


def _steps(cfg: SolveConfig) -> int:
    return 1 if cfg.method == "sequential" else 2 if cfg.method == "colored" else STEPS


QUERIES = {
    "m70_balanced_pcg": _solved(DAYS),
    "m67_additive_pcg_distributed": _solved(DAYS.but(extents=(96,), p=8, kind="additive")),
    "m125_ft_solved": _solved(FT.but(method="flexible"), failed=FAILS),
    "m68_kernel": _solved(BASE1.but(kind="kernel", tol=1e-10)),
    "m74_inexact_local": _solved(BASE2.but(inner_sweeps=30, method="flexible"), "B2"),
    "m92_direct": _direct(BASE1.but(method="direct")),
    "m24_lebesgue_solve": _solved(BASE2.but(curve="lebesgue"), "B2"),
    "m70_balanced_2d": _solved(BASE2, "B2"),
    "m77_richardson_2d": _solved(BASE2.but(method="richardson", xi=1.0, tol=1e-10), "B2"),
    "b1_solution_extremes": b1_solution_extremes,
    **{f.__name__: f for f in (m118_copies_agree, m119_rebuilt_rows, m120_lost_slices, m121_coarse_copy)},
    **{name: _solved(cfg, steps=_steps(cfg), spectrum=BOUNDS) for name, cfg in STEPPED.items()},
    **{name: _solved(cfg, steps=STEPS, failed=FAILS) for name, cfg in FAULTY.items()},
    **{name: _applied(cfg) for name, cfg in APPLIED.items()},
}
_TWO = ("m74_inexact_local", "m24_lebesgue_solve", "m70_balanced_2d", "m77_richardson_2d")
_N, _P = FT.extents[0], FT.p
_LINE = f"(SELECT a.i, b.i AS j, CASE WHEN a.i = b.i THEN 2.0 ELSE -1.0 END * {(_N + 1) ** 2} AS v FROM range({_N}) a(i) JOIN range({_N}) b(i) ON abs(a.i - b.i) <= 1)"
SQL = {
    **{name: exact2_sql(G2S) for name in _TWO},
    **{name: exact1_sql(G1) for name in ("m125_ft_solved", "m68_kernel", "m92_direct", "m120_lost_slices")},
    "m70_balanced_pcg": exact1_sql(GridSpec(DAYS.extents)),
    "m67_additive_pcg_distributed": exact1_sql(GridSpec((96,))),
    "b1_solution_extremes": f"SELECT * FROM ({exact1_sql(G1)}) ORDER BY u DESC, id LIMIT 5",
    "m118_copies_agree": f"SELECT pos, CAST(count(*) AS BIGINT) AS holders, true AS agree FROM ({members_sql(_N, _P, 1.0)}) GROUP BY pos",
    "m119_rebuilt_rows": f"SELECT m.sub, CAST(count(*) AS BIGINT) AS entries, CAST(0 AS BIGINT) AS differing FROM ({members_sql(_N, _P, 1.0)}) m JOIN {_LINE} a ON a.i = m.pos WHERE m.sub IN (1, 4) GROUP BY m.sub",
    "m121_coarse_copy": f"SELECT CAST(a.i AS BIGINT) AS i, CAST(b.i AS BIGINT) AS j, CAST(CASE WHEN a.i = b.i THEN 2 ELSE -1 END * {(_N + 1) ** 2} AS DOUBLE) AS v FROM range({_P * FT.q}) a(i) JOIN range({_P * FT.q}) b(i) ON abs(a.i - b.i) <= 1",
    **{name: iterate(cfg, _steps(cfg), _groups(cfg), None, BOUNDS) for name, cfg in STEPPED.items()},
    **{name: iterate(cfg, STEPS, None, FAILS) for name, cfg in FAULTY.items()},
    **{name: application(cfg) for name, cfg in APPLIED.items()},
}
