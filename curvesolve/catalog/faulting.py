"""Fault schedules, rebuilding, recoverability, bounds and measures of histories."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import faults, partition
from ..plans import measures, theory
from ..sources import tables
from .shared import GAMMA, N, P, members_sql, uniform_sql

Spark = SparkSession
CYCLES, PF, RUNS = 20, 0.1, 3


def _schedule(spark: Spark) -> DataFrame:
    return faults.bernoulli(spark, P, CYCLES, PF, seed=5, runs=RUNS)


def _members(spark: Spark) -> DataFrame:
    return partition.members(spark.range(N).select(F.col("id").alias("pos")), N, P, GAMMA)


def m112_bernoulli(spark: Spark, sf_dir: str) -> DataFrame:
    return _schedule(spark)


def m113_weibull(spark: Spark, sf_dir: str) -> DataFrame:
    return faults.weibull(spark, P, CYCLES, 0.7, 8.0, seed=5)


def m114_trace(spark: Spark, sf_dir: str) -> DataFrame:
    return faults.from_events(tables.table(spark, sf_dir, "events"), P)


def m115_fixed_size(spark: Spark, sf_dir: str) -> DataFrame:
    return faults.fixed_size(spark, P, CYCLES, 2, seed=5)


def m116_outages(spark: Spark, sf_dir: str) -> DataFrame:
    return faults.outages(_schedule(spark), 3)


def m117_states(spark: Spark, sf_dir: str) -> DataFrame:
    return faults.states(_schedule(spark))


def _lost(spark: Spark) -> DataFrame:
    return _schedule(spark).where("failed and run = 0").select("cycle", "sub")


def m119_donors(spark: Spark, sf_dir: str) -> DataFrame:
    return faults.donors(_members(spark), _lost(spark), P)


def m120_rebuild(spark: Spark, sf_dir: str) -> DataFrame:
    """Rebuilt values of lost slices; equal to what they held."""
    state = _members(spark).select("sub", "pos", (F.col("pos") * 3 + 1).alias("v"))
    return faults.rebuild(state, faults.donors(_members(spark), _lost(spark), P))


def m122_recoverable(spark: Spark, sf_dir: str) -> DataFrame:
    return faults.recoverable(_schedule(spark), P, GAMMA)


def m122_recoverable_by_position(spark: Spark, sf_dir: str) -> DataFrame:
    return faults.recoverable_by_position(_schedule(spark), _members(spark))


def m126_random_assignment(spark: Spark, sf_dir: str) -> DataFrame:
    return faults.assign_random(spark, P + 1, CYCLES, seed=5)


def m127_takeover(spark: Spark, sf_dir: str) -> DataFrame:
    return faults.neighbour_takeover(_schedule(spark), P)


def m130_stats(spark: Spark, sf_dir: str) -> DataFrame:
    out = faults.stats(_schedule(spark))
    return out.select("run", "cycle", "failures", "p_k", F.round("mean_p_k", 9).alias("mean_p_k"), F.round("mean_p_k2", 9).alias("mean_p_k2"))


def _heard(spark: Spark, sf_dir: str) -> DataFrame:
    """(run, cycle, p_k): slices heard from without an error in cycles of ten minutes of the event log; a day is a run."""
    log = faults.from_events(tables.table(spark, sf_dir, "events"), P, 600)
    return faults.stats(log.withColumn("run", F.floor(F.col("cycle") / 144).cast("int"))).select("run", "cycle", "p_k")


def m100_expected_bound(spark: Spark, sf_dir: str) -> DataFrame:
    return theory.expected_bound(_heard(spark, sf_dir), P, 0.9, 1.1, 12.0).select("run", "cycle", F.round("bound", 9).alias("bound"))


def m102_one_step(spark: Spark, sf_dir: str) -> DataFrame:
    return theory.one_step_bound(_heard(spark, sf_dir), P, 12.0).select("run", "cycle", F.round("factor", 9).alias("factor"))


def m103_fault_bound(spark: Spark, sf_dir: str) -> DataFrame:
    return theory.fault_bound(_heard(spark, sf_dir), P, 12.0).select("run", "cycle", F.round("bound", 9).alias("bound"))


def m101_mean_rate(spark: Spark, sf_dir: str) -> DataFrame:
    """One rate per run, from the sizes of its cycles."""
    return theory.mean_rates(_heard(spark, sf_dir), P, 0.9, 1.1, 12.0).select("run", F.round("rate", 9).alias("rate"))


def _history(spark: Spark) -> DataFrame:
    k = F.col("id") % 41
    run = F.floor(F.col("id") / 41).cast("int")
    return spark.range(41 * 3).select(run.alias("run_id"), k.cast("int").alias("k"), F.pow(F.lit(0.6) + run * 0.05, k).alias("err"), (run != 2).alias("ok"))


def m95_rates(spark: Spark, sf_dir: str) -> DataFrame:
    slow = spark.range(251).select(F.lit(3).alias("run_id"), F.col("id").cast("int").alias("k"), (F.pow(F.lit(0.9), "id") * (2 + F.sin("id"))).alias("err"), F.lit(True).alias("ok"))
    out = measures.rates(_history(spark).unionByName(slow))
    return out.select("run_id", "k_iter", *[F.round(c, 9).alias(c) for c in ("rho_ave", "rho_asy", "quotient")])


def m123_average_runs(spark: Spark, sf_dir: str) -> DataFrame:
    return faults.average_runs(_history(spark)).select("k", F.round("err", 9).alias("err"), "runs")


def m78_damping(spark: Spark, sf_dir: str) -> DataFrame:
    rows = [(lo, hi, theory.damping(lo, hi), theory.rate(theory.damping(lo, hi), lo, hi)) for lo, hi in ((0.07, 1.12), (0.13, 1.01), (0.034, 2.5))]
    return spark.createDataFrame(rows, "lo double, hi double, xi double, rho double").select("lo", "hi", F.round("xi", 9).alias("xi"), F.round("rho", 9).alias("rho"))


def m105_cg_bound(spark: Spark, sf_dir: str) -> DataFrame:
    rows = [(k, theory.cg_bound(16.0, k)) for k in range(1, 31)]
    return spark.createDataFrame(rows, "k int, bound double").select("k", F.round("bound", 9).alias("bound"))


def m93_schwarz_bound(spark: Spark, sf_dir: str) -> DataFrame:
    rows = [(w, o, theory.schwarz_bound(w, o), theory.schwarz_bound(w, o, False)) for w in (0.25, 0.125) for o in (0.03125, 0.0625)]
    return spark.createDataFrame(rows, "width double, overlap double, two_level double, one_level double")


def m104_constant_failure(spark: Spark, sf_dir: str) -> DataFrame:
    return spark.createDataFrame([(p, theory.constant_failure(0.1, p)) for p in (10, 100, 255)], "p int, left_over int")


QUERIES = {f.__name__: f for f in (
    m112_bernoulli, m113_weibull, m114_trace, m115_fixed_size, m116_outages, m117_states, m119_donors, m120_rebuild, m122_recoverable, m122_recoverable_by_position, m126_random_assignment,
    m127_takeover, m130_stats, m100_expected_bound, m101_mean_rate, m102_one_step, m103_fault_bound, m95_rates, m123_average_runs, m78_damping, m93_schwarz_bound, m104_constant_failure, m105_cg_bound)}

_G = f"SELECT CAST(r AS INTEGER) AS run, CAST(c AS INTEGER) AS cycle, CAST(s AS INTEGER) AS sub FROM range({RUNS}) a(r), range({CYCLES}) b(c), range({P}) d(s)"
_S = f"SELECT *, {uniform_sql('5', 'run', 'cycle', 'sub')} < {PF} AS failed FROM ({_G})"
_M = members_sql(N, P, GAMMA)
_L = f"SELECT cycle, sub FROM ({_S}) WHERE failed AND run = 0"
_D = (f"SELECT l.cycle, l.sub AS lost_sub, m.pos, arg_min(o.sub, (o.sub - l.sub + {P}) % {P}) AS donor FROM ({_L}) l JOIN ({_M}) m ON m.sub = l.sub JOIN ({_M}) o ON o.pos = m.pos AND o.sub <> l.sub "
      f"WHERE NOT EXISTS (SELECT 1 FROM ({_L}) x WHERE x.cycle = l.cycle AND x.sub = o.sub) GROUP BY 1, 2, 3")
_OK = f"SELECT run, cycle, bool_and(alive) AS ok FROM (SELECT s.run, s.cycle, m.pos, bool_or(NOT s.failed) AS alive FROM ({_S}) s JOIN ({_M}) m ON m.sub = s.sub GROUP BY 1, 2, 3) GROUP BY 1, 2"
_T = f"SELECT run, cycle, CAST(count(*) FILTER (WHERE failed) AS BIGINT) AS failures, CAST(count(*) FILTER (WHERE NOT failed) AS BIGINT) AS p_k FROM ({_S}) GROUP BY 1, 2"
_E = (f"SELECT CAST(floor(cycle / 144) AS INTEGER) AS run, cycle, CAST(count(*) FILTER (WHERE NOT failed) AS BIGINT) AS p_k FROM (SELECT CAST(floor(epoch(ts) / 600) AS BIGINT) AS cycle, "
      f"user_id % {P} AS sub, bool_or(event_type = 'error') AS failed FROM events GROUP BY 1, 2) GROUP BY 1, 2")
_RUN = "OVER (PARTITION BY run ORDER BY cycle ROWS UNBOUNDED PRECEDING)"


def _ranked(tag: str, n: int) -> str:
    g = f"SELECT CAST(0 AS INTEGER) AS run, CAST(c AS INTEGER) AS cycle, CAST(s AS INTEGER) AS sub FROM range({CYCLES}) b(c), range({n}) d(s)"
    return f"SELECT *, row_number() OVER (PARTITION BY cycle ORDER BY {uniform_sql('5', repr(tag), 'cycle', 'sub')}, sub) AS r FROM ({g})"


_H = "SELECT CAST(r AS INTEGER) AS run_id, CAST(k AS INTEGER) AS k, power(0.6 + r * 0.05, k) AS err, r <> 2 AS ok FROM range(3) a(r), range(41) b(k)"
SQL = {
    "m112_bernoulli": _S,
    "m113_weibull": f"WITH g AS (SELECT CAST(c AS INTEGER) AS k, CAST(s AS INTEGER) AS sub FROM range({CYCLES}) b(c), range({P}) d(s)), t AS (SELECT sub, sum(8.0 * power(-ln(1 - {uniform_sql('5', repr('w'), 'sub', 'k')}), 1.0 / 0.7)) OVER (PARTITION BY sub ORDER BY k) AS at FROM g) "
                    f"SELECT CAST(0 AS INTEGER) AS run, g.k AS cycle, g.sub, EXISTS (SELECT 1 FROM t WHERE t.sub = g.sub AND floor(t.at) = g.k) AS failed FROM g",
    "m114_trace": f"SELECT CAST(floor(epoch(ts) / 3600) AS BIGINT) AS cycle, CAST(user_id % {P} AS INTEGER) AS sub, bool_or(event_type = 'error') AS failed FROM events GROUP BY 1, 2",
    "m115_fixed_size": f"SELECT run, cycle, sub, r <= 2 AS failed FROM ({_ranked('f', P)})",
    "m116_outages": f"SELECT a.run, a.cycle, a.sub, EXISTS (SELECT 1 FROM ({_S}) b WHERE b.run = a.run AND b.sub = a.sub AND b.failed AND b.cycle BETWEEN a.cycle - 2 AND a.cycle) AS failed FROM ({_S}) a",
    "m117_states": f"SELECT *, CASE WHEN failed THEN 'failed' WHEN lag(failed, 1, false) OVER (PARTITION BY run, sub ORDER BY cycle) THEN 'returning' ELSE 'active' END AS state FROM ({_S})",
    "m119_donors": _D,
    "m120_rebuild": f"SELECT cycle, lost_sub AS sub, pos, pos * 3 + 1 AS v FROM ({_D})",
    "m122_recoverable": _OK, "m122_recoverable_by_position": _OK,
    "m126_random_assignment": f"SELECT cycle, sub AS problem, CAST(r - 1 AS INTEGER) AS worker FROM ({_ranked('a', P + 1)})",
    "m127_takeover": f"SELECT *, CAST(CASE WHEN failed THEN (sub + 1) % {P} ELSE sub END AS INTEGER) AS done_by, CAST(failed AS INTEGER) AS delay FROM ({_S})",
    "m130_stats": f"SELECT run, cycle, failures, p_k, round(avg(p_k) {_RUN}, 9) AS mean_p_k, round(avg(p_k * p_k) {_RUN}, 9) AS mean_p_k2 FROM ({_T})",
    "m100_expected_bound": f"SELECT run, cycle, round(exp(sum(ln(1 - {0.9 * 1.1 * (2 - 0.9 * 1.1)} * p_k / {12.0 * (P + 1)})) {_RUN}), 9) AS bound FROM ({_E})",
    "m101_mean_rate": f"SELECT run, round(1 - {0.9 * 1.1 * (2 - 0.9 * 1.1) / 12.0} * avg(p_k) / {P + 1}, 9) AS rate FROM ({_E}) GROUP BY run",
    "m102_one_step": f"SELECT run, cycle, round(1 - p_k * p_k / {12.0 * P * P}, 9) AS factor FROM ({_E})",
    "m103_fault_bound": f"SELECT run, cycle, round(exp(sum(ln(1 - p_k * p_k / {12.0 * P * P})) {_RUN}), 9) AS bound FROM ({_E})",
    "m95_rates": f"WITH h AS (SELECT run_id, k, err FROM ({_H}) UNION ALL SELECT 3, CAST(k AS INTEGER), power(0.9::DOUBLE, k) * (2 + sin(k)) FROM range(251) t(k)), "
                 "f AS (SELECT run_id, err AS e0 FROM h WHERE k = 0), l AS (SELECT run_id, min(k) FILTER (WHERE err <= 1e-8 * e0) AS k_iter, coalesce(min(k) FILTER (WHERE err <= 1e-8 * e0), max(k)) AS last, any_value(e0) AS e0 FROM h JOIN f USING (run_id) GROUP BY 1), "
                 "m AS (SELECT *, least(last, greatest(5, ceil(0.05 * last))) AS win FROM l) "
                 "SELECT run_id, k_iter, round(power(e.err / e0, 1.0 / last), 9) AS rho_ave, round(power(e.err / w.err, 1.0 / win), 9) AS rho_asy, round(power(e.err / e0, 1.0 / last) / power(e.err / w.err, 1.0 / win), 9) AS quotient FROM m JOIN h e USING (run_id) JOIN h w USING (run_id) WHERE e.k = last AND w.k = last - win",
    "m123_average_runs": f"SELECT k, round(avg(err), 9) AS err, CAST(count(*) AS BIGINT) AS runs FROM ({_H}) WHERE run_id <> 2 GROUP BY k",
    "m78_damping": "SELECT CAST(lo AS DOUBLE) AS lo, CAST(hi AS DOUBLE) AS hi, round(2.0 / (lo + hi), 9) AS xi, round(1 - 2.0 * lo / (lo + hi), 9) AS rho FROM (VALUES (0.07::DOUBLE, 1.12::DOUBLE), (0.13, 1.01), (0.034, 2.5)) t(lo, hi)",
    "m93_schwarz_bound": "SELECT CAST(w AS DOUBLE) AS width, CAST(o AS DOUBLE) AS overlap, CAST(1 + w / o AS DOUBLE) AS two_level, CAST((1 + w / o) / (w * w) AS DOUBLE) AS one_level FROM (VALUES (0.25::DOUBLE), (0.125)) a(w), (VALUES (0.03125::DOUBLE), (0.0625)) b(o)",
    "m104_constant_failure": "SELECT CAST(p AS INTEGER) AS p, CAST(floor(0.9 * (p + 1)) AS INTEGER) AS left_over FROM (VALUES (10), (100), (255)) t(p)",
    "m105_cg_bound": "SELECT CAST(k AS INTEGER) AS k, round(2 * power(3.0 / 5.0, k), 9) AS bound FROM range(1, 31) t(k)",
}
