"""Rates and bounds: closed forms and running products over observed subset sizes."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def damping(lam_min: float, lam_max: float) -> float:
    return 2 / (lam_min + lam_max)


def rate(xi: float, lam_min: float, lam_max: float) -> float:
    """Energy-norm rate of the damped iteration; below 1 exactly for 0 < xi < 2 / lam_max."""
    return max(abs(1 - xi * lam_min), abs(1 - xi * lam_max))


def best_rate(kappa: float) -> float:
    return 1 - 2 / (1 + kappa)


def cg_bound(kappa: float, k: int) -> float:
    root = math.sqrt(kappa)
    return 2 * ((root - 1) / (root + 1)) ** k


def schwarz_bound(width: float, overlap: float, coarse: bool = True) -> float:
    """Order of the condition number: 1 + H / delta, times H^-2 without a coarse problem."""
    return (1 + width / overlap) * (1 if coarse else width**-2)


def constant_failure(share: float, p: int) -> int:
    """Subset size left if a constant share of the p + 1 problems fails."""
    return math.floor((1 - share) * (p + 1))


def iterations_for(rho: float, tol: float = 1e-8) -> int:
    return math.ceil(math.log(tol) / math.log(rho))


def mean_rate(p_k: list[int], p: int, xi: float, lam_max: float, kappa: float) -> float:
    share = sum(p_k) / len(p_k) / (p + 1)
    return 1 - lam_max * xi * (2 - lam_max * xi) * share / kappa


def mean_rates(sizes: DataFrame, p: int, xi: float, lam_max: float, kappa: float) -> DataFrame:
    """(run, rate): ``mean_rate`` of each run's sizes p_k."""
    share = F.avg("p_k") / F.lit(p + 1)
    return sizes.groupBy("run").agg((1 - F.lit(lam_max * xi * (2 - lam_max * xi)) * share / F.lit(kappa)).alias("rate"))


def _product(sizes: DataFrame, factor) -> DataFrame:
    by = Window.partitionBy("run").orderBy("cycle").rowsBetween(Window.unboundedPreceding, 0)
    return sizes.withColumn("factor", factor).withColumn("bound", F.exp(F.sum(F.ln("factor")).over(by)))


def expected_bound(sizes: DataFrame, p: int, xi: float, lam_max: float, kappa: float) -> DataFrame:
    """(.., factor, bound): expected squared error bound for random subsets of p_k of the p + 1 spaces."""
    return _product(sizes, 1 - F.lit(lam_max * xi * (2 - lam_max * xi)) * F.col("p_k") / F.lit(kappa * (p + 1)))


def one_step_bound(sizes: DataFrame, p: int, kappa: float) -> DataFrame:
    """Adds the factor 1 - p_k^2 / (kappa P^2) of a step scaled by p_k / (P lam_max)."""
    return sizes.withColumn("factor", 1 - F.col("p_k") * F.col("p_k") / F.lit(kappa * p * p))


def fault_bound(sizes: DataFrame, p: int, kappa: float) -> DataFrame:
    """Running product of the one-step factors: coarse problem always on, p_k slices at random."""
    return _product(sizes, 1 - F.col("p_k") * F.col("p_k") / F.lit(kappa * p * p))


def holder_exponent(d: int) -> tuple[float, float]:
    """Of the Hilbert and of the Lebesgue curve."""
    return 1 / d, 1 / (d * math.log2(3))
