"""Measures of convergence, balance, storage, traffic and cost."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def rates(history: DataFrame, tol: float = 1e-8) -> DataFrame:
    """Per run_id: k_iter, rho_ave, rho_asy, quotient of histories (run_id, k, err)."""
    first = history.where("k = 0").select("run_id", F.col("err").alias("e0"))
    both = history.join(first, "run_id")
    at = both.groupBy("run_id").agg(F.min(F.when(F.col("err") <= tol * F.col("e0"), F.col("k"))).alias("k_iter"), F.max("k").alias("k_max"))
    last = at.withColumn("last", F.coalesce("k_iter", "k_max"))
    window = F.least(F.greatest(F.lit(5), F.ceil(F.col("last") * 0.05)), F.col("last"))
    last = last.withColumn("from", F.col("last") - window)
    ends = both.join(last, "run_id").groupBy("run_id", "k_iter", "last", "from", "e0").agg(
        F.max(F.when(F.col("k") == F.col("last"), F.col("err"))).alias("e1"), F.max(F.when(F.col("k") == F.col("from"), F.col("err"))).alias("ew"))
    ave = F.pow(F.col("e1") / F.col("e0"), 1 / F.col("last"))
    asy = F.pow(F.col("e1") / F.col("ew"), 1 / (F.col("last") - F.col("from")))
    return ends.select("run_id", "k_iter", ave.alias("rho_ave"), asy.alias("rho_asy"), (ave / asy).alias("quotient"))


def scaling(results: DataFrame) -> DataFrame:
    """Per method and kind: spread of iterations over P and the slope of log K over log P."""
    return results.groupBy("method", "kind").agg((F.max("k_iter") - F.min("k_iter")).alias("spread"), F.regr_slope(F.ln("k_iter"), F.ln("p")).alias("slope"))


def balance(slices: DataFrame) -> DataFrame:
    return slices.agg((F.max("size") - F.min("size")).alias("spread"), F.count("*").alias("p"))


def storage(members: DataFrame, n: int) -> DataFrame:
    """Rows held over rows owned."""
    return members.agg((F.count("*") / F.lit(n)).alias("factor"))


def traffic(a: DataFrame, members: DataFrame) -> DataFrame:
    """(sub, overlap_rows, halo_rows): what a slice receives per cycle."""
    from ..operators.matrices import halo

    over = members.groupBy("sub").agg(F.count_if(F.col("sub") != F.col("owner")).alias("overlap_rows"))
    far = halo(a, members).groupBy("sub").agg(F.count("*").alias("halo_rows"))
    return over.join(far, "sub", "left").select("sub", "overlap_rows", F.coalesce("halo_rows", F.lit(0)).alias("halo_rows"))


def apply_cost(kind: str) -> dict[str, int]:
    """Products with the matrix, vector additions, coarse and local solves of one application."""
    table = {"one_level": (0, 0, 0, 1), "additive": (0, 1, 1, 1), "deflated": (1, 2, 2, 1), "balanced": (2, 3, 2, 1), "kernel": (0, 1, 1, 1)}
    return dict(zip(("matvec", "axpy", "coarse", "local"), table[kind]))


def level_distance(n: int, p: int, q: int, d: int) -> float:
    """Ratio of coarse to fine mesh width."""
    return (q * p / n) ** (-1.0 / d)


def coarse_share(n: int, p: int, q: int) -> float:
    """Size of the coarse problem over that of a slice."""
    return q * p / (n / p)


def effective_weight(xi: float, gamma: float) -> tuple[float, float]:
    """Damping times the uniform weight, beside the weight itself."""
    return xi / (2 * gamma + 1), 1 / (2 * gamma + 1)
