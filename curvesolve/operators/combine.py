"""Combination of anisotropic grids: level sets, signs, subproblem counts, solving and adding."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import SolveConfig
from ..functions.grid import GridSpec


def levels(spark: SparkSession, d: int, level: int) -> DataFrame:
    """(layer, l, coef): levels of sum L + d - 1 - layer, all positive, with signed binomial weights."""
    base = spark.range(d).select(F.col("id").cast("int").alias("layer"), F.array().cast("array<int>").alias("l"), (F.lit(level + d - 1) - F.col("id")).cast("int").alias("left"))
    for j in range(d - 1):
        rest = d - 1 - j
        base = base.where(F.col("left") > rest).select("layer", "l", "left", F.explode(F.sequence(F.lit(1), F.col("left") - rest)).alias("x")).select(
            "layer", F.concat("l", F.array("x")).alias("l"), (F.col("left") - F.col("x")).alias("left"))
    full = base.where("left > 0").select("layer", F.concat("l", F.array("left")).alias("l"))
    return full.withColumn("coef", coef(F.col("layer"), d))


def coef(layer: Column, d: int) -> Column:
    out = F.lit(0)
    for i in range(d):
        out = F.when(layer == i, F.lit((-1) ** i * math.comb(d - 1, i))).otherwise(out)
    return out.cast("int")


def count(d: int, level: int, layer: int) -> int:
    n = level + d - 2 - layer
    return math.comb(n, d - 1) if n >= d - 1 else 0


def total_subdomains(d: int, level: int, p_hat: int) -> int:
    """Slices over all grids if a grid of layer i has p_hat * 2^(d-1-i)."""
    return p_hat * sum(2 ** (d - 1 - i) * count(d, level, i) for i in range(d))


def counts(spark: SparkSession, d: int, level: int, p_hat: int) -> DataFrame:
    rows = [(i, count(d, level, i), p_hat * 2 ** (d - 1 - i)) for i in range(d)]
    return spark.createDataFrame(rows, "layer int, grids long, p long")


def component_rhs(levels_: tuple[int, ...], fine: np.ndarray, top: int) -> np.ndarray:
    """Values of a function given on the full grid of level ``top`` per axis, at a component grid's points."""
    take = np.ix_(*[np.arange(1, 2**k) * 2 ** (top - k) - 1 for k in levels_])
    return fine[take].ravel()


def solve_all(grids: DataFrame, rhs_on_full: np.ndarray, top: int, p_hat: int = 1, p_fault: float = 0.0, tol: float = 1e-12) -> DataFrame:
    """(l, coef, k, u, k_iter, ok): every grid a task of its own; ``k`` the point's coordinates.

    ``rhs_on_full`` is the right-hand side sampled on the full grid, whose size bounds what is sent.
    """
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from ..kernels import System, rates, solve

        for pdf in batches:
            for row in pdf.itertuples():
                lv = tuple(int(x) for x in row.l)
                spec = GridSpec.of_levels(lv)
                p = max(1, min(int(p_hat * 2 ** (len(lv) - 1 - row.layer)), spec.size // 2))
                cfg = SolveConfig(spec.extents, p, 1, 0.5 if p > 1 else 1.0, tol=tol, p_fault=p_fault, maxit=500, weight="omega", method="flexible")
                system = System(cfg)
                b = component_rhs(lv, rhs_on_full, top)[system.order] / spec.diagonal
                got = solve(system, b)
                u = np.empty(spec.size)
                u[system.order] = got.x
                k = np.stack(np.unravel_index(np.arange(spec.size), spec.extents), 1) + 1
                yield pd.DataFrame({"l": [list(lv)] * spec.size, "coef": int(row.coef), "k": k.tolist(), "u": u, "k_iter": rates(got.errors, tol)["k_iter"], "ok": got.ok})

    return grids.repartition(max(1, min(200, len(rhs_on_full) or 1)), "l").mapInPandas(run, "l array<int>, coef int, k array<int>, u double, k_iter double, ok boolean")


def evaluate(points: DataFrame, solutions: DataFrame, grids: DataFrame) -> DataFrame:
    """(id, u): the signed sum of multilinear interpolants at points (id, x array<double>).

    Each point meets each grid's 2^d corners by an equi-join on (grid, corner); corners on the boundary are zero.
    """
    d = len(grids.select("l").first()["l"])
    # The list of grids is C(L + d - 2, d - 1) rows or so, whatever the number of points.
    every = [r["l"] for r in grids.select("l").collect()]
    met = points.withColumn("l", F.explode(F.array(*[F.lit(x) for x in every])))
    scaled = F.transform(F.arrays_zip("x", "l"), lambda z: z["x"] * F.pow(F.lit(2.0), z["l"]))
    met = met.withColumn("s", scaled).withColumn("base", F.transform("s", lambda v: F.floor(v).cast("int")))
    corners = F.transform(F.sequence(F.lit(0), F.lit(2**d - 1)), lambda c: F.struct(
        F.transform("base", lambda b, j: b + F.getbit(c.cast("long"), j).cast("int")).alias("k"),
        F.aggregate(F.transform("s", lambda v, j: F.when(F.getbit(c.cast("long"), j) == 1, v - F.floor(v)).otherwise(1 - v + F.floor(v))), F.lit(1.0), lambda a, w: a * w).alias("w")))
    at = met.select("id", "l", F.explode(corners).alias("c")).select("id", "l", "c.k", "c.w").where("w > 0")
    return at.join(solutions.select("l", "k", "coef", "u"), ["l", "k"]).groupBy("id").agg(F.sum(F.col("coef") * F.col("w") * F.col("u")).alias("u"))
