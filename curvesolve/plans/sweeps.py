"""Many independent solves as one DataFrame: a row of parameters in, a result row or a history out.

Each system lives in one task; runs are spread over the cluster. This is the second level of
parallelism beside the distributed plans for one large system.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import SolveConfig
from ..runtime import one_task_frame

PARAMS = ("workload string, extents array<int>, p int, q int, gamma double, curve string, weight string, kind string, method string, xi double, "
          "coarse_weight double, tol double, maxit int, p_fault double, seed int, run int, spectrum boolean, inner_sweeps int, switch int")
NAMES = [c.strip().split(" ")[0] for c in PARAMS.split(",")]
RESULT = ("workload string, method string, kind string, weight string, d int, n bigint, p int, q int, gamma double, p_fault double, run int, k_iter int, "
          "rho_ave double, rho_asy double, kappa double, lam_max double, xi double, ok boolean, clipped boolean")


def config(row) -> SolveConfig:
    got = {n: getattr(row, n) for n in NAMES if n != "workload"}
    for n in ("p", "q", "maxit", "seed", "run", "inner_sweeps", "switch"):
        got[n] = int(got[n])
    return SolveConfig(**got | {"extents": tuple(int(e) for e in got["extents"]), "spectrum": bool(got["spectrum"])})


def _runs(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    from ..kernels import System, rates, solve

    system, built = None, None
    for pdf in batches:
        for row in pdf.itertuples():
            cfg = config(row)
            # Runs that differ in method, faults or start share a system; they come one after another.
            same = cfg.but(method="pcg", p_fault=0.0, run=0, seed=1, xi=0.0, spectrum=False, maxit=1, tol=1.0, switch=0)
            if same != built:
                system, built = System(cfg), same
            system.cfg = cfg
            out = solve(system)
            r = rates(out.errors, cfg.tol)
            ok = out.ok and r["k_iter"] is not None
            yield pd.DataFrame([{
                "workload": row.workload, "method": cfg.method, "kind": cfg.kind, "weight": cfg.weight, "d": len(cfg.extents), "n": system.n, "p": cfg.p, "q": cfg.q,
                "gamma": cfg.gamma, "p_fault": cfg.p_fault, "run": cfg.run, "k_iter": r["k_iter"] if ok else None, "rho_ave": r["rho_ave"], "rho_asy": r["rho_asy"],
                "kappa": out.lam[1] / out.lam[0], "lam_max": out.lam[1], "xi": out.xi, "ok": ok, "clipped": False}]).astype({"k_iter": "Int32"})


def sweep(spark: SparkSession, runs: list[tuple[str, SolveConfig]], partitions: int = 1000) -> DataFrame:
    """One result row per (workload, config)."""
    rows = [{"workload": w, **c.row()} for w, c in runs]
    key = ["workload", "kind", "weight", "extents", "p", "q", "gamma", "inner_sweeps", "coarse_weight"]
    # A task takes a system's runs by fours; a method of its own only where there are few runs.
    dealt = spark.createDataFrame([tuple(r[n] for n in NAMES) for r in rows], PARAMS).withColumn("_part", F.floor(F.col("run") / 4))
    width = dealt.select(*key, "_part", "method").distinct().count()
    dealt = dealt.repartition(max(1, min(partitions, 4 * width)), *key, "_part", "method").sortWithinPartitions(*key, "_part").drop("_part")
    return dealt.mapInPandas(_runs, RESULT)


def _histories(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    from ..kernels import System, solve

    for pdf in batches:
        for row in pdf.itertuples():
            cfg = config(row)
            out = solve(System(cfg))
            yield pd.DataFrame({"workload": row.workload, "run_id": cfg.run, "k": np.arange(len(out.errors), dtype=np.int32), "err": out.errors, "ok": out.ok})


def histories(spark: SparkSession, runs: list[tuple[str, SolveConfig]], partitions: int = 1000) -> DataFrame:
    """(workload, run_id, k, err, ok)."""
    rows = [{"workload": w, **c.row()} for w, c in runs]
    return one_task_frame(spark, rows, PARAMS, partitions).mapInPandas(_histories, "workload string, run_id int, k int, err double, ok boolean")


def solve_rhs(rhs: DataFrame, cfg: SolveConfig, scale: float) -> DataFrame:
    """(id, u) of a right-hand side (id, cents) in lexicographic ids, divided by ``scale``; the system must fit one task."""
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        from ..functions.grid import GridSpec
        from ..kernels import System, solve

        b = np.zeros(GridSpec(cfg.extents).size)
        b[pdf["id"].to_numpy()] = pdf["cents"].to_numpy() / scale
        system = System(cfg)
        got = solve(system, b[system.order] / GridSpec(cfg.extents).diagonal)
        return pd.DataFrame({"id": system.order, "u": got.x, "k_iter": len(got.errors) - 1})

    return rhs.groupBy().applyInPandas(run, "id long, u double, k_iter int")
