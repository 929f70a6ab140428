"""What the experiments are reported to show, as statements over their rows.

A statement has a name, the reported value if there is one, the band its value must lie in, and an
expression over an experiment's rows. Queries return whether each holds; the SQL side states that it
should. Reported counts get a band of 15 percent, ratios and rates the precision they are given with.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


class Value(str):
    """An SQL expression that can be added to, subtracted from and divided by others."""

    def __sub__(self, other: Value) -> Value:
        return Value(f"({self}) - ({other})")

    def __truediv__(self, other: Value) -> Value:
        return Value(f"({self}) / ({other})")

    def __neg__(self) -> Value:
        return Value(f"-({self})")


@dataclass(frozen=True)
class Claim:
    name: str
    low: float
    high: float
    value: Value
    reported: float | None = None


def _where(**of) -> str:
    return " AND ".join(["ok", *[f"abs({n} - {v!r}D) < 1e-9" if isinstance(v, float) else f"{n} = {v!r}" for n, v in of.items()]])


def mean(column: str = "k_iter", **of) -> Value:
    return Value(f"avg(CASE WHEN {_where(**of)} THEN {column} END)")


def highest(**of) -> Value:
    return Value(f"max(CASE WHEN {_where(**of)} THEN k_iter END)")


def lowest(**of) -> Value:
    return Value(f"min(CASE WHEN {_where(**of)} THEN k_iter END)")


def gap(**of) -> Value:
    return mean("rho_asy - rho_ave", **of)


def runs(**of) -> Value:
    """Runs that lost nothing for good."""
    return Value(f"CAST(count_if({_where(**of)}) AS DOUBLE)")


def spread(**of) -> Value:
    return highest(**of) / lowest(**of)


def about(name: str, reported: float, value: Value, share: float = 0.15) -> Claim:
    return Claim(name, reported * (1 - share), reported * (1 + share), value, reported)


def most(name: str, reported: float, value: Value) -> Claim:
    return Claim(name, 0.0, reported, value, reported)


def rising(name: str, values: list[Value], slack: float = 0.0) -> Claim:
    """Each value at least the one before, less a slack."""
    steps = [b - a for a, b in zip(values, values[1:])]
    return Claim(name, -slack, 1e9, Value(f"least({', '.join(steps)})") if len(steps) > 1 else steps[0])


def held(rows: DataFrame, claims: list[Claim]) -> DataFrame:
    """(claim, reported, low, high, holds)."""
    parts = [F.struct(F.lit(c.name).alias("claim"), F.lit(c.reported).cast("double").alias("reported"), F.lit(c.low).cast("double").alias("low"), F.lit(c.high).cast("double").alias("high"),
                      F.coalesce(F.expr(c.value).between(c.low, c.high), F.lit(False)).alias("holds")) for c in claims]
    return rows.agg(F.array(*parts).alias("c")).select(F.explode("c").alias("c")).select("c.*")


def measured(rows: DataFrame, claims: list[Claim]) -> DataFrame:
    """(claim, reported, value)."""
    parts = [F.struct(F.lit(c.name).alias("claim"), F.lit(c.reported).cast("double").alias("reported"), F.expr(c.value).cast("double").alias("value")) for c in claims]
    return rows.agg(F.array(*parts).alias("c")).select(F.explode("c").alias("c")).select("c.*")


def sql(claims: list[Claim]) -> str:
    rows = ", ".join(f"('{c.name}', {'NULL' if c.reported is None else repr(float(c.reported))}, {float(c.low)!r}, {float(c.high)!r})" for c in claims)
    return f"SELECT claim, CAST(reported AS DOUBLE) AS reported, CAST(low AS DOUBLE) AS low, CAST(high AS DOUBLE) AS high, true AS holds FROM (VALUES {rows}) t(claim, reported, low, high)"


R, C = "richardson", "pcg"
_PLAIN = {"kind": "additive", "p": 256}
CLAIMS: dict[str, list[Claim]] = {
    "w05_plain": [
        about("damped, rate at 256 slices", 0.98, mean("rho_ave", method=R, weight="omega", p=256), 0.015),
        about("conjugate gradients, asymptotic less average rate", 0.08, gap(method=C, weight="omega", p=256), 0.5),
        Claim("omega and unity agree", 0.98, 1.02, mean(method=R, weight="omega", p=256) / mean(method=R, weight="unity", p=256)),
        Claim("weights reduce the damped count", 1.0, 2.0, mean(method=R, weight="none", p=256) / mean(method=R, weight="omega", p=256)),
        Claim("conjugate gradients: weak scaling from 64 slices", 0.9, 1.2, mean(method=C, weight="omega", p=256) / mean(method=C, weight="omega", p=64)),
    ],
    "w06_balanced": [
        about("damped, rate at 256 slices", 0.9, mean("rho_ave", method=R, weight="omega", p=256), 0.1),
        about("conjugate gradients, average rate", 0.6, mean("rho_ave", method=C, weight="omega", p=256), 0.15),
        about("conjugate gradients, asymptotic less average rate", 0.13, gap(method=C, weight="omega", p=256), 0.5),
        Claim("all weights agree", 0.97, 1.03, mean(method=R, weight="none", p=256) / mean(method=R, weight="omega", p=256)),
        Claim("damped: weak scaling", 1.0, 1.1, spread(method=R, weight="omega")),
        Claim("conjugate gradients: weak scaling from 64 slices", 0.9, 1.1, mean(method=C, weight="omega", p=256) / mean(method=C, weight="omega", p=64)),
    ],
    "w07_kinds": [
        Claim("balanced beats the kernel form", 1.0, 1e9, mean(kind="kernel", p=64) / mean(kind="balanced", p=64)),
        Claim("balanced is no slower than plain", 1.0, 1e9, mean(kind="additive", p=64) / mean(kind="balanced", p=64)),
        Claim("deflated is close to balanced", 0.9, 1.5, mean(kind="deflated", p=64) / mean(kind="balanced", p=64)),
        Claim("one level does not scale", 2.0, 1e9, mean(kind="one_level", p=256) / mean(kind="one_level", p=64)),
        Claim("balanced scales", 0.9, 1.1, mean(kind="balanced", p=256) / mean(kind="balanced", p=64)),
    ],
    "w08_gamma_plain_weight": [
        Claim("damped: one half is best, a fifth bad", 1.1, 1e9, mean(method=R, gamma=0.2) / mean(method=R, gamma=0.5)),
        rising("damped: half-integers rise", [mean(method=R, gamma=g) for g in (0.5, 1.0, 1.5, 2.0, 3.0)], 1.0),
        rising("conjugate gradients improve with overlap", [-mean(method=C, gamma=g) for g in (0.2, 0.5, 1.0, 2.0, 3.0)], 1.0),
    ],
    "w09_gamma_omega": [
        Claim("damped: one half is best, a fifth bad", 1.1, 1e9, mean(method=R, gamma=0.2) / mean(method=R, gamma=0.5)),
        rising("damped: half-integers rise", [mean(method=R, gamma=g) for g in (0.5, 1.0, 1.5, 2.0, 3.0)], 1.0),
        Claim("damped: other overlaps are worse", 1.0, 1e9, mean(method=R, gamma=0.75) / mean(method=R, gamma=0.5)),
        rising("conjugate gradients improve with overlap", [-mean(method=C, gamma=g) for g in (0.2, 0.5, 1.0, 2.0, 3.0)], 1.0),
    ],
    "w10_gamma_3d": [
        *[about(f"damped, omega, overlap {g}", 50, mean(method=R, weight="omega", gamma=g), 0.3) for g in (0.5, 1.0)],
        Claim("damped, omega: a fifth is worse", 1.05, 1e9, mean(method=R, weight="omega", gamma=0.2) / mean(method=R, weight="omega", gamma=0.5)),
        Claim("omega improves the damped iteration", 1.0, 1e9, mean(method=R, weight="none", gamma=1.0) / mean(method=R, weight="omega", gamma=1.0)),
        rising("conjugate gradients, omega, improve with overlap", [-mean(method=C, weight="omega", gamma=g) for g in (0.2, 0.5, 1.0)], 1.0),
    ],
    "w11_asymmetric": [
        Claim("the flexible form converges where the operator is not symmetric", 1.0, 1e9, mean(method="flexible")),
        Claim("plain conjugate gradients suffer", 1.1, 1e9, Value("coalesce(" + mean(method=C, weight="unity") + ", 400.0)") / mean(method=C, weight="omega")),
    ],
    "w12_size": [
        rising("damped: grows with the slice", [mean(method=R, n=2**s * 64) for s in (6, 8, 10)]),
        rising("conjugate gradients: grows with the slice", [mean(method=C, n=2**s * 64) for s in (6, 8, 10, 12)]),
    ],
    "w13_size_q": [
        about("damped: limit for large slices", 145, mean(method=R, n=2**12 * 64, workload="w13")),
        most("conjugate gradients: at most", 29, highest(method=C, workload="w13")),
        Claim("quadrupled pieces: the damped count shrinks", 1.0, 1e9, mean(method=R, workload="w13 quadrupled", n=2**6 * 64) / mean(method=R, workload="w13 quadrupled", n=2**8 * 64)),
        Claim("quadrupled pieces: the count of conjugate gradients shrinks", 1.0, 1e9, mean(method=C, workload="w13 quadrupled", n=2**6 * 64) / mean(method=C, workload="w13 quadrupled", n=2**8 * 64)),
    ],
    "w14_dimension": [
        about("damped, six dimensions", 26, mean(method=R, d=6), 0.3),
        about("conjugate gradients, six dimensions", 16, mean(method=C, d=6), 0.3),
        Claim("one dimension is the hardest, damped", 1.0, 1e9, mean(method=R, d=1) / highest(method=R, **{"least(d, 2)": 2})),
        Claim("one dimension is the hardest, conjugate gradients", 1.0, 1e9, mean(method=C, d=1) / highest(method=C, **{"least(d, 2)": 2})),
    ],
    "w16_strong": [
        Claim("rises first", 0.0, 1e9, mean(p=64) - mean(p=16)),
        Claim("declines after its peak", 1.0, 1e9, mean(p=256) - mean(p=1024)),
        Claim("dips where slices are equal", 0.0, 1e9, mean(p=200) - mean(p=256)),
    ],
    "w17_strong_q": [
        Claim("stays within a narrow range from 64 slices", 1.0, 1.6, spread(method=C, **{"least(p, 64)": 64})),
    ],
    "w18_consistency": [
        Claim(f"level {level} is {s} points a slice", 0.0, 0.0, mean(workload=f"strong {level}") - mean(workload=f"weak {s}")) for level, s in ((16, 8), (18, 10), (20, 12))
    ],
    "w19_faults_1d": [
        *[about(f"conjugate gradients, overlap 2, rate {f}", k, mean(method=C, gamma=2.0, p_fault=f)) for f, k in ((0.0, 25), (0.01, 28), (0.02, 31), (0.05, 37), (0.1, 54))],
        *[about(f"conjugate gradients, rate 0.05, overlap {g}", k, mean(method=C, gamma=g, p_fault=0.05), 0.2) for g, k in ((1.0, 50), (1.5, 43))],
        Claim("overlap one half survives 0.02", 1.0, 10.0, runs(method=C, gamma=0.5, p_fault=0.02)),
        Claim("overlap one half does not survive 0.1", 0.0, 0.0, runs(gamma=0.5, p_fault=0.1)),
        Claim("overlap 2 survives 0.1", 1.0, 10.0, runs(method=C, gamma=2.0, p_fault=0.1)),
        about("without faults, conjugate gradients need this share of the damped count", 0.25, mean(method=C, gamma=2.0, p_fault=0.0) / mean(method=R, gamma=2.0, p_fault=0.0), 0.3),
        about("at rate 0.1, this share", 0.5, mean(method=C, gamma=2.0, p_fault=0.1) / mean(method=R, gamma=2.0, p_fault=0.1), 0.3),
    ],
    "w20_faults_6d": [
        Claim("damped: nearly the same for all rates", 0.8, 1.4, mean(method=R, gamma=2.0, p_fault=0.2) / mean(method=R, gamma=2.0, p_fault=0.0)),
        Claim("conjugate gradients lose their advantage at rate 0.2", 1.0, 1e9, mean(method=C, gamma=2.0, p_fault=0.2) / mean(method=R, gamma=2.0, p_fault=0.2)),
        Claim("overlap one half does not survive 0.2", 0.0, 0.0, runs(gamma=0.5, p_fault=0.2)),
    ],
    "w21_weak_faults_1d": [
        Claim("damped: weak scaling under faults", 0.9, 1.25, mean(method=R, p_fault=0.1, p=128) / mean(method=R, p_fault=0.1, p=64)),
        rising("conjugate gradients deteriorate with the rate", [mean(method=C, p_fault=f) for f in (0.0, 0.02, 0.05, 0.1, 0.2)]),
        Claim("conjugate gradients need fewer than the damped iteration", 1.0, 1e9, mean(method=R, p_fault=0.1) / mean(method=C, p_fault=0.1)),
        Claim("damped: average and asymptotic rates are close", -0.05, 0.05, gap(method=R, p_fault=0.05)),
    ],
    "w22_weak_faults_6d": [
        Claim("damped: nearly the same up to rate 0.1", 0.8, 1.3, mean(method=R, p_fault=0.1) / mean(method=R, p_fault=0.0)),
        Claim("damped: more at rate 0.2", 1.0, 1.6, mean(method=R, p_fault=0.2) / mean(method=R, p_fault=0.0)),
        rising("conjugate gradients rise with the rate", [mean(method=C, p_fault=f) for f in (0.0, 0.05, 0.1, 0.2)], 0.5),
    ],
    "w23_switch": [
        Claim("the best start by averaging beats none", 1.0, 1e9, spread()),
    ],
    "w24_more_slices": [
        *[about(f"200 slices, rate {f}", k, mean(p_fault=f), 0.2) for f, k in ((0.0, 25), (0.02, 31), (0.05, 37), (0.1, 54))],
    ],
    "w25_plain_faults": [
        Claim("damped plain iteration: faults change little", 0.7, 1.2, mean(p_fault=0.05) / mean(p_fault=0.0)),
    ],
}
