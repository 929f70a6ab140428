"""Tensor grids: extents, mesh widths, and the lexicographic numbering of interior points."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


@dataclass(frozen=True)
class GridSpec:
    """Interior points per axis; the mesh width of an axis is 1 / (points + 1)."""

    extents: tuple[int, ...]

    def __post_init__(self) -> None:
        if not self.extents or min(self.extents) < 1:
            raise ValueError("every axis needs at least one interior point")

    @classmethod
    def of_levels(cls, levels: tuple[int, ...]) -> GridSpec:
        if min(levels, default=0) < 1:
            raise ValueError("levels must be positive")
        return cls(tuple(2**k - 1 for k in levels))

    @property
    def d(self) -> int:
        return len(self.extents)

    @property
    def size(self) -> int:
        return math.prod(self.extents)

    @property
    def widths(self) -> tuple[float, ...]:
        return tuple(1.0 / (n + 1) for n in self.extents)

    @property
    def strides(self) -> tuple[int, ...]:
        """Of the lexicographic number; the last axis runs fastest."""
        return tuple(math.prod(self.extents[j + 1:]) for j in range(self.d))

    @property
    def bits(self) -> int:
        """Curve resolution: enough bits for the largest coordinate."""
        return max(1, max(self.extents).bit_length())

    @property
    def diagonal(self) -> float:
        return sum(2.0 / h**2 for h in self.widths)


def unknowns(levels: tuple[int, ...]) -> int:
    return GridSpec.of_levels(levels).size


def needle(d: int, level: int) -> GridSpec:
    """One fine axis, one point on every other axis."""
    return GridSpec.of_levels((level,) + (1,) * (d - 1))


def levels_for(d: int, s: int, p: int) -> tuple[int, ...]:
    """Isotropic levels for a budget of 2**s points for each of p slices; rounded down."""
    return (max(1, int(math.floor((s + math.log2(p)) / d))),) * d


def level_column(d: Column, s: int, p: Column) -> Column:
    """The level of ``levels_for``, for columns of whole numbers."""
    return F.greatest(F.lit(1), F.floor((F.length(F.bin(p.cast("long"))) - 1 + s) / d)).cast("int")


def extents_for_budget(d: int, n: int) -> tuple[int, ...]:
    """Near-isotropic extents whose product is about n and not above it."""
    out: list[int] = []
    for left in range(d, 0, -1):
        k = max(1, round(n ** (1 / left)))
        while k > 1 and k**left > n * (1 + 1e-9) and left == 1:
            k -= 1
        out.append(k)
        n = max(1, n // k)
    return tuple(sorted(out, reverse=True))


def cells(spark: SparkSession, spec: GridSpec, partitions: int | None = None) -> DataFrame:
    """(id, k1..kd) of all interior points, from a range; coordinates begin at 1."""
    base = spark.range(0, spec.size, 1, partitions) if partitions else spark.range(spec.size)
    return base.select("id", *from_lex(F.col("id"), spec))


def from_lex(number: Column, spec: GridSpec) -> list[Column]:
    return [(F.floor(number / F.lit(s)) % n + 1).cast("int").alias(f"k{j + 1}") if s > 1 else (number % n + 1).cast("int").alias(f"k{j + 1}")
            for j, (s, n) in enumerate(zip(spec.strides, spec.extents))]


def lex_id(coords: list[Column], spec: GridSpec) -> Column:
    out = F.lit(0).cast("long")
    for c, s in zip(coords, spec.strides):
        out = out + (c.cast("long") - 1) * s
    return out


def axis_cell(code: Column, codes: int, n: int) -> Column:
    """Axis cell 1..n of an integer code 0..codes-1; null outside that range."""
    return F.when((code >= 0) & (code < codes), (F.floor(code.cast("long") * n / F.lit(codes)) + 1).cast("int"))
