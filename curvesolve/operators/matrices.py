"""Sparse matrices and vectors as frames: MatrixFrame (i, j, v), VectorFrame (i, v)."""

from __future__ import annotations

import itertools
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.grid import GridSpec, cells
from ..functions.uniform import uniform


def _stacked(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def _entries(grid: DataFrame, spec: GridSpec, offsets: list[tuple[tuple[int, ...], Column | float]]) -> DataFrame:
    """Entries at neighbour offsets, one pass over the cells: an explode of the offsets that stay inside."""
    made = []
    for step, value in offsets:
        inside = F.lit(True)
        for j, s in enumerate(step):
            if s:
                inside = inside & (F.col(f"k{j + 1}") + s).between(1, spec.extents[j])
        shift = sum(s * w for s, w in zip(step, spec.strides))
        v = value if isinstance(value, Column) else F.lit(float(value))
        made.append(F.when(inside, F.struct((F.col("id") + shift).alias("j"), v.alias("v"))))
    both = F.filter(F.array(*made), lambda x: x.isNotNull())
    return grid.select(F.col("id").alias("i"), F.explode(both).alias("e")).select("i", "e.j", "e.v")


def unit(d: int, j: int, s: int) -> tuple[int, ...]:
    return tuple(s if k == j else 0 for k in range(d))


def laplace(spark: SparkSession, spec: GridSpec) -> DataFrame:
    """Finite differences, zero boundary values, lexicographic ids; rows are made where they are needed, without a join."""
    offsets: list = [((0,) * spec.d, spec.diagonal)]
    for j, h in enumerate(spec.widths):
        offsets += [(unit(spec.d, j, -1), -1 / h**2), (unit(spec.d, j, 1), -1 / h**2)]
    return _entries(cells(spark, spec), spec, offsets)


def fem(spark: SparkSession, spec: GridSpec) -> DataFrame:
    """Multilinear finite elements: tensor products of one-dimensional stiffness and mass matrices."""
    offsets = []
    for step in itertools.product((-1, 0, 1), repeat=spec.d):
        total = 0.0
        for a in range(spec.d):
            term = 1.0
            for j, (s, h) in enumerate(zip(step, spec.widths)):
                stiff, mass = (2 / h if s == 0 else -1 / h), (2 * h / 3 if s == 0 else h / 6)
                term *= stiff if j == a else mass
            total += term
        offsets.append((step, total))
    return _entries(cells(spark, spec), spec, offsets)


def diffusion(spark: SparkSession, spec: GridSpec, alpha: DataFrame) -> DataFrame:
    """Variable coefficient: (id, alpha); a face takes the harmonic mean of its cells, a boundary face its cell's value."""
    grid = cells(spark, spec).join(alpha, "id")
    diag, sides = F.lit(0.0), []
    for j, (h, w) in enumerate(zip(spec.widths, spec.strides)):
        for s in (-1, 1):
            inside = (F.col(f"k{j + 1}") + s).between(1, spec.extents[j])
            near = alpha.select((F.col("id") - s * w).alias("id"), F.col("alpha").alias(f"_n{j}{s + 1}"))
            grid = grid.join(near, "id", "left")
            face = F.when(inside, 2 * F.col("alpha") * F.col(f"_n{j}{s + 1}") / (F.col("alpha") + F.col(f"_n{j}{s + 1}"))).otherwise(F.col("alpha")) / h**2
            diag = diag + face
            sides.append((unit(spec.d, j, s), -face))
    return _entries(grid, spec, [((0,) * spec.d, diag), *sides])


def boundary_load(spark: SparkSession, spec: GridSpec, value: Column | float) -> DataFrame:
    """(i, v): what boundary values add to the right-hand side; ``value`` may use k1..kd of the boundary point."""
    grid, parts = cells(spark, spec), []
    for j, h in enumerate(spec.widths):
        for edge, outside in ((1, 0), (spec.extents[j], spec.extents[j] + 1)):
            at = grid.where(F.col(f"k{j + 1}") == edge).withColumn(f"k{j + 1}", F.lit(outside))
            v = value if isinstance(value, Column) else F.lit(float(value))
            parts.append(at.select(F.col("id").alias("i"), (v / h**2).alias("v")))
    return _stacked(parts).groupBy("i").agg(F.sum("v").alias("v"))


def reaction(spark: SparkSession, level: int, sigma: float) -> DataFrame:
    """One-dimensional operator with a reaction term on the diagonal."""
    spec = GridSpec.of_levels((level,))
    return laplace(spark, spec).withColumn("v", F.when(F.col("i") == F.col("j"), F.col("v") + sigma).otherwise(F.col("v")))


def from_edges(edges: DataFrame, shift: float, nodes: DataFrame) -> DataFrame:
    """Graph Laplacian of (a, b, w) plus ``shift`` times the identity on ``nodes`` (id)."""
    both = edges.select(F.col("a").alias("i"), F.col("b").alias("j"), "w").unionByName(edges.select(F.col("b").alias("i"), F.col("a").alias("j"), "w"))
    off = both.groupBy("i", "j").agg((-F.sum("w")).cast("double").alias("v"))
    degree = both.groupBy("i").agg(F.sum("w").cast("double").alias("w"))
    diag = nodes.join(degree, nodes["id"] == degree["i"], "left").select(F.col("id").alias("i"), F.col("id").alias("j"), (F.coalesce("w", F.lit(0.0)) + shift).alias("v"))
    return off.unionByName(diag)


def jacobi_scale(a: DataFrame) -> DataFrame:
    """D^-1/2 A D^-1/2 with D the diagonal of A."""
    d = a.where("i = j").select(F.col("i").alias("n"), (1 / F.sqrt("v")).alias("t"))
    return a.join(d.withColumnsRenamed({"n": "i", "t": "ti"}), "i").join(d.withColumnsRenamed({"n": "j", "t": "tj"}), "j").select(
        "i", "j", (F.col("v") * F.col("ti") * F.col("tj")).alias("v"))


def spmv(a: DataFrame, x: DataFrame) -> DataFrame:
    """A x; ``x`` is (i, v)."""
    xs = x.select(F.col("i").alias("j"), F.col("v").alias("x"))
    return a.join(xs, "j").groupBy("i").agg(F.sum(F.col("v") * F.col("x")).alias("v"))


def spgemm(a: DataFrame, b: DataFrame) -> DataFrame:
    right = b.select(F.col("i").alias("j"), F.col("j").alias("k"), F.col("v").alias("w"))
    return a.join(right, "j").groupBy("i", F.col("k").alias("j")).agg(F.sum(F.col("v") * F.col("w")).alias("v"))


def axpy(alpha: float, x: DataFrame, y: DataFrame) -> DataFrame:
    """alpha x + y, absent entries are zero."""
    return x.withColumn("v", F.col("v") * alpha).unionByName(y).groupBy("i").agg(F.sum("v").alias("v"))


def dot(x: DataFrame, y: DataFrame) -> DataFrame:
    return x.join(y.withColumnRenamed("v", "w"), "i").agg(F.coalesce(F.sum(F.col("v") * F.col("w")), F.lit(0.0)).alias("v"))


def energy(a: DataFrame, x: DataFrame) -> DataFrame:
    """One row: the energy norm of x."""
    return dot(spmv(a, x), x).select(F.sqrt(F.greatest("v", F.lit(0.0))).alias("v"))


def random_start(grid: DataFrame, a: DataFrame, seed: int, run: int = 0) -> DataFrame:
    """Reproducible numbers in [-1, 1], scaled to unit energy norm; they depend on the ids alone."""
    x = grid.select(F.col("id").alias("i"), (2 * uniform(seed, run, F.col("id")) - 1).alias("v"))
    size = energy(a, x).first()["v"]
    return x.withColumn("v", F.col("v") / F.lit(size))


def manufactured(a: DataFrame, exact: DataFrame) -> DataFrame:
    """The right-hand side whose solution is ``exact``."""
    return spmv(a, exact)


def to_rows(a: DataFrame) -> DataFrame:
    """Compressed rows: (i, entries) with entries sorted by column."""
    return a.groupBy("i").agg(F.sort_array(F.collect_list(F.struct("j", "v"))).alias("entries"))


def halo(a: DataFrame, members: DataFrame) -> DataFrame:
    """(sub, pos): columns outside a grown slice that its rows refer to."""
    held = members.select("sub", F.col("pos").alias("i"))
    seen = a.where("i <> j").join(held, "i").select("sub", F.col("j").alias("pos")).distinct()
    return seen.join(members.select("sub", "pos"), ["sub", "pos"], "left_anti")
