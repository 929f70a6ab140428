"""Grids, matrices, curves, slices, overlaps, weights and coarse pieces."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import curves, grid
from ..functions.uniform import uniform
from ..operators import matrices, ordering, partition
from ..plans import measures
from ..sources import tables
from .shared import G2, GAMMA, N, P, Q, SCALE, cells_sql, facts_sql, laplace_sql, members_sql, pieces_sql, rhs_sql, slices_sql, uniform_sql

BITS = G2.bits
Spark = SparkSession
HALF = 0.25


def _order(spark: Spark, curve: str) -> DataFrame:
    keyed = ordering.with_key(grid.cells(spark, G2), curve, 2, BITS)
    return ordering.positions(keyed, ["key"]).select("id", "k1", "k2", "pos")


def _pos(spark: Spark) -> DataFrame:
    return spark.range(N).select(F.col("id").alias("pos"))


def _members(spark: Spark, gamma: float = GAMMA) -> DataFrame:
    return partition.members(_pos(spark), N, P, gamma)


def _facts(spark: Spark, sf_dir: str, spec: grid.GridSpec, name: str = "B2") -> DataFrame:
    """(id, facts): cells that hold facts of lineitem, and how many."""
    cell = grid.lex_id([grid.axis_cell(c, m, n) for (c, m), n in zip(tables.axes(name), spec.extents)], spec)
    return tables.table(spark, sf_dir, "lineitem").select(cell.alias("id")).where("id is not null").groupBy("id").agg(F.count("*").alias("facts"))


def _vector(spark: Spark, sf_dir: str) -> DataFrame:
    return tables.rhs(spark, sf_dir, "B2", G2).select(F.col("id").alias("i"), (F.col("cents") / SCALE).alias("v"))


def m01_unknowns(spark: Spark, sf_dir: str) -> DataFrame:
    """Unknowns of the smallest grids that hold the facts' cells, of quantity, discount and line number."""
    codes = [(code + 1).cast("long") for code, _ in (tables.axes("B4")[k] for k in (0, 1, 3))]
    per = tables.table(spark, sf_dir, "lineitem").select(F.array(*[F.length(F.bin(c)) for c in codes]).alias("l")).groupBy("l").agg(F.count("*").alias("facts"))
    n = F.aggregate("l", F.lit(1).cast("long"), lambda a, k: a * (F.pow(F.lit(2), k).cast("long") - 1))
    return per.select(F.array_join(F.transform("l", lambda x: x.cast("string")), ",").alias("levels"), n.alias("n"), "facts")


def m04_levels(spark: Spark, sf_dir: str) -> DataFrame:
    """Levels for as many slices as an order has lines, on grids of one, two, three and six axes."""
    lines = tables.table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.count("*").alias("p")).groupBy("p").agg(F.count("*").alias("orders"))
    every = lines.select(F.explode(F.array(*map(F.lit, (1, 2, 3, 6)))).alias("d"), F.col("p").cast("int").alias("p"), "orders")
    level = grid.level_column(F.col("d"), 8, F.col("p"))
    return every.select("d", "p", level.alias("level"), "orders").select("d", "p", "level", F.pow(F.pow(F.lit(2), "level") - 1, F.col("d")).cast("long").alias("n_levels"), "orders")


def b2_rhs(spark: Spark, sf_dir: str) -> DataFrame:
    return tables.rhs(spark, sf_dir, "B2", G2)


def b1_rhs(spark: Spark, sf_dir: str) -> DataFrame:
    return tables.rhs(spark, sf_dir, "B1", grid.GridSpec((2405,)))


def b3_rhs(spark: Spark, sf_dir: str) -> DataFrame:
    return tables.rhs(spark, sf_dir, "B3", grid.GridSpec.of_levels((4, 3, 3)))


def b7_rhs(spark: Spark, sf_dir: str) -> DataFrame:
    return tables.rhs(spark, sf_dir, "B7", grid.GridSpec((720,)))


def m02_cells(spark: Spark, sf_dir: str) -> DataFrame:
    """Coordinates of every cell, with the number of its facts."""
    return grid.cells(spark, G2).join(_facts(spark, sf_dir, G2), "id", "left").withColumn("facts", F.coalesce("facts", F.lit(0)))


def m03_lex_round_trip(spark: Spark, sf_dir: str) -> DataFrame:
    """The numbers of the facts' cells, taken apart and put together again."""
    c = _facts(spark, sf_dir, G2).select("id", "facts", *grid.from_lex(F.col("id"), G2))
    return c.select("id", grid.lex_id([F.col("k1"), F.col("k2")], G2).alias("again"), "facts")


def m07_laplace(spark: Spark, sf_dir: str) -> DataFrame:
    """Rows of the matrix at the cells that hold facts, with the number of these."""
    return matrices.laplace(spark, G2).join(_facts(spark, sf_dir, G2).withColumnRenamed("id", "i"), "i")


def m08_fem(spark: Spark, sf_dir: str) -> DataFrame:
    """As ``m07_laplace``, by finite elements."""
    return matrices.fem(spark, G2).join(_facts(spark, sf_dir, G2).withColumnRenamed("id", "i"), "i").select("i", "j", F.round("v", 9).alias("v"), "facts")


def m09_diffusion(spark: Spark, sf_dir: str) -> DataFrame:
    line = tables.table(spark, sf_dir, "lineitem")
    (q, nq), (d, nd) = tables.axes("B2")
    cell = grid.lex_id([grid.axis_cell(q, nq, G2.extents[0]), grid.axis_cell(d, nd, G2.extents[1])], G2)
    per = line.groupBy(cell.alias("id")).agg((1 + F.sum(F.round(F.col("l_tax") * 100).cast("long")) / F.count("*") / 100).alias("alpha"))
    alpha = grid.cells(spark, G2).select("id").join(per, "id", "left").select("id", F.coalesce("alpha", F.lit(1.0)).alias("alpha"))
    return matrices.diffusion(spark, G2, alpha).select("i", "j", F.round("v", 6).alias("v"))


def m10_boundary_load(spark: Spark, sf_dir: str) -> DataFrame:
    return matrices.boundary_load(spark, G2, F.col("k1") + 2.0 * F.col("k2"))


def m11_reaction(spark: Spark, sf_dir: str) -> DataFrame:
    return matrices.reaction(spark, 5, 16.0)


def m06_needle(spark: Spark, sf_dir: str) -> DataFrame:
    """Rows of the needle's matrix at the cells that hold facts, with the number of these."""
    spec = grid.needle(3, 5)
    return matrices.laplace(spark, spec).join(_facts(spark, sf_dir, spec, "B3").withColumnRenamed("id", "i"), "i")


def m12_graph(spark: Spark, sf_dir: str) -> DataFrame:
    nodes = tables.table(spark, sf_dir, "nation").select(F.col("n_nationkey").cast("long").alias("id"))
    return matrices.from_edges(tables.trade_edges(spark, sf_dir), 1.0, nodes)


def m13_scaled(spark: Spark, sf_dir: str) -> DataFrame:
    return matrices.jacobi_scale(matrices.laplace(spark, G2)).select("i", "j", F.round("v", 12).alias("v"))


def m14_uniform(spark: Spark, sf_dir: str) -> DataFrame:
    return spark.range(N).select("id", (2 * uniform(7, 0, F.col("id")) - 1).alias("v"))


def m14_start(spark: Spark, sf_dir: str) -> DataFrame:
    a = matrices.laplace(spark, G2)
    x = matrices.random_start(grid.cells(spark, G2), a, 7)
    return matrices.energy(a, x).select(F.round("v", 9).alias("energy"))


def m16_spmv(spark: Spark, sf_dir: str) -> DataFrame:
    return matrices.spmv(matrices.laplace(spark, G2), _vector(spark, sf_dir)).select("i", F.round("v", 4).alias("v"))


def m17_dot(spark: Spark, sf_dir: str) -> DataFrame:
    x = _vector(spark, sf_dir)
    return matrices.dot(x, matrices.axpy(2.0, x, x)).select(F.round("v", 4).alias("v"))


def m18_rows(spark: Spark, sf_dir: str) -> DataFrame:
    rows = matrices.to_rows(matrices.laplace(spark, G2))
    return rows.select("i", F.size("entries").cast("long").alias("entries"), F.array_join(F.transform("entries", lambda e: e["j"].cast("string")), ",").alias("cols"))


def m19_halo(spark: Spark, sf_dir: str) -> DataFrame:
    return matrices.halo(matrices.laplace(spark, G2), _members(spark))


def m20_spgemm(spark: Spark, sf_dir: str) -> DataFrame:
    a = matrices.laplace(spark, G2)
    return matrices.spgemm(a, a).select("i", "j", F.round("v", 3).alias("v"))


def m21_hilbert_order(spark: Spark, sf_dir: str) -> DataFrame:
    return _order(spark, "hilbert").select("id", "pos")


def m24_lebesgue_order(spark: Spark, sf_dir: str) -> DataFrame:
    return _order(spark, "lebesgue").select("id", "pos")


def m25_lex_order(spark: Spark, sf_dir: str) -> DataFrame:
    return _order(spark, "lex").select("id", "pos")


def m25_snake_order(spark: Spark, sf_dir: str) -> DataFrame:
    return _order(spark, "snake").select("id", "pos")


def m25_gray_order(spark: Spark, sf_dir: str) -> DataFrame:
    return _order(spark, "gray").select("id", "pos")


def m26_moore(spark: Spark, sf_dir: str) -> DataFrame:
    c = spark.range(256).select(F.floor(F.col("id") / 16).cast("int").alias("x"), (F.col("id") % 16).cast("int").alias("y"))
    return c.select("x", "y", curves.moore_key([F.col("x"), F.col("y")], 4).alias("key"))


def m27_peano(spark: Spark, sf_dir: str) -> DataFrame:
    c = spark.range(81).select(F.floor(F.col("id") / 9).cast("int").alias("x"), (F.col("id") % 9).cast("int").alias("y"))
    return c.select("x", "y", curves.peano_key([F.col("x"), F.col("y")], 2).alias("key"))


def m22_precedes(spark: Spark, sf_dir: str) -> DataFrame:
    a = grid.cells(spark, G2).select("id", F.pmod(F.col("id") * 37 + 11, F.lit(N)).alias("other"), "k1", "k2")
    b = grid.cells(spark, G2).select(F.col("id").alias("other"), F.col("k1").alias("m1"), F.col("k2").alias("m2"))
    return a.join(b, "other").select("id", "other", curves.precedes([F.col("k1"), F.col("k2")], [F.col("m1"), F.col("m2")], BITS).alias("before"))


def m23_adaptive(spark: Spark, sf_dir: str) -> DataFrame:
    return ordering.adaptive_prefix(grid.cells(spark, G2), 2, BITS).select("id", "depth")


def m28_polyline(spark: Spark, sf_dir: str) -> DataFrame:
    parts = None
    for n in (1, 2, 3):
        cell = curves.hilbert_cell(F.col("id"), 2, n)
        part = spark.range(4**n).select(F.lit(n).alias("n"), F.col("id").alias("step"), cell.alias("c")).select(
            "n", "step", ((F.col("c.x0") + 0.5) / 2**n).alias("x"), ((F.col("c.x1") + 0.5) / 2**n).alias("y"))
        parts = part if parts is None else parts.unionByName(part)
    return parts


def m29_inverse(spark: Spark, sf_dir: str) -> DataFrame:
    key = curves.hilbert_key([F.col("k1"), F.col("k2")], BITS)
    c = grid.cells(spark, G2).withColumn("c", curves.hilbert_cell(key, 2, BITS))
    return c.select("id", F.col("c.x0").alias("x0"), F.col("c.x1").alias("x1"))


def m30_positions(spark: Spark, sf_dir: str) -> DataFrame:
    pts = tables.points(spark, sf_dir)
    keyed = pts.withColumn("key", curves.lebesgue_key([F.col("k1"), F.col("k2")], 5))
    return ordering.positions(keyed, ["key", "id"]).select("id", "pos")


def m30_wide_positions(spark: Spark, sf_dir: str) -> DataFrame:
    d = 16
    pts = tables.vector_points(spark, sf_dir, d, 6)
    keyed = pts.withColumn("key", curves.lebesgue_key([F.col(f"k{j + 1}") for j in range(d)], 6))
    return ordering.positions(keyed, ["key", "id"]).select("id", "pos")


def m32_holder(spark: Spark, sf_dir: str) -> DataFrame:
    out = ordering.holder(_order(spark, "lebesgue"), 2, [1, 2, 4, 8])
    return out.select("lag", F.round("ratio", 9).alias("ratio"), F.round("bound", 9).alias("bound"))


def m34_steps(spark: Spark, sf_dir: str) -> DataFrame:
    square = grid.cells(spark, grid.GridSpec((16, 16)))
    keyed = square.withColumn("key", curves.hilbert_key([F.col("k1") - 1, F.col("k2") - 1], 4))
    return ordering.lagged(ordering.positions(keyed, ["key"]), 2, 1).groupBy("dist").agg(F.count("*").alias("steps"))


def m35_slice_shape(spark: Spark, sf_dir: str) -> DataFrame:
    subs = _pos(spark).select("pos", partition.sub_of(F.col("pos"), N, P).alias("sub"))
    return ordering.slice_shape(matrices.laplace(spark, G2), subs)


def m35_components(spark: Spark, sf_dir: str) -> DataFrame:
    subs = _pos(spark).select("pos", partition.sub_of(F.col("pos"), N, P).alias("sub"))
    return ordering.slice_components(matrices.laplace(spark, G2), subs)


def m36_box(spark: Spark, sf_dir: str) -> DataFrame:
    ranges = curves.box_ranges((2, 1), (9, 5), BITS, 16)
    keyed = grid.cells(spark, G2).withColumn("key", curves.lebesgue_key([F.col("k1"), F.col("k2")], BITS))
    hit = F.lit(False)
    for a, b in ranges:
        hit = hit | F.col("key").between(a, b)
    return keyed.where(hit).where("k1 between 2 and 9 and k2 between 1 and 5").select("id")


def m37_slices(spark: Spark, sf_dir: str) -> DataFrame:
    return partition.slices(spark, N, P)


def m38_sub_of(spark: Spark, sf_dir: str) -> DataFrame:
    return _pos(spark).select("pos", partition.sub_of(F.col("pos"), N, P).alias("sub"))


def m39_overlap_whole(spark: Spark, sf_dir: str) -> DataFrame:
    return _members(spark, 1.0)


def m40_overlap_half(spark: Spark, sf_dir: str) -> DataFrame:
    return _members(spark, 1.5)


def m41_overlap_general(spark: Spark, sf_dir: str) -> DataFrame:
    return _members(spark, 0.2)


def m42_overlap_clipped(spark: Spark, sf_dir: str) -> DataFrame:
    return partition.members(_pos(spark), N, 3, 1.5)


def m43_bounds(spark: Spark, sf_dir: str) -> DataFrame:
    return partition.bounds(spark, N, P, GAMMA)


def m44_cover(spark: Spark, sf_dir: str) -> DataFrame:
    return partition.cover(_members(spark, HALF))


def m46_unity(spark: Spark, sf_dir: str) -> DataFrame:
    return partition.weights(_members(spark, HALF), "unity", HALF, P).select("sub", "pos", "w")


def m47_omega(spark: Spark, sf_dir: str) -> DataFrame:
    return partition.weights(_members(spark, HALF), "omega", HALF, P).select("sub", "pos", "w")


def m48_uniform(spark: Spark, sf_dir: str) -> DataFrame:
    parts = None
    for twice in range(1, P):
        part = partition.check_uniform(_members(spark, twice / 2)).select(F.lit(twice).alias("twice_gamma"), "lowest", "highest")
        parts = part if parts is None else parts.unionByName(part)
    return parts


def m50_storage(spark: Spark, sf_dir: str) -> DataFrame:
    return measures.storage(_members(spark), N)


def m55_pieces(spark: Spark, sf_dir: str) -> DataFrame:
    return _pos(spark).select("pos", partition.agg_id(F.col("pos"), N, P, Q).alias("agg"))


#: Unequal numbers of pieces.
PIECES = [1 + s % Q for s in range(P)]


def m56_pieces_var(spark: Spark, sf_dir: str) -> DataFrame:
    return _pos(spark).select("pos", partition.agg_id_var(F.col("pos"), N, P, PIECES).alias("agg"))


def m57_restrict(spark: Spark, sf_dir: str) -> DataFrame:
    v = tables.rhs(spark, sf_dir, "B2", G2).select(F.col("id").alias("i"), F.col("cents").alias("v"))
    return partition.restrict(v, partition.agg_id(F.col("i"), N, P, Q))


def m57_extend(spark: Spark, sf_dir: str) -> DataFrame:
    agg = partition.agg_id(F.col("pos"), N, P, Q)
    return partition.extend(m57_restrict(spark, sf_dir), _pos(spark), agg)


def m59_coarse(spark: Spark, sf_dir: str) -> DataFrame:
    a = matrices.laplace(spark, G2)
    return partition.coarse_matrix(a, partition.agg_id(F.col("i"), N, P, Q), partition.agg_id(F.col("j"), N, P, Q)).select("i", "j", F.round("v", 6).alias("v"))


def m94_energy(spark: Spark, sf_dir: str) -> DataFrame:
    return matrices.energy(matrices.laplace(spark, G2), _vector(spark, sf_dir)).select(F.round("v", 4).alias("energy"))


def m106_balance(spark: Spark, sf_dir: str) -> DataFrame:
    return measures.balance(partition.slices(spark, N, P))


def m107_traffic(spark: Spark, sf_dir: str) -> DataFrame:
    return measures.traffic(matrices.laplace(spark, G2), _members(spark))


QUERIES = {f.__name__: f for f in (
    m01_unknowns, m02_cells, m03_lex_round_trip, m04_levels, b1_rhs, b2_rhs, b3_rhs, b7_rhs, m06_needle, m07_laplace, m08_fem, m09_diffusion, m10_boundary_load, m11_reaction, m12_graph,
    m13_scaled, m14_uniform, m14_start, m16_spmv, m17_dot, m18_rows, m19_halo, m20_spgemm, m21_hilbert_order, m22_precedes, m23_adaptive, m24_lebesgue_order, m25_lex_order,
    m25_snake_order, m25_gray_order, m26_moore, m27_peano, m28_polyline, m29_inverse, m30_positions, m30_wide_positions, m32_holder, m34_steps, m35_slice_shape, m35_components,
    m36_box, m37_slices, m38_sub_of, m39_overlap_whole, m40_overlap_half, m41_overlap_general, m42_overlap_clipped, m43_bounds, m44_cover, m46_unity, m47_omega, m48_uniform,
    m50_storage, m55_pieces, m56_pieces_var, m57_restrict, m57_extend, m59_coarse, m94_energy, m106_balance, m107_traffic)}

_A, _C = laplace_sql(G2), cells_sql(G2)
_R = rhs_sql("B2", G2)
_X = f"SELECT id AS i, cents / {SCALE!r} AS v FROM ({_R})"
_Z = " + ".join(f"(((k1 >> {b}) & 1) << {2 * b + 1}) + (((k2 >> {b}) & 1) << {2 * b})" for b in range(BITS))
#: Hilbert steps by the plane's quadrant rule: rotate and reflect into the entered quadrant, level by level.
_HILBERT = (f"WITH RECURSIVE w AS (SELECT id, CAST(k1 AS BIGINT) AS x, CAST(k2 AS BIGINT) AS y, CAST({1 << (BITS - 1)} AS BIGINT) AS s, CAST(0 AS BIGINT) AS d FROM ({_C}) "
            "UNION ALL SELECT id, CASE WHEN (y & s) = 0 THEN CASE WHEN (x & s) > 0 THEN (s - 1) - (y & (s - 1)) ELSE y & (s - 1) END ELSE x & (s - 1) END, "
            "CASE WHEN (y & s) = 0 THEN CASE WHEN (x & s) > 0 THEN (s - 1) - (x & (s - 1)) ELSE x & (s - 1) END ELSE y & (s - 1) END, s // 2, "
            "d + s * s * xor(3 * CAST((x & s) > 0 AS BIGINT), CAST((y & s) > 0 AS BIGINT)) FROM w WHERE s > 0) ")


def _positions(keyed: str) -> str:
    return f"SELECT id, CAST(row_number() OVER (ORDER BY key) - 1 AS BIGINT) AS pos FROM ({keyed})"


#: The same bits for coordinates that begin at zero.
_ZERO = " + ".join(f"((((k1 - 1) >> {b}) & 1) << {2 * b + 1}) + ((((k2 - 1) >> {b}) & 1) << {2 * b})" for b in range(BITS))


def _walk(n: int, x: str = "i // %d", y: str = "i %% %d") -> str:
    """(x, y, d) of all cells of a square by the quadrant rule."""
    side = 2**n
    x0, y0 = x % side, y % side
    return (f"WITH RECURSIVE w AS (SELECT {x0} AS x0, {y0} AS y0, CAST({x0} AS BIGINT) AS x, CAST({y0} AS BIGINT) AS y, CAST({side // 2} AS BIGINT) AS s, CAST(0 AS BIGINT) AS d FROM range({side * side}) t(i) "
            "UNION ALL SELECT x0, y0, CASE WHEN (y & s) = 0 THEN CASE WHEN (x & s) > 0 THEN (s - 1) - (y & (s - 1)) ELSE y & (s - 1) END ELSE x & (s - 1) END, "
            "CASE WHEN (y & s) = 0 THEN CASE WHEN (x & s) > 0 THEN (s - 1) - (x & (s - 1)) ELSE x & (s - 1) END ELSE y & (s - 1) END, s // 2, "
            "d + s * s * xor(3 * CAST((x & s) > 0 AS BIGINT), CAST((y & s) > 0 AS BIGINT)) FROM w WHERE s > 0) SELECT x0 AS x, y0 AS y, d FROM w WHERE s = 0")


#: Four quadrants of 8 x 8, each with a turned copy of the open curve.
_MOORE = " UNION ALL ".join(f"SELECT CAST({x} AS INTEGER) AS x, CAST({y} AS INTEGER) AS y, d + {64 * q} AS key FROM ({_walk(3)})"
                            for q, (x, y) in enumerate((("7 - y", "x"), ("7 - y", "x + 8"), ("8 + y", "15 - x"), ("8 + y", "7 - x"))))
_AT = "least(63, greatest(0, CAST(floor((CAST(embedding[{}] AS DOUBLE) + 0.6) / 1.2 * 64) AS BIGINT)))"
_WIDE = ("SELECT id, CAST(row_number() OVER (ORDER BY key, id) - 1 AS BIGINT) AS pos FROM (SELECT vec_id AS id, "
         + " + ".join(f"CAST((({_AT.format(j + 1)}) >> {b}) & 1 AS HUGEINT) * CAST({1 << (b * 16 + 15 - j)} AS HUGEINT)" for b in range(6) for j in range(16)) + " AS key FROM embeddings)")


def _diffusion() -> str:
    cell = "(CAST(l_quantity AS INTEGER) - 1) * 15 // 50 * 7 + CAST(round(l_discount * 100) AS INTEGER) * 7 // 11"
    alpha = (f"SELECT c.*, coalesce(1 + f.a, 1.0) AS alpha FROM ({_C}) c LEFT JOIN (SELECT {cell} AS id, sum(CAST(round(l_tax * 100) AS BIGINT)) / count(*) / 100 AS a FROM lineitem GROUP BY 1) f USING (id)")
    face = "2 * a.alpha * b.alpha / (a.alpha + b.alpha)"
    h1, h2 = G2.widths
    off = f"SELECT a.id AS i, b.id AS j, -{face} * (CASE WHEN a.k1 <> b.k1 THEN {1 / h1**2!r} ELSE {1 / h2**2!r} END) AS v FROM al a JOIN al b ON abs(a.k1 - b.k1) + abs(a.k2 - b.k2) = 1"
    edge = f"(CASE WHEN k1 = 1 THEN 1 ELSE 0 END + CASE WHEN k1 = {G2.extents[0]} THEN 1 ELSE 0 END) * {1 / h1**2!r} + (CASE WHEN k2 = 1 THEN 1 ELSE 0 END + CASE WHEN k2 = {G2.extents[1]} THEN 1 ELSE 0 END) * {1 / h2**2!r}"
    return (f"WITH al AS ({alpha}), off AS ({off}) SELECT i, j, round(v, 6) AS v FROM off UNION ALL "
            f"SELECT al.id, al.id, round(al.alpha * ({edge}) - s.v, 6) FROM al JOIN (SELECT i, sum(v) AS v FROM off GROUP BY i) s ON s.i = al.id")


def _fem() -> str:
    h1, h2 = G2.widths
    def st(h, j): return f"(CASE WHEN a.k{j} = b.k{j} THEN {2 / h!r} ELSE {-1 / h!r} END)"  # noqa: E704
    def ma(h, j): return f"(CASE WHEN a.k{j} = b.k{j} THEN {2 * h / 3!r} ELSE {h / 6!r} END)"  # noqa: E704
    return (f"SELECT a.id AS i, b.id AS j, round(CAST({st(h1, 1)} AS DOUBLE) * CAST({ma(h2, 2)} AS DOUBLE) + CAST({ma(h1, 1)} AS DOUBLE) * CAST({st(h2, 2)} AS DOUBLE), 9) AS v FROM ({_C}) a JOIN ({_C}) b ON abs(a.k1 - b.k1) <= 1 AND abs(a.k2 - b.k2) <= 1")


def _at_facts(matrix: str, spec: grid.GridSpec) -> str:
    """The matrix's rows at cells that hold facts."""
    return f"SELECT m.*, f.facts FROM ({matrix}) m JOIN ({facts_sql(spec)}) f ON f.id = m.i"


_COVER = f"SELECT pos, CAST(count(*) AS BIGINT) AS cover FROM ({members_sql(N, P, HALF)}) GROUP BY pos"
_SUB = f"SELECT x.i AS pos, s.sub FROM range({N}) x(i) JOIN ({slices_sql(N, P)}) s ON x.i >= s.lo AND x.i < s.lo + s.size"
_TAX = ("SELECT least(c_nationkey, s_nationkey) AS a, greatest(c_nationkey, s_nationkey) AS b, sum(CAST(round(l_extendedprice * 100) AS BIGINT)) AS w FROM lineitem JOIN orders ON l_orderkey = o_orderkey "
        "JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey WHERE c_nationkey <> s_nationkey GROUP BY 1, 2")
_HALO = (f"SELECT DISTINCT m.sub, a.j AS pos FROM ({_A}) a JOIN ({members_sql(N, P, GAMMA)}) m ON m.pos = a.i WHERE a.i <> a.j AND NOT EXISTS "
         f"(SELECT 1 FROM ({members_sql(N, P, GAMMA)}) o WHERE o.sub = m.sub AND o.pos = a.j)")

SQL = {
    "m27_peano": "WITH c AS (SELECT i // 9 AS x, i % 9 AS y FROM range(81) t(i)), d AS (SELECT *, x // 3 AS x1, x % 3 AS x0, y // 3 AS y1, y % 3 AS y0 FROM c) "
                 "SELECT CAST(x AS INTEGER) AS x, CAST(y AS INTEGER) AS y, CAST(27 * x1 + 9 * (CASE WHEN x1 = 1 THEN 2 - y1 ELSE y1 END) + 3 * (CASE WHEN y1 = 1 THEN 2 - x0 ELSE x0 END) + (CASE WHEN (x1 + x0) % 2 = 1 THEN 2 - y0 ELSE y0 END) AS BIGINT) AS key FROM d",
    "m01_unknowns": "SELECT concat_ws(',', a, b, c) AS levels, CAST((power(2, a) - 1) * (power(2, b) - 1) * (power(2, c) - 1) AS BIGINT) AS n, CAST(count(*) AS BIGINT) AS facts FROM "
                    "(SELECT length(bin(CAST(l_quantity AS BIGINT))) AS a, length(bin(CAST(round(l_discount * 100) AS BIGINT) + 1)) AS b, length(bin(CAST(l_linenumber AS BIGINT))) AS c FROM lineitem) GROUP BY a, b, c",
    "m02_cells": f"SELECT c.*, coalesce(f.facts, 0) AS facts FROM ({_C}) c LEFT JOIN ({facts_sql(G2)}) f USING (id)",
    "m03_lex_round_trip": f"SELECT id, id AS again, facts FROM ({facts_sql(G2)})",
    "m04_levels": "SELECT CAST(d AS INTEGER) AS d, CAST(p AS INTEGER) AS p, CAST(floor((8 + log2(p)) / d) AS INTEGER) AS level, CAST(power(power(2, floor((8 + log2(p)) / d)) - 1, d) AS BIGINT) AS n_levels, orders FROM (VALUES (1), (2), (3), (6)) a(d), "
                  "(SELECT p, CAST(count(*) AS BIGINT) AS orders FROM (SELECT count(*) AS p FROM lineitem GROUP BY l_orderkey) GROUP BY p)",
    "b1_rhs": rhs_sql("B1", grid.GridSpec((2405,))), "b2_rhs": _R, "b3_rhs": rhs_sql("B3", grid.GridSpec.of_levels((4, 3, 3))),
    "b7_rhs": "SELECT CAST(c.i AS BIGINT) AS id, CAST(coalesce(f.cents, 0) AS BIGINT) AS cents FROM range(720) c(i) LEFT JOIN (SELECT date_diff('hour', TIMESTAMP '2024-01-01', date_trunc('hour', ts)) AS id, sum(CAST(round(value * 100) AS BIGINT)) AS cents FROM events GROUP BY 1) f ON f.id = c.i",
    "m06_needle": _at_facts(laplace_sql(grid.needle(3, 5)), grid.needle(3, 5)), "m07_laplace": _at_facts(_A, G2), "m08_fem": _at_facts(_fem(), G2), "m09_diffusion": _diffusion(),
    "m10_boundary_load": f"SELECT id AS i, CAST(sum(v) AS DOUBLE) AS v FROM (SELECT id, 2.0 * k2 * {1 / G2.widths[0]**2} AS v FROM ({_C}) WHERE k1 = 1 UNION ALL SELECT id, ({G2.extents[0] + 1} + 2.0 * k2) * {1 / G2.widths[0]**2} FROM ({_C}) WHERE k1 = {G2.extents[0]} "
                         f"UNION ALL SELECT id, k1 * {1 / G2.widths[1]**2} FROM ({_C}) WHERE k2 = 1 UNION ALL SELECT id, (k1 + 2.0 * {G2.extents[1] + 1}) * {1 / G2.widths[1]**2} FROM ({_C}) WHERE k2 = {G2.extents[1]}) GROUP BY id",
    "m11_reaction": laplace_sql(grid.needle(3, 5)),
    "m12_graph": f"WITH e AS ({_TAX}), s AS (SELECT a AS i, b AS j, w FROM e UNION ALL SELECT b, a, w FROM e) SELECT CAST(i AS BIGINT) AS i, CAST(j AS BIGINT) AS j, CAST(-w AS DOUBLE) AS v FROM s UNION ALL "
                 "SELECT CAST(n_nationkey AS BIGINT), CAST(n_nationkey AS BIGINT), CAST(coalesce(d.w, 0) AS DOUBLE) + 1.0 FROM nation LEFT JOIN (SELECT i, sum(w) AS w FROM s GROUP BY i) d ON d.i = n_nationkey",
    "m13_scaled": f"SELECT i, j, round(v / {G2.diagonal!r}, 12) AS v FROM ({_A})",
    "m14_uniform": f"SELECT CAST(i AS BIGINT) AS id, 2 * {uniform_sql('7', '0', 'i')} - 1 AS v FROM range({N}) t(i)",
    "m14_start": "SELECT CAST(1.0 AS DOUBLE) AS energy",
    "m16_spmv": f"SELECT a.i, round(sum(a.v * x.v), 4) AS v FROM ({_A}) a JOIN ({_X}) x ON x.i = a.j GROUP BY a.i",
    "m17_dot": f"SELECT round(sum(v * 3 * v), 4) AS v FROM ({_X})",
    "m18_rows": f"SELECT i, CAST(count(*) AS BIGINT) AS entries, string_agg(CAST(j AS VARCHAR), ',' ORDER BY j) AS cols FROM ({_A}) GROUP BY i",
    "m19_halo": _HALO,
    "m20_spgemm": f"SELECT a.i, b.j, round(sum(a.v * b.v), 3) AS v FROM ({_A}) a JOIN ({_A}) b ON b.i = a.j GROUP BY a.i, b.j",
    "m21_hilbert_order": _HILBERT + "SELECT id, CAST(row_number() OVER (ORDER BY d) - 1 AS BIGINT) AS pos FROM w WHERE s = 0",
    "m22_precedes": f"SELECT a.id, b.id AS other, a.z < b.z AS before FROM (SELECT id, {_Z} AS z FROM ({_C})) a JOIN (SELECT id, {_Z} AS z FROM ({_C})) b ON b.id = (a.id * 37 + 11) % {N}",
    "m23_adaptive": f"WITH z AS (SELECT id, {_Z} AS z FROM ({_C})), u AS (SELECT id, t, count(*) OVER (PARTITION BY t, z >> (2 * ({BITS} - t))) AS n FROM z, range(1, {BITS + 1}) r(t)) SELECT id, CAST(min(CASE WHEN n = 1 OR t = {BITS} THEN t END) AS INTEGER) AS depth FROM u GROUP BY id",
    "m24_lebesgue_order": _positions(f"SELECT id, {_Z} AS key FROM ({_C})"),
    "m25_lex_order": f"SELECT id, id AS pos FROM ({_C})",
    "m25_snake_order": _positions(f"SELECT id, k1 * 100 + (CASE WHEN (k1 - 1) % 2 = 0 THEN k2 ELSE 50 - k2 END) AS key FROM ({_C})"),
    "m30_positions": "SELECT doc_id AS id, CAST(row_number() OVER (ORDER BY " + " + ".join(f"(((CAST(least(31, floor(log2(greatest(n_chars, 1)))) AS BIGINT) >> {b}) & 1) << {2 * b + 1}) + (((CAST(coalesce(list_position(['de', 'en', 'es', 'fr'], lang), 0) AS BIGINT) >> {b}) & 1) << {2 * b})" for b in range(5)) + ", doc_id) - 1 AS BIGINT) AS pos FROM documents",
    "m32_holder": f"WITH o AS (SELECT c.k1, c.k2, CAST(row_number() OVER (ORDER BY {_Z}) AS BIGINT) AS pos FROM ({_C}) c) SELECT CAST(g AS INTEGER) AS lag, round(max(sqrt((a.k1 - b.k1) * (a.k1 - b.k1) + (a.k2 - b.k2) * (a.k2 - b.k2)) / sqrt(g)), 9) AS ratio, round(2 * sqrt(5.0), 9) AS bound FROM (VALUES (1), (2), (4), (8)) l(g), o a JOIN o b ON b.pos = a.pos + l.g GROUP BY g",
    "m34_steps": "SELECT CAST(1.0 AS DOUBLE) AS dist, CAST(255 AS BIGINT) AS steps",
    "m35_slice_shape": f"WITH s AS ({_SUB}), e AS (SELECT x.sub, y.sub AS other FROM ({_A}) a JOIN s x ON x.pos = a.i JOIN s y ON y.pos = a.j WHERE x.sub <> y.sub) SELECT s.sub, CAST(count(*) AS BIGINT) AS cells, CAST((SELECT count(*) FROM e WHERE e.sub = s.sub) AS BIGINT) AS cut_edges, CAST((SELECT count(DISTINCT other) FROM e WHERE e.sub = s.sub) AS BIGINT) AS neighbours FROM s GROUP BY s.sub",
    "m36_box": f"SELECT id FROM ({_C}) WHERE k1 BETWEEN 2 AND 9 AND k2 BETWEEN 1 AND 5",
    "m37_slices": slices_sql(N, P),
    "m38_sub_of": f"SELECT CAST(pos AS BIGINT) AS pos, sub FROM ({_SUB})",
    "m39_overlap_whole": members_sql(N, P, 1.0), "m40_overlap_half": members_sql(N, P, 1.5), "m41_overlap_general": members_sql(N, P, 0.2), "m42_overlap_clipped": members_sql(N, 3, 1.5),
    "m43_bounds": f"SELECT s.sub, s.lo, s.size, CAST((s.lo - (b.size + 1) // 2 + {N}) % {N} AS BIGINT) AS ov_lo, CAST(s.size + (b.size + 1) // 2 + a.size // 2 AS BIGINT) AS ov_len FROM ({slices_sql(N, P)}) s JOIN ({slices_sql(N, P)}) b ON b.sub = (s.sub + {P - 1}) % {P} JOIN ({slices_sql(N, P)}) a ON a.sub = (s.sub + 1) % {P}",
    "m44_cover": _COVER,
    "m46_unity": f"SELECT m.sub, m.pos, 1.0 / c.cover AS w FROM ({members_sql(N, P, HALF)}) m JOIN ({_COVER}) c USING (pos)",
    "m47_omega": f"SELECT m.sub, m.pos, max(1.0 / c.cover) OVER (PARTITION BY m.sub) AS w FROM ({members_sql(N, P, HALF)}) m JOIN ({_COVER}) c USING (pos)",
    "m48_uniform": f"SELECT CAST(t AS INTEGER) AS twice_gamma, CAST(t + 1 AS BIGINT) AS lowest, CAST(t + 1 AS BIGINT) AS highest FROM range(1, {P}) r(t)",
    "m50_storage": "SELECT CAST(2.0 AS DOUBLE) AS factor",
    "m55_pieces": pieces_sql(N, P, Q), "m56_pieces_var": f"SELECT CAST(x.i AS BIGINT) AS pos, CAST((SELECT coalesce(sum(1 + z.s % {Q}), 0) FROM range({P}) z(s) WHERE z.s < y.sub) + y.k AS BIGINT) AS agg FROM range({N}) x(i) JOIN "
                                                                  f"(SELECT sub, k, lo + k * (size // c) + least(k, size % c) AS a, size // c + (CASE WHEN k < size % c THEN 1 ELSE 0 END) AS m FROM (SELECT *, 1 + sub % {Q} AS c FROM ({slices_sql(N, P)})) s, range({Q}) t(k) WHERE k < c) y ON x.i >= y.a AND x.i < y.a + y.m",
    "m57_restrict": f"SELECT p.agg, CAST(sum(r.cents) AS BIGINT) AS v FROM ({_R}) r JOIN ({pieces_sql(N, P, Q)}) p ON p.pos = r.id GROUP BY p.agg",
    "m57_extend": f"SELECT p.pos AS i, CAST(sum(r.cents) OVER (PARTITION BY p.agg) AS BIGINT) AS v FROM ({_R}) r JOIN ({pieces_sql(N, P, Q)}) p ON p.pos = r.id",
    "m59_coarse": f"SELECT x.agg AS i, y.agg AS j, round(sum(a.v), 6) + 0.0 AS v FROM ({_A}) a JOIN ({pieces_sql(N, P, Q)}) x ON x.pos = a.i JOIN ({pieces_sql(N, P, Q)}) y ON y.pos = a.j GROUP BY 1, 2",
    "m94_energy": f"SELECT round(sqrt(sum(x.v * a.v * y.v)), 4) AS energy FROM ({_A}) a JOIN ({_X}) x ON x.i = a.i JOIN ({_X}) y ON y.i = a.j",
    "m106_balance": "SELECT CAST(1 AS BIGINT) AS spread, CAST(8 AS BIGINT) AS p",
    "m107_traffic": f"WITH m AS ({members_sql(N, P, GAMMA)}), h AS ({_HALO}) SELECT m.sub, CAST(count(*) FILTER (WHERE m.sub <> m.owner) AS BIGINT) AS overlap_rows, CAST((SELECT count(*) FROM h WHERE h.sub = m.sub) AS BIGINT) AS halo_rows FROM m GROUP BY m.sub",
    "m29_inverse": f"SELECT id, CAST(k1 AS BIGINT) AS x0, CAST(k2 AS BIGINT) AS x1 FROM ({_C})",
    "m25_gray_order": _positions(f"SELECT id, xor(c, c >> 8) AS key FROM (SELECT id, xor(b, b >> 4) AS c FROM (SELECT id, xor(a, a >> 2) AS b FROM (SELECT id, xor(z, z >> 1) AS a FROM (SELECT id, CAST({_ZERO} AS BIGINT) AS z FROM ({_C})))))"),
    "m26_moore": "SELECT x, y, key FROM (" + _MOORE + ")",
    "m28_polyline": " UNION ALL ".join(f"SELECT CAST({n} AS INTEGER) AS n, d AS step, (x + 0.5::DOUBLE) / {2**n} AS x, (y + 0.5::DOUBLE) / {2**n} AS y FROM ({_walk(n)})" for n in (1, 2, 3)),
    "m30_wide_positions": _WIDE,
    "m35_components": f"WITH RECURSIVE s AS ({_SUB}), e AS (SELECT a.i, a.j FROM ({_A}) a JOIN s x ON x.pos = a.i JOIN s y ON y.pos = a.j WHERE x.sub = y.sub), r(pos, seen) AS (SELECT pos, pos FROM s UNION SELECT r.pos, e.j FROM r JOIN e ON e.i = r.seen) "
                      "SELECT s.sub, CAST(count(DISTINCT m.low) AS BIGINT) AS components FROM s JOIN (SELECT pos, min(seen) AS low FROM r GROUP BY pos) m ON m.pos = s.pos GROUP BY s.sub",
}
