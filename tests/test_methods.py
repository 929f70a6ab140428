"""Worked examples, invariants and reported behaviour of the methods."""

import itertools

import numpy as np
import pytest
from pyspark.sql import functions as F

from curvesolve import kernels
from curvesolve.catalog import streams
from curvesolve.catalog import workloads as w
from curvesolve.config import SolveConfig
from curvesolve.functions import curves, grid
from curvesolve.functions.uniform import hash32, py_uniform
from curvesolve.kernels import System, rates, solve
from curvesolve.operators import combine, faults, matrices, partition
from curvesolve.plans import advise, distributed, measures, spectra, theory


def iterations(cfg):
    out = solve(System(cfg))
    return rates(out.errors)["k_iter"] if out.ok else None


def test_slices_and_overlaps_by_hand(spark):
    got = partition.slices(spark, 10, 3).orderBy("sub").collect()
    assert [tuple(r) for r in got] == [(0, 0, 4), (1, 4, 3), (2, 7, 3)]
    pos = spark.range(10).select(F.col("id").alias("pos"))
    held = partition.members(pos, 10, 3, 0.5).groupBy("sub").agg(F.sort_array(F.collect_list("pos")).alias("p")).orderBy("sub").collect()
    assert [r["p"] for r in held] == [[0, 1, 2, 3, 4, 8, 9], [2, 3, 4, 5, 6, 7], [0, 1, 5, 6, 7, 8, 9]]
    quarter = {(r["sub"], r["pos"]) for r in partition.members(pos, 10, 3, 0.25).collect()}
    own = {(0, p) for p in range(4)} | {(1, p) for p in range(4, 7)} | {(2, p) for p in range(7, 10)}
    assert quarter - own == {(0, 9), (1, 3), (2, 6), (2, 0)}


@pytest.mark.parametrize("n,p,gamma", [(10, 3, 0.5), (103, 8, 0.2), (49, 4, 1.5), (100, 7, 0.75), (21, 3, 2.0)])
def test_frames_and_kernels_agree_on_overlaps(spark, n, p, gamma):
    pos = spark.range(n).select(F.col("id").alias("pos"))
    got = {(r["sub"], r["pos"]) for r in partition.members(pos, n, p, gamma).collect()}
    assert got == {(i, int(x)) for i, h in enumerate(kernels.overlap(n, p, gamma)) for x in h}
    bounds = {r["sub"]: r for r in partition.bounds(spark, n, p, gamma).collect()}
    for i in range(p):
        b = bounds[i]
        assert {(b["ov_lo"] + k) % n for k in range(b["ov_len"])} == {x for s, x in got if s == i}


def test_half_integer_overlaps_cover_evenly():
    for p in range(2, 9):
        for twice in range(1, p):
            for n in (p, 2 * p + 1, 5 * p + 3):
                if n // p < 2:
                    continue
                held = kernels.overlap(n, p, twice / 2)
                assert set(np.bincount(np.concatenate(held), minlength=n)) == {twice + 1}


def test_bad_parameters_are_refused(spark):
    for bad in ({"gamma": 0.0}, {"p": 100}, {"q": 9}, {"curve": "x"}, {"weight": "x"}, {"kind": "x"}, {"method": "x"}):
        with pytest.raises(ValueError):
            SolveConfig((20,), 4, 2).but(**bad)
    with pytest.raises(ValueError):
        grid.GridSpec.of_levels((0, 3))
    with pytest.raises(ValueError):
        partition.slices(spark, 3, 5)


@pytest.mark.parametrize("d,bits", [(2, 4), (3, 3), (4, 2), (5, 2), (6, 1)])
def test_hilbert_is_a_bijection_of_unit_steps(spark, d, bits):
    cells = np.array(list(itertools.product(range(1 << bits), repeat=d)))
    keys = curves.hilbert_array(cells, bits)
    assert sorted(keys) == list(range(len(cells)))
    walk = cells[np.argsort(keys)]
    assert (abs(np.diff(walk, axis=0)).sum(1) == 1).all()
    df = spark.createDataFrame([tuple(map(int, c)) for c in cells[:200]], ", ".join(f"k{j} int" for j in range(d)))
    got = [r[0] for r in df.select(curves.hilbert_key([F.col(f"k{j}") for j in range(d)], bits)).collect()]
    assert got == list(map(int, keys[:200]))


def test_closed_and_threefold_curves(spark, sf):
    from curvesolve.catalog.grids import m25_gray_order, m26_moore, m27_peano

    moore = sorted(m26_moore(spark, sf).collect(), key=lambda r: r["key"])
    steps = [abs(a["x"] - b["x"]) + abs(a["y"] - b["y"]) for a, b in zip(moore, moore[1:] + moore[:1])]
    assert [r["key"] for r in moore] == list(range(256)) and set(steps) == {1}
    peano = sorted(m27_peano(spark, sf).collect(), key=lambda r: r["key"])
    assert [r["key"] for r in peano] == list(range(81))
    assert {abs(a["x"] - b["x"]) + abs(a["y"] - b["y"]) for a, b in zip(peano, peano[1:])} == {1}
    assert sorted(r["pos"] for r in m25_gray_order(spark, sf).collect()) == list(range(105))


def test_wide_keys_keep_the_order(spark):
    rng = np.random.default_rng(0)
    pts = rng.integers(0, 64, (50, 12))
    df = spark.createDataFrame([tuple(map(int, p)) for p in pts], ", ".join(f"k{j} int" for j in range(12)))
    got = [bytes(r[0]) for r in df.select(curves.lebesgue_key([F.col(f"k{j}") for j in range(12)], 6)).collect()]
    exact = [sum(((int(p[j]) >> b) & 1) << (b * 12 + 11 - j) for b in range(6) for j in range(12)) for p in pts]
    assert np.argsort(exact).tolist() == sorted(range(50), key=got.__getitem__)


def test_uniforms_agree(spark):
    assert spark.range(1).select(hash32(7, 1, 3)).first()[0] == 4151147957
    assert py_uniform(7, 1, 3) == 4151147957 / 2**32


def test_needle_equals_reaction(spark):
    a = {(r["i"], r["j"]): r["v"] for r in matrices.laplace(spark, grid.needle(3, 4)).collect()}
    b = {(r["i"], r["j"]): r["v"] for r in matrices.reaction(spark, 4, 16.0).collect()}
    assert a == b


def test_coarse_matrix_of_the_line_is_tridiagonal(spark):
    spec = grid.GridSpec((30,))
    a = matrices.laplace(spark, spec).withColumn("v", F.col("v") * spec.widths[0] ** 2)
    got = partition.coarse_matrix(a, partition.agg_id(F.col("i"), 30, 5, 2), partition.agg_id(F.col("j"), 30, 5, 2)).collect()
    m = np.zeros((10, 10))
    for r in got:
        m[r["i"], r["j"]] = r["v"]
    assert np.allclose(m, 2 * np.eye(10) - np.eye(10, k=1) - np.eye(10, k=-1))


def test_positions_do_not_gather_all_rows(spark):
    from curvesolve.operators.ordering import positions

    df = spark.range(1000).select(((F.col("id") * 7919) % 1000).alias("key"))
    out = positions(df, ["key"])
    assert out.where("key <> pos").count() == 0
    plan = out._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan


@pytest.mark.parametrize("kind", ["one_level", "additive", "deflated", "balanced"])
def test_counts_of_an_application(kind):
    s = System(SolveConfig((64,), 4, 2, kind=kind))
    s.apply(np.ones(64))
    assert s.counts == measures.apply_cost(kind)


def test_projection_identities():
    s = System(SolveConfig((96,), 6, 2))
    r = np.random.default_rng(1).standard_normal(96)
    f = s.coarse(r)
    assert abs(s.coarse(r - s.a @ f)).max() < 1e-9
    assert System(SolveConfig((96,), 6, 2, weight="omega", gamma=0.3)).symmetry_gap() < 1e-10
    assert System(SolveConfig((96,), 6, 2, weight="unity", gamma=0.3)).symmetry_gap() > 1e-6


def test_three_spectra_agree(spark, sf):
    for r in spectra.table(spark, sf).collect():
        assert r["lanczos_max"] == pytest.approx(r["dense_max"], rel=0.02)
        assert r["lanczos_min"] == pytest.approx(r["dense_min"], rel=0.02)
        assert r["krylov_max"] == pytest.approx(r["dense_max"], rel=0.05)


def test_reported_iteration_counts():
    """Reported counts within 15 % at reported sizes: 64 slices of 2^10 points, 100 slices of 2^8."""
    pcg, rich = (iterations(w.weak(64, s=10, q=64, method=m)) for m in ("pcg", "richardson"))
    assert 0.85 * 145 <= rich <= 1.15 * 145 and pcg <= 29
    plain, plain_rich = (iterations(w.weak(64, s=8, kind="additive", method=m)) for m in ("pcg", "richardson"))
    bal, bal_rich = (iterations(w.weak(64, s=8, method=m)) for m in ("pcg", "richardson"))
    assert 4.5 <= plain_rich / bal_rich <= 7 and 1.6 <= plain / bal <= 2.2
    for p, k in ((0.0, 25), (0.02, 31), (0.05, 37), (0.1, 54)):
        got = [iterations(w.weak(100, gamma=2.0, p_fault=p, run=r)) for r in range(5)]
        assert abs(np.mean([g for g in got if g]) - k) <= 0.15 * k


def test_faults_go_on_beyond_any_number_of_cycles():
    faults = kernels.Faults(SolveConfig((64,), 8, 2, p_fault=0.3))
    late = np.array([faults[k] for k in range(900)])
    assert not np.array_equal(late[:400], late[400:800]) and abs(late[500:].mean() - 0.3) < 0.05


def test_operators_rank_as_reported():
    k = {kind: iterations(w.weak(32, s=6, q=4, kind=kind, maxit=4000)) for kind in ("one_level", "kernel", "additive", "deflated", "balanced")}
    assert k["balanced"] <= k["additive"] < k["kernel"]
    assert abs(k["deflated"] - k["balanced"]) <= 0.25 * k["balanced"]


def test_overlap_and_faults_move_counts_as_reported():
    by_gamma = [iterations(w.weak(32, s=6, q=4, gamma=g)) for g in (0.5, 1.0, 2.0)]
    assert by_gamma == sorted(by_gamma, reverse=True)
    by_rate = [iterations(w.weak(32, s=6, q=4, gamma=2.0, p_fault=p, seed=4)) for p in (0.0, 0.02, 0.1)]
    assert by_rate == sorted(by_rate)
    flexible = iterations(w.weak(32, s=6, q=4, gamma=2.0, p_fault=0.1, seed=4, method="flexible"))
    assert flexible <= by_rate[-1]
    assert solve(System(w.weak(32, s=6, q=4, gamma=0.5, p_fault=0.3))).ok is False


def test_rate_of_the_damped_iteration_is_the_spectral_one():
    out = solve(System(w.weak(16, s=6, q=4, method="richardson")))
    r = rates(out.errors)
    assert r["rho_asy"] == pytest.approx(theory.best_rate(out.lam[1] / out.lam[0]), abs=0.02)


def test_higher_dimension_needs_fewer_iterations():
    k = [iterations(c) for c in w.w14_dimension(p=16, s=6) if c.method == "pcg" and len(c.extents) in (1, 3, 6)]
    assert k[0] >= k[1] >= k[2] - 2


def test_random_subsets_stay_below_the_bound():
    cfg = SolveConfig((128,), 8, 2, kind="additive", weight="omega", method="random", maxit=40)
    s = System(cfg.but(method="pcg"))
    lam = kernels.lanczos(s)
    m, kappa = 6, lam[1] / lam[0]
    errs = np.mean([np.array((o := solve(System(cfg.but(xi=1 / lam[1], p_fault=0.25, run=r)))).errors[:41]) ** 2 / o.errors[0] ** 2 for r in range(12)], 0)
    bound = (1 - m / (kappa * 9)) ** np.arange(len(errs))
    assert (errs <= bound * 1.1).all()


def test_recoverability_rules_agree(spark):
    for p in (5, 6):
        for twice in range(1, p - 1):
            held = kernels.overlap(4 * p, p, twice / 2)
            for bits in range(1 << p):
                failed = np.array([[bool(bits >> i & 1) for i in range(p)]])
                alive = np.zeros(4 * p, bool)
                for i in range(p):
                    if not failed[0, i]:
                        alive[held[i]] = True
                assert bool(kernels.recoverable(failed, twice / 2)[0]) == bool(alive.all())


def test_rebuilt_slices_equal_what_was_lost(spark):
    pos = spark.range(40).select(F.col("id").alias("pos"))
    held = partition.members(pos, 40, 5, 1.0)
    state = held.select("sub", "pos", (F.col("pos") * 1.5).alias("v"))
    failed = spark.createDataFrame([(0, 1), (0, 2), (1, 4)], "cycle int, sub int")
    back = faults.rebuild(state, faults.donors(held, failed, 5))
    lost = failed.join(state, "sub").select("cycle", "sub", "pos", "v")
    assert back.exceptAll(lost).count() == 0 and lost.exceptAll(back).count() == 0


def test_combination_counts():
    assert [combine.total_subdomains(d, 20, 1) for d in range(1, 7)] == [1, 59, 1391, 20889, 237706, 2233216]
    assert [combine.count(2, 3, i) for i in range(2)] == [3, 2]


@pytest.mark.parametrize("cfg", [
    SolveConfig((63,), 6, 3), SolveConfig((63,), 6, 3, 0.3, weight="unity", method="flexible"), SolveConfig((63,), 6, 3, 0.25, kind="kernel", weight="unity", method="richardson", xi=0.5),
    SolveConfig((7, 7), 5, 3, inner_sweeps=30, method="flexible"), SolveConfig((5, 4, 3), 4, 3, 1.0, kind="deflated", method="steepest")])
def test_distributed_iterates_equal_the_kernels(spark, cfg):
    spec = grid.GridSpec(cfg.extents)
    b = np.random.default_rng(0).standard_normal(spec.size)
    s = distributed.setup(spark, cfg)
    rhs = spark.createDataFrame([(i, float(v)) for i, v in enumerate(b)], "id long, v double").join(s.order, "id").select("pos", "v")
    got = distributed.solution(s, distributed.run(s, rhs, steps=3).state).toPandas().sort_values("pos")["v"].to_numpy()
    k = System(cfg)
    exact = solve(System(cfg.but(maxit=3, tol=1e-300)), b[k.order] / spec.diagonal).x
    assert abs(got - exact).max() <= 1e-9 * abs(exact).max()


def test_lost_slices_are_rebuilt_from_neighbours(spark):
    cfg = SolveConfig((63,), 8, 3, 1.0, tol=1e-10)
    b = np.random.default_rng(1).standard_normal(63)

    def rhs(s):
        return spark.createDataFrame([(i, float(v)) for i, v in enumerate(b)], "id long, v double").join(s.order, "id").select("pos", "v")

    def values(s, out):
        return distributed.solution(s, out.state).toPandas().sort_values("pos")["v"].to_numpy()

    s = distributed.setup(spark, cfg)
    before, entries = distributed.rows_held(s).toPandas(), distributed.coarse_entries(s).toPandas()
    sound = distributed.run(s, rhs(s))
    x = values(s, sound)
    hurt = distributed.run(s, rhs(s), lost=lambda k: {3: {2, 5}, 5: {0, 1}}.get(k, set()))
    assert np.array_equal(x, values(s, hurt)) and len(hurt.history) == len(sound.history)
    order = ["sub", "i", "j"]
    assert before.sort_values(order).reset_index(drop=True).equals(distributed.rows_held(s).toPandas().sort_values(order).reset_index(drop=True))
    assert np.allclose(np.sort(entries["v"]), np.sort(distributed.coarse_entries(s).toPandas()["v"]))
    assert distributed.run(s, rhs(s), lost=lambda k: {2: {2, 3, 4}}.get(k, set())).ok is False


def test_nested_coarse_solve(spark):
    cfg = SolveConfig((32,), 8, 2, 0.5)
    b = spark.range(32).select(F.col("id").alias("pos"), (F.col("id") % 5).cast("double").alias("v"))
    direct, nested = (distributed.run(s, b, steps=1) for s in (distributed.setup(spark, cfg), distributed.setup(spark, cfg, nested=True)))
    assert np.allclose(direct.history, nested.history, rtol=1e-6)


def test_error_stop_and_spectrum(spark):
    cfg = SolveConfig((64,), 8, 2, 0.5, tol=1e-4)
    s = distributed.setup(spark, cfg)
    start = s.order.select("pos", F.sin(F.col("pos") * 1.7).alias("v"))
    out = distributed.run(s, s.order.select("pos", F.lit(0.0).alias("v")), x0=start, by_error=True)
    assert out.errors[-1] <= 1e-4 * out.errors[0] and out.errors[-2] > 1e-4 * out.errors[0]
    lam, exact = distributed.spectrum(s, 14), spectra.dense(System(cfg))
    assert lam[0] == pytest.approx(exact[0], rel=0.1) and lam[1] == pytest.approx(exact[1], rel=0.1)


def test_an_iteration_exchanges_vectors_once_between_halves(spark):
    """Two exchanges of state and parts in an application, none of the matrix, and no join."""
    s = distributed.setup(spark, SolveConfig((200,), 16, 3))
    state = distributed.begin(s, s.order.select("pos", F.lit(1.0).alias("v")))
    half = lambda block, mine, inbox: [(block.sub, distributed.STATE, mine)]
    plan = distributed._half(distributed._half(state, s.parts, half), s.parts, half)._jdf.queryExecution().executedPlan().toString()
    outside = plan.split("Initial Plan")[-1].split("InMemoryRelation")[0] + "".join(p.split("InMemoryRelation")[0] for p in plan.split("FlatMapCoGroups")[1:])
    assert "Join" not in outside and plan.count("FlatMapCoGroupsInPandas") >= 2


def test_sort_is_one_range_exchange(spark):
    from curvesolve.operators import ordering

    out = ordering.positions(spark.range(1000).withColumn("key", F.col("id") * 7 % 1009), ["key"])
    plan = out._jdf.queryExecution().executedPlan().toString()
    assert plan.count("CartesianProduct") == 0 and "BroadcastNestedLoop" not in plan and "SinglePartition" not in plan.split("BroadcastExchange")[0]


def test_advice():
    assert [advise.gamma(p) for p in (0.01, 0.05, 0.1)] == [0.5, 1.0, 2.0]
    assert advise.method(0.2, 6)[2] == "richardson" and advise.q(2**14, 64, 6) < advise.q(2**14, 64, 1)


def test_sources_round_trip(spark, sf, tmp_path):
    from curvesolve.sources import tables

    df = tables.table(spark, sf, "nation")
    for fmt in ("parquet", "orc", "json", "csv"):
        tables.write(df, f"{tmp_path}/{fmt}", fmt)
        back = tables.read(spark, f"{tmp_path}/{fmt}", fmt, tables.SCHEMAS["nation"] if fmt in ("json", "csv") else None)
        assert back.select(*df.columns).exceptAll(df).count() == 0
    with pytest.raises(ValueError):
        tables.read(spark, f"{tmp_path}/csv", "csv")


def test_box_pushes_ranges(spark):
    ranges = curves.box_ranges((0, 0), (7, 7), 4, 8)
    assert ranges == [(0, 63)]
    assert len(curves.box_ranges((1, 1), (6, 9), 4, 5)) <= 5


def test_scan_is_pruned(spark, sf):
    from curvesolve.catalog.surface import x_scan_pushdown

    plan = x_scan_pushdown(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [" in plan and "l_comment" not in plan and "l_extendedprice" not in plan


def test_slice_states_take_a_trigger_in_time_order(spark, sf, tmp_path):
    """One slice's rows come in batches of a few rows, and the files hold them against the order of time."""
    events = spark.read.parquet(f"{sf}/events.parquet")
    events.orderBy(F.desc("ts")).coalesce(1).write.parquet(str(tmp_path / "events.parquet"))
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, "16")
    try:
        got = {tuple(r) for r in streams.s06_states(spark, str(tmp_path)).collect()}
    finally:
        spark.conf.set(name, before)
    assert got == {tuple(r) for r in streams.s06_states_batch(spark, sf).collect()}
