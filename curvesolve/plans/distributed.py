"""One large system solved slice by slice: blocked vectors, one exchange of overlap values per iteration.

A row holds a slice: its part of the system (``blocks.Block``, built once in a task of its own and kept),
and its vectors on the positions it has grown to. An iteration is two halves. In the first each slice
moves its vectors, solves locally and addresses its parts to the slices that need them; in the second it
adds what arrived. Besides vectors only those parts move. Between the halves the driver learns, in one
action, the scalars of all slices and the coarse residual, which has q numbers per slice.

The coarse problem is factored on the driver up to ``COARSE`` unknowns; beyond that the method is
applied to the coarse matrix, whose entries stay a frame. The state is checkpointed every few
iterations; between checkpoints lost blocks are computed again from lineage.

Faults are real here: a lost slice's rows, vectors and part of the system are dropped, and built anew
from what neighbours hold, as overlaps keep every row of the matrix and every vector entry more than once.
"""

from __future__ import annotations

import math
import pickle
from collections.abc import Callable, Iterable
from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import SolveConfig
from ..functions.grid import GridSpec, cells
from ..functions.uniform import uniform
from ..kernels import extremes
from ..operators import matrices, ordering, partition
from ..runtime import checkpoint, flat, keep, release
from . import blocks
from .banded import Factor
from .blocks import Layout, Step

#: Coarse unknowns that the driver factors itself; iterations between checkpoints of the state.
COARSE, EVERY = 20_000, 10
#: Grown positions that go through one call together at most.
TOGETHER = 65_536
ROWS = "dst int, kind int, body binary"
STATE, MESSAGE, SUMS, BLOCK = 0, 1, 2, 3


@dataclass
class Setup:
    """order (id, pos), a (i, j, v) in positions, the parts of all slices, and the coarse solver."""

    cfg: SolveConfig
    layout: Layout
    order: DataFrame
    a: DataFrame
    parts: Parts
    coarse: Callable[[np.ndarray], np.ndarray] | None
    a0: tuple[np.ndarray, np.ndarray, np.ndarray]
    counts: dict[str, int] = field(default_factory=lambda: {"matvec": 0, "axpy": 0, "coarse": 0, "local": 0})
    held: list[DataFrame] = field(default_factory=list)

    def a0_times(self, e: np.ndarray) -> np.ndarray:
        i, j, v = self.a0
        return np.bincount(i, v * e[j], minlength=len(e)) if len(e) else e


def in_order(spark: SparkSession, cfg: SolveConfig) -> DataFrame:
    """(id, pos) of the grid's cells along the configured curve."""
    spec = GridSpec(cfg.extents)
    keyed = ordering.with_key(cells(spark, spec), cfg.curve, spec.d, spec.bits)
    return checkpoint(ordering.positions(keyed, ["key"]).select("id", "pos"))


def in_positions(a: DataFrame, order: DataFrame) -> DataFrame:
    """(i, j, v) with places along the order for ids."""
    to = order.select(F.col("id").alias("i"), F.col("pos").alias("pi"))
    return a.join(to, "i").join(order.select(F.col("id").alias("j"), F.col("pos").alias("pj")), "j").select(F.col("pi").alias("i"), F.col("pj").alias("j"), "v")


def setup(spark: SparkSession, cfg: SolveConfig, matrix: DataFrame | None = None, order: DataFrame | None = None, n: int | None = None, nested: bool = False) -> Setup:
    """Order cells, deal the matrix to grown slices, build each slice's part and the coarse solver.

    ``matrix`` is (i, j, v) in lexicographic ids, symmetric in its pattern; by default the Laplace
    operator of the grid. ``order`` (id, pos) of another system comes with its size ``n``.
    """
    spec = GridSpec(cfg.extents)
    if cfg.method in ("cg", "jacobi"):
        cfg = cfg.but(kind="identity", method="pcg") if cfg.method == "cg" else cfg.but(kind="jacobi", method="richardson", xi=cfg.xi or 0.9)
    n = n or spec.size
    order = in_order(spark, cfg) if order is None else order
    a = checkpoint(in_positions(matrix if matrix is not None else matrices.laplace(spark, spec), order))
    layout = Layout.of(cfg, n)
    held = partition.members(order, n, cfg.p, cfg.gamma).select("sub", F.col("pos").alias("i"))

    def make(pdf: pd.DataFrame) -> pd.DataFrame:
        sub = int(pdf["sub"].iloc[0])
        block = blocks.build(layout, sub, *(pdf[c].to_numpy() for c in "ijv"), sweeps=cfg.inner_sweeps)
        return pd.DataFrame({"sub": [sub], "block": [pickle.dumps(block)]})

    parts = _dealt(checkpoint(held.join(a, "i").groupBy("sub").applyInPandas(make, "sub int, block binary")), layout)
    out = Setup(cfg, layout, order, a, parts, None, ((np.zeros(0, np.int64),) * 2 + (np.zeros(0),)))
    if layout.coarse_size:
        factor_coarse(out, nested)
    return out


@dataclass
class Parts:
    """Parts (bundle, sub, block) partitioned by bundles of ``per`` neighbouring slices and kept, so that halves do not move them."""

    frame: DataFrame
    per: int


def _dealt(parts: DataFrame, layout: Layout) -> Parts:
    width = int(parts.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    grown = (2 * layout.gamma + 1) * layout.n / layout.p
    per = max(1, min(int(TOGETHER // grown), -(-layout.p // (2 * width))))
    bundled = parts.select(F.floor(F.col("sub") / F.lit(per)).cast("int").alias("bundle"), "sub", "block")
    kept = keep(bundled.repartition(min(width, -(-layout.p // per)), "bundle"))
    return Parts(kept, per)


def coarse_entries(s: Setup) -> DataFrame:
    """(i, j, v) of the coarse matrix: shares of all slices, added."""
    layout = s.layout

    def run(batches: Iterable[pd.DataFrame]):
        for pdf in batches:
            for body in pdf["block"]:
                i, j, v = blocks.coarse_part(pickle.loads(body), layout)
                yield pd.DataFrame({"i": i, "j": j, "v": v})
    return s.parts.frame.mapInPandas(run, "i long, j long, v double").groupBy("i", "j").agg(F.sum("v").alias("v"))


def factor_coarse(s: Setup, nested: bool = False) -> None:
    """Factor the coarse matrix on the driver, or set the method itself up for it."""
    n0 = s.layout.coarse_size
    if n0 <= COARSE and not nested:
        got = coarse_entries(s).toPandas()  # a few entries for each of at most COARSE rows
        i, j, v = (got[c].to_numpy() for c in "ijv")
        s.a0 = (i, j, v)
        if s.cfg.kind == "kernel":
            a0 = np.zeros((n0, n0))
            a0[i, j] = v
            inverse = np.linalg.pinv(a0)
            s.coarse = lambda b: inverse @ b
        else:
            s.coarse = Factor(i, j, v, n0)
        return
    entries = checkpoint(coarse_entries(s))
    spark = entries.sparkSession
    p = max(2, min(s.cfg.p // 4, -(-n0 // 4096)) if not nested else s.cfg.p // 4)
    order = checkpoint(spark.range(n0).select("id", F.col("id").alias("pos")))
    below = setup(spark, s.cfg.but(p=p, q=min(s.cfg.q, n0 // p), kind="balanced", weight="omega", method="pcg", tol=1e-13), entries, order, n0)
    got = entries.toPandas() if n0 <= COARSE else None

    def solve(b: np.ndarray) -> np.ndarray:
        if not b.any():
            return b
        rhs = spark.createDataFrame(pd.DataFrame({"pos": np.arange(n0), "v": b}))
        found = solution(below, run(below, rhs).state).toPandas()
        x = np.zeros(n0)
        x[found["pos"].to_numpy()] = found["v"].to_numpy()
        return x

    s.coarse = solve
    if got is not None:
        s.a0 = tuple(got[c].to_numpy() for c in "ijv")
    else:
        raise ValueError("a coarse matrix beyond the driver's room: take fewer pieces")


def _half(rows: DataFrame, parts: Parts, act) -> DataFrame:
    """``act(block, state, inbox)`` of every slice, as rows; small slices go through a call together."""
    def run(mine: pd.DataFrame, part: pd.DataFrame) -> pd.DataFrame:
        held = {int(sub): body for sub, body in zip(part["sub"], part["block"])}
        states: dict[int, dict] = {}
        inbox: dict[int, list] = {}
        for dst, kind, body in zip(mine["dst"].tolist(), mine["kind"].tolist(), mine["body"]):
            if kind == STATE:
                states[dst] = pickle.loads(body)
            elif kind == MESSAGE:
                inbox.setdefault(dst, []).append(pickle.loads(body))
        out = []
        for sub in sorted(states.keys() | inbox.keys()):
            block = pickle.loads(held[sub]) if sub in held else None
            out += [(dst, kind, pickle.dumps(body)) for dst, kind, body in act(block, states.get(sub), inbox.get(sub, []))]
        return pd.DataFrame(out, columns=["dst", "kind", "body"]).astype({"dst": "int32", "kind": "int32"})

    return rows.groupBy(F.floor(F.col("dst") / F.lit(parts.per)).cast("int").alias("bundle")).cogroup(parts.frame.groupBy("bundle")).applyInPandas(run, ROWS)


def begin(s: Setup, b: DataFrame, x0: DataFrame | None = None) -> DataFrame:
    """State rows from (pos, v) frames: right-hand side, and a start other than zero."""
    rows = b.select("pos", F.col("v").alias("b"))
    if x0 is None:
        rows = rows.select("pos", "b", F.lit(0.0).alias("x"), F.col("b").alias("r"))
    else:
        ax = matrices.spmv(s.a, x0.withColumnRenamed("pos", "i")).select(F.col("i").alias("pos"), F.col("v").alias("ax"))
        rows = rows.join(x0.withColumnRenamed("v", "x"), "pos").join(ax, "pos").select("pos", "b", "x", (F.col("b") - F.col("ax")).alias("r"))
    held = partition.members(s.order, s.layout.n, s.cfg.p, s.cfg.gamma).select("sub", "pos")

    def pack(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("pos")
        zero = np.zeros(len(pdf))
        state = {c: pdf[c].to_numpy() for c in ("b", "x", "r")} | {"p": zero, "s": zero, "old": zero}
        return pd.DataFrame({"dst": [int(pdf["sub"].iloc[0])], "kind": [STATE], "body": [pickle.dumps(state)]}).astype({"dst": "int32", "kind": "int32"})

    return checkpoint(held.join(rows, "pos").groupBy("sub").applyInPandas(pack, ROWS))


def solution(s: Setup, state: DataFrame, name: str = "x") -> DataFrame:
    """(pos, v) of a vector of the state, each position from its owner."""
    layout = s.layout

    def run(batches: Iterable[pd.DataFrame]):
        for pdf in batches:
            for sub, kind, body in zip(pdf["dst"], pdf["kind"], pdf["body"]):
                if kind == STATE:
                    pos, (lo, size) = layout.grown(int(sub)), layout.bounds(int(sub))
                    own = (pos >= lo) & (pos < lo + size)
                    yield pd.DataFrame({"pos": pos[own], "v": pickle.loads(body)[name][own]})
    return state.mapInPandas(run, "pos long, v double")


def copies(s: Setup, state: DataFrame, name: str = "r") -> DataFrame:
    """(sub, pos, v): a vector as every slice holds it, for checks of the redundancy."""
    layout = s.layout

    def run(batches: Iterable[pd.DataFrame]):
        for pdf in batches:
            for sub, kind, body in zip(pdf["dst"], pdf["kind"], pdf["body"]):
                if kind == STATE:
                    yield pd.DataFrame({"sub": int(sub), "pos": layout.grown(int(sub)), "v": pickle.loads(body)[name]}).astype({"sub": "int32"})
    return state.mapInPandas(run, "sub int, pos long, v double")


def rows_held(s: Setup) -> DataFrame:
    """(sub, i, j, v): the matrix as every slice holds it."""
    def run(batches: Iterable[pd.DataFrame]):
        for pdf in batches:
            for sub, body in zip(pdf["sub"], pdf["block"]):
                i, j, v = pickle.loads(body).entries()
                yield pd.DataFrame({"sub": int(sub), "i": i, "j": j, "v": v}).astype({"sub": "int32"})
    return s.parts.frame.mapInPandas(run, "sub int, i long, j long, v double")


def _exchange(s: Setup, rows: DataFrame, step: Step) -> tuple[DataFrame, dict]:
    """Both halves of one application, in one action; the new state, and the sums over all slices."""
    def first(block, state, inbox):
        state, sent = blocks.advance(block, state, step)
        return [(block.sub, STATE, state), *[(to, MESSAGE, part) for to, part in sent]]

    def second(block, state, inbox):
        state, sums = blocks.gather(block, state, inbox)
        return [(block.sub, STATE, state), (block.sub, SUMS, sums)]

    out = keep(_half(_half(rows, s.parts, first), s.parts, second))
    s.held.append(out)
    total: dict = {"zr": np.zeros(s.layout.coarse_size), "zay": np.zeros(s.layout.coarse_size)}
    for r in out.where(F.col("kind") == SUMS).select("body").collect():  # a few numbers for each slice
        got = pickle.loads(r["body"])
        for k in ("zr", "zay"):
            np.add.at(total[k], got["index"], got[k])
        for k, v in got.items():
            if k not in ("index", "zr", "zay"):
                total[k] = total.get(k, 0.0) + float(v)
    # The action above has made the rows: those before are needed no more, and come from lineage if a machine is lost.
    release(*s.held[:-1])
    del s.held[:-1]
    return flat(out.where(F.col("kind") == STATE)), total


@dataclass
class Outcome:
    """The state, (k, residual norm) and (k, energy norm of the error) where the solution is known, operations, and whether data survived."""

    state: DataFrame
    history: list[float]
    errors: list[float]
    ok: bool = True
    alphas: list[float] = field(default_factory=list)
    betas: list[float] = field(default_factory=list)


def _order_of(cfg: SolveConfig, k: int) -> list[tuple[bool, frozenset | None]]:
    """The corrections of step k: whether the coarse one takes part, and which slices."""
    rng = np.random.default_rng([cfg.seed, cfg.run, 77, k])
    if cfg.method == "sequential":
        return [(True, frozenset())] + [(False, frozenset([i])) for i in range(cfg.p)]
    if cfg.method == "colored":
        colors = 2 * math.ceil(2 * cfg.gamma) + 1
        return [(True, frozenset())] + [(False, frozenset(range(c, cfg.p, colors))) for c in range(min(colors, cfg.p))]
    if cfg.method == "all":
        return [(True, None)]
    m = max(1, round((1 - cfg.p_fault) * cfg.p))
    chosen = rng.permutation(cfg.p + (cfg.method == "random"))[:m] - (cfg.method == "random")
    return [(cfg.method == "coarse_random" or -1 in chosen, frozenset(int(c) for c in chosen if c >= 0))]


SUBSPACE = ("sequential", "colored", "random", "coarse_random", "all")


def run(s: Setup, b: DataFrame, x0: DataFrame | None = None, steps: int | None = None, failed: Callable[[int], set[int]] | None = None,
        lost: Callable[[int], set[int]] | None = None, by_error: bool = False, xi: float | None = None, spectrum: tuple[float, float] | None = None) -> Outcome:
    """The configured iteration on (pos, v) to a relative residual of ``tol``, or by the error in energy norm (zero right-hand side).

    ``failed(k)``: slices whose local solve adds nothing in cycle k. ``lost(k)``: slices that lose all
    they hold before cycle k and are built anew; data that no slice holds any more end the run.
    ``steps`` fixes the number of steps instead of the tolerance.
    """
    cfg, kind = s.cfg, s.cfg.kind
    cw, n0 = cfg.coarse_weight, s.layout.coarse_size
    state, zero = begin(s, b, x0), np.zeros(n0)
    xi, lam = xi or cfg.xi or 1.0, spectrum or (math.nan, math.nan)
    step, zr, zs, old_zr = Step(kind), None, zero, zero
    rz_old = ps = 0.0
    history: list[float] = []
    errors: list[float] = []
    alphas: list[float] = []
    betas: list[float] = []
    alpha, calm = 0.0, cfg.method not in SUBSPACE
    todo: list[tuple[bool, frozenset | None]] = []
    limit = steps if steps is not None else cfg.maxit
    k, applied = 0, 0
    while True:
        # One application to the present residual, which the first half brings about.
        if lost is not None and (gone := lost(k)):
            state, ok = recover(s, state, gone)
            if not ok:
                return Outcome(state, history, errors, False, alphas, betas)
        use_coarse, active = True, None
        if not calm:
            if not todo:
                todo = _order_of(cfg, k)
            use_coarse, active = todo.pop(0)
        if failed is not None:
            out_now = failed(k)
            active = frozenset(range(cfg.p)) - out_now if active is None else active - out_now
        guess = zr if zr is not None else _restricted(s, state)
        step.c = cw * s.coarse(guess) if n0 and kind == "balanced" and use_coarse else zero
        step.active, step.fine, step.plain_weight = active, active is None or bool(active), cfg.method == "sequential"
        state, got = _exchange(s, state, step)
        s.counts["local"] += 1
        applied += 1
        if applied % EVERY == 0:
            state = checkpoint(state)
        zr = got["zr"]
        history_now = math.sqrt(max(0.0, got["rr"]))
        if calm or len(todo) == len(_order_of(cfg, k)) - 1:  # the residual between steps
            history.append(history_now)
            errors.append(math.sqrt(max(0.0, -got["xr"] - got["xb"])))
            measure = errors if by_error else history
            if (steps is None and measure[-1] <= cfg.tol * measure[0]) or k >= limit or not math.isfinite(history[-1]) or history[-1] > 1e8 * history[0]:
                return Outcome(state, history, errors, True, alphas, betas)
        e = zero
        if n0 and use_coarse:
            c = step.c if kind == "balanced" else cw * s.coarse(zr)
            s.counts["coarse"] += 1
            e = c
            if kind in ("deflated", "balanced"):
                e = c - cw * s.coarse(got["zay"])
                s.counts["coarse"] += 1
        a0e = s.a0_times(e)
        rz = got["ry"] + float(zr @ e)
        zaz = got["yay"] + 2 * float(got["zay"] @ e) + float(e @ a0e)
        method = cfg.method
        nxt = Step(kind, e=e)
        if not calm:
            nxt.a, nxt.t = 1.0, cfg.xi or (1.0 if method in ("sequential", "colored") else 0.5)
            if not todo:
                k += 1
        else:
            if method == "richardson":
                nxt.a, nxt.t = 1.0, (1 / lam[1] if cfg.switch and k < cfg.switch else xi)
            elif method == "steepest":
                nxt.a, nxt.t = 1.0, rz / zaz
            elif method == "two_step":
                root = math.sqrt(lam[1] / lam[0])
                nxt.a, nxt.t = 4 / (math.sqrt(lam[0]) + math.sqrt(lam[1])) ** 2, 1.0
                nxt.beta = ((root - 1) / (root + 1)) ** 2 if k else 0.0
            else:
                oz = got["oy"] + float(old_zr @ e)
                nxt.a = 1.0
                nxt.beta = 0.0 if not k else ((rz - oz) if method == "flexible" else rz) / rz_old
                ps = zaz + 2 * nxt.beta * (got["sy"] + float(zs @ e)) + nxt.beta**2 * ps
                alpha = rz / ps
                nxt.t = alpha
                alphas.append(alpha)
                betas.append(nxt.beta)
            k += 1
        zs = nxt.a * (got["zay"] + a0e) + nxt.beta * zs
        old_zr, rz_old = zr, rz
        zr = zr - nxt.t * zs
        step = nxt


def _restricted(s: Setup, state: DataFrame) -> np.ndarray:
    """Coarse residual of the first state, summed over pieces on the executors."""
    n0, layout = s.layout.coarse_size, s.layout
    if not n0:
        return np.zeros(0)

    def run(batches: Iterable[pd.DataFrame]):
        for pdf in batches:
            for sub, body in zip(pdf["dst"], pdf["body"]):
                pos, (lo, size) = layout.grown(int(sub)), layout.bounds(int(sub))
                own = (pos >= lo) & (pos < lo + size)
                i, a, v = layout.spread(pos[own])
                yield pd.DataFrame({"a": a, "v": v * pickle.loads(body)["r"][own][i]})
    got = state.mapInPandas(run, "a long, v double").groupBy("a").agg(F.sum("v").alias("v")).toPandas()
    out = np.zeros(n0)
    out[got["a"].to_numpy()] = got["v"].to_numpy()
    return out


def recover(s: Setup, state: DataFrame, gone: set[int]) -> tuple[DataFrame, bool]:
    """Drop what the slices ``gone`` hold, and build it anew from their neighbours: bounds, rows, factor, vectors.

    The donor of a position is the first slice after the lost one that still holds it. False if some
    position is held by none.
    """
    layout, sweeps, gone = s.layout, s.cfg.inner_sweeps, set(gone)
    for sub in sorted(gone):
        pos = layout.grown(sub)
        at, who = layout.holders(pos)
        if not np.isin(np.arange(len(pos)), at[~np.isin(who, list(gone))]).all():
            return state, False
    left = Parts(s.parts.frame.where(~F.col("sub").isin(list(gone))), s.parts.per)
    state = state.where(~F.col("dst").isin(list(gone)))

    def donate(block, mine, inbox):
        out: list[tuple] = [(block.sub, STATE, mine)]
        i, j, v = block.entries()
        for sub in gone:
            pos = layout.grown(sub)
            at, who = layout.holders(pos)
            alive = ~np.isin(who, list(gone))
            first = np.full(len(pos), layout.p)
            np.minimum.at(first, at[alive], (who[alive] - sub) % layout.p)
            give = pos[(first + sub) % layout.p == block.sub]
            if len(give):
                k, rows = np.searchsorted(block.pos, give), np.isin(i, give)
                out.append((sub, MESSAGE, {"sub": sub, "pos": give, "vectors": {n: x[k] for n, x in mine.items()}, "rows": (i[rows], j[rows], v[rows])}))
        return out

    def take(block, mine, inbox):
        if block is not None:
            return [(block.sub, STATE, mine)]
        pos = np.concatenate([m["pos"] for m in inbox])
        order = np.argsort(pos)
        mine = {n: np.concatenate([m["vectors"][n] for m in inbox])[order] for n in inbox[0]["vectors"]}
        sub = inbox[0]["sub"]
        made = blocks.build(layout, sub, *(np.concatenate([m["rows"][c] for m in inbox]) for c in range(3)), sweeps=sweeps)
        return [(sub, STATE, mine), (sub, BLOCK, made)]

    moved = keep(_half(_half(state, left, donate), left, take))
    fresh = moved.where(F.col("kind") == BLOCK)

    def unpack(batches: Iterable[pd.DataFrame]):
        for pdf in batches:
            yield pd.DataFrame({"sub": pdf["dst"].astype("int32"), "block": pdf["body"]})

    old = s.parts.frame
    s.parts = _dealt(checkpoint(left.frame.select("sub", "block").unionByName(fresh.mapInPandas(unpack, "sub int, block binary"))), layout)
    state = checkpoint(moved.where(F.col("kind") == STATE))
    release(old, moved)
    return state, True


def spectrum(s: Setup, steps: int = 30, seed: int = 9) -> tuple[float, float]:
    """Extreme eigenvalues of the preconditioned operator, from conjugate-gradient coefficients on a random right-hand side."""
    if s.cfg.method not in ("pcg", "cg"):
        s = replace(s, cfg=s.cfg.but(method="pcg"), held=[])
    b = s.order.select("pos", (2 * uniform(F.lit(seed), F.col("pos")) - 1).alias("v"))
    out = run(s, b, steps=min(steps, s.layout.n))
    n = next((i for i, h in enumerate(out.history) if h <= 1e-11 * out.history[0]), len(out.alphas))
    return extremes(out.alphas[:n], out.betas[1:n] + [0.0])


def solve_table(spark: SparkSession, rhs: DataFrame, cfg: SolveConfig, scale: float, **options) -> DataFrame:
    """(id, u) of a right-hand side (id, cents) divided by ``scale``."""
    s = setup(spark, cfg)
    b = checkpoint(rhs.join(s.order, "id").select("pos", (F.col("cents") / F.lit(scale)).alias("v")))
    out = run(s, b, **options)
    return solution(s, out.state).join(s.order, "pos").select("id", F.col("v").alias("u"))
