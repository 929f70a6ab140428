"""What one slice holds and does: its part of the system, and the two halves of an iteration.

A slice keeps everything on its grown positions, so that neighbours hold copies of each other's rows and
vectors. A half takes the slice's part, its vectors and what others sent, and returns new vectors, what
to send, and sums over the positions it owns.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from ..config import SolveConfig
from ..kernels import overlap, slice_bounds
from .banded import Factor


@dataclass
class Layout:
    """Slices, overlaps, pieces and weights of N positions in closed form; nothing here grows with N."""

    n: int
    p: int
    q: int
    gamma: float
    weight: str
    kind: str

    @classmethod
    def of(cls, cfg: SolveConfig, n: int) -> Layout:
        return cls(n, cfg.p, cfg.q, cfg.gamma, cfg.weight, cfg.kind)

    @property
    def coarse_size(self) -> int:
        return {"one_level": 0, "identity": 0, "jacobi": 0, "kernel": self.p}.get(self.kind, self.p * self.q)

    def bounds(self, sub: int) -> tuple[int, int]:
        w, r = self.n // self.p, self.n % self.p
        return sub * w + min(sub, r), w + (sub < r)

    def owner(self, pos: np.ndarray) -> np.ndarray:
        w, r = self.n // self.p, self.n % self.p
        edge = r * (w + 1)
        return np.where(pos < edge, pos // (w + 1), r + (pos - edge) // max(1, w))

    def grown(self, sub: int) -> np.ndarray:
        """Sorted positions of a grown slice."""
        whole, milli = int(self.gamma), round((self.gamma - int(self.gamma)) * 1000)
        if 2 * (whole + 1) + 1 > self.p:
            return overlap(self.n, self.p, self.gamma)[sub]
        parts = []
        for k in range(sub - whole, sub + whole + 1):
            lo, size = self.bounds(k % self.p)
            parts.append(np.arange(lo, lo + size))
        if milli:
            lo, size = self.bounds((sub - whole - 1) % self.p)
            parts.append(np.arange(lo + size - -(-milli * size // 1000), lo + size))
            lo, size = self.bounds((sub + whole + 1) % self.p)
            parts.append(np.arange(lo, lo + milli * size // 1000))
        return np.unique(np.concatenate(parts))

    def holders(self, pos: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(index into pos, slice) pairs: every grown slice that holds a position, once."""
        whole, milli = int(self.gamma), round((self.gamma - int(self.gamma)) * 1000)
        own = self.owner(pos)
        w, r = self.n // self.p, self.n % self.p
        size = w + (own < r)
        rank = pos - (own * w + np.minimum(own, r))
        at, every = np.arange(len(pos)), []
        for k in range(-whole, whole + 1):
            every.append((at, (own + k) % self.p))
        if milli:
            tail, head = rank >= size - -(-milli * size // 1000), rank < milli * size // 1000
            every += [(at[tail], (own[tail] + whole + 1) % self.p), (at[head], (own[head] - whole - 1) % self.p)]
        pairs = np.unique(np.concatenate([a * self.p + s for a, s in every]))
        return pairs // self.p, pairs % self.p

    def spread(self, pos: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Entries (index into pos, coarse unknown, value) of the map from coarse unknowns to positions."""
        if not self.coarse_size:
            return (np.zeros(0, np.int64),) * 2 + (np.zeros(0),)
        if self.kind == "kernel":
            at, sub = self.holders(pos)
            return at, sub, (1.0 / np.bincount(at, minlength=len(pos)))[at]
        own = self.owner(pos)
        w, r = self.n // self.p, self.n % self.p
        size, rank = w + (own < r), pos - (own * w + np.minimum(own, r))
        a, b = size // self.q, size % self.q
        edge = b * (a + 1)
        piece = np.where(rank < edge, rank // (a + 1), b + (rank - edge) // np.maximum(a, 1))
        return np.arange(len(pos)), own * self.q + piece, np.ones(len(pos))


@dataclass
class Block:
    """A slice's rows of the matrix on its grown positions, local factor, coarse couplings and addressees."""

    sub: int
    pos: np.ndarray
    own: np.ndarray
    w: np.ndarray
    cols: np.ndarray
    at: np.ndarray
    rows: np.ndarray
    col: np.ndarray
    vals: np.ndarray
    z: tuple[np.ndarray, np.ndarray, np.ndarray]
    az: tuple[np.ndarray, np.ndarray, np.ndarray]
    send: list[tuple[int, np.ndarray]]
    solve: Factor | None
    diagonal: np.ndarray = field(default_factory=lambda: np.zeros(0))

    def times(self, y: np.ndarray) -> np.ndarray:
        """A y on the grown positions; y on all columns of their rows."""
        return np.bincount(self.rows, self.vals * y[self.col], minlength=len(self.pos))

    def lift(self, e: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Coarse values on the grown positions, and A times them."""
        m = len(self.pos)
        if not len(e):
            return np.zeros(m), np.zeros(m)
        (i, a, v), (k, b, u) = self.z, self.az
        return np.bincount(i, v * e[a], minlength=m), np.bincount(k, u * e[b], minlength=m)

    def entries(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        return self.pos[self.rows], self.cols[self.col], self.vals


def build(layout: Layout, sub: int, i: np.ndarray, j: np.ndarray, v: np.ndarray, sweeps: int = 0) -> Block:
    """The block of a slice from the entries of the rows it holds."""
    pos = layout.grown(sub)
    order = np.lexsort((j, i))
    i, j, v = i[order], j[order], v[order]
    rows, cols = np.searchsorted(pos, i), np.unique(np.concatenate([pos, j]))
    col, at = np.searchsorted(cols, j), np.searchsorted(cols, pos)
    lo, size = layout.bounds(sub)
    own = (pos >= lo) & (pos < lo + size)
    k, _ = layout.holders(pos)
    cover = np.bincount(k, minlength=len(pos))
    w = np.ones(len(pos)) if layout.weight == "none" else 1.0 / cover
    if layout.weight == "omega":
        w = np.full(len(pos), w.max())
    # Coarse values reach a row's columns; A times them on the grown rows.
    zi, za, zv = layout.spread(cols)
    n0 = max(1, layout.coarse_size)
    first, count = np.searchsorted(zi, col), np.searchsorted(zi, col, "right") - np.searchsorted(zi, col)
    e = np.repeat(np.arange(len(col)), count)
    t = np.repeat(first, count) + (np.arange(len(e)) - np.repeat(np.cumsum(count) - count, count))
    key, back = np.unique(rows[e] * n0 + za[t], return_inverse=True) if len(e) else (np.zeros(0, np.int64), np.zeros(0, np.int64))
    val = np.bincount(back, v[e] * zv[t], minlength=len(key)) if len(e) else np.zeros(0)
    full = np.zeros(len(cols), bool)
    full[at] = True
    place = np.full(len(cols), -1)
    place[at] = np.arange(len(pos))
    on = full[zi]
    # Whoever holds a row that touches a position needs what this slice adds there.
    jk, jsub = layout.holders(cols)
    jf, jn = np.searchsorted(jk, col), np.searchsorted(jk, col, "right") - np.searchsorted(jk, col)
    e2 = np.repeat(np.arange(len(col)), jn)
    t2 = np.repeat(jf, jn) + (np.arange(len(e2)) - np.repeat(np.cumsum(jn) - jn, jn))
    pairs = np.unique(jsub[t2] * len(pos) + rows[e2])
    to, who = pairs // len(pos), pairs % len(pos)
    edge = np.searchsorted(to, np.unique(to))
    send = [(int(to[a]), who[a:b]) for a, b in zip(edge, np.r_[edge[1:], len(to)])]
    inner = place[col] >= 0
    r, c, u = rows[inner], place[col[inner]], v[inner]
    diagonal = np.ones(len(pos))
    diagonal[r[r == c]] = u[r == c]
    solver = None
    if layout.kind not in ("identity", "jacobi"):
        solver = Sweeps(r, c, u, diagonal, sweeps) if sweeps else Factor(r, c, u, len(pos))
    return Block(sub, pos, own, w, cols, at, rows, col, v, (place[zi[on]], za[on], zv[on]), (key // n0, key % n0, val), send, solver, diagonal)


@dataclass
class Sweeps:
    """Inexact local solver: a fixed number of damped Jacobi sweeps, symmetric and linear."""

    rows: np.ndarray
    cols: np.ndarray
    vals: np.ndarray
    diagonal: np.ndarray
    sweeps: int

    def __call__(self, b: np.ndarray) -> np.ndarray:
        x = np.zeros_like(b)
        for _ in range(self.sweeps):
            x = x + 0.6 * (b - np.bincount(self.rows, self.vals * x[self.cols], minlength=len(b))) / self.diagonal
        return x


@dataclass
class Step:
    """What the driver tells all slices for one half: coefficients, coarse values, and who takes part."""

    kind: str
    a: float = 0.0
    beta: float = 0.0
    t: float = 0.0
    e: np.ndarray = field(default_factory=lambda: np.zeros(0))
    c: np.ndarray = field(default_factory=lambda: np.zeros(0))
    active: frozenset | None = None
    fine: bool = True
    plain_weight: bool = False


def advance(block: Block, state: dict, step: Step) -> tuple[dict, list[tuple[int, tuple[np.ndarray, np.ndarray]]]]:
    """Move along the direction that the last answer gives, then solve locally and address the parts.

    The answer is z = y + lifted e; the direction p = a z + beta p; x moves by t p, r by -t A p.
    """
    r = state["r"]
    if "y" in state:
        lifted, a_lifted = block.lift(step.e)
        state["p"] = step.a * (state["y"] + lifted) + step.beta * state["p"]
        state["s"] = step.a * (state["ay"] + a_lifted) + step.beta * state["s"]
        state["old"] = r
        state["x"] = state["x"] + step.t * state["p"]
        r = state["r"] = r - step.t * state["s"]
    if not step.fine or (step.active is not None and block.sub not in step.active):
        return state, []
    if step.kind in ("identity", "jacobi"):
        part = np.where(block.own, r / (block.diagonal if step.kind == "jacobi" else 1.0), 0.0)
    else:
        if step.kind == "balanced":
            r = r - block.lift(step.c)[1]
        part = block.solve(r) * (1.0 if step.plain_weight else block.w)
    return state, [(to, (block.pos[who], part[who])) for to, who in block.send]


def gather(block: Block, state: dict, inbox: list[tuple[np.ndarray, np.ndarray]]) -> tuple[dict, dict]:
    """Add the parts, and give the sums over owned positions that the driver needs."""
    y = np.zeros(len(block.cols))
    for pos, v in inbox:
        k = np.minimum(np.searchsorted(block.cols, pos), len(block.cols) - 1)
        hit = block.cols[k] == pos
        y[k[hit]] += v[hit]
    state["ay"], state["y"] = block.times(y), y[block.at]
    own = block.own
    r, x, b, yo, ay = (state[n][own] for n in ("r", "x", "b", "y", "ay"))
    sums = {"rr": r @ r, "ry": r @ yo, "yay": yo @ ay, "xr": x @ r, "xb": x @ b, "bb": b @ b,
            "oy": state["old"][own] @ yo, "sy": state["s"][own] @ yo, "py": state["p"][own] @ yo}
    i, a, v = block.z
    k, c, u = block.az
    mine, mine2 = own[i], own[k]
    index, back = np.unique(np.r_[a[mine], c[mine2]], return_inverse=True)
    zr = np.bincount(back[:mine.sum()], v[mine] * state["r"][i[mine]], minlength=len(index))
    zay = np.bincount(back[mine.sum():], u[mine2] * state["y"][k[mine2]], minlength=len(index))
    return state, sums | {"index": index, "zr": zr, "zay": zay}


def coarse_part(block: Block, layout: Layout) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The slice's share of the coarse matrix, over the rows it owns, as entries."""
    i, a, v = block.z
    k, c, u = block.az
    first, n = np.searchsorted(k, i), np.searchsorted(k, i, "right") - np.searchsorted(k, i)
    n = np.where(block.own[i], n, 0)
    e = np.repeat(np.arange(len(i)), n)
    t = np.repeat(first, n) + (np.arange(len(e)) - np.repeat(np.cumsum(n) - n, n))
    key, back = np.unique(a[e] * max(1, layout.coarse_size) + c[t], return_inverse=True)
    return key // max(1, layout.coarse_size), key % max(1, layout.coarse_size), np.bincount(back, v[e] * u[t], minlength=len(key))
