"""SQL of single steps on the line, built from closed forms: an oracle that knows nothing of factors, blocks or messages.

On the line every stretch of neighbouring positions has a tridiagonal matrix, whose inverse is known in
closed form; so has the coarse matrix of piecewise constants. Operators and iterations are chains of CTEs.
"""

from __future__ import annotations

import itertools

from ..config import SolveConfig
from .shared import SCALE, members_sql, pieces_sql, rhs_sql
from ..functions.grid import GridSpec


class Line:
    """CTEs of vectors (t, v) on positions 0..n-1; ``let`` adds one and gives its name."""

    def __init__(self, cfg: SolveConfig):
        self.cfg, self.n = cfg, cfg.extents[0]
        self.h2 = (1 / (self.n + 1)) ** 2
        self.names = itertools.count()
        self.ctes: list[tuple[str, str]] = []
        n, p, q = self.n, cfg.p, cfg.q
        self.ctes += [
            ("b", f"SELECT id AS t, cents / {SCALE!r} AS v FROM ({rhs_sql('B1', GridSpec(cfg.extents))})"),
            ("m", f"SELECT sub, pos, pos - row_number() OVER (PARTITION BY sub ORDER BY pos) AS isle FROM ({members_sql(n, p, cfg.gamma)})"),
            ("cover", "SELECT pos, count(*) AS c FROM m GROUP BY pos"),
            ("mw", f"SELECT m.*, row_number() OVER (PARTITION BY m.sub, isle ORDER BY m.pos) AS k, count(*) OVER (PARTITION BY m.sub, isle) AS len, {self._weight()} AS w FROM m JOIN cover USING (pos)"),
            ("g", f"SELECT a.sub, a.pos AS t, b.pos AS u, a.w, {self.h2!r} * least(a.k, b.k) * (a.len + 1 - greatest(a.k, b.k)) / (a.len + 1) AS v FROM mw a JOIN mw b ON a.sub = b.sub AND a.isle = b.isle"),
            ("agg", pieces_sql(n, p, q)),
        ]
        if cfg.kind == "kernel":
            self.ctes[-1] = ("agg", "SELECT m.pos, m.sub AS agg, 1.0 / c AS z FROM m JOIN cover USING (pos)")

    def _weight(self) -> str:
        return {"none": "1.0", "unity": "1.0 / c", "omega": "max(1.0 / c) OVER (PARTITION BY m.sub)"}[self.cfg.weight]

    def let(self, sql: str) -> str:
        name = f"v{next(self.names)}"
        self.ctes.append((name, sql))
        return name

    def combine(self, *terms: tuple[str, str]) -> str:
        """Sum of (coefficient, vector)."""
        return self.let("SELECT t, sum(v) AS v FROM (" + " UNION ALL ".join(f"SELECT t, {c} * v AS v FROM {x}" for c, x in terms) + ") GROUP BY t")

    def times(self, x: str) -> str:
        """A x."""
        return self.let(f"SELECT c.i AS t, sum(CASE WHEN x.t = c.i THEN 2.0 ELSE -1.0 END * x.v) / {self.h2!r} AS v FROM range({self.n}) c(i) JOIN {x} x ON abs(x.t - c.i) <= 1 GROUP BY c.i")

    def fine(self, r: str, active: set[int] | None = None, plain: bool = False) -> str:
        on = "" if active is None else f" AND g.sub IN ({', '.join(map(str, sorted(active))) or '-1'})"
        return self.let(f"SELECT c.i AS t, coalesce(f.v, 0.0) AS v FROM range({self.n}) c(i) LEFT JOIN (SELECT g.t, sum({'1.0' if plain else 'g.w'} * g.v * r.v) AS v FROM g JOIN {r} r ON r.t = g.u{on} GROUP BY g.t) f ON f.t = c.i")

    def coarse(self, r: str) -> str:
        n0 = self.cfg.p * self.cfg.q
        return self.let(f"SELECT o.pos AS t, {self.h2!r} * sum(least(o.agg, s.agg) * ({n0} - greatest(o.agg, s.agg)) / {n0 + 1}.0 * s.v + s.v * ({n0} - greatest(o.agg, s.agg)) / {n0 + 1}.0) AS v "
                        f"FROM agg o, (SELECT agg, sum(r.v) AS v FROM agg JOIN {r} r ON r.t = agg.pos GROUP BY agg) s GROUP BY o.pos")

    def apply(self, r: str, active: set[int] | None = None) -> str:
        """The configured operator on r."""
        kind, cw = self.cfg.kind, self.cfg.coarse_weight
        if kind == "identity":
            return r
        if kind == "jacobi":
            return self.let(f"SELECT t, v * {self.h2 / 2!r} AS v FROM {r}")
        if kind == "one_level":
            return self.fine(r, active)
        c = self.coarse(r)
        if kind == "additive":
            return self.combine((repr(cw), c), ("1.0", self.fine(r, active)))
        y = self.fine(r if kind == "deflated" else self.combine(("1.0", r), (repr(-cw), self.times(c))), active)
        return self.combine(("1.0", y), (repr(cw), c), (repr(-cw), self.coarse(self.times(y))))

    def dot(self, x: str, y: str) -> str:
        name = f"s{next(self.names)}"
        self.ctes.append((name, f"SELECT sum(a.v * b.v) AS v FROM {x} a JOIN {y} b USING (t)"))
        return f"(SELECT v FROM {name})"

    def select(self, x: str, digits: int = 6) -> str:
        return f"WITH {', '.join(f'{n} AS MATERIALIZED ({s})' for n, s in self.ctes)} SELECT CAST(t AS BIGINT) AS id, round(v, {digits}) + 0.0 AS u FROM {x}"


def application(cfg: SolveConfig) -> str:
    line = Line(cfg)
    return line.select(line.apply("b"))


def iterate(cfg: SolveConfig, steps: int, groups=None, failed=None, lam: tuple[float, float] | None = None) -> str:
    """The iterate after so many steps from zero. ``groups(k)``: corrections of a subspace step; ``failed(k)``: slices switched off."""
    import math

    if cfg.method in ("cg", "jacobi"):
        cfg = cfg.but(kind="identity", method="pcg") if cfg.method == "cg" else cfg.but(kind="jacobi", method="richardson", xi=cfg.xi or 0.9)
    line = Line(cfg)
    x, r = line.let("SELECT t, 0.0 AS v FROM b"), "b"
    p = z = None
    every = set(range(cfg.p))
    for k in range(steps):
        on = None if failed is None else every - failed(k)
        if groups is not None:
            t = cfg.xi or (1.0 if cfg.method in ("sequential", "colored") else 0.5)
            for use_coarse, who in groups(k):
                parts = ([(repr(cfg.coarse_weight), line.coarse(r))] if use_coarse else []) + ([("1.0", line.fine(r, None if who is None else set(who), cfg.method == "sequential"))] if who is None or who else [])
                if not parts:
                    continue
                step = line.combine(*parts)
                x, r = line.combine(("1.0", x), (repr(t), step)), line.combine(("1.0", r), (repr(-t), line.times(step)))
            continue
        old_z, z = z, line.apply(r, on)
        if cfg.method == "richardson":
            a = repr(1 / lam[1] if cfg.switch and k < cfg.switch else cfg.xi)
            p = z
        elif cfg.method == "steepest":
            p, a = z, f"({line.dot(r, z)} / {line.dot(z, line.times(z))})"
        elif cfg.method == "two_step":
            root = math.sqrt(lam[1] / lam[0])
            terms = [(repr(4 / (math.sqrt(lam[0]) + math.sqrt(lam[1])) ** 2), z)]
            p, a = line.combine(*terms, *([(repr(((root - 1) / (root + 1)) ** 2), p)] if p else [])), "1.0"
        else:
            if p is None:
                p = z
            else:
                top = line.dot(line.combine(("1.0", r), ("-1.0", old_r)), z) if cfg.method == "flexible" else line.dot(r, z)
                p = line.combine(("1.0", z), (f"({top} / {line.dot(old_r, old_z)})", p))
            a = f"({line.dot(r, p)} / {line.dot(p, line.times(p))})"
        x, old_r, r = line.combine(("1.0", x), (a, p)), r, line.combine(("1.0", r), (f"-{a}", line.times(p)))
    return line.select(x)
