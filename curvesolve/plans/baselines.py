"""Baselines under faults, nested coarse solves, and the finite-element comparison."""

from __future__ import annotations

import numpy as np

from ..config import SolveConfig
from ..kernels import Outcome, Faults, Sparse, System, rates, recoverable, solve


def _drawn(cfg: SolveConfig) -> np.ndarray:
    """(cycles, slices): failures of all cycles a run may take."""
    faults = Faults(cfg)
    return np.array([faults[k] for k in range(cfg.maxit)])


def restart_from_snapshot(cfg: SolveConfig, every: int = 5) -> Outcome:
    """Checkpoint and restart: any failure in a cycle loses the work since the last snapshot."""
    system = System(cfg.but(p_fault=0.0))
    failed = _drawn(cfg).any(axis=1)
    x = snapshot = system.start()
    out = Outcome([system.energy(x)], x)
    done = 0
    for k in range(cfg.maxit):
        if failed[k % len(failed)]:
            x, done, out.lost = snapshot.copy(), 0, out.lost + done + 1
        else:
            x = x - cfg.xi * system.apply(system.matvec(x))
            done += 1
            if done == every:
                snapshot, done = x.copy(), 0
        out.errors.append(system.energy(x))
        if out.errors[-1] <= cfg.tol * out.errors[0]:
            break
    return out


def without_recovery(cfg: SolveConfig) -> Outcome:
    """A slice that has failed stays away for good; the others and the coarse problem go on."""
    system = System(cfg.but(p_fault=0.0))
    failed = np.logical_or.accumulate(_drawn(cfg), axis=0)
    x = system.start()
    out = Outcome([system.energy(x)], x)
    for k in range(cfg.maxit):
        x = x - cfg.xi * system.apply(system.matvec(x), ~failed[k % len(failed)])
        out.errors.append(system.energy(x))
        if out.errors[-1] <= cfg.tol * out.errors[0]:
            break
    return out


def restart_from_zero(cfg: SolveConfig) -> Outcome:
    """A failure that redundancy cannot repair begins the run anew."""
    system = System(cfg)
    ok = recoverable(_drawn(cfg), cfg.gamma)
    x = start = system.start()
    active = ~_drawn(cfg)
    out = Outcome([system.energy(x)], x)
    for k in range(cfg.maxit):
        x = start.copy() if not ok[k % len(ok)] else x - cfg.xi * system.apply(system.matvec(x), active[k % len(active)])
        out.errors.append(system.energy(x))
        if out.errors[-1] <= cfg.tol * out.errors[0]:
            break
    return out


class Nested(System):
    """The coarse problem is itself solved by the two-level method, on the coarse matrix and fewer slices."""

    def _factor_coarse(self, agg: np.ndarray, n0: int) -> None:
        key = agg[self.a.rows] * n0 + agg[self.a.cols]
        keys, back = np.unique(key, return_inverse=True)
        a0 = Sparse(keys // n0, keys % n0, np.bincount(back, self.a.vals), n0)
        p = max(2, self.cfg.p // 4)
        inner = System(SolveConfig((n0,), p, max(1, min(4, n0 // p)), 0.5, tol=1e-12, maxit=400), a0)
        self._coarse = lambda r: solve(inner, np.bincount(agg, r, minlength=n0)).x[agg]


def norm_ratio(n: int, seed: int = 3) -> tuple[float, float]:
    """Smallest and largest quotient of the finite-element and finite-difference energies of random vectors, in two dimensions scaled by h^2."""
    from ..functions.grid import GridSpec

    spec = GridSpec((n, n))
    h = spec.widths[0]
    ids = np.arange(spec.size).reshape(n, n)
    rng = np.random.default_rng(seed)
    ratios = []
    from ..kernels import laplace

    fd, order = laplace(spec, "lex", scaled=False)
    for k in range(20):
        x = rng.standard_normal(spec.size) if k < 10 else np.sin(np.pi * (k - 9) * (ids.ravel() // n + 1) * h) * np.sin(np.pi * (ids.ravel() % n + 1) * h)
        u = np.pad(x.reshape(n, n), 1)
        fe = 0.0
        for a in (-1, 0, 1):
            for b in (-1, 0, 1):
                s = [(2 / h if t == 0 else -1 / h) for t in (a, b)]
                m = [(2 * h / 3 if t == 0 else h / 6) for t in (a, b)]
                fe += (s[0] * m[1] + m[0] * s[1]) * float((u[1:-1, 1:-1] * u[1 + a:n + 1 + a, 1 + b:n + 1 + b]).sum())
        ratios.append(fe / (h * h * float(x @ (fd @ x))))
    return min(ratios), max(ratios)


def table(name: str, cfg: SolveConfig) -> dict:
    run = {"snapshot": restart_from_snapshot, "no recovery": without_recovery, "from zero": restart_from_zero, "rebuild": lambda c: solve(System(c))}[name]
    out = run(cfg)
    return {"baseline": name, "p_fault": cfg.p_fault, "k_iter": rates(out.errors, cfg.tol)["k_iter"], "lost": int(out.lost), "last": out.errors[-1] / out.errors[0]}


__all__ = ["Nested", "norm_ratio", "restart_from_snapshot", "restart_from_zero", "table", "without_recovery"]
