"""Choice of parameters."""

from __future__ import annotations

import math

from ..config import SolveConfig
from ..kernels import System, rates, solve


def gamma(p_fault: float) -> float:
    """Overlap for a share of failing solves: multiples of a half."""
    return next(g for limit, g in ((0.02, 0.5), (0.05, 1.0), (0.1, 2.0), (1.0, 3.0)) if p_fault <= limit)


def q(n: int, p: int, d: int) -> int:
    """Coarse pieces per slice in proportion to the slice, fewer in high dimension."""
    return max(1, n // p // (16 if d <= 3 else 32))


def method(p_fault: float, d: int) -> tuple[str, str, str]:
    """(operator, weight, iteration)."""
    return "balanced", "omega", "richardson" if p_fault >= 0.1 and d >= 6 else "pcg" if p_fault == 0 else "flexible"


def iteration_cap(cfg: SolveConfig) -> int | None:
    """Iterations of the one-dimensional system with as many points, slices and pieces: no system of more dimensions takes more."""
    n = math.prod(cfg.extents)
    return rates(solve(System(cfg.but(extents=(n,)))).errors, cfg.tol)["k_iter"]
