"""Parameters of a solve."""

from __future__ import annotations

from dataclasses import asdict, dataclass, replace

CURVES = ("hilbert", "lebesgue", "gray", "lex", "snake", "moore", "peano")
WEIGHTS = ("none", "omega", "unity")
KINDS = ("one_level", "additive", "deflated", "balanced", "kernel", "identity", "jacobi")
METHODS = ("richardson", "pcg", "flexible", "steepest", "two_step", "cg", "jacobi", "direct", "sequential", "colored", "random", "coarse_random", "all")


@dataclass(frozen=True)
class SolveConfig:
    """``extents``: interior points per axis; ``p`` slices, ``q`` coarse pieces per slice, ``gamma`` overlap in slices."""

    extents: tuple[int, ...]
    p: int
    q: int = 1
    gamma: float = 0.5
    curve: str = "hilbert"
    weight: str = "omega"
    kind: str = "balanced"
    method: str = "pcg"
    xi: float = 0.0
    coarse_weight: float = 1.0
    tol: float = 1e-8
    maxit: int = 2000
    p_fault: float = 0.0
    seed: int = 1
    run: int = 0
    spectrum: bool = False
    inner_sweeps: int = 0
    switch: int = 0

    def __post_init__(self) -> None:
        n = 1
        for e in self.extents:
            n *= e
        if self.gamma <= 0:
            raise ValueError("the overlap must be positive")
        if not 1 <= self.p <= n:
            raise ValueError("there must be between one and N slices")
        if not 1 <= self.q <= n // self.p:
            raise ValueError("a slice has room for at most floor(N / P) coarse pieces")
        for value, known, what in ((self.curve, CURVES, "curve"), (self.weight, WEIGHTS, "weight"), (self.kind, KINDS, "operator"), (self.method, METHODS, "method")):
            if value not in known:
                raise ValueError(f"unknown {what} {value!r}")

    def but(self, **changes) -> SolveConfig:
        return replace(self, **changes)

    def row(self) -> dict:
        return asdict(self) | {"extents": list(self.extents)}

    @property
    def symmetric(self) -> bool:
        """Whether the preconditioner is symmetric, as plain conjugate gradients assume."""
        return self.weight != "unity" or (2 * self.gamma) == int(2 * self.gamma) and 2 * self.gamma <= self.p - 1
