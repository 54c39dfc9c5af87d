"""Parameters of the solvers, checked on the driver."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace


#: Walks up to which "auto" takes the portable generator.
PORTABLE_WALKS = 1 << 20


@dataclass(frozen=True)
class PprParams:
    """``alpha`` is the stop probability; the constants are those of the guarantee's proof.

    phase1_const  walks of the first phase: ceil(phase1_const * ln(2 n^3) / tol)
    median_const  trials of the third phase: ceil(median_const * ln(2 n^2))
    theta_const   push threshold: tol^2 * walks / (theta_const * rough score)
    mode          halving search: "resume" continues the last accepted push, "restart" begins anew
    engine        "kernel" (adjacency broadcast to the tasks), "frame" (shuffles), or "auto" by size
    rng           "portable" (31-bit, the same in SQL), "wide" (64-bit), or "auto" by the number of walks
    cost_cap      "n2", a number of operations, or None: beyond it the power method answers
    """

    alpha: float = 0.2
    seed: int = 1
    phase1_const: float = 12.0
    median_const: float = 18.0
    theta_const: float = 6.0
    mode: str = "restart"
    engine: str = "auto"
    rng: str = "auto"
    cost_cap: str | int | None = None
    force_walks: int | None = None
    force_trials: int | None = None
    force_phase1: int | None = None
    adaptive: bool = True
    skip_noop: bool = True
    max_rounds: int = 20_000
    table_every: int = 6

    def __post_init__(self) -> None:
        if not 0 < self.alpha < 1:
            raise ValueError("alpha must be inside (0, 1)")
        if self.engine not in ("auto", "kernel", "frame"):
            raise ValueError("engine must be auto, kernel or frame")
        if self.rng not in ("portable", "wide", "auto"):
            raise ValueError("rng must be portable, wide or auto")
        if self.mode not in ("restart", "resume"):
            raise ValueError("mode must be restart or resume")

    def with_(self, **changes) -> "PprParams":
        return replace(self, **changes)

    def generator(self, total: int) -> str:
        """The generator for ``total`` walks of one call: beyond ``PORTABLE_WALKS`` 31 bits would be shared by many."""
        if self.rng != "auto":
            return self.rng
        return "portable" if total <= PORTABLE_WALKS else "wide"

    def phase1_walks(self, n: int, tol: float) -> int:
        return self.force_phase1 or math.ceil(self.phase1_const * (math.log(2) + 3 * math.log(n)) / tol)

    def trials(self, n: int) -> int:
        return self.force_trials or math.ceil(self.median_const * (math.log(2) + 2 * math.log(n)))

    def rounds_for(self, tail: float) -> int:
        return math.ceil(math.log(tail) / math.log(1 - self.alpha))


def check_tol(tol: float) -> float:
    if not 0 < tol < 1:
        raise ValueError("a tolerance must be inside (0, 1)")
    return tol
