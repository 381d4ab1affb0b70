"""Parameters of one alignment run, checked once."""

from __future__ import annotations

from dataclasses import dataclass, replace

SECOND = 1_000_000


@dataclass(frozen=True)
class AlignParams:
    """theta in microseconds, beta in rows; weight (k1 p + b) / (k2 d + c); delta None: no model constraint."""

    theta: int = 90 * SECOND
    beta: int = 1
    k1: float = 3.0
    k2: float = 2.0
    b: float = 1.0
    c: float = 1.0
    delta: float | None = None
    tie: str = "first"
    seed: int = 0
    max_rounds: int = 5
    literal: bool = False
    expect_live_only: bool = False
    expect_mode: str = "sum"
    lam_mode: str = "value"
    cap: int = 5_000_000

    def __post_init__(self):
        if self.theta < 0 or self.beta < 0:
            raise ValueError("theta and beta must not be negative")
        if self.c <= 0 or min(self.k1, self.k2, self.b) < 0:
            raise ValueError("weights need c > 0 and k1, k2, b >= 0")
        if self.tie not in ("first", "hash", "random"):
            raise ValueError(f"unknown tie rule {self.tie!r}")
        if self.expect_mode not in ("sum", "best_disjoint"):
            raise ValueError(f"unknown expect_mode {self.expect_mode!r}")

    def with_(self, **changes) -> AlignParams:
        return replace(self, **changes)
