"""Parameter profiles: what the analysis asks for, and what fits real sizes."""

from __future__ import annotations

from dataclasses import dataclass, replace
from math import ceil, log, log2


@dataclass(frozen=True)
class Params:
    """Sizes of samples and sketches for n rows, d columns and k picks; every answer names its profile."""

    n: int
    d: int
    k: int
    eps: float
    profile: str
    cap: int
    budget: int
    buckets: int
    reps: int = 3
    slots: int = 96
    levels: int = 20
    l0_slots: int = 1024
    l0_reps: int = 3
    seed: int = 1

    def __post_init__(self):
        if self.n * self.width >= 1 << 62:
            raise ValueError(f"{self.n} rows and {self.d} columns do not fit 62 bits")
        if not 0 < self.eps < 1 or self.k < 1 or self.k > self.d or self.n < 0:
            raise ValueError(f"need 0 < eps < 1 and 1 <= k <= d, got eps={self.eps}, k={self.k}, d={self.d}")

    @property
    def width(self) -> int:
        """Entries (i, j) are coded i * width + j."""
        return 1 << max(1, (self.d + 1).bit_length())

    @property
    def wide(self) -> bool:
        """Do codes pass the hash's prime? Then they are folded, and all sums are decimals."""
        return self.n * self.width >= (1 << 31) - 1

    @staticmethod
    def delta_multiplier(n: int, d: int, eps: float) -> float:
        """(2 + ln d) times the logarithm of the number of levels to base 1 / (1 - eps), at least ln 2."""
        return (2 + log(max(d, 2))) * log(max(2.0, log(max(n, 2)) / -log(1 - eps)))

    @classmethod
    def theory(cls, n: int, d: int, k: int, eps: float) -> Params:
        inner = eps / 48 / 8
        multiplier = cls.delta_multiplier(n, d, inner)
        cap = max(1, ceil(d * log(1 / inner) / (inner * k)))
        budget = ceil(24 * d * multiplier * log(1 / inner) * log(max(d, 2)) / ((1 - inner) * inner**3))
        return cls(n, d, k, eps, "theory", min(cap, d), min(budget, max(1, n * d)), ceil(k * log(max(d, 2)) / inner**2), ceil(log(d / inner)), levels=max(1, ceil(log2(max(n, 2)))))

    @classmethod
    def practical(cls, n: int, d: int, k: int, eps: float = 0.25) -> Params:
        """Measured defaults without a guarantee."""
        cap = max(8, ceil(d * log(1 / eps) / (eps * k)))
        theory = 24 * d * cls.delta_multiplier(n, d, eps) * log(1 / eps) * log(max(d, 2)) / ((1 - eps) * eps**3)
        return cls(n, d, k, eps, "practical", cap, int(min(theory, 50 * d * k)), 4 * k * ceil(log(max(d, 2))), levels=max(1, ceil(log2(max(n, 2)))), slots=max(64, 8 * ceil(d / k)))

    @classmethod
    def explicit(cls, n: int, d: int, k: int, cap: int, budget: int, eps: float = 0.25, **more) -> Params:
        return replace(cls.practical(n, d, k, eps), profile="explicit", cap=cap, budget=budget, **more)


def moment_samples(gamma: float, p: int, delta: float) -> int:
    """Samples the moment complement needs by the analysis; far above practical sizes."""
    eps = gamma ** (1 / (p - 1)) / (16 * 2**p)
    return ceil(2 / eps**2 * log(16 / delta))
