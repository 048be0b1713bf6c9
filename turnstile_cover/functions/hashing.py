"""Seeded hash families as column expressions that stay inside whole-stage codegen.

``poly4`` is a cubic polynomial modulo a Mersenne prime (four-wise independent); other engines
can evaluate it bit for bit. Ids must be non-negative and below the prime; wider ids (below 2**62) are
folded first: low part plus a random multiple of the high part, modulo the prime.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, functions as F

PRIME = (1 << 31) - 1


@dataclass(frozen=True)
class Seed:
    """Four coefficients of a cubic polynomial, drawn from a seed and a role."""

    coefficients: tuple[int, int, int, int]

    @classmethod
    def of(cls, seed: int, role: int = 0) -> Seed:
        state, out = (seed * 1_000_003 + role) & (2**64 - 1), []
        for _ in range(4):
            state = (state + 0x9E3779B97F4A7C15) & (2**64 - 1)
            z = (state ^ (state >> 30)) * 0xBF58476D1CE4E5B9 & (2**64 - 1)
            z = (z ^ (z >> 27)) * 0x94D049BB133111EB & (2**64 - 1)
            out.append(1 + (z ^ (z >> 31)) % (PRIME - 1))
        return cls(tuple(out))

    @property
    def multiple(self) -> int:
        return 1 + (self.coefficients[0] * 48_271 + self.coefficients[1]) % (PRIME - 1)

    def sql(self, x: str, wide: bool = False) -> str:
        """The same polynomial as SQL text."""
        a, b, c, d = self.coefficients
        x = f"((({x}) % {PRIME} + ({x}) // {PRIME} * {self.multiple}) % {PRIME})" if wide else x
        return f"(((((({a} * ({x}) + {b}) % {PRIME}) * ({x}) + {c}) % {PRIME}) * ({x}) + {d}) % {PRIME})"

    def value(self, x: int, wide: bool = False) -> int:
        h = 0
        x = (x % PRIME + x // PRIME * self.multiple) % PRIME if wide else x
        for k in self.coefficients:
            h = (h * x + k) % PRIME
        return h


def poly4(x: Column | str, seed: Seed, wide: bool = False) -> Column:
    x = (F.col(x) if isinstance(x, str) else x).cast("long")
    if wide:
        low = x % PRIME
        x = (low + F.call_function("div", x - low, F.lit(PRIME)) * seed.multiple % PRIME) % PRIME
    a, b, c, d = (F.lit(k).cast("long") for k in seed.coefficients)
    return (((((a * x + b) % PRIME) * x + c) % PRIME) * x + d) % PRIME


def sign(h: Column) -> Column:
    """+1 or -1 from a hash."""
    return F.lit(2) * h.bitwiseAND(1) - 1


def level(h: Column, top: int) -> Column:
    """Geometric level: trailing zero bits, at most top; level m holds a row with probability 2**-m."""
    return F.least(F.bit_count(h.bitwiseAND(-h) - 1), F.lit(top)).cast("int")


def level_sql(h: str, top: int) -> str:
    return f"least(CAST(bit_count(({h} & -({h})) - 1) AS INT), {top})"
