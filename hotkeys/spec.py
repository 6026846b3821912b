"""What is asked for: support, error bound, owners and buffer sizes, as exact numbers."""

from __future__ import annotations

from dataclasses import dataclass, field
from fractions import Fraction

Number = int | float | str | Fraction


def exact(x: Number) -> Fraction:
    """A decimal or ratio as written: 0.001 is 1/1000, not the nearest double."""
    return x if isinstance(x, Fraction) else Fraction(str(x))


def exceeds(count: int, phi: Fraction, n: int, inclusive: bool = False) -> bool:
    """count > phi * n in integers; inclusive also lets equality pass."""
    left, right = count * phi.denominator, phi.numerator * n
    return left >= right if inclusive else left > right


@dataclass(frozen=True)
class SupportSpec:
    """phi: support; eps: error, phi / 10 unless given; owners, slots and every: T, D and E.

    dist is 'any' or 'zipf' (then skew is its exponent); counters overrides the counters an owner gets.
    """

    phi: Fraction
    eps: Fraction = field(default=Fraction(0))
    owners: int = 24
    slots: int = 4096
    every: int = 100_000
    dist: str = "any"
    skew: float = 1.0
    seed: int = 42
    counters: int | None = None

    def __post_init__(self) -> None:
        object.__setattr__(self, "phi", exact(self.phi))
        object.__setattr__(self, "eps", exact(self.eps) or self.phi / 10)
        if not 0 < self.phi < 1 or not 0 < self.eps < 1:
            raise ValueError("phi and eps must lie between 0 and 1")
        if self.eps > self.phi:
            raise ValueError("eps must not exceed phi")
        if min(self.owners, self.slots, self.every) < 1:
            raise ValueError("owners, slots and every must be positive")
        if self.dist not in ("any", "zipf"):
            raise ValueError("dist is 'any' or 'zipf'")

    def per_owner(self) -> int:
        from hotkeys.plans.sizing import counters_any, counters_zipf

        if self.counters is not None:
            return self.counters
        if self.dist == "zipf" and self.skew > 1:
            return counters_zipf(self.eps, self.owners, self.skew)
        return counters_any(self.eps, self.owners)
