"""Edge weights as integers over a common scale, so that every distance is one integer ratio."""

from __future__ import annotations

from collections.abc import Callable
from decimal import Decimal
from fractions import Fraction
from math import lcm

#: A rule gives, for a tree of some height, the scaled weight of an edge into each level and the scale.
Rule = Callable[[int], tuple[dict[int, int], int]]


def exponential(base: int = 2) -> Rule:
    """An edge into level 1 is 1; each level divides by the base."""

    def rule(height: int) -> tuple[dict[int, int], int]:
        top = max(height, 1)
        return {level: base ** (top - level) for level in range(1, top + 1)}, base ** (top - 1)

    return rule


def uniform() -> Rule:
    return lambda height: (dict.fromkeys(range(1, max(height, 1) + 1), 1), 1)


def by_level(weights: list[float | str | Decimal | Fraction]) -> Rule:
    """Any positive weights, one for each level; made integers over their least common denominator."""
    exact = [Fraction(str(w)) for w in weights]

    def rule(height: int) -> tuple[dict[int, int], int]:
        if len(exact) < height or any(w <= 0 for w in exact):
            raise ValueError(f"{height} positive weights are needed")
        scale = lcm(*(w.denominator for w in exact))
        return {i + 1: int(w * scale) for i, w in enumerate(exact[: max(height, 1)])}, scale

    return rule
