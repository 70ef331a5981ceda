"""What "the quantile q of n values" means, in exact arithmetic on the driver."""

from __future__ import annotations

import math
from dataclasses import dataclass
from fractions import Fraction

RULES = ("floor0", "nearest", "midpoint", "linear")


@dataclass(frozen=True)
class Target:
    """0-based ranks of the value and its upper neighbour, and the neighbour's weight."""

    low: int
    high: int
    weight: Fraction


def exact_share(q) -> Fraction:
    """0.1 is one tenth, not the double nearest to it."""
    share = q if isinstance(q, Fraction) else Fraction(str(q))
    if not 0 <= share <= 1:
        raise ValueError(f"a quantile is between 0 and 1, not {q}")
    return share


def target_rank(n: int, q, rule: str = "nearest") -> Target | None:
    """``floor0``: floor(q n), ``nearest``: ceil(q n) as SQL's discrete percentile, ``midpoint``: the
    mean of both middle values where q n is whole, ``linear``: as SQL's continuous one."""
    share = exact_share(q)
    if rule not in RULES:
        raise ValueError(f"no rank rule {rule!r}")
    if n <= 0:
        return None
    if rule == "linear":
        h = (n - 1) * share
        low = math.floor(h)
        return Target(low, min(low + 1, n - 1), h - low)
    at = share * n
    if rule == "floor0":
        k = min(math.floor(at), n - 1)
        return Target(k, k, Fraction(0))
    k = max(1, math.ceil(at)) - 1
    if rule == "midpoint" and at.denominator == 1 and 0 < at < n:
        return Target(k, k + 1, Fraction(1, 2))
    return Target(k, k, Fraction(0))


def rank_gap(k: int, below: int, equal: int) -> tuple[str, int]:
    """Where rank k lies from a pivot with that many values below and equal: ("hit", 0), or the
    side and how many steps away. Ties count as the pivot itself, so they never widen a gap."""
    if below <= k < below + equal:
        return "hit", 0
    return ("right", k - (below + equal) + 1) if k >= below + equal else ("left", below - k)
