"""Rewrites that are applied while the DataFrames are built."""

from __future__ import annotations

import math

#: Thresholds in tenths are compared with this tolerance.
EPSILON = 1e-9


def probability(n: float, lam: float = 1.2, mu: float = 0.2, mode: str = "literal") -> float:
    """Chance that a signature shared by n records identifies; relative: over that of n=1."""
    p = 1 / (1 + lam**n * mu)
    return p if mode == "literal" else p * (1 + lam * mu)


def n_max(p_t: float, lam: float = 1.2, mu: float = 0.2, mode: str = "literal") -> int | None:
    """Largest n whose probability is at least p_t: the rule as a whole-number cap, which
    bounds a signature's join fan-out.  0: none passes; None: all pass."""
    limit = p_t if mode == "literal" else p_t / (1 + lam * mu)
    if limit <= 0:
        return None
    if limit >= 1:
        return 0
    n = math.floor(math.log((1 / limit - 1) / mu) / math.log(lam) + EPSILON)
    return max(n, 0)


def relational_bound(s_t: float, beta: float) -> float:
    """Least attribute similarity from which the blend can still reach s_t, as a relational
    similarity is at most one."""
    return 0.0 if beta == 0 else (s_t - (1 - beta)) / beta - EPSILON


def prune_by_completeness(masks: set[int], completeness: dict[int, float], c_t: float) -> set[int]:
    """Masks that can reach c_t: a score never exceeds its completeness."""
    return {m for m in masks if completeness[m] >= c_t - EPSILON}


def refuse_cartesian(rows: int, limit: int = 50_000_000) -> None:
    if rows > limit:
        raise ValueError(f"{rows} pairs without blocking; the limit is {limit}")
