"""Two-class mixture over agreement patterns, fitted by EM; missing values are ignorable.

Spark counts the patterns (at most 4 levels per attribute); EM runs on those few rows.
"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reclink.baselines.comparison import AGREE, MISSING
from reclink.plans.planner import EPSILON


def _pattern(attrs: Sequence[str]):
    return F.concat_ws("", *[F.when(F.col(f"l_{c}") == MISSING, F.lit("-")).otherwise(F.col(f"l_{c}").cast("string")) for c in attrs])


def patterns(levels: DataFrame, attrs: Sequence[str]) -> DataFrame:
    return levels.select(_pattern(attrs).alias("pattern")).groupBy("pattern").agg(F.count(F.lit(1)).alias("cnt"))


def patterns_of_kinds(kinds: DataFrame, attrs: Sequence[str]) -> DataFrame:
    """patterns of pairs counted by match and levels."""
    return kinds.select(_pattern(attrs).alias("pattern"), "n").groupBy("pattern").agg(F.sum("n").alias("cnt"))


def fit(rows: Sequence[tuple[str, int]], width: int, iterations: int = 50, tolerance: float = 1e-6, share: float = 0.05, least_m: Sequence[float] | None = None, prior: tuple[float, float] | None = None):
    """(posterior by pattern, match share, m, u).

    least_m: lower bounds of m's agreement, from expected change rates; prior: a Beta prior
    of the match share.  m starts leaning to agreement, so the classes cannot swap.
    """
    codes = np.array([[-1 if x == "-" else int(x) for x in p] for p, _ in rows], int).reshape(-1, width)
    counts = np.array([n for _, n in rows], float)
    m = np.tile([0.1, 0.2, 0.7], (width, 1))
    u = np.tile([0.8, 0.1, 0.1], (width, 1))
    if not len(counts):
        return {}, share, m, u
    seen = codes >= 0
    pick = np.where(seen, codes, 0)
    columns = np.arange(width)
    for _ in range(iterations):
        log_m = np.where(seen, np.log(m[columns, pick]), 0).sum(axis=1) + np.log(share)
        log_u = np.where(seen, np.log(u[columns, pick]), 0).sum(axis=1) + np.log1p(-share)
        r = 1 / (1 + np.exp(np.clip(log_u - log_m, -700, 700)))
        a, b = prior or (0.0, 0.0)
        new = float(np.clip(((counts * r).sum() + a) / (counts.sum() + a + b), 1e-9, 1 - 1e-9))
        for table, weight in ((m, counts * r), (u, counts * (1 - r))):
            for c in range(width):
                sums = np.bincount(pick[:, c], weight * seen[:, c], 3) + 1e-6
                table[c] = sums / sums.sum()
        if least_m is not None:
            for c, low in enumerate(least_m):
                if m[c, AGREE] < low:
                    m[c] = m[c] * (1 - low) / max(1e-9, 1 - m[c, AGREE])
                    m[c, AGREE] = low
        if abs(new - share) < tolerance:
            share = new
            break
        share = new
    return dict(zip((p for p, _ in rows), r.tolist())), share, m, u


def em_link(levels: DataFrame, attrs: Sequence[str], s_t: float = 0.8, **options) -> DataFrame:
    """a_id, b_id, s (posterior) of pairs at or above s_t."""
    table = _posterior(patterns(levels, attrs), attrs, **options)
    return levels.select("a_id", "b_id", _pattern(attrs).alias("pattern")).join(table, "pattern").where(F.col("s") >= s_t - EPSILON).select("a_id", "b_id", "s")


def em_link_of_kinds(kinds: DataFrame, attrs: Sequence[str], s_t: float = 0.8, **options) -> DataFrame:
    """match, n and s of the pairs that em_link finds, of pairs counted by match and levels."""
    table = _posterior(patterns_of_kinds(kinds, attrs), attrs, **options)
    return kinds.select("match", "n", _pattern(attrs).alias("pattern")).join(table, "pattern").where(F.col("s") >= s_t - EPSILON).select("match", "n", "s")


def _posterior(counted: DataFrame, attrs: Sequence[str], **options) -> DataFrame:
    rows = [(r["pattern"], r["cnt"]) for r in counted.orderBy("pattern").collect()]
    posterior, *_ = fit(rows, len(attrs), **options)
    return F.broadcast(counted.sparkSession.createDataFrame([(k, float(v)) for k, v in posterior.items()], "pattern string, s double"))  # at most 4**attrs rows
