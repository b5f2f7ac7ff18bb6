"""Step 1: attribute combinations by completeness and Gini impurity, level by level.

Combinations are bit masks on the driver; the data is read once for the null patterns
(all completenesses) and once per level and batch for the impurities (grouping sets).
"""

from __future__ import annotations

import random
from collections.abc import Iterable, Sequence
from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from reclink.plans.model import Combo, Qid, check_columns
from reclink.plans.planner import EPSILON, prune_by_completeness

#: Grouping sets that one job expands the rows for.
BATCH = 8


def attrs_of(mask: int, qids: Sequence[Qid]) -> tuple[str, ...]:
    return tuple(q.name for i, q in enumerate(qids) if mask >> i & 1)


def mask_of(attrs: Iterable[str], qids: Sequence[Qid]) -> int:
    names = [q.name for q in qids]
    return sum(1 << names.index(a) for a in attrs)


def null_mask(qids: Sequence[Qid]) -> Column:
    """Bit i is set where attribute i has no value."""
    return sum((F.when(q.token().isNull(), F.lit(1 << i)).otherwise(F.lit(0)) for i, q in enumerate(qids)), F.lit(0))


def null_patterns(df: DataFrame, qids: Sequence[Qid]) -> DataFrame:
    """mask (of nulls), cnt: at most 2**len(qids) rows from one scan."""
    return df.select(null_mask(qids).alias("mask")).groupBy("mask").agg(F.count(F.lit(1)).alias("cnt"))


def completeness(df: DataFrame, qids: Sequence[Qid]) -> DataFrame:
    """s_c: share of records with all the attributes."""
    present = F.lit(True)
    for q in qids:
        present = present & q.token().isNotNull()
    return df.agg(F.try_divide(F.count_if(present), F.count(F.lit(1))).alias("s_c"))


def completeness_all(patterns: Sequence[tuple[int, int]], masks: Iterable[int]) -> dict[int, float]:
    total = sum(n for _, n in patterns) or 1
    return {m: sum(n for nulls, n in patterns if nulls & m == 0) / total for m in masks}


def gini(df: DataFrame, qids: Sequence[Qid], null_is_value: bool = False, denominator: str = "all") -> DataFrame:
    """s_g: sum of (f/N)(1 - f/N) over the values f records share.  N counts all records, or
    those with the attributes (`denominator="present"`); a missing value is no value."""
    keys = [q.token().alias(f"k{i}") for i, q in enumerate(qids)]
    rows = df.select(*keys)
    groups = (rows if null_is_value else rows.dropna()).groupBy(*rows.columns).agg(F.count(F.lit(1)).alias("f"))
    sums = groups.agg(F.sum("f").alias("sf"), F.sum(F.col("f").cast("double") * F.col("f")).alias("sff"))
    n = F.col("sf") if denominator == "present" else F.col("n")
    return df.agg(F.count(F.lit(1)).alias("n")).crossJoin(F.broadcast(sums)).select((F.try_divide("sf", n) - F.try_divide("sff", n.cast("double") * n)).alias("s_g"))


def score(s_c: float, s_g: float, alpha: float) -> float:
    return alpha * s_c + (1 - alpha) * s_g


def level_sums(df: DataFrame, qids: Sequence[Qid], masks: Sequence[int]) -> DataFrame:
    """mask, sf, sff and the number of groups of several combinations in one job.

    Tokens are hashed to 64 bits before the shuffle; a rolled-up column and a missing value
    look alike in a grouping set, so rows missing one of a set's attributes are dropped by
    their null mask, which is part of each set.
    """
    columns = [F.xxhash64(q.token()).alias(f"h{i}") for i, q in enumerate(qids)]
    rows = df.select(*columns, null_mask(qids).alias("nulls"))
    expanded = rows.select("*", F.explode(F.array(*[F.lit(m) for m in masks])).alias("mask")).where(F.col("nulls").bitwiseAND(F.col("mask")) == 0)
    kept = [F.when(F.col("mask").bitwiseAND(F.lit(1 << i)) != 0, F.col(f"h{i}")).alias(f"h{i}") for i in range(len(qids))]
    groups = expanded.select("mask", *kept).groupBy("mask", *[f"h{i}" for i in range(len(qids))]).agg(F.count(F.lit(1)).alias("f"))
    return groups.groupBy("mask").agg(F.sum("f").alias("sf"), F.sum(F.col("f").cast("double") * F.col("f")).alias("sff"), F.count(F.lit(1)).alias("groups"))


def grouping_sets_sums(df: DataFrame, qids: Sequence[Qid], masks: Sequence[int]) -> DataFrame:
    """The same by GROUPING SETS and grouping_id; each set has the columns of one mask."""
    n = len(qids)
    rows = df.select(*[F.coalesce(F.xxhash64(q.token()), F.lit(0)).alias(f"h{i}") for i, q in enumerate(qids)], *[q.token().isNull().alias(f"z{i}") for i, q in enumerate(qids)])
    columns = [F.col(f"{kind}{i}") for i in range(n) for kind in "hz"]
    sets = [[F.col(f"{kind}{i}") for i in range(n) if m >> i & 1 for kind in "hz"] for m in masks]
    groups = rows.groupingSets(sets, *columns).agg(F.grouping_id().alias("gid"), F.count(F.lit(1)).alias("f"), F.lit(0).alias("_"))
    absent = sum((F.when(F.col(f"z{i}"), F.lit(1)).otherwise(F.lit(0)) for i in range(n)), F.lit(0))
    gid = {m: sum(3 << 2 * (n - 1 - i) for i in range(n) if not m >> i & 1) for m in masks}
    name = F.create_map(*[F.lit(x) for m in masks for x in (gid[m], m)])
    complete = groups.where(absent == 0).select(name[F.col("gid").cast("int")].alias("mask"), "f")
    return complete.groupBy("mask").agg(F.sum("f").alias("sf"), F.sum(F.col("f").cast("double") * F.col("f")).alias("sff"))


def estimated_sums(df: DataFrame, qids: Sequence[Qid], masks: Sequence[int], estimator: str, size: int = 256) -> dict[int, float]:
    """Sum of squared shares of each combination without a wide shuffle.

    ams: `size` signed sums of hash parities, the mean of whose squares is the second
    moment.  sample: the squares of one value in `size` by hash, times `size`.
    """
    total = df.count() or 1
    rows = df.select(*[F.xxhash64(q.token()).alias(f"h{i}") for i, q in enumerate(qids)], null_mask(qids).alias("nulls"))
    each = rows.select("*", F.explode(F.array(*[F.lit(m) for m in masks])).alias("mask")).where(F.col("nulls").bitwiseAND(F.col("mask")) == 0)
    parts = [F.when(F.col("mask").bitwiseAND(F.lit(1 << i)) != 0, F.col(f"h{i}")).otherwise(F.lit(0)) for i in range(len(qids))]
    own = each.select("mask", F.xxhash64(*parts).alias("v"))
    if estimator == "ams":
        # 64 signs from each of size/64 hashes of a value
        words = own.select("mask", *[F.xxhash64("v", F.lit(s)).alias(f"w{s}") for s in range(-(-size // 64))])
        signs = [F.sum(1 - 2 * F.shiftrightunsigned(F.col(f"w{s // 64}"), s % 64).bitwiseAND(F.lit(1))).alias(f"s{s}") for s in range(size)]
        return {r["mask"]: sum(float(r[f"s{s}"]) ** 2 for s in range(size)) / size / total**2 for r in words.groupBy("mask").agg(*signs).collect()}
    groups = own.where(F.pmod(F.xxhash64("v", F.lit(7)), F.lit(size)) == 0).groupBy("mask", "v").agg(F.count(F.lit(1)).alias("f"))
    sums = groups.groupBy("mask").agg(F.sum(F.col("f").cast("double") * F.col("f")).alias("sff"))
    found = {r["mask"]: r["sff"] * size / total**2 for r in sums.collect()}
    return {m: found.get(m, 0.0) for m in masks}


# ---------------------------------------------------------------- the level loop
def next_level(level: set[int], width: int) -> set[int]:
    """Masks one attribute larger all of whose parts one smaller are in the level."""
    grown = {m | 1 << i for m in level for i in range(width) if not m >> i & 1}
    return {m for m in grown if all(m ^ 1 << i in level for i in range(width) if m >> i & 1)}


def apply_policy(kept: dict[int, float], policy: str) -> dict[int, float]:
    """drop: a combination goes if a larger one is kept; dominated: only if the larger one
    scores at least as much; keep: none goes."""
    if policy == "keep":
        return dict(kept)
    larger = lambda m: [o for o in kept if o != m and o & m == m]
    return {m: s for m, s in kept.items() if not any(policy == "drop" or kept[o] >= s - EPSILON for o in larger(m))}


def top_combinations(kept: dict[int, tuple[float, float, float]], qids: Sequence[Qid], n_a: int) -> list[Combo]:
    order = sorted(kept, key=lambda m: (-round(kept[m][2], 9), m.bit_count(), attrs_of(m, qids)))
    return [Combo(i + 1, attrs_of(m, qids), *kept[m]) for i, m in enumerate(order[:n_a])]


class Selection:
    """What a selection looked at: scores by mask, groups of each mask (of exact sums), masks
    of each level, kept masks."""

    def __init__(self):
        self.scores: dict[int, tuple[float, float, float]] = {}
        self.groups: dict[int, int] = {}
        self.levels: list[set[int]] = []
        self.kept: dict[int, float] = {}


def select_combinations(
    df: DataFrame, qids: Sequence[Qid], n_a: int = 5, alpha: float = 0.5, c_t: float = 0.7, prune: str = "apriori", subset_policy: str = "drop",
    min_size: int = 2, max_size: int | None = None, max_missing: float | None = None, estimator: str = "exact", trace: Selection | None = None,
) -> list[Combo]:
    """The n_a best combinations.

    prune: apriori grows passing combinations only; completeness grows all whose
    completeness can still pass (no false prune); none scores every combination.
    """
    check_columns(df.schema, qids)
    trace = trace if trace is not None else Selection()
    patterns = [(r["mask"], r["cnt"]) for r in null_patterns(df, qids).collect()]
    total = sum(n for _, n in patterns)
    width = len(qids)
    if total == 0:
        return []
    usable = [i for i in range(width) if max_missing is None or sum(n for m, n in patterns if m >> i & 1) / total <= max_missing]
    level = {1 << i for i in usable}
    kept: dict[int, float] = {}
    size = 1
    while level and size <= min(max_size or width, width):
        if size >= min_size:
            trace.levels.append(set(level))
            s_c = completeness_all(patterns, level)
            able = level if prune == "none" else prune_by_completeness(level, s_c, c_t)
            todo = sorted(able)
            for at in range(0, len(todo), BATCH):
                batch = todo[at : at + BATCH]
                if estimator == "exact":
                    sums = level_sums(df, qids, batch).collect()
                    squares = {r["mask"]: r["sff"] / total**2 for r in sums}
                    trace.groups |= dict.fromkeys(batch, 0) | {r["mask"]: r["groups"] for r in sums}
                else:
                    squares = estimated_sums(df, qids, batch, estimator)
                for m in batch:
                    s_g = s_c[m] - squares.get(m, 0.0)
                    trace.scores[m] = (s_c[m], s_g, score(s_c[m], s_g, alpha))
            passing = {m for m in able if trace.scores[m][2] >= c_t - EPSILON}
            kept |= {m: trace.scores[m][2] for m in passing}
            level = {"apriori": passing, "completeness": able, "none": level}[prune]
        level = next_level(level, width)
        size += 1
    trace.kept = apply_policy(kept, subset_policy)
    return top_combinations({m: trace.scores[m] for m in trace.kept}, qids, n_a)


def passing_masks(scores: dict[int, tuple[float, float, float]], c_t: float, width: int, min_size: int = 2) -> dict[int, float]:
    """What the level loop keeps at c_t, of scores that it found at c_t or below."""
    kept: dict[int, float] = {}
    for m in sorted(scores, key=int.bit_count):
        parts = [m ^ 1 << i for i in range(width) if m >> i & 1]
        if scores[m][2] >= c_t - EPSILON and (m.bit_count() <= min_size or all(p in kept for p in parts)):
            kept[m] = scores[m][2]
    return kept


def select_many(df: DataFrame, qids: Sequence[Qid], settings: Sequence[tuple[float, str]], n_a: int = 5, **options) -> dict[tuple[float, str], list[Combo]]:
    """The n_a best combinations for each (c_t, subset policy), from one look at the data at
    the smallest c_t."""
    trace = Selection()
    select_combinations(df, qids, n_a, c_t=min(c for c, _ in settings), subset_policy="keep", trace=trace, **options)
    out = {}
    for c_t, policy in settings:
        kept = apply_policy(passing_masks(trace.scores, c_t, len(qids)), policy)
        out[c_t, policy] = top_combinations({m: trace.scores[m] for m in kept}, qids, n_a)
    return out


def random_combinations(qids: Sequence[Qid], n_a: int, seed: int, sizes: Sequence[int] | None = None) -> list[Combo]:
    pool = [c for k in (sizes or range(2, len(qids) + 1)) for c in combinations([q.name for q in qids], k)]
    return fixed_combinations(random.Random(seed).sample(pool, min(n_a, len(pool))))


def fixed_combinations(attrs: Sequence[Sequence[str]]) -> list[Combo]:
    return [Combo(i + 1, tuple(a)) for i, a in enumerate(attrs)]


def missing_shares(df: DataFrame, qids: Sequence[Qid]) -> DataFrame:
    """attr, missing_share."""
    row = df.agg(*[F.avg(q.token().isNull().cast("double")).alias(q.name) for q in qids])
    return row.unpivot([], [q.name for q in qids], "attr", "missing_share")
