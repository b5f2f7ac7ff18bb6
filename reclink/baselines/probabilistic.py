"""Classical probabilistic linkage and its redistribution of weights for missing values."""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from reclink.baselines import em
from reclink.baselines.comparison import AGREE, MISSING
from reclink.operators import evaluate
from reclink.plans.planner import EPSILON

CLAMP = 1e-6


def estimate_mu(levels: DataFrame, truth: DataFrame, attrs: Sequence[str]) -> DataFrame:
    """attr, m, u: agreement rates among true and among other compared pairs, values present
    on both sides; clamped away from 0 and 1."""
    named = [f"l_{c}" for c in attrs]
    return mu_of_kinds(evaluate.marked_slices(levels, truth, lambda marked: marked.groupBy(F.col("hit").isNotNull().alias("match"), *named).agg(F.count(F.lit(1)).alias("n"))), attrs)


def mu_of_kinds(kinds: DataFrame, attrs: Sequence[str]) -> DataFrame:
    """estimate_mu of pairs counted by match and levels."""
    each = kinds.select("match", "n", F.explode(F.array(*[F.struct(F.lit(c).alias("attr"), F.col(f"l_{c}").alias("l")) for c in attrs])).alias("v")).select("match", "n", "v.*").where(F.col("l") != MISSING)
    clamp = lambda c: F.least(F.greatest(F.coalesce(c, F.lit(0.5)), F.lit(CLAMP)), F.lit(1 - CLAMP))
    agree = F.when(F.col("l") == AGREE, F.col("n")).otherwise(F.lit(0))
    rate = lambda among: clamp(F.sum(F.when(among, agree)).cast("double") / F.sum(F.when(among, F.col("n"))))
    return each.groupBy("attr").agg(rate(F.col("match")).alias("m"), rate(~F.col("match")).alias("u"))


def mu_from_mixture(levels: DataFrame, attrs: Sequence[str], **options) -> dict[str, tuple[float, float]]:
    """attr -> (m, u) without known pairs: the agreement rates of a two-class mixture."""
    return mu_from_patterns(em.patterns(levels, attrs), attrs, **options)


def mu_from_patterns(patterns: DataFrame, attrs: Sequence[str], **options) -> dict[str, tuple[float, float]]:
    rows = [(r["pattern"], r["cnt"]) for r in patterns.orderBy("pattern").collect()]
    _, _, m, u = em.fit(rows, len(attrs), **options)
    clamp = lambda x: min(max(float(x), CLAMP), 1 - CLAMP)
    return {c: (clamp(m[i, AGREE]), clamp(u[i, AGREE])) for i, c in enumerate(attrs)}


def weights(mu: dict[str, tuple[float, float]]) -> dict[str, tuple[float, float]]:
    """attr -> (agreement weight, disagreement weight), in bits."""
    return {c: (math.log2(m / u), math.log2((1 - m) / (1 - u))) for c, (m, u) in mu.items()}


def _total(levels: DataFrame, w: dict[str, tuple[float, float]], missing: str, split: str | None) -> Column:
    none = F.lit(0.0)
    present = {c: F.col(f"l_{c}") != MISSING for c in w}
    plain = {c: F.when(F.col(f"l_{c}") == AGREE, F.lit(x)).otherwise(F.lit(y)) for c, (x, y) in w.items()}
    if split is None:
        return sum((F.when(present[c], plain[c]).otherwise(F.lit(w[c][1] if missing == "disagree" else 0.0)) for c in w), none)
    agreement = {c: w[c][0] for c in w}
    held = sum((F.when(present[c], F.lit(agreement[c])).otherwise(none) for c in w), none)
    if split == "proportional":
        factor = F.coalesce(F.try_divide(F.lit(sum(agreement.values())), held), none)
        return factor * sum((F.when(present[c], plain[c]).otherwise(none) for c in w), none)
    count = sum((present[c].cast("int") for c in w), F.lit(0))
    spare = F.coalesce(F.try_divide(F.lit(sum(agreement.values())) - held, count), none)
    sign = {c: F.when(F.col(f"l_{c}") == AGREE, spare).otherwise(-spare) for c in w}
    return sum((F.when(present[c], plain[c] + sign[c]).otherwise(none) for c in w), none)


def weighted(levels: DataFrame, w: dict[str, tuple[float, float]], missing: str = "disagree", split: str | None = None) -> DataFrame:
    """a_id, b_id (or what stands beside the levels), weight, s: summed weights, and normalised to
    [0, 1] by their range.

    missing: disagree or neutral.  split redistributes the weight of attributes missing on
    either side: proportional to the weights present, or equal.  All missing gives s = 0.
    """
    low, high = sum(y for _, y in w.values()), sum(x for x, _ in w.values())
    total = _total(levels, w, missing, split)
    any_present = F.lit(False)
    for c in w:
        any_present = any_present | (F.col(f"l_{c}") != MISSING)
    s = F.greatest(F.lit(0.0), F.least(F.lit(1.0), (total - low) / (high - low)))
    return levels.select(*[c for c in levels.columns if not c.startswith("l_")], total.alias("weight"), F.when(any_present, s).otherwise(F.lit(0.0)).alias("s"))


def decide_three_ways(scored: DataFrame, upper: float, lower: float) -> DataFrame:
    """Adds decision: match, possible or non-match."""
    return scored.withColumn("decision", F.when(F.col("s") >= upper - EPSILON, "match").when(F.col("s") >= lower - EPSILON, "possible").otherwise("non-match"))


def probabilistic_link(levels: DataFrame, mu: DataFrame, s_t: float = 0.8, missing: str = "disagree", split: str | None = None) -> DataFrame:
    """a_id, b_id, s of pairs at or above s_t; mu is small (one row per attribute)."""
    w = weights({r["attr"]: (r["m"], r["u"]) for r in mu.collect()})
    return weighted(levels, dict(sorted(w.items())), missing, split).where(F.col("s") >= s_t - EPSILON).select("a_id", "b_id", "s")
