"""Accuracy, cost and significance measures.  There is no F-measure, on purpose."""

from __future__ import annotations

import math
from collections.abc import Callable, Sequence

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reclink.plans.planner import EPSILON
from reclink.sources import store

#: Bytes of pairs that go to the records by broadcast.
FEW_BYTES = 8 << 20
S_T = (0.5, 0.6, 0.7, 0.8, 0.9, 1.0)


def truth_of(a: DataFrame, b: DataFrame) -> DataFrame:
    """a_id, b_id of records with the same entity, and that."""
    left, right = (x.select("entity_id", F.col("record_id").alias(name)) for x, name in ((a, "a_id"), (b, "b_id")))
    out = left.join(right, "entity_id").select("a_id", "b_id", "entity_id")
    out._sides = (left, right)
    return out


def sides_of(truth: DataFrame) -> tuple[DataFrame, DataFrame] | None:
    """entity_id with a_id, and with b_id, of a truth_of."""
    return truth.__dict__.get("_sides")


def written_truth(truth: DataFrame) -> DataFrame:
    """a_id, b_id as files, in slices of entities where there are many; a truth_of stays as it is,
    as true_among and count_truth need no join of it."""
    if store.is_kept(truth) or sides_of(truth):
        return truth
    n = store.slices_of(truth) if "entity_id" in truth.columns else 1
    return store.in_slices(lambda i: store.part(truth, "entity_id", i, n).select("a_id", "b_id"), n, "truth")


def true_among(pairs: DataFrame, truth: DataFrame) -> DataFrame:
    """a_id, b_id of written pairs that are true, without joining the databases: the entities of
    a_id go to the pairs, then those of b_id must be the same, in slices of pairs and records.
    Few pairs go to the records by broadcast."""
    left, right = sides_of(truth)
    few = store.read_bytes(pairs) <= FEW_BYTES
    n = 1 if few else store.slices_of(left)
    put = F.broadcast if few else lambda rows: rows
    asked = pairs.select("a_id", "b_id")
    known = store.in_slices(lambda i: store.part(left, "a_id", i, n).join(put(store.part(asked, "a_id", i, n)), "a_id"), n, "known")
    out = store.in_slices(lambda i: store.part(right, "b_id", i, n).join(put(store.part(known, "b_id", i, n)), ["b_id", "entity_id"]).select("a_id", "b_id"), n, "true")
    store.release(known)
    return out


def count_truth(truth: DataFrame) -> DataFrame:
    """truth, the number of true pairs; of a truth_of of many records from the number of records
    of an entity on both sides, in slices of entities."""
    n = store.slices_of(truth)
    if n == 1 or not sides_of(truth):
        return truth.agg(F.count(F.lit(1)).alias("truth"))
    left, right = sides_of(truth)
    side = lambda rows, x, y, i: store.part(rows, "entity_id", i, n).select("entity_id", F.lit(x).alias("x"), F.lit(y).alias("y"))
    both = lambda i: side(left, 1, 0, i).unionByName(side(right, 0, 1, i)).where("entity_id IS NOT NULL").groupBy("entity_id").agg(F.sum("x").alias("x"), F.sum("y").alias("y"))
    counts = store.in_slices(lambda i: both(i).agg(F.sum(F.col("x") * F.col("y")).alias("n")), n, "truth")
    return counts.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("truth"))


def marked_slices(pairs: DataFrame, truth: DataFrame, of: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """`of` (pairs with hit, 1 or null) over all pairs, or, where the files are large, its rows
    of each slice of a_id; pairs and truth are then written first."""
    n = store.slices_of(pairs, truth)
    mark = lambda p, t: p.join(t.select("a_id", "b_id", F.lit(1).alias("hit")), ["a_id", "b_id"], "left")
    if n == 1:
        return of(mark(pairs, truth))
    mine = pairs if store.is_kept(pairs) else store.keep(pairs, "pairs")
    known = true_among(mine, truth) if sides_of(truth) else written_truth(truth)
    n = store.slices_of(mine, known)
    out = store.in_slices(lambda i: of(mark(store.part(mine, "a_id", i, n), store.part(known, "a_id", i, n))), n, "marked")
    store.release(*[x for x, given in ((mine, pairs), (known, truth)) if x is not given])
    return out


def precision_recall(pairs: DataFrame, truth: DataFrame) -> DataFrame:
    """predicted, tp, truth, precision, recall as one row; nothing predicted gives null."""
    if store.slices_of(pairs, truth) > 1:
        truth = written_truth(truth)
    count = lambda marked: marked.agg(F.count(F.lit(1)).alias("predicted"), F.count("hit").alias("tp"))
    counts = marked_slices(pairs if store.is_kept(pairs) else pairs.select("a_id", "b_id"), truth, count).agg(F.sum("predicted").alias("predicted"), F.sum("tp").alias("tp"))
    both = counts.crossJoin(F.broadcast(count_truth(truth)))
    return both.select("predicted", "tp", "truth", F.round(F.try_divide("tp", "predicted"), 6).alias("precision"), F.round(F.try_divide("tp", "truth"), 6).alias("recall"))


def accuracy_of_counts(counts: DataFrame, truth: int) -> DataFrame:
    """precision_recall of found pairs that are counted: match, n."""
    total = lambda c: F.coalesce(F.sum(c), F.lit(0).cast("long"))
    both = counts.agg(total("n").alias("predicted"), total(F.when(F.col("match"), F.col("n"))).alias("tp")).withColumn("truth", F.lit(truth).cast("long"))
    return both.select("predicted", "tp", "truth", F.round(F.try_divide("tp", "predicted"), 6).alias("precision"), F.round(F.try_divide("tp", "truth"), 6).alias("recall"))


def pr_curve(scored: DataFrame, truth: DataFrame, thresholds: Sequence[float] = S_T) -> DataFrame:
    """precision_recall of (a_id, b_id, s) at every threshold from one pass."""
    marked = scored.select("a_id", "b_id", "s").join(truth.select("a_id", "b_id", F.lit(1).alias("hit")), ["a_id", "b_id"], "left")
    each = marked.select("s", "hit", F.explode(F.array(*[F.lit(float(t)) for t in thresholds])).alias("s_t")).where(F.col("s") >= F.col("s_t") - EPSILON)
    counts = each.groupBy("s_t").agg(F.count(F.lit(1)).alias("predicted"), F.count("hit").alias("tp"))
    both = counts.crossJoin(F.broadcast(truth.agg(F.count(F.lit(1)).alias("truth"))))
    return both.select("s_t", "predicted", "tp", "truth", F.round(F.try_divide("tp", "predicted"), 6).alias("precision"), F.round(F.try_divide("tp", "truth"), 6).alias("recall"))


def blocking_quality(pairs: DataFrame, truth: DataFrame, n_a: int, n_b: int) -> DataFrame:
    """candidates, candidate recall and reduction ratio."""
    found = precision_recall(pairs, truth)
    return found.select(F.col("predicted").alias("candidates"), F.col("recall").alias("candidate_recall"), F.round(1 - F.col("predicted") / F.lit(float(n_a) * n_b), 6).alias("reduction"))


def blocking_of_counts(counts: DataFrame, truth: int, n_a: int, n_b: int) -> DataFrame:
    """blocking_quality of candidates that are counted: match, n."""
    found = accuracy_of_counts(counts, truth)
    return found.select(F.col("predicted").alias("candidates"), F.col("recall").alias("candidate_recall"), F.round(1 - F.col("predicted") / F.lit(float(n_a) * n_b), 6).alias("reduction"))


def change_rates(a: DataFrame, b: DataFrame, attrs: Sequence[str]) -> DataFrame:
    """attr, compared, rate: share of true pairs with both values whose values differ."""
    left = a.select("entity_id", *[F.col(c).cast("string").alias(f"a_{c}") for c in attrs])
    right = b.select("entity_id", *[F.col(c).cast("string").alias(f"b_{c}") for c in attrs])
    each = [F.struct(F.lit(c).alias("attr"), F.col(f"a_{c}").alias("x"), F.col(f"b_{c}").alias("y")) for c in attrs]
    rows = left.join(right, "entity_id").select(F.explode(F.array(*each)).alias("v")).select("v.*").where("x IS NOT NULL AND y IS NOT NULL")
    return rows.groupBy("attr").agg(F.count(F.lit(1)).alias("compared"), F.round(F.avg((F.col("x") != F.col("y")).cast("double")), 6).alias("rate"))


def dataset_summary(a: DataFrame, b: DataFrame, attrs: Sequence[str]) -> DataFrame:
    """side, records, missing_share (records lacking a value), truth."""
    lacks = F.exists(F.array(*[F.col(c).cast("string") for c in attrs]), lambda x: x.isNull()).cast("double")
    side = lambda df, name: df.agg(F.count(F.lit(1)).alias("records"), F.round(F.avg(lacks), 6).alias("missing_share")).withColumn("side", F.lit(name))
    truth = truth_of(a, b).agg(F.count(F.lit(1)).alias("truth"))
    return side(a, "A").unionByName(side(b, "B")).crossJoin(F.broadcast(truth)).select("side", "records", "missing_share", "truth")


# ---------------------------------------------------------------- Tukey's range test
def tukey_statistics(runs: DataFrame, group: str = "method", value: str = "recall") -> DataFrame:
    """Pairs of groups with the difference of their means and the range statistic q; groups
    have equally many runs."""
    groups = runs.groupBy(group).agg(F.avg(value).alias("mean"), F.var_samp(value).alias("var"), F.count(F.lit(1)).alias("r"))
    pooled = groups.agg(F.avg("var").alias("mse"))
    a = groups.select(F.col(group).alias("first"), F.col("mean").alias("m1"), "r")
    b = groups.select(F.col(group).alias("second"), F.col("mean").alias("m2"))
    both = a.join(b, F.col("first") < F.col("second")).crossJoin(F.broadcast(pooled))
    return both.select("first", "second", F.round(F.col("m1") - F.col("m2"), 6).alias("difference"), F.round(F.abs(F.col("m1") - F.col("m2")) / F.sqrt(F.col("mse") / F.col("r")), 6).alias("q"))


def _phi(x: np.ndarray) -> np.ndarray:
    return np.array([0.5 * math.erfc(-v / math.sqrt(2)) for v in np.ravel(x)]).reshape(np.shape(x))


def studentised_range_cdf(q: float, groups: int, df: int) -> float:
    """P(range of `groups` means / pooled deviation <= q), by quadrature."""
    z = np.linspace(-8, 8, 321)
    density = np.exp(-z * z / 2) / math.sqrt(2 * math.pi)
    # scale s of the pooled deviation: s**2 * df is chi-squared
    s = np.linspace(1e-4, 1 + 8 / math.sqrt(2 * df), 201)
    log_f = math.log(2) + df / 2 * math.log(df / 2) - math.lgamma(df / 2) + (df - 1) * np.log(s) - df * s * s / 2
    low = _phi(z)
    inner = np.array([np.trapezoid(groups * density * np.maximum(_phi(z + q * v) - low, 0) ** (groups - 1), z) for v in s])
    return float(min(1.0, np.trapezoid(np.exp(log_f) * inner, s)))


def critical_range(level: float, groups: int, df: int) -> float:
    """q that the range exceeds with chance `level`."""
    low, high = 0.0, 50.0
    for _ in range(40):
        middle = (low + high) / 2
        low, high = (middle, high) if studentised_range_cdf(middle, groups, df) < 1 - level else (low, middle)
    return (low + high) / 2


def tukey_test(runs: DataFrame, group: str = "method", value: str = "recall", level: float = 0.05) -> DataFrame:
    """tukey_statistics with the critical value of q and whether the pair differs."""
    groups, total = runs.agg(F.count_distinct(group), F.count(value)).first()
    critical = critical_range(level, groups, total - groups)
    return tukey_statistics(runs, group, value).withColumn("critical", F.lit(round(critical, 4))).withColumn("differs", F.col("q") > critical)
