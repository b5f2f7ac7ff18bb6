"""Field-wise comparison of record pairs, which the weight and mixture baselines share.

The baselines are given here in their generally published form.
"""

from __future__ import annotations

from collections.abc import Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from reclink.operators import pairing
from reclink.operators.match import candidate_pairs, meet, meeting, signature_sets
from reclink.plans.model import Combo, Qid, Settings
from reclink.plans.planner import refuse_cartesian
from reclink.sources import store

MISSING, DISAGREE, PARTIAL, AGREE = -1, 0, 1, 2


def string_similarity(x: Column, y: Column) -> Column:
    """1 - edit distance / longer length."""
    return 1 - F.levenshtein(x, y) / F.greatest(F.length(x), F.length(y), F.lit(1))


def level(x: Column, y: Column, cut: float = 0.8, partial: float | None = None) -> Column:
    """AGREE, PARTIAL (if a partial cut is given), DISAGREE, or MISSING."""
    sim = string_similarity(x, y)
    out = F.when(x.isNull() | y.isNull(), F.lit(MISSING)).when((x == y) | (sim >= cut), F.lit(AGREE))
    if partial is not None:
        out = out.when(sim >= partial, F.lit(PARTIAL))
    return out.otherwise(F.lit(DISAGREE))


def blocked_pairs(a: DataFrame, b: DataFrame, block: str = "signature", keys: Sequence[str] = (), sa: DataFrame | None = None, sb: DataFrame | None = None) -> DataFrame:
    """a_id, b_id: signature (shared kept signature), keys (equal in one of the keys), none."""
    if block == "signature":
        return candidate_pairs(sa, sb).select("a_id", "b_id")
    left, right = a.select(F.col("record_id").alias("a_id"), *keys), b.select(F.col("record_id").alias("b_id"), *keys)
    if block == "keys":
        passes = [left.select("a_id", k).join(right.select("b_id", k), k).select("a_id", "b_id") for k in keys]
        return reduce(DataFrame.unionByName, passes).distinct()
    refuse_cartesian(a.count() * b.count())
    return left.select("a_id").crossJoin(right.select("b_id"))


def compared(a: DataFrame, b: DataFrame, pairs: DataFrame, attrs: Sequence[str], cut: float = 0.8, partial: float | None = None) -> DataFrame:
    """a_id, b_id and l_<attr> levels."""
    rows = pairs.select("a_id", "b_id").join(_values(a, "a", attrs, "a_id"), "a_id").join(_values(b, "b", attrs, "b_id"), "b_id")
    return _levels(rows, attrs, cut, partial)


def _values(df: DataFrame, side: str, attrs: Sequence[str], key: str = "record_id") -> DataFrame:
    return df.select(F.col("record_id").alias(key), *[F.col(c).cast("string").alias(f"{side}_{c}") for c in attrs])


def _levels(rows: DataFrame, attrs: Sequence[str], cut: float, partial: float | None) -> DataFrame:
    return rows.select("a_id", "b_id", *[level(F.col(f"a_{c}"), F.col(f"b_{c}"), cut, partial).alias(f"l_{c}") for c in attrs])


def compared_candidates(a: DataFrame, b: DataFrame, sa: DataFrame, sb: DataFrame, attrs: Sequence[str], cut: float = 0.8, partial: float | None = None) -> DataFrame:
    """`compared` over all pairs that share a kept signature, written.  Values travel with the
    signatures, so that neither pairs nor whole databases are shuffled for them."""
    sa, sb = meeting(sa, sb)
    left, right = (signature_sets(s, side, more=_values(df, side, attrs)) for s, df, side in ((sa, a, "a"), (sb, b, "b")))
    levels = meet(left, right, lambda rows: _levels(rows, attrs, cut, partial))
    levels = levels if store.is_kept(levels) else store.keep(levels, "levels")
    store.release(left, right)
    return levels


def kinds_of(levels: DataFrame, attrs: Sequence[str]) -> DataFrame:
    """match, l_<attr> and n: rows of the same, summed."""
    return levels.groupBy("match", *[f"l_{c}" for c in attrs]).agg(F.sum("n").alias("n"))


def compared_kinds(rows: pairing.Rows, qids: Sequence[Qid], combos: Sequence[Combo], attrs: Sequence[str], settings: Settings = Settings(), cut: float = 0.8, partial: float | None = None) -> DataFrame:
    """match, l_<attr> and n: how many of all pairs that share a kept signature have these levels,
    and are true or not: at most two times 4 to the power of the attributes rows, written."""
    grouped = pairing.groups(rows, qids, combos, settings)
    levels = [level(F.col(f"a_{c}"), F.col(f"b_{c}"), cut, partial).alias(f"l_{c}") for c in attrs]
    count = lambda pairs: kinds_of(pairs.select((F.col("a_row") == F.col("b_row")).alias("match"), *levels, F.lit(1).alias("n")), attrs)
    held = lambda i: rows.slices[i].select("row", *[F.col(f"{s}_{c}").cast("string").alias(f"{s}_{c}") for s in "ab" for c in attrs])
    out = store.keep(kinds_of(pairing.counted(rows, pairing.pair_rows(grouped), {"shared": F.count(F.lit(1))}, held, count), attrs), "kinds")
    store.release(grouped)
    return out
