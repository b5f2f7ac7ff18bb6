"""Joins and aggregations that Spark has no single operator for."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from reclink.sources import store


def range_join(points: DataFrame, ranges: DataFrame, point: str, low: str, high: str, width: int) -> DataFrame:
    """Rows with low <= point < high (numbers): both sides meet in buckets of `width`, so no
    nested loop over all pairs; a range enters each bucket it touches."""
    left = points.withColumn("_bucket", F.floor(F.col(point) / width))
    right = ranges.withColumn("_bucket", F.explode(F.sequence(F.floor(F.col(low) / width), F.floor(F.col(high) / width))))
    return left.join(right, "_bucket").where((F.col(point) >= F.col(low)) & (F.col(point) < F.col(high))).drop("_bucket")


def interval_join(a: DataFrame, b: DataFrame, a_day: str, b_day: str, days: int, on: Sequence[str] = ()) -> DataFrame:
    """Pairs whose dates lie at most `days` apart."""
    number = lambda c: F.datediff(F.col(c), F.lit("1970-01-01").cast("date"))
    width = max(1, days)
    left = a.withColumn("_n", number(a_day)).withColumn("_bucket", F.floor(F.col("_n") / width))
    right = b.withColumn("_m", number(b_day)).withColumn("_bucket", F.explode(F.transform(F.array(F.lit(-1), F.lit(0), F.lit(1)), lambda k: F.floor(F.col("_m") / width) + k)))
    return left.join(right, [*on, "_bucket"]).where(F.abs(F.col("_n") - F.col("_m")) <= days).drop("_n", "_m", "_bucket")


def asof_join(left: DataFrame, right: DataFrame, on: str, left_time: str, right_time: str, value: str) -> DataFrame:
    """left with the latest `value` of right, same key, at or before its time: one union and
    one running window instead of a join of all earlier rows."""
    kind = dict(left.dtypes)
    a = left.select(*left.columns, F.col(left_time).alias("_t"), F.lit(1).alias("_side"), F.lit(None).cast(dict(right.dtypes)[value]).alias("_v"))
    b = right.select(*[F.col(on).alias(c) if c == on else F.lit(None).cast(kind[c]).alias(c) for c in left.columns], F.col(right_time).alias("_t"), F.lit(0).alias("_side"), F.col(value).alias("_v"))
    order = Window.partitionBy(on).orderBy("_t", "_side").rowsBetween(Window.unboundedPreceding, 0)
    return a.unionByName(b).withColumn(f"last_{value}", F.last("_v", ignorenulls=True).over(order)).where("_side = 1").drop("_t", "_side", "_v")


def similarity_join(a: DataFrame, b: DataFrame, a_id: str, b_id: str, tokens: str, threshold: float) -> DataFrame:
    """Pairs of token sets with Jaccard >= threshold, by prefix filter: sets in order of
    global rarity can only be similar if their prefixes share a token."""
    both = a.select(F.explode(F.array_distinct(tokens)).alias("t")).unionByName(b.select(F.explode(F.array_distinct(tokens)).alias("t")))
    df = both.groupBy("t").agg(F.count(F.lit(1)).alias("f"))

    def ordered(rows: DataFrame, key: str) -> DataFrame:
        each = rows.select(key, F.explode(F.array_distinct(tokens)).alias("t")).join(df, "t")
        sets = each.groupBy(key).agg(F.array_sort(F.collect_list(F.struct("f", "t"))).alias("s"))
        return sets.select(key, F.transform("s", lambda x: x["t"]).alias("s"))

    left, right = ordered(a, a_id).withColumnRenamed("s", "sa"), ordered(b, b_id).withColumnRenamed("s", "sb")
    size = lambda c: F.size(c) - F.ceil(F.size(c) * threshold - 1e-9).cast("int") + 1
    prefix = lambda rows, key, c: rows.select(key, F.explode(F.slice(c, F.lit(1), size(c))).alias("t"))
    pairs = prefix(left, a_id, F.col("sa")).join(prefix(right, b_id, F.col("sb")), "t").select(a_id, b_id).distinct()
    common = F.size(F.array_intersect("sa", "sb"))
    rows = pairs.join(left, a_id).join(right, b_id).withColumn("similarity", common / (F.size("sa") + F.size("sb") - common))
    return rows.where(F.col("similarity") >= threshold - 1e-9).select(a_id, b_id, "similarity")


def salted_sum(df: DataFrame, key: str, value: Column, salts: int = 16) -> DataFrame:
    """key, total in two phases: a hot key is summed by `salts` tasks first."""
    salted = df.withColumn("_salt", F.pmod(F.xxhash64(*df.columns), F.lit(salts)))
    part = salted.groupBy(key, "_salt").agg(F.sum(value).alias("_part"))
    return part.groupBy(key).agg(F.sum("_part").alias("total"))


#: Rows of a key from which it counts as hot; hot keys that are broadcast; salts otherwise.
HOT, HOT_KEYS, SALTS = 256, 200_000, 8


def hot_join(rows: DataFrame, keyed: DataFrame, on: Sequence[str] | str, count: str, hot: int = HOT, most: int = HOT_KEYS, salts: int = SALTS) -> DataFrame:
    """Inner join of rows with keyed (one row per key; `count` says how many rows have it) in
    which no key lands in one task: keys of more than `hot` rows are broadcast, if at most
    `most` are, and else repeated under `salts` salts; all others meet by a shuffle."""
    on = [on] if isinstance(on, str) else list(on)
    often, seldom = store.keep(keyed.where(F.col(count) > hot), "hot-keys"), keyed.where(F.col(count) <= hot)
    found = often.limit(most + 1).count()
    if not found:
        return rows.join(keyed, on)
    if found <= most:
        rest = rows.join(F.broadcast(often.select(*on)), on, "left_anti")
        return rest.join(seldom, on).unionByName(rows.join(F.broadcast(often), on))
    spread = keyed.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    salted = rows.withColumn("_salt", F.pmod(F.xxhash64(*rows.columns), F.lit(salts)).cast("int"))
    return salted.join(spread, [*on, "_salt"]).drop("_salt")
