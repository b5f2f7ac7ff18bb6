"""Missing values, corruption, drift and snapshots, all by portable hashes.

Whether and how a record is hit depends on its id and a salt alone, so retries and other
engines get the same data.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence
from itertools import combinations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from reclink.functions.hashing import portable

THOUSAND = 1000


def _hit(key: str, salt: str, share: float) -> Column:
    return portable(F.col(key), salt, THOUSAND) < round(share * THOUSAND)


def picks(n: int, count: int, pick: str) -> list[int]:
    """Sets of `count` of n attributes, as bit masks, of which a hashed one is hit: runs from
    each attribute (`run`), or all sets of that size (`any`)."""
    if pick == "run":
        return [sum(1 << (start + k) % n for k in range(count)) for start in range(n)]
    return [sum(1 << j for j in own) for own in combinations(range(n), count)]


def _with_choice(df: DataFrame, salt: str, share: float, most: int, n: int, key: str, pick: str = "run") -> DataFrame:
    """Adds _hit and _mask, the 1..most attributes picked for a record, once, so the hashes are
    not computed for each attribute, and those of the mask only for records that are hit."""
    count, place = portable(F.col(key), f"{salt}-k", most), portable(F.col(key), f"{salt}-o", n if pick == "run" else 1 << 30)
    masks = [picks(n, k, pick) for k in range(1, most + 1)]
    found = F.lit(0)
    for k, own in enumerate(masks):
        found = F.when(F.col("_count") == k, F.get(F.array(*[F.lit(m) for m in own]), (F.col("_place") % len(own)).cast("int"))).otherwise(found)
    rows = df.withColumn("_hit", _hit(key, salt, share))
    rows = rows.withColumns({"_count": F.when(F.col("_hit"), count), "_place": F.when(F.col("_hit"), place)})
    return rows.withColumn("_mask", found).drop("_count", "_place")


def _chosen(j: int) -> Column:
    """Whether attribute j is among those picked for a hit record."""
    return F.col("_hit") & (F.col("_mask").bitwiseAND(F.lit(1 << j)) != 0)


def inject_mcar(df: DataFrame, attrs: Sequence[str], share: float, max_missing: int, salt: str = "mcar", key: str = "record_id", pick: str = "run") -> DataFrame:
    """Completely at random: 1..max_missing of attrs (see picks) are lost in a share of the records."""
    n = len(attrs)
    rows = _with_choice(df, salt, share, min(max_missing, n), n, key, pick)
    return rows.withColumns({a: F.when(~_chosen(j), F.col(a)) for j, a in enumerate(attrs)}).drop("_hit", "_mask")


def inject_mar(df: DataFrame, attr: str, by: str, share_by_value: dict[str, float], salt: str = "mar", key: str = "record_id") -> DataFrame:
    """At random given another attribute: the share lost depends on the value of `by`."""
    limit = F.lit(0)
    for value, share in share_by_value.items():
        limit = F.when(F.col(by) == F.lit(value), F.lit(round(share * THOUSAND))).otherwise(limit)
    return df.withColumn(attr, F.when(~(portable(F.col(key), salt, THOUSAND) < limit), F.col(attr)))


def inject_mnar(df: DataFrame, attr: str, predicate: Callable[[Column], Column]) -> DataFrame:
    """Not at random: values for which predicate holds are lost."""
    return df.withColumn(attr, F.when(~F.coalesce(predicate(F.col(attr)), F.lit(False)), F.col(attr)))


def inject_structural(df: DataFrame, attr: str, predicate: Column) -> DataFrame:
    """Rightly empty: attr has no value where predicate holds (a child's occupation)."""
    return df.withColumn(attr, F.when(~F.coalesce(predicate, F.lit(False)), F.col(attr)))


def _damaged(attr: str, place: str, op: str) -> Column:
    """One of seven changes of a text at a place (from 1), or none.  As text of SQL, which is built in
    one call."""
    v, p = f"`{attr}`", f"`{place}`"
    before, after = lambda n: f"substr({v}, 1, {n})", lambda n: f"substr({v}, {n})"
    one = lambda at: f"substr({v}, {at}, 1)"
    changes = [
        f"concat({before(f'{p} - 1')}, {after(f'{p} + 1')})",
        f"concat({before(p)}, 'x', {after(f'{p} + 1')})",
        f"concat({before(f'{p} - 1')}, 'z', {after(f'{p} + 1')})",
        f"concat({before(f'{p} - 1')}, {one(f'{p} + 1')}, {one(p)}, {after(f'{p} + 2')})",
        before(1),
        f"regexp_replace({v}, ' [^ ]*$', '')",
        f"translate({v}, 'cgi', 'kjy')",
    ]
    return F.expr(f"CASE WHEN `{op}` IS NULL THEN {v} " + " ".join(f"WHEN `{op}` = {i} THEN {x}" for i, x in enumerate(changes)) + " END")


def corrupt(df: DataFrame, attrs: Sequence[str], share: float = 0.2, most: int = 3, salt: str = "cor", key: str = "record_id", pick: str = "run") -> DataFrame:
    """1..most of attrs (see picks) are damaged in a share of the records: delete, insert, substitute,
    transpose, abbreviate, drop the last word, swap like-sounding letters."""
    n = len(attrs)
    rows = _with_choice(df, salt, share, min(most, n), n, key, pick)
    places = {f"_p{j}": F.when(_chosen(j), (1 + portable(F.col(key), f"{salt}-p-{a}", 97) % F.greatest(F.length(a), F.lit(1))).cast("int")) for j, a in enumerate(attrs)}
    ops = {f"_o{j}": F.when(_chosen(j), portable(F.col(key), f"{salt}-op-{a}", 7)) for j, a in enumerate(attrs)}
    rows = rows.withColumns(places | ops)
    changed = {a: _damaged(a, f"_p{j}", f"_o{j}") for j, a in enumerate(attrs)}
    return rows.withColumns(changed).drop("_hit", "_mask", *places, *ops)


def shift_dates(df: DataFrame, attrs: Sequence[str], share: float = 0.2, most_days: int = 31, salt: str = "day", key: str = "record_id") -> DataFrame:
    """Dates (yyyy-MM-dd) of a share of the records move by 1..most_days days, forward or
    back; what is no such date stays, and so does a missing value."""
    moved = {}
    for a in attrs:
        days = 1 + portable(F.col(key), f"{salt}-n-{a}", most_days)
        days = F.when(portable(F.col(key), f"{salt}-sign-{a}", 2) == 0, days).otherwise(-days).cast("int")
        # a pattern, as parsing also takes years or months alone
        there = F.when(F.col(a).rlike(r"^[0-9]{4}-[0-9]{2}-[0-9]{2}$"), F.expr(f"try_cast(`{a}` AS date)"))
        new = F.date_format(F.date_add(there, days), "yyyy-MM-dd")
        moved[a] = F.when(_hit(key, f"{salt}-{a}", share), F.coalesce(new, F.col(a))).otherwise(F.col(a))
    return df.withColumns(moved)


def donor_pool(df: DataFrame, rates: dict[str, float], donors: int = 1024, salt: str = "drift", key: str = "record_id") -> DataFrame:
    """The values of the record with the smallest id in each hashed bucket of records."""
    bucket = portable(F.col(key), f"{salt}-donor", donors)
    return df.select(bucket.alias("_bucket"), F.col(key).alias("_id"), *rates).groupBy("_bucket").agg(*[F.min_by(a, "_id").alias(f"_{a}") for a in rates])


def drift(df: DataFrame, rates: dict[str, float], donors: int = 1024, salt: str = "drift", key: str = "record_id", pool: DataFrame | None = None) -> DataFrame:
    """Values that change over time: at its rate an attribute takes the value of another
    record, the one with the smallest id in a hashed bucket of records.  `pool` is the donor_pool
    of all records where df is a slice of them."""
    pool = donor_pool(df, rates, donors, salt, key) if pool is None else pool
    out = df
    for a, rate in rates.items():
        give = F.broadcast(pool.select(F.col("_bucket"), F.col(f"_{a}").alias("_new")))  # at most `donors` rows
        out = out.withColumn("_bucket", F.when(_hit(key, f"{salt}-{a}", rate), portable(F.col(key), f"{salt}-to-{a}", donors)))
        out = out.join(give, "_bucket", "left").withColumn(a, F.when(F.col("_bucket").isNotNull(), F.coalesce("_new", a)).otherwise(F.col(a))).drop("_bucket", "_new")
    return out


def snapshots(df: DataFrame, keep_a: float, keep_b: float, shared: float, salt: str = "snap", key: str = "record_id") -> tuple[DataFrame, DataFrame]:
    """Two snapshots: records of the first are kept with keep_a; the second has the share
    `shared` of its records from the first and the others from outside it."""
    h = portable(F.col(key), salt, THOUSAND * THOUSAND)
    million = THOUSAND * THOUSAND
    a_end = round(keep_a * million)
    both = round(min(keep_b * shared, keep_a) * million)
    alone = round(keep_b * (1 - shared) * million)
    return df.where(h < a_end), df.where((h < both) | ((h >= a_end) & (h < a_end + alone)))


def rename_ids(df: DataFrame, prefix: str) -> DataFrame:
    return df.withColumn("record_id", F.concat(F.lit(prefix), F.col("record_id")))
