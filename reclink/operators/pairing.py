"""Pairs of two large databases by row numbers, counted without being written one by one.

Signatures, values and ids of records as strings take many times the disk of the databases.
Here a signature is the list of the row numbers that share it: its hashes are in the shuffle
files of one slice only, and values meet pairs slice by slice.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from reclink.operators.signatures import HOT, attribute_signature, attribute_signatures
from reclink.plans.model import Combo, Qid, Settings
from reclink.plans.planner import n_max
from reclink.sources import store

#: A row number is its slice times 2 to this power, plus a number within the slice.
SLICE_BITS = 48
#: One row of so many looks for signatures of very many records.
LOOK = 16
#: Slices of the databases whose signatures of one combination are grouped at a time.
PARTS = 4
#: Sorted numbers are stored as differences.
NUMBERS = {"parquet.writer.version": "v2", "parquet.enable.dictionary": "false"}


@dataclass
class Rows:
    """Two databases, slice by slice: row, a_<x> and b_<x> of each attribute.  A row holds a
    record of either side, and these two are the only true pair that either of them is in."""

    slices: Sequence[DataFrame]
    #: All slices, by one scan where they are files.
    whole: DataFrame | None = None

    @property
    def every(self) -> DataFrame:
        return reduce(DataFrame.unionByName, self.slices) if self.whole is None else self.whole

    def side(self, side: str, attrs: Sequence[str]) -> DataFrame:
        """record_id, a row number, and attributes of one database."""
        return self.every.select(F.col("row").alias("record_id"), *[F.col(f"{side}_{c}").alias(c) for c in attrs])

    def count(self) -> int:
        return self.every.count()


def numbered(i: int) -> Column:
    """Row numbers of slice i, to be written with it."""
    return F.monotonically_increasing_id() + F.lit(i << SLICE_BITS)


def slice_of(row: str) -> Column:
    return F.shiftright(F.col(row), SLICE_BITS)


def groups(rows: Rows, qids: Sequence[Qid], combos: Sequence[Combo], settings: Settings = Settings(), whole: bool = False) -> DataFrame:
    """a_rows, b_rows: for each signature the rows of either side that keep it, n its records on
    the side where they are more; `whole` has those of one side only, too.  Equal to the frequency
    filter: a side over the cap has no rows.

    Signatures that are over the cap already among one row of LOOK leave before the shuffle, if
    they are of very many rows; all others are counted in full when their rows are together."""
    cap = n_max(settings.p_t, settings.lam, settings.mu, settings.prob_mode)
    if cap is None:
        raise ValueError("signatures are grouped under a frequency cap only")
    union, none = settings.count_scope == "union", F.array().cast("array<long>")

    def signed(side: str, c: Combo) -> DataFrame:
        row = F.col("record_id") if side == "a" else -F.col("record_id") - 1
        found = rows.side(side, c.attrs).select(row.alias("v"), attribute_signature(c, qids).alias("sig")).where("sig IS NOT NULL")
        return found.select(F.xxhash64(F.lit(c.combo_id), "sig").alias("h"), F.xxhash64("sig", F.lit(1)).alias("c"), "v")

    def looked(side: str) -> DataFrame:
        some = rows.side(side, list(dict.fromkeys(x for c in combos for x in c.attrs))).where(F.pmod(F.xxhash64("record_id"), F.lit(LOOK)) == 0)
        return attribute_signatures(some, qids, combos).groupBy(F.lit(side).alias("side"), "combo_id", F.col("sig_hash").alias("h")).agg(F.count(F.lit(1)).alias("n"))

    hot = store.keep(looked("a").unionByName(looked("b")).where(F.col("n") > max(cap, HOT // LOOK)).select("side", "combo_id", "h"), "hot")

    def make(c: Combo, i: int, n: int) -> DataFrame:
        def rest(side: str) -> DataFrame:
            mine = signed(side, c) if n == 1 else signed(side, c).where(F.pmod("h", F.lit(n)) == i)
            return mine.join(F.broadcast(hot.where((F.col("side") == side) & (F.col("combo_id") == c.combo_id)).select("h")), "h", "left_anti")

        met = rest("a").unionByName(rest("b")).repartition("h")
        of_a, of_b = F.when(F.col("v") >= 0, F.col("v")), F.when(F.col("v") < 0, -F.col("v") - 1)
        sums = met.groupBy("h", "c").agg(*[x for name, v in (("a", of_a), ("b", of_b)) for x in (F.count(v).alias(f"n{name}"), F.min(v).alias(f"{name}0"), F.max(v).alias(f"{name}1"))])
        over = (F.col("na") + F.col("nb") > cap,) * 2 if union else (F.col("na") > cap, F.col("nb") > cap)
        # a side over the cap counts as empty; up to two rows are their least and their greatest
        sums = sums.withColumns({name: F.when(x, F.lit(0)).otherwise(F.col(name)) for name, x in zip(("na", "nb"), over)})  # noqa: B905
        sums = sums.where("na > 0 OR nb > 0" if whole else "na > 0 AND nb > 0")
        few = "na <= 2 AND nb <= 2"
        pair = lambda s: F.when(F.col(f"n{s}") == 0, none).when(F.col(f"n{s}") == 1, F.array(f"{s}0")).otherwise(F.array(f"{s}0", f"{s}1")).alias(f"{s}_rows")
        small = sums.where(few).select(pair("a"), pair("b"))
        more = met.join(sums.where(f"NOT ({few})").select("h", "c", "na", "nb").hint("shuffle_hash"), ["h", "c"])
        side = lambda s, v: F.sort_array(F.collect_list(F.when(F.col(f"n{s}") > 0, v))).alias(f"{s}_rows")
        found = small.unionByName(more.groupBy("h", "c").agg(side("a", of_a), side("b", of_b)).select("a_rows", "b_rows"))
        found = found.withColumn("n", F.greatest(F.size("a_rows"), F.size("b_rows")))
        return found.sortWithinPartitions(F.coalesce(F.get("a_rows", F.lit(0)), F.get("b_rows", F.lit(0))))

    n = len(rows.slices)
    parts = -(-n // PARTS)
    steps = [(c, i, parts) for c in combos for i in range(parts)]
    if n == 1:
        found = store.keep(reduce(DataFrame.unionByName, [make(*x) for x in steps]), "groups", **NUMBERS)
    else:
        found = store.in_slices(lambda i: make(*steps[i]), len(steps), "groups", **NUMBERS)
    store.release(hot)
    return found


def by_truth(pairs: DataFrame) -> DataFrame:
    """match, whether a pair of rows is true, and n."""
    return pairs.groupBy((F.col("a_row") == F.col("b_row")).alias("match")).agg(F.count(F.lit(1)).alias("n"))


def pair_counts(rows: Rows, qids: Sequence[Qid], combos: Sequence[Combo], settings: Settings = Settings()) -> DataFrame:
    """match and n: how many pairs share a kept signature, true and not; written."""
    grouped = groups(rows, qids, combos, settings)
    found = scored(rows, pair_rows(grouped).select("a_row", "b_row"), {"shared": F.count(F.lit(1))}, by_truth)
    out = store.keep(found.groupBy("match").agg(F.sum("n").alias("n")), "tally")
    store.release(grouped, found)
    return out


def pair_rows(grouped: DataFrame) -> DataFrame:
    """a_row, b_row, n: a pair for each signature that it shares."""
    return grouped.select(F.explode("a_rows").alias("a_row"), "b_rows", "n").select("a_row", F.explode("b_rows").alias("b_row"), "n")


def signature_numbers(grouped: DataFrame, i: int) -> DataFrame:
    """row, a_n, b_n: kept signatures of the records of slice i."""
    side = lambda name, x, y: grouped.select(F.explode(f"{name}_rows").alias("row")).where(slice_of("row") == i).select("row", F.lit(x).alias("x"), F.lit(y).alias("y"))
    return side("a", 1, 0).unionByName(side("b", 0, 1)).groupBy("row").agg(F.sum("x").alias("a_n"), F.sum("y").alias("b_n"))


def counted(rows: Rows, met: DataFrame, shared: dict[str, Column], held: Callable[[int], DataFrame], of: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """`of` (a_row, b_row, what the aggregates `shared` say of a pair's rows in `met`, and a_*, b_*
    of its records) over every pair, a part for each slice: written, so `of` should count.

    `held` gives row, a_*, b_* of a slice.  Pairs within a slice, of which the true ones need one
    look-up, meet both records there; others take along what the first holds."""
    n = len(rows.slices)
    of_pairs = lambda some, *key: some.groupBy(*key).agg(*[x.alias(name) for name, x in shared.items()])
    far = store.keep(met.where(slice_of("a_row") != slice_of("b_row")), "far") if n > 1 else None
    done, known = [], []
    for i in range(n):
        mine = held(i)
        left, right = (mine.select(F.col("row").alias(f"{s}_row"), *[c for c in mine.columns if c.startswith(f"{s}_")]) for s in "ab")
        near = met if n == 1 else met.where((slice_of("a_row") == i) & (slice_of("b_row") == i))
        same = of_pairs(near.where("a_row = b_row").withColumnRenamed("a_row", "row"), "row").join(mine, "row")
        same = same.withColumnRenamed("row", "a_row").withColumn("b_row", F.col("a_row"))
        other = of_pairs(near.where("a_row <> b_row").repartition("a_row"), "a_row", "b_row").join(left, "a_row").join(right, "b_row")
        done.append(store.keep(of(same.unionByName(other)), "counted"))
        if far is not None:
            first = of_pairs(far.where(slice_of("a_row") == i).repartition("a_row"), "a_row", "b_row").join(left, "a_row")
            known.append(store.keep(first, "known"))
        store.release(mine)
    if far is not None:
        store.release(far)
        firsts = store.together(known)
        for i in range(n):
            mine = held(i)
            right = mine.select(F.col("row").alias("b_row"), *[c for c in mine.columns if c.startswith("b_")])
            done.append(store.keep(of(firsts.where(slice_of("b_row") == i).join(right, "b_row")), "counted"))
            store.release(mine)
        store.release(*known)
    return store.together(done)


def similar(rows: Rows, grouped: DataFrame, of: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """`of` (a_row, b_row, common, and a_n, b_n, the sizes of both sets of signatures) over every
    pair of a `whole` grouping, a part for each slice: written."""
    return counted(rows, pair_rows(grouped), {"common": F.count(F.lit(1))}, lambda i: store.keep(signature_numbers(grouped, i), "numbers"), of)


def scored(rows: Rows, met: DataFrame, shared: dict[str, Column], of: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """`of` (a_row, b_row and the aggregates `shared`) over every pair, by slices of a_row: written."""
    n = len(rows.slices)
    mine = lambda i: met if n == 1 else met.where(slice_of("a_row") == i)
    return store.in_slices(lambda i: of(mine(i).groupBy("a_row", "b_row").agg(*[x.alias(name) for name, x in shared.items()])), n, "counted")
