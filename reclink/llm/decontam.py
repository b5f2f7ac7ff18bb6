"""Benchmark decontamination as a prefix-filtered set join, in DataFrame operations only.

Every benchmark item gives windows of `width` consecutive words (a shorter item is one
window).  A text holds a window only if it holds all of its words, so when the words of a
window are put in order of rarity in the corpus, its first one alone is a sufficient
prefix: texts are joined on that rarest word, and at each place where it occurs the
length bound (the text has room for the window) and the positional bound (the window
starts inside the text) come before the exact comparison of the words.

Rarity counts the benchmark's words over all texts.  Both word tables are as large as the
benchmark; they are broadcast only if they have at most `broadcast_rows` rows and are
shuffled under salts otherwise, so that a frequent word is dealt over tasks.

Null texts and texts without words have no words and no hits.  Rows are told apart by
(doc_id, hash and length of the text), so repeated rows each get the same result and null
doc_ids are kept.  Items without words give no windows; windows of items with a null item_id
count as hits, but the list of items leaves them out.  Items that repeat an item_id are one
item with the windows of all.  Of words that are equally rare the first in order is the
prefix, which changes no result.  Empty tables on either side are fine.  Further columns,
whatever their names, are kept by `clean_documents` and dropped by `contamination`.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from reclink.llm._common import bounded, lower_ascii, materialise

SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
WIDTH = 13
#: With about 200 bytes a row (13 words) at most 40 MB are broadcast.
BROADCAST_ROWS = 200_000
#: Times that a table is repeated where its words are joined by a shuffle.
SALTS = 8


def words(text: Column) -> Column:
    return F.array_remove(F.split(lower_ascii(F.coalesce(text, F.lit(""))), SEPARATORS), "")


def windows(benchmark: DataFrame, width: int = WIDTH) -> DataFrame:
    """Distinct windows (array of words) with the sorted ids of the items that have them."""
    items = benchmark.select(F.col("item_id"), words(F.col("text")).alias("w")).where(F.size("w") > 0)
    size = F.least(F.lit(width), F.size("w"))
    starts = F.sequence(F.lit(1), F.size("w") - size + 1)
    each = items.select("item_id", F.explode(F.transform(starts, lambda i: F.slice(F.col("w"), i, size))).alias("window"))
    return each.groupBy("window").agg(F.collect_set("item_id").alias("items"))


def salted(rows: DataFrame, table: DataFrame, broadcast_rows: int, *by: str) -> DataFrame:
    """Inner join on word: table is broadcast if it is small, else repeated under SALTS salts
    that rows get by a hash of the columns `by`, so that no word's rows meet in one task."""
    small = bounded(table, broadcast_rows)
    if small is not table:
        return rows.join(small, "word")
    salt = F.pmod(F.xxhash64(*by), F.lit(SALTS)).cast("int")
    return rows.withColumn("salt", salt).join(table.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1)))), ["word", "salt"]).drop("salt")


def prefixes(docs: DataFrame, wins: DataFrame, broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """Per window its rarest word in the corpus and the place of that word in the window."""
    vocabulary = wins.select(F.explode("window").alias("word")).distinct()
    found = docs.select(F.explode(words(F.col("text"))).alias("word"))
    # the words are counted before they meet the vocabulary if that has to be shuffled
    small = bounded(vocabulary, broadcast_rows)
    found = found.join(small, "word", "left_semi") if small is not vocabulary else found
    counts = found.groupBy("word").agg(F.count(F.lit(1)).alias("n"))
    known = materialise(vocabulary.join(counts, "word", "left").select("word", F.coalesce("n", F.lit(0)).alias("n")), "rarity")
    placed = wins.select("window", F.posexplode("window").alias("shift", "word"))
    rarest = F.min_by(F.struct("word", "shift"), F.struct("n", "word", "shift"))
    chosen = salted(placed, known, broadcast_rows, "window").groupBy("window").agg(rarest.alias("p"))
    chosen = chosen.join(wins, "window")
    return chosen.select(F.col("p.word").alias("word"), F.col("p.shift").alias("shift"), "window", "items", F.size("window").alias("len"))


def _keyed(docs: DataFrame) -> DataFrame:
    text = F.coalesce(F.col("text"), F.lit(""))
    return docs.select(F.col("doc_id"), F.xxhash64(text).alias("k1"), F.octet_length(text).alias("k2"), words(text).alias("w"))


def hits(docs: DataFrame, prefix: DataFrame, width: int = WIDTH, broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """Verified windows: doc_id, k1, k2, the start in words, the length and the items.

    If the prefixes are broadcast, a text is compared where it is.  If not, a place of a text
    is shuffled with the words around it that a window can cover, so what is sent grows with
    the text's length and not with its square.
    """
    start, end = F.col("pos") - F.col("shift"), F.col("pos") - F.col("shift") + F.col("len")
    found = ["doc_id", "k1", "k2", start.alias("start"), "len", "items"]
    each = _keyed(docs).select("doc_id", "k1", "k2", "w", F.posexplode("w").alias("pos", "word"))
    small = bounded(prefix, broadcast_rows)
    if small is not prefix:
        fits = (start >= 0) & (end <= F.size("w")) & (F.slice("w", F.greatest(start + 1, F.lit(1)), F.col("len")) == F.col("window"))
        return each.join(small, (each["word"] == small["word"]) & fits).select(*found)
    low = F.greatest(F.col("pos") - (width - 1), F.lit(0))
    near = each.select("doc_id", "k1", "k2", "pos", "word", low.alias("low"), F.size("w").alias("total"), F.slice("w", low + 1, F.col("pos") + width - low).alias("near"))
    met = salted(near, prefix, broadcast_rows, "doc_id", "k1", "pos").where((start >= 0) & (end <= F.col("total")))
    return met.where(F.slice("near", F.greatest(start - F.col("low") + 1, F.lit(1)), F.col("len")) == F.col("window")).select(*found)


def contamination(docs: DataFrame, benchmark: DataFrame, width: int = WIDTH, broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """Per row of docs: doc_id, n_words, n_hit, n_items, items_sha256, contaminated, and the
    key (k1, k2) of its text."""
    prefix = materialise(prefixes(docs, windows(benchmark, width), broadcast_rows), "prefixes")
    key = ["doc_id", "k1", "k2"]
    found = materialise(hits(docs, prefix, width, broadcast_rows), "hits")
    order = Window.partitionBy(*key).orderBy("start", "stop").rowsBetween(Window.unboundedPreceding, -1)
    spans = found.groupBy(*key, "start").agg(F.max(F.col("start") + F.col("len")).alias("stop"))
    fresh = F.greatest(F.lit(0), F.col("stop") - F.greatest("start", F.coalesce(F.max("stop").over(order), F.lit(0))))
    covered = spans.withColumn("fresh", fresh).groupBy(*key).agg(F.sum("fresh").alias("n_hit"))
    named = found.select(*key, F.explode("items").alias("item")).distinct().groupBy(*key).agg(F.count(F.lit(1)).alias("n_items"), F.array_sort(F.collect_list(F.col("item").cast("string"))).alias("item_ids"))
    rows = _keyed(docs).select(*key, F.size("w").cast("long").alias("n_words"))
    marks = covered.join(named, [covered[c].eqNullSafe(named[c]) for c in key], "left").select(*[covered[c].alias(f"m_{c}") for c in key], "n_hit", "n_items", "item_ids")
    out = rows.join(marks, [rows[c].eqNullSafe(marks[f"m_{c}"]) for c in key], "left")
    n_hit = F.coalesce("n_hit", F.lit(0)).cast("long")
    return out.select(
        "doc_id", "n_words", n_hit.alias("n_hit"), F.coalesce("n_items", F.lit(0)).cast("long").alias("n_items"),
        F.sha2(F.coalesce(F.array_join("item_ids", ","), F.lit("")), 256).alias("items_sha256"),
        ((n_hit > 0) & (20 * n_hit >= F.col("n_words"))).alias("contaminated"), "k1", "k2",
    )


def clean_documents(docs: DataFrame, benchmark: DataFrame, width: int = WIDTH, broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """The rows of docs that are not contaminated, with all their columns."""
    dirty = contamination(docs, benchmark, width, broadcast_rows).where("contaminated").select("doc_id", "k1", "k2").distinct()
    dirty = bounded(materialise(dirty, "contaminated"), broadcast_rows)
    text = F.coalesce(docs["text"], F.lit(""))
    same = docs["doc_id"].eqNullSafe(dirty["doc_id"]) & (F.xxhash64(text) == dirty["k1"]) & (F.octet_length(text) == dirty["k2"])
    return docs.join(dirty, same, "left_anti")
