"""MinHash near-duplicate components, verified through odd sketches and full sets.

Each text becomes its set of distinct five-word shingles (64-bit hashes; words are cut at
ASCII white space after lowering A-Z; fewer words than five are one shingle).  The steps:

1. Texts with the same set are one class (set size and two independent 64-bit sums), so
   groups of exact copies are one row from here on, however large.
2. MinHash: bands of `ROWS` minima put classes into buckets, as many as `bands` says for
   the threshold: 20 for 0.85, 29 for 0.8.  A pair at the threshold misses all bands with a
   chance of about 1e-5.
3. Odd sketches are parity bitmaps: two sketches differ in at most as many bits as the
   folded sets differ in elements.  One folds the MinHash samples, whose count of
   differing bits estimates the similarity (pairs more than six deviations under the
   threshold go); one folds the set itself, whose count of differing bits is a lower bound
   of the symmetric difference (pairs beyond the largest difference allowed go, without
   error).
4. Pairs that remain are confirmed on their full sets.

Large groups never emit all their pairs.  First each class is tried against one pivot, the
smallest class it shares a bucket with; confirmed links give components.  Only buckets that
still hold several components are looked at again.  They are dealt over tiles of bounded
size, in which the sketches of classes outside the bucket's largest component are compared
with the others'; a tile gives as few pairs as join the components that its sketches would
join, so at most one less than its classes.  After two such rounds (a few bands, then all)
every pair that the sketches leave between two components is confirmed.  So every link
between different components that the bands can show is found, and no partner is capped.

Null, empty and blank texts have the empty set and are linked with nothing.  Rows with
equal doc_ids are told apart; null doc_ids are kept, and a component's id is its smallest
non-null doc_id.  Empty tables give no rows.  Further columns, whatever their names, are kept
by `drop_near_copies` and ignored by `near_copies`.  Buckets and classes of very many rows
are joined without a shuffle on their key, or salted (`hot_join`).
"""

from __future__ import annotations

import functools
import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reclink.llm._common import SpanHasher, bounded, hot_join, materialise, splitmix, text_steps, tidy, word_spans

WORDS = 5
#: BANDS is for a threshold of 0.85.
BANDS, ROWS = 20, 5
#: Chance that a pair at a lower threshold may miss all bands.
MISS = 1.3e-5
SAMPLE_BITS, SET_BITS = 512, 1024
#: Classes on a side of a tile; bands that the first tile round looks at; rows of tiles a task.
TILE, TILE_BANDS, TASK_ROWS = 2048, 3, 4096
MOST_TASKS = 50_000
#: Ids of texts to be confirmed: 16 bytes each, so at most 16 MB are broadcast.
BROADCAST_ROWS = 500_000

U64 = np.uint64


@functools.lru_cache
def _coefficients(samples: int) -> tuple[np.ndarray, np.ndarray]:
    """Multipliers and addends of the MinHash functions."""
    numbers = np.arange(samples, dtype=np.uint64)[:, None]
    return splitmix(numbers + U64(5001)) | U64(1), splitmix(numbers + U64(9001))


def bands(percent: int) -> int:
    """Bands that a pair at the threshold misses with a chance of at most MISS."""
    return BANDS if percent >= 85 else math.ceil(math.log(MISS) / math.log(1 - (percent / 100) ** ROWS))


# ---------------------------------------------------------------- sets and sketches
def shingle_sets(data: np.ndarray, offsets: np.ndarray, hasher: SpanHasher, width: int = WORDS) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each row."""
    starts, ends, first = word_spans(data, offsets)
    with np.errstate(over="ignore"):
        words = hasher.spans(data, starts, ends)
        step = U64(0x9E3779B97F4A7C15)
        powers = [U64(pow(int(step), j, 1 << 64)) for j in range(width)]
        runs = max(0, len(words) - width + 1)
        mixed = np.zeros(runs, np.uint64)
        for j in range(width):
            mixed += words[j : j + runs] * powers[j]
        mixed = splitmix(mixed)
        out = []
        for a, b in zip(first[:-1].tolist(), first[1:].tolist()):
            if b - a >= width:
                out.append(np.unique(mixed[a : b - width + 1]))
            elif b > a:
                whole = np.array([sum(int(w) * int(p) for w, p in zip(words[a:b], powers)) + (b - a) & 0xFFFFFFFFFFFFFFFF], np.uint64)
                out.append(splitmix(splitmix(whole)))
            else:
                out.append(mixed[:0])
    return out


def minima(values: np.ndarray, block: int = 4096, samples: int = BANDS * ROWS) -> np.ndarray:
    """The MinHash samples of a non-empty set."""
    best = np.full(samples, np.iinfo(np.uint64).max, np.uint64)
    multipliers, addends = _coefficients(samples)
    with np.errstate(over="ignore"):
        for at in range(0, len(values), block):
            np.minimum(best, (values[None, at : at + block] * multipliers + addends).min(axis=1), out=best)
    return best


def fold(bits: np.ndarray, size: int) -> np.ndarray:
    """Parity bitmap (array of 64-bit words) of bit numbers."""
    return np.packbits((np.bincount(bits, minlength=size) & 1).astype(np.uint8), bitorder="little").view("<i8")


def sample_sketch(samples: np.ndarray) -> np.ndarray:
    place = splitmix(samples ^ splitmix(np.arange(len(samples), dtype=np.uint64)))
    return fold((place % U64(SAMPLE_BITS)).astype(np.int64), SAMPLE_BITS)


def estimate(differing_bits: float, samples: int = BANDS * ROWS, size: int = SAMPLE_BITS) -> float:
    """Similarity from the differing bits of two sample sketches."""
    left = max(1 - 2 * differing_bits / size, 1e-9)
    return 1 + size / (4 * samples) * math.log(left)


def sample_limit(threshold: float, samples: int = BANDS * ROWS, size: int = SAMPLE_BITS) -> int:
    """Differing bits that a pair of the threshold's similarity stays under, but for about
    one in a billion: each unequal sample toggles at most two bits."""
    unequal = samples * (1 - threshold) + 6 * math.sqrt(samples * threshold * (1 - threshold))
    return min(size, math.ceil(2 * unequal))


_SIGNATURE = "row long, doc_id long, k long, n long, s1 long, s2 long, keys array<long>, samples array<long>, parity array<long>"


def signatures(docs: DataFrame, count: int = BANDS) -> DataFrame:
    """Per row: k (hash of the text), n (set size), s1 and s2 (sums that name the set), keys
    of `count` bands and sketches."""

    def sign(batches):
        from pyspark import TaskContext

        row = TaskContext.get().partitionId() << 40
        hasher = SpanHasher(5)
        weights = splitmix(np.arange(ROWS, dtype=np.uint64) + U64(301)) | U64(1)
        band = splitmix(np.arange(count, dtype=np.uint64) + U64(401))
        for batch in batches:
            for at, to, data, offsets in text_steps(batch.column(1), 2 << 20):
                rows = []
                with np.errstate(over="ignore"):
                    for values in shingle_sets(data, offsets, hasher):
                        if len(values) == 0:
                            rows.append((0, 0, 0, [], [], []))
                            continue
                        best = minima(values, samples=count * ROWS)
                        keys = splitmix((best.reshape(count, ROWS) * weights).sum(axis=1, dtype=np.uint64) ^ band)
                        sums = [int(splitmix(values ^ U64(seed)).sum(dtype=np.uint64).astype(np.int64)) for seed in (17, 1717)]
                        parity = fold((values % U64(SET_BITS)).astype(np.int64), SET_BITS)
                        rows.append((len(values), *sums, keys.view(np.int64), sample_sketch(best), parity))
                n, s1, s2, keys, samples, parity = (list(x) for x in zip(*rows))
                number = pa.array(np.arange(row, row + to - at))
                row += to - at
                longs = pa.list_(pa.int64())
                yield pa.RecordBatch.from_arrays(
                    [number, batch.column(0).slice(at, to - at), batch.column(2).slice(at, to - at), *(pa.array(x, pa.int64()) for x in (n, s1, s2)), *(pa.array(x, longs) for x in (keys, samples, parity))],
                    names=["row", "doc_id", "k", "n", "s1", "s2", "keys", "samples", "parity"],
                )

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.xxhash64("text").alias("k"))
    return rows.mapInArrow(tidy(sign), _SIGNATURE)


def sets_of(docs: DataFrame, classes: DataFrame, broadcast_rows: int) -> DataFrame:
    """Full sets of classes (c, doc_id, n, s1, s2) from the texts: c, set (array of long)."""

    def sets(batches):
        hasher = SpanHasher(5)
        for batch in batches:
            for at, to, data, offsets in text_steps(batch.column(1), 2 << 20):
                found = shingle_sets(data, offsets, hasher)
                with np.errstate(over="ignore"):
                    sums = [[int(splitmix(v ^ U64(seed)).sum(dtype=np.uint64).astype(np.int64)) for v in found] for seed in (17, 1717)]
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).slice(at, to - at), *(pa.array(x, pa.int64()) for x in ([len(v) for v in found], *sums)), pa.array([v.view(np.int64) for v in found], pa.list_(pa.int64()))],
                    names=["d", "m", "t1", "t2", "set"],
                )

    wanted = bounded(classes.select(F.col("doc_id").alias("wanted")).distinct(), broadcast_rows)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    texts = texts.join(wanted, texts["doc_id"].eqNullSafe(wanted["wanted"]), "left_semi")
    found = texts.mapInArrow(tidy(sets), "d long, m long, t1 long, t2 long, set array<long>")
    joined = found.join(classes, (found["t1"] == classes["s1"]) & (found["t2"] == classes["s2"]) & (found["m"] == classes["n"]) & found["d"].eqNullSafe(classes["doc_id"]))
    return joined.select("c", "set").dropDuplicates(["c"])


# ---------------------------------------------------------------- pairs
def _differing(a: str, b: str, words: int):
    return sum((F.bit_count(F.get(a, F.lit(i)).bitwiseXOR(F.get(b, F.lit(i)))) for i in range(1, words)), F.bit_count(F.get(a, F.lit(0)).bitwiseXOR(F.get(b, F.lit(0)))))


def _tiles(percent: int):
    """Pairs of tiles that the sketches leave, as few as join the components they would
    join: the pieces of a bucket of any size are compared without emitting all pairs."""
    limit = sample_limit(percent / 100, bands(percent) * ROWS)

    def one(c, l, minor, n, block, cross, parity, samples) -> list[tuple]:
        root: dict[int, int] = {}

        def find(v: int) -> int:
            while (up := root.get(v, v)) != v:
                v = up
            return v

        out = []
        for i in np.flatnonzero(minor).tolist():
            fits = (l != l[i]) & (100 * np.minimum(n, n[i]) >= percent * np.maximum(n, n[i])) & (~minor | (c > c[i]))
            if cross:
                fits &= block != block[i]
            near = np.flatnonzero(fits)
            if not len(near):
                continue
            apart = np.bitwise_count(parity[near] ^ parity[i]).sum(axis=1, dtype=np.int64)
            good = apart <= (n[near] + n[i]) * (100 - percent) // (100 + percent)
            near, apart = near[good], apart[good]
            good = np.bitwise_count(samples[near] ^ samples[i]).sum(axis=1, dtype=np.int64) <= limit
            near, apart = near[good], apart[good]
            for j in near[np.argsort(apart, kind="stable")].tolist():
                a, b = find(int(l[i])), find(int(l[j]))
                if a != b:
                    root[max(a, b)] = min(a, b)
                    out.append((c[i], c[j]))
        return out

    def link(rows: pd.DataFrame) -> pd.DataFrame:
        key, t0, t1 = (rows[k].to_numpy() for k in ("key", "t0", "t1"))
        order = np.lexsort([rows["c"].to_numpy(), t1, t0, key])
        key, t0, t1 = key[order], t0[order], t1[order]
        c, l, minor, n, block = (rows[k].to_numpy()[order] for k in ("c", "l", "minor", "n", "block"))
        parity, samples = (np.stack(rows[k].to_numpy()[order]).astype(np.int64).view(np.uint64) for k in ("parity", "samples"))
        cuts = np.flatnonzero((key[1:] != key[:-1]) | (t0[1:] != t0[:-1]) | (t1[1:] != t1[:-1])) + 1
        out = []
        for at, to in zip([0, *cuts.tolist()], [*cuts.tolist(), len(key)]):
            part = slice(at, to)
            out += one(c[part], l[part], minor[part], n[part], block[part], t0[at] != t1[at], parity[part], samples[part])
        return pd.DataFrame(out, columns=["x", "y"]).astype("int64")

    return link


class _Run:
    """The tables that the rounds of one run share."""

    def __init__(self, docs: DataFrame, percent: int, broadcast_rows: int):
        self.docs, self.percent, self.broadcast_rows = docs, percent, broadcast_rows
        self.rows = materialise(signatures(docs, bands(percent)), "signatures")
        live = self.rows.where("n > 0")
        heads = live.groupBy("n", "s1", "s2").agg(F.min("row").alias("c"), F.min("doc_id").alias("lowest"), F.count(F.lit(1)).alias("copies"))
        self.names = materialise(heads, "classes")
        own = self.names.select("c")
        self.classes = materialise(live.join(own, live["row"] == own["c"]).select("c", "doc_id", "n", "s1", "s2", "keys", "samples", "parity"), "class-signatures")

    def near(self, x: str = "x", y: str = "y"):
        """Sketch bounds on columns x.n, x.samples, x.parity and those of y."""
        most = F.floor((F.col(f"{x}.n") + F.col(f"{y}.n")) * (100 - self.percent) / (100 + self.percent))
        sizes = 100 * F.least(f"{x}.n", f"{y}.n") >= self.percent * F.greatest(f"{x}.n", f"{y}.n")
        close = _differing(f"{x}.parity", f"{y}.parity", SET_BITS // 64) <= most
        alike = _differing(f"{x}.samples", f"{y}.samples", SAMPLE_BITS // 64) <= sample_limit(self.percent / 100, bands(self.percent) * ROWS)
        return sizes & close & alike

    def confirm(self, pairs: DataFrame, tag: str) -> DataFrame:
        """The pairs (x, y) whose full sets are similar enough."""
        pairs = materialise(pairs, f"{tag}-pairs")
        ends = pairs.select(F.col("x").alias("c")).unionByName(pairs.select(F.col("y").alias("c"))).distinct()
        sets = materialise(sets_of(self.docs, ends.join(self.classes.select("c", "doc_id", "n", "s1", "s2"), "c"), self.broadcast_rows), f"{tag}-sets")
        left, right = sets.select(F.col("c").alias("x"), F.col("set").alias("sx")), sets.select(F.col("c").alias("y"), F.col("set").alias("sy"))
        both = F.size(F.array_intersect("sx", "sy"))
        joined = pairs.join(left, "x").join(right, "y")
        return materialise(joined.where(100 * both >= self.percent * (F.size("sx") + F.size("sy") - both)).select("x", "y"), f"{tag}-links")


def components(links: DataFrame, tag: str = "labels") -> DataFrame:
    """v, l: smallest vertex of the component, for every vertex of the links (x, y).

    Smallest-neighbour labels with pointer jumping; each round is written, so lineage
    stays short and a lost executor costs one round at most.
    """
    both = links.select(F.col("x").alias("v"), F.col("y").alias("u")).unionByName(links.select(F.col("y").alias("v"), F.col("x").alias("u")))
    labels = materialise(both.groupBy("v").agg(F.least(F.col("v"), F.min("u")).alias("l")), tag)
    while True:
        near = both.join(labels.select(F.col("v").alias("u"), F.col("l").alias("lu")), "u").groupBy("v").agg(F.min("lu").alias("near"))
        lower = labels.join(near, "v").select("v", F.least("l", "near").alias("m"), F.col("l").alias("old"))
        jump = labels.select(F.col("v").alias("m"), F.col("l").alias("lm"))
        after = materialise(lower.join(jump, "m", "left").select("v", F.least(F.col("m"), F.coalesce("lm", "m")).alias("l"), "old"), tag)
        changed = after.where("l <> old").limit(1).count()
        labels = after.select("v", "l")
        if not changed:
            return labels


def near_copies(docs: DataFrame, percent: int = 85, broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """Per row of docs (doc_id, text): row, doc_id, k (hash of the text),
    n_shingles, component_id, class_id, kept."""
    run = _Run(docs, percent, broadcast_rows)
    sketch = run.classes.select("c", F.struct("n", "samples", "parity").alias("k"))
    members = run.classes.select(F.posexplode("keys").alias("band", "key"), "c")
    shared = members.groupBy("key").agg(F.min("c").alias("pivot"), F.count(F.lit(1)).alias("m")).where("m > 1")
    shared = materialise(shared, "shared")
    buckets = materialise(hot_join(members, shared, "key", "m").drop("m"), "buckets")

    def with_sketches(pairs: DataFrame) -> DataFrame:
        """The pairs (x, y) that the sketches leave."""
        a = sketch.select(F.col("c").alias("x"), F.col("k").alias("kx"))
        b = sketch.select(F.col("c").alias("y"), F.col("k").alias("ky"))
        return pairs.join(a, "x").join(b, "y").where(run.near("kx", "ky")).select("x", "y")

    def label(frame: DataFrame, known: DataFrame, vertex: str, out: str) -> DataFrame:
        named = known.select(F.col("v").alias(vertex), F.col("l").alias("_l"))
        return frame.join(named, vertex, "left").withColumn(out, F.coalesce("_l", vertex)).drop("_l")

    def unsettled(known: DataFrame, first: int) -> DataFrame:
        """key, c, l, major, m, k of all members of buckets with several components; major is
        the bucket's largest one, m all its members, minors those of its others, k sketches."""
        placed = materialise(label(buckets.where(F.col("band") < first).select("key", "c"), known, "c", "l"), "placed")
        each = placed.groupBy("key", "l").agg(F.count(F.lit(1)).alias("m"))
        mixed = each.groupBy("key").agg(F.max_by("l", F.struct("m", "l")).alias("major"), F.count(F.lit(1)).alias("parts"), F.sum("m").alias("m"), F.max("m").alias("most")).where("parts > 1")
        mixed = materialise(mixed.select("key", "major", "m", (F.col("m") - F.col("most")).alias("minors")), "mixed")
        return hot_join(placed, mixed, "key", "m").join(sketch, "c")

    stars = buckets.where("c <> pivot").groupBy("c").agg(F.min("pivot").alias("y")).select(F.col("c").alias("x"), "y")
    links = run.confirm(with_sketches(stars), "star")
    labels = components(links)

    for first in (TILE_BANDS, bands(percent)):
        open_ = materialise(unsettled(labels, first), "open-buckets")
        blocks = F.ceil(F.col("m") / TILE).cast("int")
        block = F.pmod(F.xxhash64("c"), blocks).cast("int")
        rows = open_.agg(F.sum(blocks)).first()[0] or 0
        tasks = min(-(-rows // TASK_ROWS), MOST_TASKS) or 1
        tiles = open_.select("key", "c", "l", (F.col("l") != F.col("major")).alias("minor"), "k.*", block.alias("block"), F.explode(F.sequence(F.lit(0), blocks - 1)).alias("other"))
        tiles = tiles.withColumns({"t0": F.least("block", "other"), "t1": F.greatest("block", "other")}).drop("other")
        dealt = tiles.withColumn("task", F.pmod(F.xxhash64("key", "t0", "t1"), F.lit(tasks))).repartition(tasks, "task")
        found = dealt.groupBy("task").applyInPandas(_tiles(percent), "x long, y long")
        links = materialise(links.unionByName(run.confirm(found.distinct(), "tile")), "links")
        labels = components(links)

    # what is left meets in tiles too: members outside the largest component against all
    open_ = materialise(unsettled(labels, bands(percent)), "open-buckets")
    tile = lambda n, salt: (F.ceil(F.col(n) / TILE).cast("int"), F.pmod(F.xxhash64("c", F.lit(salt)), F.ceil(F.col(n) / TILE).cast("int")).cast("int"))
    (bx, px), (by, py) = tile("minors", 1), tile("m", 2)
    x = open_.where("l <> major").select("key", F.col("c").alias("x"), F.col("l").alias("lx"), F.col("k").alias("kx"), "major", px.alias("px"), F.explode(F.sequence(F.lit(0), by - 1)).alias("py"))
    y = open_.select(F.col("key").alias("key_y"), F.col("c").alias("y"), F.col("l").alias("ly"), F.col("k").alias("ky"), py.alias("py_y"), F.explode(F.sequence(F.lit(0), bx - 1)).alias("px_y"))
    once = (F.col("ly") == F.col("major")) | (F.col("x") < F.col("y"))
    meet = (F.col("key") == F.col("key_y")) & (F.col("px") == F.col("px_y")) & (F.col("py") == F.col("py_y")) & (F.col("lx") != F.col("ly")) & once & run.near("kx", "ky")
    tested = links.unionByName(links.select(F.col("y").alias("x"), F.col("x").alias("y")))
    last = run.confirm(x.join(y, meet).select("x", "y").distinct().join(tested, ["x", "y"], "left_anti"), "rest")
    if last.limit(1).count():
        links = materialise(links.unionByName(last), "links")
        labels = components(links)

    named = label(run.names, labels, "c", "l")
    lowest = named.groupBy("l").agg(F.min("lowest").alias("component_id"))
    name = F.struct("n", "s1", "s2").alias("name")
    named = materialise(named.join(lowest, "l").select(name, F.col("l").alias("class_id"), "component_id", "copies"), "membership")
    rows = run.rows.select("row", "doc_id", "k", name)
    found = hot_join(rows.where("name.n > 0"), named, "name", "copies").drop("copies")
    alone = rows.where("name.n = 0").select("*", F.lit(None).cast("long").alias("class_id"), F.col("doc_id").alias("component_id"))
    out = found.unionByName(alone)
    return out.select("row", "doc_id", "k", F.col("name.n").alias("n_shingles"), "component_id", "class_id", F.col("component_id").eqNullSafe(F.col("doc_id")).alias("kept"))


def drop_near_copies(docs: DataFrame, percent: int = 85) -> DataFrame:
    """docs with one row of each component, with all columns.

    The row with the smallest doc_id stays (null is the largest; of rows with that doc_id the
    one with the smallest hash of its text); of rows that agree in doc_id and text one stays,
    which one is open.  Texts without words are in no component and all stay.
    """
    linked = materialise(near_copies(docs, percent).where("n_shingles > 0").select("class_id", F.struct(F.col("doc_id").isNull().alias("absent"), "doc_id", "k").alias("name")), "linked")
    rows = linked.groupBy("class_id", "name").agg(F.count(F.lit(1)).alias("m"))
    rows = materialise(rows, "linked-names")
    heads = rows.groupBy("class_id").agg(F.min("name").alias("head"), F.count(F.lit(1)).alias("names")).where("names > 1")
    away = hot_join(rows.select("class_id", "name"), materialise(heads, "heads"), "class_id", "names").where("name <> head").select("name.*")
    twice = rows.where("m > 1").select("name.*")

    def matching(keys: DataFrame, tag: str):
        keys = bounded(materialise(keys.distinct(), tag), BROADCAST_ROWS)
        return keys, lambda frame: frame["doc_id"].eqNullSafe(keys["doc_id"]) & (F.xxhash64(frame["text"]) == keys["k"])

    gone, same = matching(away, "gone")
    left = docs.join(gone, same(docs), "left_anti")
    again, same = matching(twice, "twice")
    if not again.limit(1).count():
        return left
    once = left.join(again, same(docs), "left_anti")
    text = F.struct("doc_id", F.xxhash64("text"))
    first = left.join(again, same(docs), "left_semi").groupBy(text.alias("key")).agg(F.first(F.struct(*[F.col(f"`{c}`") for c in docs.columns])).alias("one"))
    return once.unionByName(first.select("one.*"))
