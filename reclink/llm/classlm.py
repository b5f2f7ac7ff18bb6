"""Language-model scoring with Brown classes: P(w | v) = P(class w | class v) P(w | class w).

Everything is counted over all training texts:

* every word's count, in a table that is written and never collected;
* counts of neighbouring *items*.  An item is one of the `items` most frequent words or,
  for all other words, one of the ending groups by a word's last two bytes.  Exchange
  clustering moves items between `classes` classes as long as the likelihood of the class
  bigrams grows;
* for every other word, however rare, how often each class stands before and after it.
  Each goes, apart from the others, to the class where the same likelihood grows most for
  a word that is a small part of its class;
* transitions between the classes that the words have in the end.

So each word of the training texts has a class by its own neighbours, and an ending group's
class is left to words that were never seen.  Counts and classes of frequent words come
from a table of at most `frequent` words that goes with the tasks; those of all others are
joined by a shuffle, where none of them is frequent, and the places next to them are
counted or scored after it.  The result is the same for every size of that table.

Tokens are lower-cased words and one end per text.  Null and empty texts have the end
alone.  Repeated rows and equal doc_ids are scored row by row.  Without training texts all
counts are zero.  Empty tables give no rows; further columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from reclink.llm._common import SpanHasher, materialise, text_steps, tidy, word_spans

ITEMS, ENDINGS, CLASSES, FREQUENT = 2048, 511, 64, 1 << 18
ADD, BACK = 0.5, 5.0
#: What stands for the end of a text among word hashes.
END = np.uint64(0x9E3779B97F4A7C15)
_LOWER = np.arange(256, dtype=np.int64)
_LOWER[65:91] = _LOWER[97:123]


def _ending(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Group of each word by its last two bytes (a one-byte word: that byte twice)."""
    last, before = _LOWER[data[ends - 1]], _LOWER[data[np.maximum(ends - 2, starts)]]
    return ((last * 257 + before) * 2654435761 % (1 << 32)) % ENDINGS


# ---------------------------------------------------------------- counting
def count_words(texts: DataFrame) -> DataFrame:
    """h (hash), g (ending group; -1 for the end token), c (count) of every word."""

    def count(batches):
        hasher = SpanHasher(31)
        for batch in batches:
            hashes, groups = [], []
            for _, _, data, offsets in text_steps(batch.column(0)):
                starts, ends, _ = word_spans(data, offsets)
                hashes.append(hasher.spans(data, starts, ends))
                groups.append(_ending(data, starts, ends).astype(np.int16) if len(starts) else np.zeros(0, np.int16))
            if batch.num_rows:
                h, at, c = np.unique(np.concatenate(hashes), return_index=True, return_counts=True)
                g = np.concatenate(groups)[at]
                h, g, c = np.append(h, END), np.append(g, -1), np.append(c, batch.num_rows)
                yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(g.astype(np.int16)), pa.array(c)], names=["h", "g", "c"])

    return texts.select("text").mapInArrow(tidy(count), "h long, g short, c long").groupBy("h").agg(F.first("g").alias("g"), F.sum("c").alias("c"))


def most_frequent(words: DataFrame, most: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """(h, k, c) of all words counted more than a limit, sorted by h, and that limit: the
    smallest that leaves at most `most` words.  Found from a histogram of fixed length."""
    scale = 64
    level = F.floor(F.log2("c") * scale)
    histogram = words.where("g >= 0").groupBy(level.alias("b")).agg(F.count(F.lit(1)).alias("n"), F.max("c").alias("top")).collect()
    left, limit = most, 0
    for row in sorted(histogram, key=lambda r: -r["b"]):
        left -= row["n"]
        if left < 0:
            limit = row["top"]
            break
    table = words.where((F.col("g") >= 0) & (F.col("c") > limit)).select("h", "k", "c").toArrow()
    h = table["h"].to_numpy().view(np.uint64)
    order = np.argsort(h)
    return h[order], table["k"].to_numpy()[order].astype(np.int64), table["c"].to_numpy()[order], int(limit)


class Spots:
    """Places of hashes in a sorted array: by a table of their leading bits, and by search where
    several of the array share these."""

    def __init__(self, hashes: np.ndarray):
        self.hashes = hashes
        bits = max(8, len(hashes).bit_length() + 2)
        self.shift = np.uint64(64 - bits)
        lead = (hashes >> self.shift).astype(np.int64)
        self.first, self.shared = np.zeros(1 << bits, np.int32), np.zeros(1 << bits, bool)
        self.first[lead[::-1]] = np.arange(len(hashes))[::-1]
        self.shared[lead[1:][lead[1:] == lead[:-1]]] = True

    def of(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(place, found or not) of each h."""
        if not len(self.hashes) or not len(h):
            return np.zeros(len(h), np.int64), np.zeros(len(h), bool)
        lead = (h >> self.shift).astype(np.int64)
        spot = self.first[lead].astype(np.int64)
        hit = self.hashes[spot] == h
        at = np.flatnonzero(self.shared[lead] & ~hit)
        spot[at] = np.minimum(np.searchsorted(self.hashes, h[at]), len(self.hashes) - 1)
        hit[at] = self.hashes[spot[at]] == h[at]
        return spot, hit


class Items:
    """Words to items: 0..n-1 frequent words by hash, then ending groups, then the end."""

    def __init__(self, hashes: np.ndarray):
        self.hashes = np.sort(hashes)
        self.spots = Spots(self.hashes)
        self.first_group = len(self.hashes)
        self.end = self.first_group + ENDINGS
        self.size = self.end + 1

    def of(self, h: np.ndarray, groups: np.ndarray) -> np.ndarray:
        at, hit = self.spots.of(h)
        return np.where(hit, at, groups + self.first_group)

    def sequence(self, data: np.ndarray, offsets: np.ndarray, hasher: SpanHasher):
        """Items and word hashes, with one end after each text."""
        starts, ends, first = word_spans(data, offsets)
        h = hasher.spans(data, starts, ends)
        words = self.of(h, _ending(data, starts, ends)) if len(starts) else np.zeros(0, np.int64)
        return np.insert(words, first[1:], self.end), np.insert(h, first[1:], END)


def count_pairs(texts: DataFrame, items: Items) -> np.ndarray:
    """Matrix of neighbouring items over all texts; before a text stands an end.  Tasks count
    the pairs they see; only the matrix, whose size is that of the items, comes to the driver."""
    size = items.size

    def count(batches):
        hasher = SpanHasher(31)
        for batch in batches:
            for _, _, data, offsets in text_steps(batch.column(0)):
                line, _ = items.sequence(data, offsets, hasher)
                before = np.concatenate([[items.end], line[:-1]])
                cells, c = np.unique(before * size + line, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(cells), pa.array(c)], names=["cell", "c"])

    table = texts.select("text").mapInArrow(tidy(count), "cell long, c long").groupBy("cell").agg(F.sum("c").alias("c")).toArrow()
    out = np.zeros(size * size, np.int64)
    out[table["cell"].to_numpy()] = table["c"].to_numpy()
    return out.reshape(size, size)


# ---------------------------------------------------------------- clustering
def _xlogx(x: np.ndarray) -> np.ndarray:
    return x * np.log(np.maximum(x, 1e-300))


def exchange(pairs: np.ndarray, classes: int = CLASSES, rounds: int = 4) -> np.ndarray:
    """Class of each item by exchange clustering of the item matrix.

    Items start dealt by frequency; each round takes every item out of its class and puts
    it where the sum of N log N over class pairs, less that over classes, grows most.  The
    last item (the end) keeps a class of its own.
    """
    n = len(pairs) - 1
    counts = pairs.astype(np.float64)
    weight = counts.sum(axis=0)
    order = np.argsort(-weight[:n], kind="stable")
    member = np.empty(n + 1, np.int64)
    member[order] = np.arange(n) % (classes - 1)
    member[n] = classes - 1
    one = np.eye(classes)[member]
    a = one.T @ counts @ one
    for _ in range(rounds):
        moved = 0
        for w in order:
            if weight[w] == 0:
                break
            old, own = member[w], counts[w, w]
            out = np.bincount(member, counts[w], classes)
            into = np.bincount(member, counts[:, w], classes)
            out[old] -= own
            into[old] -= own
            a[old] -= out
            a[:, old] -= into
            a[old, old] -= own
            # class totals with the item's neighbours in them, wherever the item goes
            rows, columns = a.sum(axis=1) + into, a.sum(axis=0) + out
            now = _xlogx(a)
            gain = (_xlogx(a + out) - now).sum(axis=1) + (_xlogx(a + into[:, None]) - now).sum(axis=0)
            d = np.arange(classes)
            gain += _xlogx(a[d, d] + out + into + own) - _xlogx(a[d, d] + out) - _xlogx(a[d, d] + into) + now[d, d]
            gain -= _xlogx(rows + out.sum() + own) - _xlogx(rows) + _xlogx(columns + into.sum() + own) - _xlogx(columns)
            gain[classes - 1] = -np.inf
            new = int(gain.argmax())
            a[new] += out
            a[:, new] += into
            a[new, new] += own
            member[w] = new
            moved += new != old
        if not moved:
            break
    return member


def count_contexts(texts: DataFrame, items: Items, member: np.ndarray, classes: int) -> DataFrame:
    """h and cells of every word that is no item.  A cell counts a class after the word (from
    0), before it (from `classes`), or the word next to itself (2 * classes), so a word has
    at most 2 * classes + 1 cells."""
    width = 2 * classes + 1

    def count(batches):
        hasher = SpanHasher(31)
        for batch in batches:
            words, cells = [], []
            for _, _, data, offsets in text_steps(batch.column(0)):
                line, h = items.sequence(data, offsets, hasher)
                kind = member[line]
                at = np.flatnonzero((line >= items.first_group) & (line < items.end))
                follower = np.append(h[1:], END)[at] == h[at]
                leader = np.concatenate([[END], h[:-1]])[at] == h[at]
                after = np.where(follower, 2 * classes, np.append(kind[1:], classes - 1)[at])
                before = np.concatenate([[classes - 1], kind[:-1]])[at] + classes
                words += [h[at], h[at[~leader]]]
                cells += [after, before[~leader]]
            if not words:
                continue
            distinct, place = np.unique(np.concatenate(words), return_inverse=True)
            key, c = np.unique(place * width + np.concatenate(cells), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(distinct[key // width].view(np.int64)), pa.array((key % width).astype(np.int32)), pa.array(c)], names=["h", "cell", "c"])

    each = texts.select("text").mapInArrow(tidy(count), "h long, cell int, c long").groupBy("h", "cell").agg(F.sum("c").alias("c"))
    return each.groupBy("h").agg(F.collect_list(F.struct("cell", "c")).alias("cells"))


def context_gains(a: np.ndarray, back: float = BACK) -> np.ndarray:
    """Per cell of `count_contexts` and class: what one occurrence adds to the sum of N log N
    over class pairs, less that over classes, where a word is a small part of its class."""
    classes = len(a)
    rows, columns = a.sum(axis=1), a.sum(axis=0)
    before, after = ((x + ADD) / (x.sum() + ADD * classes) for x in (rows, columns))
    out = np.log((a + back * after) / (rows[:, None] + back))
    into = np.log((a + back * before[:, None]) / (columns + back))
    own = out.diagonal() - np.log(columns + back)
    gains = np.vstack([out.T, into, own])
    gains[:, classes - 1] = -np.inf
    return gains


def place(contexts: DataFrame, a: np.ndarray, block: int = 8192) -> DataFrame:
    """h, k (class) of every word of `count_contexts`: the class of the largest gain."""
    gains = context_gains(a)

    def choose(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, block):
                part = batch.slice(at, block)
                flat, first = part.column(1).flatten(), np.cumsum(part.column(1).value_lengths().to_numpy())
                each = gains[flat.field(0).to_numpy()] * flat.field(1).to_numpy()[:, None]
                best = np.add.reduceat(each, np.concatenate([[0], first[:-1]]), axis=0).argmax(axis=1)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(best.astype(np.int16))], names=["h", "k"])

    return contexts.mapInArrow(tidy(choose), "h long, k short")


# ---------------------------------------------------------------- texts as classes
class Lines:
    """Texts to classes, as far as the table of frequent words goes.  A word that is not in
    it is open unless the table is complete; until then it has its ending group's class."""

    def __init__(self, sent: dict):
        self.__dict__.update(sent)
        self.hasher, self.spots = SpanHasher(31), Spots(self.hashes)

    def read(self, data: np.ndarray, offsets: np.ndarray):
        """(class, open or not, row of distinct open words or -1; all with one end after each
        text), words of each text, (spot, hit) in the table of each word, and the distinct
        open words of the texts: first of each text, hash, class for now, times."""
        starts, ends, first = word_spans(data, offsets)
        h, words, rows = self.hasher.spans(data, starts, ends), np.diff(first), len(offsets) - 1
        groups = _ending(data, starts, ends) if len(starts) else np.zeros(0, np.int64)
        spot, hit = self.spots.of(h)
        kind = self.endings[groups]
        kind[hit] = self.kinds[spot[hit]]
        free = np.zeros(len(h), bool) if self.complete else ~hit
        at = np.flatnonzero(free)
        text = np.repeat(np.arange(rows), words)[at]
        order = np.lexsort([h[at], text])
        st, sh = text[order], h[at][order]
        new = np.ones(len(at), bool)
        new[1:] = (st[1:] != st[:-1]) | (sh[1:] != sh[:-1])
        heads = np.flatnonzero(new)
        cuts = np.searchsorted(st[heads], np.arange(rows + 1))
        number = np.full(len(h), -1)
        number[at[order]] = np.cumsum(new) - 1 - cuts[st]
        distinct = cuts, sh[heads], kind[at][order][heads], np.diff(np.append(heads, len(at)))
        put = lambda x, end: np.insert(x, first[1:], end)
        return put(kind, self.end), put(free, False), put(number, -1), words, spot, hit, distinct

    def links(self, kind: np.ndarray, free: np.ndarray, number: np.ndarray, words: np.ndarray):
        """(before, closed, left, right, cuts): the class before each place, whether both are
        known, and of the other places both ends, as a class or -1 - number."""
        before = np.concatenate([[self.end], kind[:-1]])
        closed = ~(free | np.concatenate([[False], free[:-1]]))
        code = np.where(free, -1 - number, kind)
        at = np.flatnonzero(~closed)
        left = np.concatenate([[self.end], code[:-1]])[at]
        cuts = np.searchsorted(at, np.concatenate([[0], np.cumsum(words + 1)]))
        return before, closed, left, code[at], cuts


def _lists(cuts: np.ndarray, values: np.ndarray, kind) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(cuts.astype(np.int32)), pa.array(values.astype(kind)))


def _settled(rows: DataFrame, rare: DataFrame, *columns: str) -> DataFrame:
    """row, columns, and k and c (class, count) of each of the row's open words h, in order;
    words that `rare` lacks keep their class e and count nothing."""
    each = rows.where(F.size("h") > 0).select("row", F.posexplode(F.arrays_zip("h", "e")).alias("i", "p")).select("row", "i", F.col("p.h").alias("h"), F.col("p.e").alias("e"))
    named = each.join(rare, "h", "left").select("row", F.struct("i", F.coalesce("k", "e").alias("k"), F.coalesce("c", F.lit(0)).alias("c")).alias("s"))
    found = named.groupBy("row").agg(F.array_sort(F.collect_list("s")).alias("s"))
    return rows.where(F.size("h") > 0).join(found, "row").select("row", *columns, F.col("s.k").alias("k"), F.col("s.c").alias("c"))


def _ends(batch, left: int, right: int, kinds: int) -> tuple[np.ndarray, np.ndarray]:
    """Classes at both ends of a batch's links; kinds is the column of the open words'."""
    lists = batch.column(kinds)
    flat = lists.flatten().to_numpy().astype(np.int64)
    first = np.concatenate([[0], np.cumsum(lists.value_lengths().to_numpy())])[:-1]
    start = np.repeat(first, batch.column(left).value_lengths().to_numpy())
    codes = (batch.column(j).flatten().to_numpy().astype(np.int64) for j in (left, right))
    return tuple(np.where(x < 0, flat[np.where(x < 0, start - 1 - x, 0)], x) for x in codes)


def count_classes(texts: DataFrame, model: Model) -> np.ndarray:
    """Matrix of neighbouring classes over all texts; before a text stands an end."""
    sent, classes = texts.sparkSession.sparkContext.broadcast(model.portable()), model.classes

    def count(batches):
        from pyspark import TaskContext

        lines, total = Lines(sent.value), np.zeros(classes * classes, np.int64)
        row = TaskContext.get().partitionId() << 40
        blank = lambda n: pa.nulls(n, pa.int64())
        names = ["row", "cell", "n", "h", "e", "left", "right"]
        for batch in batches:
            for at, to, data, offsets in text_steps(batch.column(0)):
                kind, free, number, words, _, _, (cuts, h, e, _) = lines.read(data, offsets)
                before, closed, left, right, ends = lines.links(kind, free, number, words)
                total += np.bincount((before * classes + kind)[closed], minlength=classes * classes)
                if len(h):
                    n = to - at
                    arrays = [pa.array(np.arange(row, row + n)), blank(n), blank(n), _lists(cuts, h.view(np.int64), np.int64), _lists(cuts, e, np.int16), _lists(ends, left, np.int32), _lists(ends, right, np.int32)]
                    yield pa.RecordBatch.from_arrays(arrays, names=names).filter(pa.array(np.diff(cuts) > 0))
                    row += n
        cells = np.flatnonzero(total)
        none = [pa.nulls(len(cells), pa.list_(t)) for t in (pa.int64(), pa.int16(), pa.int32(), pa.int32())]
        yield pa.RecordBatch.from_arrays([blank(len(cells)), pa.array(cells), pa.array(total[cells]), *none], names=names)

    def resolve(batches):
        total = np.zeros(classes * classes, np.int64)
        for batch in batches:
            left, right = _ends(batch, 0, 1, 2)
            total += np.bincount(left * classes + right, minlength=classes * classes)
        cells = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(cells), pa.array(total[cells])], names=["cell", "n"])

    rows = materialise(texts.select("text").mapInArrow(tidy(count), "row long, cell long, n long, h array<long>, e array<short>, left array<int>, right array<int>"), "class-lines")
    cells = rows.where("cell IS NOT NULL").select("cell", "n")
    if not model.complete:
        settled = _settled(rows.where("cell IS NULL"), model.rare, "left", "right")
        cells = cells.unionByName(settled.select("left", "right", "k").mapInArrow(tidy(resolve), "cell long, n long"))
    table = cells.groupBy("cell").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(classes * classes, np.int64)
    out[table["cell"].to_numpy()] = table["n"].to_numpy()
    return out.reshape(classes, classes)


# ---------------------------------------------------------------- the model
class Model:
    """Class transitions, class totals, and counts and classes of words: of the frequent ones
    in arrays, of all others in the table `rare`."""

    def __init__(self, texts: DataFrame, frequent: int = FREQUENT, items: int = ITEMS, classes: int = CLASSES):
        self.classes, self.end = classes, classes - 1
        counts = materialise(count_words(texts), "word-counts")
        top = counts.where("g >= 0").orderBy(F.desc("c"), "h").select("h").limit(items).toArrow()["h"].to_numpy().view(np.uint64)
        self.items = Items(top)
        pairs = count_pairs(texts, self.items)
        member = exchange(pairs, classes)
        self.endings = member[self.items.first_group : self.items.end]
        one = np.eye(classes)[member]
        placed = place(count_contexts(texts, self.items, member, classes), one.T @ pairs @ one)
        rows = [(int(h), int(k)) for h, k in zip(self.items.hashes.view(np.int64), member)]
        fixed = texts.sparkSession.createDataFrame([*rows, (int(END.view(np.int64)), self.end)], "h long, k short")
        self.words = materialise(counts.join(placed.unionByName(fixed), "h"), "word-classes")
        v, n = np.zeros(classes), np.zeros(classes)
        for row in self.words.groupBy("k").agg(F.count(F.lit(1)).alias("v"), F.sum("c").alias("n")).collect():
            v[row["k"]], n[row["k"]] = row["v"], row["n"]
        self.tokens, self.distinct, self.end_count = int(n.sum()), int(v.sum()), int(n[self.end])
        self.hashes, self.kinds, self.counts, self.limit = most_frequent(self.words, frequent)
        self.complete = self.limit == 0
        self.rare = self.words.where((F.col("g") >= 0) & (F.col("c") <= self.limit)).select("h", "c", "k")
        a = count_classes(texts, self)
        self.emission = np.log10(n + ADD * (v + 1))
        share = (n + ADD) / (n.sum() + ADD * classes)
        self.transition = np.log10((a + BACK * share) / (a.sum(axis=1, keepdims=True) + BACK))
        self.base = np.log10(self.tokens + ADD * (self.distinct + 1))

    def portable(self) -> dict:
        names = ("hashes", "kinds", "counts", "endings", "end", "complete", "end_count", "emission", "transition", "base")
        return {k: getattr(self, k) for k in names if hasattr(self, k)}


_ROWS = "row long, doc_id long, mark boolean, n_tokens long, known long, base double, score double, h array<long>, e array<short>, n array<int>, left array<int>, right array<int>"


def score(docs: DataFrame, model: Model, mark: Column | None = None) -> DataFrame:
    """Per row of docs (doc_id, text): doc_id, mark (carried along), n_tokens, n_known,
    base_score, score and perplexity."""
    sent = docs.sparkSession.sparkContext.broadcast(model.portable())

    def apply(batches):
        from pyspark import TaskContext

        m, lines = sent.value, Lines(sent.value)
        row = TaskContext.get().partitionId() << 40
        logs = np.log10(m["counts"] + ADD)
        end_log, end_known = np.log10(m["end_count"] + ADD), int(m["end_count"] > 0)
        for batch in batches:
            for at, to, data, offsets in text_steps(batch.column(2), 2 << 20):
                kind, free, number, words, spot, hit, (cuts, h, e, times) = lines.read(data, offsets)
                before, closed, left, right, ends = lines.links(kind, free, number, words)
                model_log = np.where(closed, m["transition"][before, kind], 0) - np.where(free, 0, m["emission"][kind])
                sums = np.concatenate([[0], np.cumsum(model_log)])
                score = np.diff(sums[np.concatenate([[0], np.cumsum(words + 1)])])
                log = np.zeros(len(hit))
                log[hit] = logs[spot[hit]]
                edge = np.concatenate([[0], np.cumsum(words)])
                total = lambda x: np.diff(np.concatenate([[0], np.cumsum(x)])[edge])
                unseen = total(~hit & m["complete"]) * np.log10(ADD)
                shared = total(log) + unseen + end_log
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(np.arange(row, row + to - at)), batch.column(0).slice(at, to - at), batch.column(1).slice(at, to - at), pa.array(words + 1),
                        pa.array(total(hit).astype(np.int64) + end_known), pa.array(shared - m["base"] * (words + 1)), pa.array(shared + score),
                        _lists(cuts, h.view(np.int64), np.int64), _lists(cuts, e, np.int16), _lists(cuts, times, np.int32), _lists(ends, left, np.int32), _lists(ends, right, np.int32),
                    ],
                    names=["row", "doc_id", "mark", "n_tokens", "known", "base", "score", "h", "e", "n", "left", "right"],
                )
                row += to - at

    def resolve(batches):
        m = sent.value
        for batch in batches:
            kinds, counts, times = (batch.column(j).flatten().to_numpy().astype(np.int64) for j in (4, 5, 3))
            before, kind = _ends(batch, 1, 2, 4)
            part = lambda x, j: np.diff(np.concatenate([[0], np.cumsum(x)])[np.concatenate([[0], np.cumsum(batch.column(j).value_lengths().to_numpy())])])
            log = part(times * np.log10(counts + ADD), 4)
            more = log + part(m["transition"][before, kind], 1) - part(times * m["emission"][kinds], 4)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(log), pa.array(more), pa.array(part(np.where(counts > 0, times, 0), 4))], names=["row", "log", "more", "seen"])

    mark = F.lit(None).cast("boolean") if mark is None else mark
    rows = materialise(docs.select(F.col("doc_id").cast("long").alias("doc_id"), mark.alias("mark"), "text").mapInArrow(tidy(apply), _ROWS), "scored")
    found = _settled(rows, model.rare, "left", "right", "n").mapInArrow(tidy(resolve), "row long, log double, more double, seen long")
    joined = rows.drop("h", "e", "n", "left", "right").join(found, "row", "left")
    total = F.col("score") + F.coalesce("more", F.lit(0.0))
    return joined.select(
        "doc_id", "mark", "n_tokens", (F.col("known") + F.coalesce("seen", F.lit(0))).cast("long").alias("n_known"), F.lit(model.tokens).cast("long").alias("train_tokens"),
        (F.col("base") + F.coalesce("log", F.lit(0.0))).alias("base_score"), total.alias("score"), F.pow(F.lit(10.0), -total / F.col("n_tokens")).alias("perplexity"),
    )
