"""Best-fit packing by a grouping genetic algorithm.

Texts become token ids plus an end id.  A text longer than the sequence is cut so that
every piece but the first fills a sequence by itself.  The remaining pieces are dealt over
groups of bounded size by a hash of their row.  Each group is packed by several islands, which
are Spark groups of their own:

* a packing is a list of bins; the first ones come from best fit in falling length and
  from best fit in disturbed orders;
* crossover injects whole well-filled bins of one parent into the other, drops the bins
  that then hold a piece twice, and best-fits the displaced pieces;
* after each epoch the populations are written, and the best packing of each island moves to
  the next island of its group.

A group whose best fit meets the bound (tokens over capacity, or pieces over half of it) has
a packing that nothing can better and is left as it is.  Between groups well-filled bins stay,
and the pieces of the others are dealt to joint groups and packed in the same way.  No task or
driver holds more than a group, whatever the size of the corpus.

Null and empty texts give one piece, the end id alone.  Repeated rows are packed each for
itself; sequence numbers are any distinct numbers, and of equally good packings that of the
first island counts.  An empty table gives no rows.  Further columns are ignored.
"""

from __future__ import annotations

import random
import zlib

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reclink.llm._common import materialise, text_steps, tidy, worker_cache
from reclink.llm._tokens import CACHE_CHUNKS, ChunkEncoder, tokenizer_path

CAPACITY = 2048
#: Pieces that are packed together.
GROUP_PIECES = 4096
WELL_FILLED = 0.995
#: Islands of a group, packings of an island, epochs between which elites move, and
#: generations of an epoch.
ISLANDS, SIZE, EPOCHS, GENERATIONS = 2, 4, 2, 10
MOST_TASKS = 50_000

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


# ---------------------------------------------------------------- one island
class BestFit:
    """Open bins by free space: stacks per free space and a bit mask of those in use."""

    def __init__(self, capacity: int, bins: list[list[int]], lengths: list[int]):
        self.capacity, self.lengths, self.bins = capacity, lengths, bins
        self.stacks: list[list[int]] = [[] for _ in range(capacity + 1)]
        self.mask = 0
        for k, one in enumerate(bins):
            self._file(k, capacity - sum(lengths[i] for i in one))

    def _file(self, k: int, free: int) -> None:
        if free:
            self.stacks[free].append(k)
            self.mask |= 1 << free

    def add(self, item: int) -> None:
        need = self.lengths[item]
        room = self.mask >> need
        if room:
            free = need + (room & -room).bit_length() - 1
            stack = self.stacks[free]
            k = stack.pop()
            if not stack:
                self.mask ^= 1 << free
        else:
            k, free = len(self.bins), self.capacity
            self.bins.append([])
        self.bins[k].append(item)
        self._file(k, free - need)


def best_fit(order: list[int], lengths: list[int], capacity: int, bins: list[list[int]] | None = None) -> list[list[int]]:
    packer = BestFit(capacity, bins or [], lengths)
    for item in order:
        packer.add(item)
    return packer.bins


def fitness(bins: list[list[int]], lengths: list[int], capacity: int) -> tuple[int, float]:
    """Fewer bins are better; among equals, unevenly filled ones."""
    return -len(bins), sum((sum(lengths[i] for i in one) / capacity) ** 2 for one in bins)


def crossover(receiver: list[list[int]], donor: list[list[int]], lengths: list[int], capacity: int, share: float, rng: random.Random) -> list[list[int]]:
    """Inject whole bins of the donor: of a drawn share of them those that are well filled, or
    else the fullest.  Bins of the receiver that hold one of their items go, and their other
    items are best-fitted in falling length."""
    drawn = rng.sample(donor, max(1, int(share * len(donor))))
    fill = [sum(lengths[i] for i in one) for one in drawn]
    full = [one for one, f in zip(drawn, fill) if f >= WELL_FILLED * capacity] or [drawn[fill.index(max(fill))]]
    injected = {i for one in full for i in one}
    kept, displaced = [list(one) for one in full], []
    for one in receiver:
        if injected.isdisjoint(one):
            kept.append(list(one))
        else:
            displaced += [i for i in one if i not in injected]
    displaced.sort(key=lambda i: -lengths[i])
    return best_fit(displaced, lengths, capacity, kept)


def least_bins(lengths: list[int], capacity: int) -> int:
    """Bins that any packing needs."""
    large = sum(2 * x > capacity for x in lengths)
    return max(-(-sum(lengths) // capacity), large)


def settle(lengths: list[int], capacity: int, size: int, rng: random.Random) -> list[list[list[int]]]:
    """A first population: best fit in falling length, and in disturbed orders."""
    people = [best_fit(sorted(range(len(lengths)), key=lambda i: -lengths[i]), lengths, capacity)]
    while len(people) < size:
        noise = [x * rng.uniform(0.8, 1.2) for x in lengths]
        people.append(best_fit(sorted(range(len(lengths)), key=lambda i: -noise[i]), lengths, capacity))
    return people


def epoch(people: list[list[list[int]]], lengths: list[int], capacity: int, generations: int, rng: random.Random) -> list[list[list[int]]]:
    """The population after so many generations, best first; the worst makes room for each
    child.  It stops where no packing can do with fewer bins."""
    score = lambda bins: fitness(bins, lengths, capacity)
    least, size = least_bins(lengths, capacity), len(people)
    ranked = sorted(((score(p), p) for p in people), key=lambda x: x[0], reverse=True)
    for _ in range(generations):
        if size < 2 or -ranked[0][0][0] == least:
            break
        # both parents are drawn in tournaments of two, each receives once
        a, b = (min(rng.sample(range(size), 2)) for _ in range(2))
        if a == b:
            b = (a + 1) % size
        for receiver, donor in ((a, b), (b, a)):
            child = crossover(ranked[receiver][1], ranked[donor][1], lengths, capacity, rng.choice((0.15, 0.3, 0.6)), rng)
            ranked.append((score(child), child))
        ranked.sort(key=lambda x: x[0], reverse=True)
        # of packings that are filled alike one stays
        ranked = [x for k, x in enumerate(ranked) if k == 0 or x[0] != ranked[k - 1][0]][:size] + [x for k, x in enumerate(ranked) if k and x[0] == ranked[k - 1][0]]
        ranked = ranked[:size]
    return [p for _, p in ranked]


def evolve(lengths: list[int], capacity: int = CAPACITY, islands: int = ISLANDS, size: int = SIZE, epochs: int = EPOCHS, generations: int = GENERATIONS, seed: int = 7) -> list[list[int]]:
    """What `pack` does with a group of items, in one process: islands evolve apart, and after
    each epoch the best packing of each joins the next one's population."""
    if not lengths:
        return []
    rngs = [random.Random(f"{seed}/{k}") for k in range(islands)]
    people = [settle(lengths, capacity, size, rng) for rng in rngs]
    for _ in range(epochs):
        people = [epoch(p, lengths, capacity, generations, rng) for p, rng in zip(people, rngs)]
        people = [p[:-1] + [people[k - 1][0]] if size > 1 else p for k, p in enumerate(people)]
    return max((one for p in people for one in p), key=lambda bins: fitness(bins, lengths, capacity))


# ---------------------------------------------------------------- Spark
def pieces(docs: DataFrame, path: str, capacity: int = CAPACITY, end_id: int = 0, spaced: bool = True, step_bytes: int = 2 << 20, cache_chunks: int = CACHE_CHUNKS) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 of every piece of every text.  Smaller steps
    and caches take less of a worker's memory and more of its time."""

    def cut(batches):
        store = worker_cache()
        if ("encoder", path) not in store:
            store["encoder", path] = ChunkEncoder(path, spaced, cache_chunks)
        encoder = store["encoder", path]
        for batch in batches:
            names = batch.column(0)
            for at, to, data, offsets in text_steps(batch.column(1), step_bytes):
                ids, sizes = encoder.encode(data, offsets)
                ids = np.insert(ids, np.cumsum(sizes), np.uint32(end_id)).astype("<u4")
                sizes = sizes + 1
                count = -(-sizes // capacity)
                row = np.repeat(np.arange(len(sizes)), count)
                number = np.arange(len(row)) - np.repeat(np.cumsum(count) - count, count)
                lead = sizes - (count - 1) * capacity
                start = np.where(number == 0, 0, lead[row] + (number - 1) * capacity)
                length = np.where(number == 0, lead[row], capacity)
                base = (np.cumsum(sizes) - sizes)[row] + start
                view = memoryview(ids.tobytes())
                sums = [zlib.crc32(view[4 * a : 4 * b]) for a, b in zip(base.tolist(), (base + length).tolist())]
                yield pa.RecordBatch.from_arrays([names.slice(at, to - at).take(pa.array(row)), pa.array(number.astype(np.int32)), pa.array(start), pa.array(length), pa.array(sums, pa.int64())], names=["doc_id", "piece", "start", "length", "ids_crc32"])
        encoder.release()

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(tidy(cut), PIECES)


def _code(bins: list[list[int]], n: int) -> bytes:
    """A packing as the bin number of each item."""
    out = np.zeros(n, "<i4")
    for k, one in enumerate(bins):
        out[one] = k
    return out.tobytes()


def _bins(code: bytes) -> list[list[int]]:
    home = np.frombuffer(code, "<i4")
    order = np.argsort(home, kind="stable")
    return [x.tolist() for x in np.split(order, np.flatnonzero(np.diff(home[order])) + 1)]


def _found(capacity: int):
    """Of a group's pieces: lengths, the best fit, and whether no packing can be better."""

    def found(rows: pd.DataFrame) -> pd.DataFrame:
        lengths = rows.sort_values("row", kind="stable")["length"].tolist()
        bins = best_fit(sorted(range(len(lengths)), key=lambda i: -lengths[i]), lengths, capacity)
        proven = len(bins) == least_bins(lengths, capacity)
        return pd.DataFrame({"group": rows["group"][:1], "lengths": [np.array(lengths, "<i4").tobytes()], "packing": [_code(bins, len(lengths))], "proven": [proven]})

    return found


def _live(capacity: int, size: int, generations: int, number: int):
    """An epoch of an island: its population and the elite that has come, if any."""

    def live(rows: pd.DataFrame) -> pd.DataFrame:
        group, island = int(rows["group"].iloc[0]), int(rows["island"].iloc[0])
        rng = random.Random(f"{group}/{island}/{number}")
        lengths = np.frombuffer(rows["lengths"].iloc[0], "<i4").tolist()
        codes = rows.sort_values(["place", "packing"], kind="stable")["packing"]
        people = settle(lengths, capacity, size, rng) if number == 0 else [_bins(x) for x in codes][: size + 1]
        people = epoch(people, lengths, capacity, generations, rng)[:size]
        scores = [fitness(p, lengths, capacity) for p in people]
        n = len(people)
        return pd.DataFrame({"group": [group] * n, "island": [island] * n, "place": range(n), "lengths": [rows["lengths"].iloc[0]] * n, "packing": [_code(p, len(lengths)) for p in people], "bins": [-s[0] for s in scores], "fill": [s[1] for s in scores]})

    return live


def _place(capacity: int, last: bool):
    """Bin, offset and whether the bin is filled, of each piece of a group."""

    def place(rows: pd.DataFrame, packing: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values("row", kind="stable", ignore_index=True)
        lengths = rows["length"].to_numpy()
        home = np.frombuffer(packing["packing"].iloc[0], "<i4").astype(np.int64)
        order = np.argsort(home, kind="stable")
        ends = np.cumsum(lengths[order])
        first = np.flatnonzero(np.concatenate([[True], home[order][1:] != home[order][:-1]]))
        begin = ends[first] - lengths[order][first]
        offset = np.empty(len(rows), np.int64)
        offset[order] = ends - lengths[order] - np.repeat(begin, np.diff(np.append(first, len(rows))))
        fill = np.bincount(home, lengths)
        stays = np.full(len(rows), 1) if last else (fill[home] >= WELL_FILLED * capacity).astype(int)
        return rows.assign(bin=home, offset=offset, stays=stays)

    return place


def _evolve_groups(short: DataFrame, capacity: int, islands: int, size: int, epochs: int, generations: int, last: bool, tag: str) -> DataFrame:
    """short (with a column group) with the bin and offset of each piece, and stays: 0 where
    the bin is not well filled (never if `last`).

    A group is packed by `islands` islands, each a Spark group of its own with the group's
    lengths.  After an epoch the populations are written, and the elite of each island moves
    to the next one of the group.  A group whose best fit is proven to need no bin too many
    has nothing to evolve.
    """
    state = "group long, island int, place int, lengths binary, packing binary, bins int, fill double"
    first = materialise(short.groupBy("group").applyInPandas(_found(capacity), "group long, lengths binary, packing binary, proven boolean"), f"{tag}-groups")
    chosen = first.select("group", "packing")
    open_ = first.where("NOT proven")
    count = open_.count()
    if count and epochs:
        live = open_.select("group", "lengths", "packing", F.lit(0).alias("place"), F.explode(F.sequence(F.lit(0), F.lit(islands - 1))).alias("island"))
        for number in range(epochs):
            dealt = live.repartition(min(count * islands, MOST_TASKS), "group", "island")
            live = materialise(dealt.groupBy("group", "island").applyInPandas(_live(capacity, size, generations, number), state), f"{tag}-epoch")
            best = live
            elite = live.where("place = 0").withColumn("island", F.pmod(F.col("island") + 1, F.lit(islands))).withColumn("place", F.lit(-1))
            live = live.unionByName(elite)
        best = best.groupBy("group").agg(F.max_by("packing", F.struct(-F.col("bins"), "fill", -F.col("island"))).alias("better"))
        chosen = chosen.join(best, "group", "left").select("group", F.coalesce("better", "packing").alias("packing"))
    out = PIECES + ", row long, group long, bin long, offset long, stays long"
    return short.groupBy("group").cogroup(chosen.groupBy("group")).applyInPandas(_place(capacity, last), out)


def pack(items: DataFrame, capacity: int = CAPACITY, group_pieces: int = GROUP_PIECES, islands: int = ISLANDS, size: int = SIZE, epochs: int = EPOCHS, generations: int = GENERATIONS) -> DataFrame:
    """Give every piece a sequence_id and an offset.  items are read several times, so they
    should come from files; a row's number is then the same each time."""
    items = materialise(items.withColumn("row", F.monotonically_increasing_id()), "pieces")
    whole = items.where(F.col("length") == capacity).select("*", (-F.col("row") - 1).alias("sequence_id"), F.lit(0).cast("long").alias("offset"))
    short = items.where(F.col("length") < capacity)
    groups = max(1, -(-short.count() // group_pieces))
    deal = lambda n: F.pmod(F.xxhash64("row"), F.lit(n))
    ways = capacity, islands, size, epochs, generations
    one = materialise(_evolve_groups(short.withColumn("group", deal(groups)), *ways, groups == 1, "pack"), "packed")
    named = one.where("stays = 1")
    if groups > 1:
        rest = materialise(one.where("stays = 0").drop("bin", "offset", "stays", "group"), "poor")
        joint = max(1, -(-rest.count() // group_pieces))
        named = named.unionByName(_evolve_groups(rest.withColumn("group", F.lit(groups) + deal(joint)), *ways, True, "joint"))
    named = named.withColumn("sequence_id", F.col("group") * F.lit(1 << 24) + F.col("bin"))
    columns = ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]
    return named.select(columns).unionByName(whole.select(columns))


def pack_documents(docs: DataFrame, path: str | None = None, capacity: int = CAPACITY, **limits) -> DataFrame:
    return pack(pieces(docs, path or tokenizer_path("byte_bpe_50k.json"), capacity, **limits), capacity)
