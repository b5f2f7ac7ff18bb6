"""The operators on documents against plain versions, with awkward rows."""

import collections
import hashlib
import math
import random
import re
import struct
import zlib

import numpy as np
import pytest

from reclink.llm import binpack, classlm, dac, decontam, langid, oddsketch
from reclink.llm._common import SpanHasher, hot_join, word_spans
from reclink.llm._tokens import ChunkEncoder, tokenizer_path

LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def words(text):
    return re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate(LOWER))


def rows_of(frame):
    return sorted((tuple(r) for r in frame.collect()), key=repr)


# ---------------------------------------------------------------- shared parts
def test_word_spans_and_hashes():
    texts = ["a bb  a", "", " x\n", "bb a", "Ünit ünit"]
    data = np.frombuffer("".join(texts).encode(), np.uint8)
    offsets = np.concatenate([[0], np.cumsum([len(t.encode()) for t in texts])])
    starts, ends, first = word_spans(data, offsets)
    got = [[bytes(data[s:e]).decode() for s, e in zip(starts[a:b], ends[a:b])] for a, b in zip(first[:-1], first[1:])]
    assert got == [["a", "bb", "a"], [], ["x"], ["bb", "a"], ["Ünit", "ünit"]]
    h = SpanHasher(1).spans(data, starts, ends)
    flat = [w.translate(LOWER) for t in got for w in t]
    for i in range(len(flat)):
        for j in range(len(flat)):
            assert (h[i] == h[j]) == (flat[i] == flat[j])


@pytest.mark.parametrize(("name", "spaced"), [("byte_bpe_50k.json", True), ("word_bpe_49k.json", False)])
def test_chunked_encoding_equals_the_library(name, spaced):
    rng = random.Random(5)
    alphabet = ["a", "B", "é", " ", "  ", "\n", "\t", " ", "　", "'s", "7", "!", "́", "Σ", "<|endoftext|>", "\x1c", "\r\n", "ß", "中"]
    texts = ["".join(rng.choice(alphabet) for _ in range(rng.randrange(40))) for _ in range(1500)]
    encoder = ChunkEncoder(tokenizer_path(name), spaced)
    data = np.frombuffer("".join(texts).encode(), np.uint8)
    offsets = np.concatenate([[0], np.cumsum([len(t.encode()) for t in texts])])
    ids, sizes = encoder.encode(data, offsets)
    ends = np.cumsum(sizes)
    for text, end, size, want in zip(texts, ends, sizes, encoder.tokenizer.encode_batch(texts, add_special_tokens=False)):
        assert ids[end - size : end].tolist() == want.ids, repr(text)


# ---------------------------------------------------------------- 10 token files
@pytest.mark.parametrize("bits", [8, 16])
def test_codes_give_random_access(bits):
    rng = np.random.default_rng(2)
    ids = np.concatenate([rng.integers(0, 300, 3000), rng.integers(0, 1 << 32, 700), [0, 255, 256, 65535, 65536, (1 << 32) - 1]]).astype(np.uint32)
    codes = dac.Codes(dac.encode(ids, bits))
    assert len(codes) == len(ids)
    assert (codes.all() == ids).all()
    assert all(codes[i] == ids[i] for i in range(0, len(ids), 7))
    assert len(dac.Codes(dac.encode(ids[:0], bits)).all()) == 0
    with pytest.raises(IndexError):
        codes[len(ids)]


def _plain_ids(texts, name):
    tokenizer = ChunkEncoder(tokenizer_path(name), True).tokenizer
    return [x.ids for x in tokenizer.encode_batch([t or "" for t in texts], add_special_tokens=False)]


def crc(ids):
    return zlib.crc32(struct.pack(f"<{len(ids)}I", *ids))


def test_token_file_round_trip(docs, empty, rows, tmp_path):
    got = dac.token_file(docs).collect()
    ids = [x + [2] for x in _plain_ids([r[1] for r in rows], "word_bpe_49k.json")]
    assert sorted((repr(r["doc_id"]), r["n_tokens"], r["ids_crc32"]) for r in got) == sorted((repr(r[0]), len(x), crc(x)) for r, x in zip(rows, ids))
    at = 0
    for r in sorted(got, key=lambda r: r["start"]):
        assert r["start"] == at
        at += r["n_tokens"]
    order = [r["doc_id"] for r in sorted(got, key=lambda r: r["start"])]
    assert order == sorted(order, key=lambda x: (x is not None, x or 0))
    assert dac.token_file(empty).count() == 0


def test_shard_reader_reads_single_tokens(tmp_path):
    uri = f"file://{tmp_path}/one.dac"
    shard = dac.ShardWriter(uri)
    ids = np.arange(1000, dtype=np.uint32) * 77
    for part in np.array_split(ids, 3):
        shard.segment(np.array([1]), np.array([False]), np.array([len(part)]), part)
    shard.close()
    reader = dac.ShardReader(uri)
    assert [reader.token(i) for i in (0, 333, 334, 999, 5)] == ids[[0, 333, 334, 999, 5]].tolist()


# ---------------------------------------------------------------- 9 packing
def test_evolution_packs_within_one_of_the_bound():
    rng = random.Random(1)
    lengths = [rng.randrange(1, 2048) for _ in range(1500)]
    bins = binpack.evolve(lengths)
    assert sorted(i for one in bins for i in one) == list(range(len(lengths)))
    assert all(sum(lengths[i] for i in one) <= 2048 for one in bins)
    assert len(bins) <= -(-sum(lengths) // 2048) * 1.02 + 1
    assert binpack.evolve([]) == []


def test_crossover_keeps_every_item_once():
    rng = random.Random(4)
    lengths = [rng.randrange(100, 1500) for _ in range(200)]
    a = binpack.best_fit(sorted(range(200), key=lambda i: -lengths[i]), lengths, 2048)
    b = binpack.best_fit(list(range(200)), lengths, 2048)
    child = binpack.crossover(a, b, lengths, 2048, 0.5, rng)
    assert sorted(i for one in child for i in one) == list(range(200))
    assert all(sum(lengths[i] for i in one) <= 2048 for one in child)


def test_packing(docs, empty, rows):
    got = binpack.pack_documents(docs).collect()
    want = []
    for r, ids in zip(rows, (x + [0] for x in _plain_ids([r[1] for r in rows], "byte_bpe_50k.json"))):
        lead = (len(ids) - 1) % 2048 + 1
        cuts = [0, *range(lead, len(ids) + 1, 2048)]
        want += [(repr(r[0]), k, a, b - a, crc(ids[a:b])) for k, (a, b) in enumerate(zip(cuts, cuts[1:]))]
    assert sorted((repr(r["doc_id"]), r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in got) == sorted(want)
    bins = collections.defaultdict(list)
    for r in got:
        bins[r["sequence_id"]].append((r["offset"], r["length"]))
    for one in bins.values():
        at = 0
        for offset, length in sorted(one):
            assert offset == at
            at += length
        assert at <= 2048
    assert len(bins) == -(-sum(r["length"] for r in got) // 2048)
    assert binpack.pack_documents(empty).count() == 0


# ---------------------------------------------------------------- 8 decontamination
def contaminated(rows, items):
    cut = lambda t: [w for w in re.split(r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate(LOWER)) if w]
    wins = collections.defaultdict(set)
    for item, text in items:
        w = cut(text)
        n = min(13, len(w))
        for i in range(len(w) - n + 1) if w else []:
            wins[tuple(w[i : i + n])].add(item)
    out = []
    for doc, text, *_ in rows:
        w, hit, found = cut(text), set(), set()
        for win, owners in wins.items():
            for i in range(len(w) - len(win) + 1):
                if tuple(w[i : i + len(win)]) == win:
                    hit |= set(range(i, i + len(win)))
                    found |= owners
        found.discard(None)
        names = ",".join(sorted(map(str, found)))
        out.append((doc, len(w), len(hit), len(found), hashlib.sha256(names.encode()).hexdigest(), len(hit) > 0 and 20 * len(hit) >= len(w)))
    return sorted(out, key=repr)


ITEMS = [(1, "over the LAZY dog, near the river bank today"), (10, "kurz"), (2, ""), (3, None), (None, "quick brown"), (4, "word " * 14), (4, "12 34"), (5, " ".join(f"w{i}" for i in range(30)))]


@pytest.mark.parametrize("broadcast_rows", [1000, 0])
def test_contamination(spark, docs, empty, rows, broadcast_rows):
    bench = spark.createDataFrame(ITEMS, "item_id long, text string")
    more = [(100, "intro " + " ".join(f"w{i}" for i in range(5, 25)) + " outro w1 w2", None, None, 1), (101, "w0 w1 w2", None, None, 1)]
    frame = docs.unionByName(spark.createDataFrame(more, "doc_id long, text string, lang string, source string, n_chars long"), allowMissingColumns=True)
    got = rows_of(decontam.contamination(frame, bench, broadcast_rows=broadcast_rows).drop("k1", "k2"))
    assert got == contaminated([*rows, *more], ITEMS)
    clean = decontam.clean_documents(frame, bench, broadcast_rows=broadcast_rows)
    assert clean.columns == frame.columns
    assert clean.count() == sum(not r[-1] for r in got)
    assert decontam.contamination(empty, bench).count() == 0
    assert decontam.contamination(docs, bench.where("false")).where("contaminated").count() == 0


# ---------------------------------------------------------------- 5 near copies
def components(rows, percent=85):
    sets = []
    for doc, text, *_ in rows:
        w = words(text)
        sets.append({tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set())
    head = list(range(len(rows)))

    def find(i):
        while head[i] != i:
            i = head[i]
        return i

    for i in range(len(rows)):
        for j in range(i):
            if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= percent * len(sets[i] | sets[j]):
                head[find(i)] = find(j)
    groups = collections.defaultdict(list)
    for i, r in enumerate(rows):
        groups[find(i)].append(r[0])
    out = []
    for i, r in enumerate(rows):
        known = [x for x in groups[find(i)] if x is not None]
        component = min(known) if known and sets[i] else r[0] if not sets[i] else None
        out.append((r[0], len(sets[i]), component, component == r[0]))
    return sorted(out, key=repr)


def test_near_copies_of_awkward_rows(docs, empty, rows):
    got = oddsketch.near_copies(docs).select("doc_id", "n_shingles", "component_id", "kept")
    assert rows_of(got) == components(rows)
    assert oddsketch.near_copies(empty).count() == 0
    kept = oddsketch.drop_near_copies(docs)
    assert kept.columns == docs.columns
    # one row of each group stays, and every row without words
    found = components(rows)
    alone = [(r[0],) for r in found if not r[1]]
    one_each = {r[2] if r[2] is not None else "null" for r in found if r[1]}
    assert kept.count() == len(alone) + len(one_each)
    assert oddsketch.drop_near_copies(empty).count() == 0


def test_rows_with_the_same_doc_id(spark):
    """Repeated rows and equal doc_ids with different texts: one row of the group stays."""
    text = " ".join(f"w{i}" for i in range(100))
    near = text.replace("w50 ", "x ")
    rows = [(1, text), (1, text), (1, near), (2, near), (None, text), (None, text), (3, ""), (3, ""), (None, "only null"), (None, "only null")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 AS m", "'x' AS name", "0 AS head")
    kept = [(r["doc_id"], r["text"]) for r in oddsketch.drop_near_copies(docs).collect()]
    assert len(kept) == 4 and sorted(kept, key=repr) == sorted([(3, ""), (3, ""), (None, "only null"), next(x for x in kept if x[0] == 1)], key=repr)


@pytest.mark.parametrize(("hot", "broadcast_rows"), [(1, 100), (1, 0), (100, 100)])
def test_hot_join(spark, hot, broadcast_rows):
    rows = spark.range(40).selectExpr("id", "if(id < 30, 0, id) AS key")
    keyed = rows.groupBy("key").count()
    got = hot_join(rows, keyed, "key", "count", hot, broadcast_rows)
    assert sorted(map(tuple, got.select("key", "id", "count").collect())) == sorted((min(i, 0) if i < 30 else i, i, 30 if i < 30 else 1) for i in range(40))


def test_near_copies_against_brute_force(spark):
    """Chains of copies with a few words changed, whose similarities straddle the limit."""
    rng = random.Random(9)
    rows = []
    for base in range(6):
        text = [f"b{base}x{rng.randrange(10**6)}" for _ in range(rng.choice([20, 60, 150]))]
        for _ in range(25):
            copy = list(text)
            for _ in range(rng.randrange(4)):
                copy[rng.randrange(len(copy))] = f"m{rng.randrange(10**6)}"
            rows.append((len(rows), " ".join(copy), "en", "a", 1))
            if rng.random() < 0.3:
                text = copy
    frame = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    got = oddsketch.near_copies(frame).select("doc_id", "n_shingles", "component_id", "kept")
    assert rows_of(got) == components(rows)


def test_odd_sketches_bound_and_estimate():
    rng = np.random.default_rng(3)
    base = rng.integers(0, 1 << 63, 400, dtype=np.uint64)
    for changed in (0, 5, 20, 60):
        other = base.copy()
        other[:changed] = rng.integers(0, 1 << 63, changed, dtype=np.uint64)
        a, b = np.unique(base), np.unique(other)
        parity = [oddsketch.fold((x % np.uint64(oddsketch.SET_BITS)).astype(np.int64), oddsketch.SET_BITS) for x in (a, b)]
        assert int(np.bitwise_count((parity[0] ^ parity[1]).view(np.uint64)).sum()) <= 2 * changed
        sketch = [oddsketch.sample_sketch(oddsketch.minima(x)) for x in (a, b)]
        bits = int(np.bitwise_count((sketch[0] ^ sketch[1]).view(np.uint64)).sum())
        true = (400 - changed) / (400 + changed)
        assert abs(oddsketch.estimate(bits) - true) < 0.2
        if true >= 0.85:
            assert bits <= oddsketch.sample_limit(0.85)


# ---------------------------------------------------------------- 1 language
def _languages(spark, n=60):
    rng = random.Random(2)
    parts = {"en": ["the", "ing", "er", "th"], "de": ["sch", "ung", "ein", "ich"], "fr": ["eau", "oux", "tion", "é"]}
    rows = [(i, " ".join("".join(rng.choice(parts[lang]) for _ in range(3)) for _ in range(rng.randrange(5, 200))), lang) for i, lang in enumerate(sorted(parts) * n)]
    return rows, spark.createDataFrame(rows, "doc_id long, text string, lang string")


def test_language_accuracy_and_edges(spark, docs, empty):
    rows, frame = _languages(spark)
    model = langid.train(frame.where("doc_id % 3 = 0 OR doc_id % 7 = 1"))
    got = {r["doc_id"]: r for r in langid.predict(frame, model).collect()}
    assert np.mean([got[i]["lang_pred"] == lang for i, _, lang in rows]) > 0.97
    assert all(0 <= r["score"] <= 1 for r in got.values())
    odd = langid.predict(docs, model).collect()
    assert sum(r["lang_pred"] == "und" for r in odd) == 5  # nulls, blanks and signs only
    assert all(r["score"] == 0 for r in odd if r["lang_pred"] == "und")
    assert langid.keep_known(docs, model).columns == docs.columns
    assert langid.predict(empty, model).count() == 0
    assert {r["lang_pred"] for r in langid.predict(docs, langid.train(empty)).collect()} == {"und"}


def test_tables_equal_the_network():
    rng = np.random.default_rng(1)
    p = langid._start(3, rng)
    x = langid._FOLD[rng.integers(0, 256, (50, langid.WINDOW)).astype(np.uint8)]
    e = p["embed"][x]
    pooled = []
    for w in langid.WIDTHS:
        steps = x.shape[1] - w + 1
        pooled.append(sum(e[:, t : t + steps] @ p[f"filter{w}"][t] for t in range(w)).max(axis=1) + p[f"bias{w}"])
    s = np.maximum(np.concatenate(pooled, axis=1), 0) @ p["out"] + p["out_bias"]
    s = np.exp(s - s.max(axis=1, keepdims=True))
    assert np.abs(langid.Tables(p).probabilities(x) - s / s.sum(axis=1, keepdims=True)).max() < 1e-3


def test_gradients_are_right():
    rng = np.random.default_rng(4)
    p = {k: v.astype(np.float64) for k, v in langid._start(3, rng).items()}
    x, y = rng.integers(97, 103, (6, 20)), rng.integers(0, 3, 6)
    _, g = langid._gradients(p, x, y)
    for name in ("filter3", "out", "bias2", "embed"):
        spot = np.unravel_index(np.abs(g[name]).argmax(), g[name].shape)
        old = p[name][spot]
        losses = []
        for step in (1e-5, -1e-5):
            p[name][spot] = old + step
            losses.append(langid._gradients(p, x, y)[0])
        p[name][spot] = old
        assert abs((losses[0] - losses[1]) / 2e-5 - g[name][spot]) < 1e-4


# ---------------------------------------------------------------- 2 language model
@pytest.mark.parametrize("frequent", [1 << 18, 3])
def test_base_score_and_smoothing(spark, docs, empty, rows, frequent):
    more = [(100 + i, " ".join(f"w{(i * j) % 11}" for j in range(30)), None, None, 1) for i in range(20)]
    frame = docs.unionByName(spark.createDataFrame(more, "doc_id long, text string, lang string, source string, n_chars long"), allowMissingColumns=True)
    train = [r for r in [*rows, *more] if zlib.crc32(("" if r[0] is None else str(r[0])).encode()) % 5 != 1]
    held = "pmod(crc32(coalesce(CAST(doc_id AS STRING), '')), 5) = 1"
    model = classlm.Model(frame.where(f"NOT {held}"), frequent=frequent, items=8, classes=6)
    counts = collections.Counter(w for r in train for w in [*words(r[1]), "\n"])
    n, v = sum(counts.values()), len(counts)
    assert (model.tokens, model.distinct) == (n, v)
    want = []
    for r in [*rows, *more]:
        tokens = [*words(r[1]), "\n"]
        want.append((repr(r[0]), len(tokens), sum(counts[w] > 0 for w in tokens), round(sum(math.log10((counts[w] + 0.5) / (n + 0.5 * (v + 1))) for w in tokens), 5)))
    got = classlm.score(frame, model).collect()
    assert sorted((repr(r["doc_id"]), r["n_tokens"], r["n_known"], round(r["base_score"], 5)) for r in got) == sorted(want)
    assert all(r["score"] < 0 and r["train_tokens"] == n for r in got)
    # transitions sum to one over classes; emissions over known words and the unseen one
    assert np.allclose((10**model.transition).sum(axis=1), 1)
    assert classlm.score(empty, model).count() == 0
    untrained = classlm.Model(empty)
    assert max(abs(r["base_score"]) for r in classlm.score(docs, untrained).collect()) < 1e-9


def test_scores_do_not_depend_on_the_frequent_table(spark, docs):
    a, b = (sorted((repr(r["doc_id"]), round(r["score"], 6)) for r in classlm.score(docs, classlm.Model(docs, frequent=f, items=8, classes=6)).collect()) for f in (1 << 18, 0))
    assert a == b


def test_exchange_finds_alternating_classes():
    rng = np.random.default_rng(0)
    pairs = np.zeros((9, 9), np.int64)
    for i in range(4):
        for j in range(4, 8):
            pairs[i, j], pairs[j, i] = rng.integers(50, 90, 2)
    pairs[8, 0] = pairs[5, 8] = 1
    member = classlm.exchange(pairs, classes=3)
    assert len(set(member[:4])) == 1 and len(set(member[4:8])) == 1 and member[0] != member[4]
    assert member[8] == 2
