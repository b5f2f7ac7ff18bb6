"""Classes of rare words in the language model."""

import random

import numpy as np
import pytest
from reclink.llm import classlm
from reclink.llm._common import SpanHasher


@pytest.mark.parametrize("frequent", [1 << 18, 40, 0])
def test_rare_words_have_classes_by_their_own_neighbours(spark, frequent):
    """Words of one ending, of which only two are items: their neighbours tell them apart."""
    rng = random.Random(4)
    x, y = ([f"{k}{i}zz" for i in range(60)] + [f"{k}0zz"] * 20 for k in "xy")
    rows = [(i, " ".join(rng.choice(p) for _ in range(20) for p in (["the"], x, ["of"], y))) for i in range(40)]
    train = spark.createDataFrame(rows, "doc_id long, text string")
    model = classlm.Model(train, frequent=frequent, items=4, classes=5)
    kinds = {r["h"]: r["k"] for r in model.words.collect()}
    of = lambda w: kinds[int(SpanHasher(31).spans(np.frombuffer(w.encode(), np.uint8), np.array([0]), np.array([len(w)])).view(np.int64)[0])]
    seen = {w for r in rows for w in r[1].split()}
    kx, ky = ({of(w) for w in p if w in seen} for p in (x, y))
    assert not kx & ky
    texts = [(1, "the x1zz of y1zz the x2zz of y2zz"), (2, "the y1zz of x1zz the y2zz of x2zz"), (3, "the newzz of x3zz")]
    got = {r["doc_id"]: r["score"] for r in classlm.score(spark.createDataFrame(texts, "doc_id long, text string"), model).collect()}
    whole = classlm.score(spark.createDataFrame(texts, "doc_id long, text string"), classlm.Model(train, items=4, classes=5)).collect()
    assert got[1] > got[2] + 1
    assert all(abs(got[r["doc_id"]] - r["score"]) < 1e-9 for r in whole)


def _objective(pairs, member, classes):
    one = np.eye(classes)[member]
    a = one.T @ pairs @ one
    x = lambda v: (v * np.log(np.maximum(v, 1e-300))).sum()
    return x(a) - x(a.sum(axis=0)) - x(a.sum(axis=1))


def test_exchange_ends_where_no_move_helps():
    rng = np.random.default_rng(5)
    pairs = rng.poisson(rng.gamma(0.4, 6, (25, 1)) * rng.gamma(0.4, 6, (1, 25))).astype(np.int64)
    member = classlm.exchange(pairs, classes=5, rounds=50)
    found = _objective(pairs.astype(float), member, 5)
    for w in np.flatnonzero(pairs[:, :24].sum(axis=0)):
        for k in range(4):
            other = member.copy()
            other[w] = k
            assert _objective(pairs.astype(float), other, 5) <= found + 1e-6


@pytest.mark.parametrize("frequent", [1 << 18, 5])
def test_scores_against_a_plain_version(spark, frequent):
    """Counts, transitions and scores from the classes that the model gives the words."""
    rng = random.Random(8)
    rows = [(i, " ".join(f"{rng.choice('abc')}{rng.randrange(12)}{rng.choice(['ing', 'ed', 'é'])}" for _ in range(rng.randrange(25)))) for i in range(30)]
    train, size = rows[:20], 6
    model = classlm.Model(spark.createDataFrame(train, "doc_id long, text string"), frequent=frequent, items=10, classes=size)
    kinds = {r["h"]: (r["k"], r["c"]) for r in model.words.collect()}
    hasher = SpanHasher(31)

    def read(text):
        out = []
        for w in text.split():
            raw = np.frombuffer(w.encode(), np.uint8)
            spot = np.array([0]), np.array([len(raw)])
            h = int(hasher.spans(raw, *spot).view(np.int64)[0])
            out.append(kinds.get(h) or (int(model.endings[classlm._ending(raw, *spot)[0]]), 0))
        return [*out, (size - 1, len(train))]

    pairs, words, distinct = np.zeros((size, size)), np.zeros(size), np.zeros(size)
    for _, text in train:
        line = [size - 1] + [k for k, _ in read(text)]
        for a, b in zip(line, line[1:]):
            pairs[a, b] += 1
            words[b] += 1
    for k, _ in kinds.values():
        distinct[k] += 1
    share = (words + classlm.ADD) / (words.sum() + classlm.ADD * size)
    want = {}
    for i, text in rows:
        total, before = 0.0, size - 1
        for k, c in read(text):
            total += np.log10((pairs[before, k] + classlm.BACK * share[k]) / (pairs[before].sum() + classlm.BACK))
            total += np.log10((c + classlm.ADD) / (words[k] + classlm.ADD * (distinct[k] + 1)))
            before = k
        want[i] = total
    got = {r["doc_id"]: r["score"] for r in classlm.score(spark.createDataFrame(rows, "doc_id long, text string"), model).collect()}
    assert got.keys() == want.keys() and all(abs(got[i] - want[i]) < 1e-6 for i in want)


def test_places_by_leading_bits_equal_a_search():
    rng = np.random.default_rng(1)
    for n in (0, 1, 2, 50, 5000):
        table = np.unique(np.concatenate([rng.integers(0, 1 << 64, n, dtype=np.uint64), rng.integers(0, 1 << 40, n, dtype=np.uint64)]))
        asked = np.concatenate([table, rng.integers(0, 1 << 64, 1000, dtype=np.uint64), rng.integers(0, 1 << 40, 1000, dtype=np.uint64), table + np.uint64(1)])
        spot, hit = classlm.Spots(table).of(asked)
        assert (hit == np.isin(asked, table)).all()
        assert (table[spot[hit]] == asked[hit]).all() if n else not hit.any()
