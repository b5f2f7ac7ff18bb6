"""The grouping genetic algorithm on lengths that best fit does not solve."""

import collections
import random

import pandas as pd
import pytest

from reclink.llm import binpack


def triplets(bins, seed, capacity):
    """Items of which three each fill a bin: best fit pairs the wrong ones."""
    rng, out = random.Random(seed), []
    for _ in range(bins):
        a = rng.randrange(38 * capacity // 100, 49 * capacity // 100)
        c = rng.randrange(capacity // 4, (capacity - a) // 2 + 1)
        out += [a, c, capacity - a - c]
    return out


def falling(lengths, capacity):
    return binpack.best_fit(sorted(range(len(lengths)), key=lambda i: -lengths[i]), lengths, capacity)


@pytest.mark.parametrize("seed", range(4))
def test_evolution_beats_best_fit(seed):
    lengths = triplets(40, seed, 2048)
    bins = binpack.evolve(lengths, 2048, generations=30)
    assert sorted(i for one in bins for i in one) == list(range(120))
    assert all(sum(lengths[i] for i in one) <= 2048 for one in bins)
    assert 40 <= len(bins) < len(falling(lengths, 2048))


def test_elites_move_between_islands():
    """An island that gets a better packing than its own goes on with it."""
    lengths = triplets(20, 1, 2048)
    best = [[3 * k, 3 * k + 1, 3 * k + 2] for k in range(20)]
    own = binpack._code(falling(lengths, 2048), 60)
    raw = binpack.np.array(lengths, "<i4").tobytes()
    rows = pd.DataFrame({"group": [0] * 3, "island": [1] * 3, "place": [-1, 0, 1], "lengths": [raw] * 3, "packing": [binpack._code(best, 60), own, own]})
    out = binpack._live(2048, 2, 3, 1)(rows)
    assert out["bins"].tolist()[0] == 20 and out["place"].tolist() == [0, 1]


def test_groups_evolve_in_spark(spark):
    lengths = triplets(60, 5, 2048)
    items = spark.createDataFrame([(i, 0, 0, n, i) for i, n in enumerate(lengths)], "doc_id long, piece int, start long, length long, ids_crc32 long")
    plain = falling(lengths, 2048)
    for group_pieces in (1000, 60):
        got = binpack.pack(items, 2048, group_pieces=group_pieces, generations=25).collect()
        bins = collections.defaultdict(list)
        for r in got:
            bins[r["sequence_id"]].append((r["offset"], r["length"]))
        assert sorted(r["doc_id"] for r in got) == list(range(180))
        for one in bins.values():
            one.sort()
            assert [a for a, _ in one] == [sum(n for _, n in one[:k]) for k in range(len(one))] and sum(n for _, n in one) <= 2048
        assert len(bins) < len(plain) or group_pieces < 100


def test_bound():
    assert binpack.least_bins([1100] * 5, 2048) == 5 and binpack.least_bins([100] * 50, 2048) == 3
