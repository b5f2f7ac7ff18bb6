"""Attribute selection: exact values of the worked example, invariants, policies."""

from fractions import Fraction as Fr

import pytest

from reclink.operators import select
from reclink.plans.model import Qid
from reclink.sources.views import example

NAMES = ["first_name", "last_name", "birth_date", "street", "city", "phone"]
SHORT = dict(zip(NAMES, ["First", "Last", "Birth", "Street", "City", "Phone"]))
QIDS = [Qid(n) for n in NAMES]


def label(attrs):
    return "+".join(SHORT[a] for a in attrs)


@pytest.fixture(scope="module")
def one(spark):
    return example(spark).where("database = 'A'").cache()


@pytest.fixture(scope="module")
def both(spark):
    return example(spark).cache()


def pairs_of(df):
    found = select.select_combinations(df, QIDS, n_a=99, c_t=0.0, max_size=2, subset_policy="keep")
    return {label(c.attrs): (c.s_c, c.s_g, c.score) for c in found}


def test_pair_scores_of_one_database(one):
    got = pairs_of(one)
    assert len(got) == 15
    for name, want in {"First+Last": (Fr(2, 3), Fr(4, 9), Fr(5, 9)), "First+Birth": (1, Fr(4, 9), Fr(13, 18)), "Street+Phone": (Fr(2, 3), Fr(4, 9), Fr(5, 9)), "City+Phone": (Fr(1, 3), Fr(2, 9), Fr(5, 18))}.items():
        assert got[name] == pytest.approx([float(x) for x in want])


def test_pair_scores_of_both(both):
    got = pairs_of(both)
    wanted = {"First+Last": ("4/5", "14/25", "17/25"), "First+Birth": ("4/5", "2/5", "3/5"), "First+City": ("3/5", "12/25", "27/50"), "Last+Birth": ("3/5", "2/5", "1/2"), "City+Phone": ("2/5", "6/25", "8/25"), "Street+City": ("2/5", "8/25", "9/25")}
    for name, want in wanted.items():
        assert got[name] == pytest.approx([float(Fr(x)) for x in want])


@pytest.mark.parametrize(
    ("c_t", "scored", "kept"),
    [(0.5, 22, {"First+Last+Birth", "First+Birth+City", "First+Birth+Street+Phone"}), (0.7, 15, {"First+Birth"}), (0.9, 15, set())],
)
def test_literal_selection_of_one_database(one, c_t, scored, kept):
    trace = select.Selection()
    found = select.select_combinations(one, QIDS, n_a=99, c_t=c_t, trace=trace)
    assert {label(c.attrs) for c in found} == kept
    assert sum(map(len, trace.levels)) == scored


def test_literal_selection_of_both(both):
    found = select.select_combinations(both, QIDS, n_a=99, c_t=0.5)
    assert {label(c.attrs) for c in found} == {"First+City", "First+Last+Birth", "First+Last+Street", "First+Birth+Street", "First+Street+Phone"}
    assert select.select_combinations(both, QIDS, c_t=0.7) == []


def test_scores_obey_their_bounds(both):
    trace = select.Selection()
    select.select_combinations(both, QIDS, c_t=0.0, prune="none", trace=trace)
    for m, (s_c, s_g, s) in trace.scores.items():
        assert 0 <= s_g <= s_c + 1e-9 and s <= s_c + 1e-9
        for i in range(6):
            smaller = trace.scores.get(m & ~(1 << i))
            if m >> i & 1 and smaller:
                assert s_c <= smaller[0] + 1e-9  # completeness never grows
                assert s_c - s_g <= smaller[0] - smaller[1] + 1e-9  # nor does the sum of squares


def test_sound_prune_equals_exhaustive(both):
    exhaustive, sound = (select.select_combinations(both, QIDS, n_a=99, c_t=0.5, prune=p, subset_policy="keep") for p in ("none", "completeness"))
    assert exhaustive == sound


def test_grown_sets_have_all_their_parts_passing(both):
    trace = select.Selection()
    select.select_combinations(both, QIDS, c_t=0.5, trace=trace)
    for m in trace.scores:
        if m.bit_count() > 2:
            assert all(trace.scores[m ^ 1 << i][2] >= 0.5 - 1e-9 for i in range(6) if m >> i & 1)


def test_policies():
    kept = {0b011: 0.9, 0b111: 0.8, 0b100: 0.5}
    assert set(select.apply_policy(kept, "drop")) == {0b111}
    assert set(select.apply_policy(kept, "dominated")) == {0b011, 0b111}
    assert set(select.apply_policy(kept, "keep")) == set(kept)


def test_levels_and_random_choice():
    assert select.next_level({0b011, 0b101, 0b110}, 3) == {0b111}
    assert select.next_level({0b011, 0b101}, 3) == set()
    assert select.random_combinations(QIDS, 4, 1) == select.random_combinations(QIDS, 4, 1)


def test_grouping_sets_equal_single_groups(both):
    masks = [0b000011, 0b000101, 0b111000]
    a, b = ({r["mask"]: (r["sf"], r["sff"]) for r in f(both, QIDS, masks).collect()} for f in (select.level_sums, select.grouping_sets_sums))
    assert a == b


def test_gini_options(both):
    attrs = [Qid("last_name")]
    assert select.gini(both, attrs).first()[0] == pytest.approx(0.8 - (4 + 1 + 1) / 25)
    assert select.gini(both, attrs, denominator="present").first()[0] == pytest.approx(1 - 6 / 16)
    assert select.gini(both, attrs, null_is_value=True).first()[0] == pytest.approx(1 - 7 / 25)


def test_estimators_come_close(spark):
    frame = spark.range(20000).selectExpr("CAST(id % 50 AS STRING) AS a", "CAST(id % 7 AS STRING) AS b")
    qids = [Qid("a"), Qid("b")]
    true = sum((20000 / 350) ** 2 for _ in range(350)) / 20000**2
    assert select.estimated_sums(frame, qids, [3], "ams", 400)[3] == pytest.approx(true, rel=0.5)
    assert select.estimated_sums(frame, qids, [3], "sample", 4)[3] == pytest.approx(true, rel=0.5)


def test_edges(spark, both):
    assert select.select_combinations(both.where("false"), QIDS) == []
    with pytest.raises(ValueError):
        select.select_combinations(both, [Qid("nothing")])
    blank = spark.createDataFrame([(None, None)] * 3, "a string, b string")
    assert select.select_combinations(blank, [Qid("a"), Qid("b")], c_t=0.5) == []
    few = select.select_combinations(both, QIDS, n_a=99, c_t=0.0, max_size=2, subset_policy="keep", max_missing=0.2)
    assert {a for c in few for a in c.attrs} == {"first_name", "last_name", "birth_date", "street"}
