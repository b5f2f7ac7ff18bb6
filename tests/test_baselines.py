"""Baselines and measures: invariants, small exact cases, the range test's table value."""

import numpy as np
import pytest

from reclink.baselines import comparison, em, prob_signature, probabilistic, simple
from reclink.functions.udx import jaro_winkler
from reclink.operators import evaluate, joins, perturb, select, signatures
from reclink.plans.model import Qid, Settings
from reclink.queries import workloads as w
from reclink.queries.linkage import linked
from reclink.sources import views

ATTRS = ("x", "y", "z")


@pytest.fixture(scope="module")
def levels(spark):
    rows = [("a1", "b1", 2, 2, 2), ("a2", "b2", 2, 2, -1), ("a3", "b3", 0, 2, 0), ("a4", "b4", 0, 0, 0), ("a5", "b5", -1, -1, -1)]
    return spark.createDataFrame(rows, "a_id string, b_id string, l_x int, l_y int, l_z int").cache()


W = {"x": (4.0, -2.0), "y": (3.0, -1.0), "z": (2.0, -1.0)}


def scores(frame):
    return {r["a_id"]: r["s"] for r in frame.collect()}


def test_weights_and_redistribution(levels):
    plain = scores(probabilistic.weighted(levels, W))
    neutral = scores(probabilistic.weighted(levels, W, missing="neutral"))
    spread = scores(probabilistic.weighted(levels, W, split="proportional"))
    equal = scores(probabilistic.weighted(levels, W, split="equal"))
    assert plain["a1"] == 1 and plain["a4"] == 0 and plain["a5"] == 0
    assert plain["a2"] == pytest.approx((7 - 1 + 4) / 13) and neutral["a2"] == pytest.approx(11 / 13)
    assert spread["a2"] == pytest.approx(1) and equal["a2"] == pytest.approx(1)
    for k in ("a1", "a3", "a4"):  # nothing missing: nothing to spread
        assert spread[k] == equal[k] == plain[k]


def test_mixture_separates_and_is_monotone():
    rng = np.random.default_rng(0)
    match = rng.random(4000) < 0.1
    codes = np.where(match[:, None], rng.random((4000, 3)) < 0.9, rng.random((4000, 3)) < 0.1) * 2
    texts = ["".join("-" if gone else str(c) for c, gone in zip(row, lost)) for row, lost in zip(codes, rng.random((4000, 3)) < 0.2)]
    counts = {t: texts.count(t) for t in set(texts)}
    posterior, share, m, u = em.fit(sorted(counts.items()), 3)
    assert share == pytest.approx(0.1, abs=0.03)
    assert (m[:, 2] > u[:, 2]).all()
    assert posterior["222"] > posterior["22-"] > posterior["2--"] > posterior["0--"] > posterior["000"]
    assert em.fit([], 3)[0] == {}


def test_levels(spark):
    a = spark.createDataFrame([("1", "Miller", None)], "record_id string, x string, y string")
    b = spark.createDataFrame([("2", "Millar", "q")], "record_id string, x string, y string")
    pairs = spark.createDataFrame([("1", "2")], "a_id string, b_id string")
    row = comparison.compared(a, b, pairs, ("x", "y"), cut=0.9, partial=0.5).first()
    assert (row["l_x"], row["l_y"]) == (comparison.PARTIAL, comparison.MISSING)


def test_uncorrupted_twin_is_found_whole(spark, small):
    p = views.person(spark, small).where("household < 300").dropDuplicates(list(w.VOTER))
    b = perturb.rename_ids(p, "b")
    pair = w.Pair(p, b, evaluate.truth_of(p, b), w.VOTER, w.VOTER_COMBOS, w.PAIRS["w4"](spark, small).rules, Settings())
    row = evaluate.precision_recall(linked(pair).pairs, pair.truth).first()
    exact = evaluate.precision_recall(simple.exact_link(p, b, w.VOTER), pair.truth).first()
    assert (exact["precision"], exact["recall"]) == (1.0, 1.0)
    # members of a household that differ in one attribute may be taken for each other
    assert row["recall"] == 1.0 and row["precision"] > 0.95


def test_directions_of_the_comparison(spark, small):
    """More is missing, less is found; ours finds what shared signatures find, and more."""
    recall = {}
    for name in ("w4", "w5"):
        p = w.PAIRS[name](spark, small)
        r = linked(p)
        ours = evaluate.precision_recall(r.pairs, p.truth).first()
        theirs = evaluate.precision_recall(prob_signature.prob_signature_link(r.sig_a, r.sig_b), p.truth).first()
        assert ours["recall"] >= theirs["recall"] and ours["precision"] > 0.9
        recall[name] = ours["recall"]
    assert recall["w4"] > recall["w5"]


def test_stricter_frequency_rule_does_not_lower_precision(spark, small):
    p = w.PAIRS["w4"](spark, small)
    combos = select.fixed_combinations(p.combos)
    found = []
    for p_t in (0.5, 0.7, 0.8):
        settings = Settings(p_t=p_t, s_t=0.5)
        sa, sb = signatures.kept_signatures(p.a, p.b, p.qids, combos, settings)
        found.append(evaluate.precision_recall(prob_signature.prob_signature_link(sa, sb, settings=settings), p.truth).first()["precision"])
    assert found == sorted(found)


def test_cascade_and_complete_cases(spark):
    a = spark.createDataFrame([("1", "Anna", "x"), ("2", "Bert", None)], "record_id string, n string, v string")
    b = spark.createDataFrame([("3", "Anna", "x"), ("4", "Burt", "y")], "record_id string, n string, v string")
    stages = [lambda x, y: simple.exact_link(x, y, ("n", "v")), lambda x, y: simple.phonetic_link(x, y, ("n",), ())]
    assert sorted((r["a_id"], r["b_id"], r["stage"]) for r in simple.cascade_link(a, b, stages).collect()) == [("1", "3", 1), ("2", "4", 2)]
    assert simple.complete_case(a, ("n", "v"))[0].count() == 1
    assert simple.complete_case(a, ("n", "v"), "attributes")[1] == ["n"]
    assert simple.brute_force_link(a, b, ("n",), 0.75).count() == 2


def test_range_test_table_values():
    assert evaluate.critical_range(0.05, 5, 20) == pytest.approx(4.23, abs=0.02)
    assert evaluate.critical_range(0.05, 3, 12) == pytest.approx(3.77, abs=0.02)


def test_perturbations_hit_their_shares(spark, small):
    p = views.person(spark, small)
    n = p.count()
    assert n == p.select("record_id").distinct().count()
    hit = perturb.inject_mcar(p, w.VOTER, 0.2, 5)
    lacks = hit.where(" OR ".join(f"{c} IS NULL" for c in w.VOTER)).count() / n
    assert lacks == pytest.approx(0.2, abs=0.02)
    rates = {r["attr"]: r["rate"] for r in evaluate.change_rates(p, perturb.drift(p, w.VOTER_RATES), list(w.VOTER_RATES)).collect()}
    assert rates["street"] == pytest.approx(0.17, abs=0.02)
    assert perturb.inject_mcar(p, w.VOTER, 0.0, 5).exceptAll(p).count() == 0
    a, b = perturb.snapshots(p, 0.94, 0.92, 0.89)
    both = a.join(b, "record_id", "left_semi").count()
    assert both / b.count() == pytest.approx(0.89, abs=0.04)


def test_jaro_winkler():
    assert jaro_winkler("MARTHA", "MARHTA") == pytest.approx(0.961111, abs=1e-5)
    assert jaro_winkler("DIXON", "DICKSONX") == pytest.approx(0.813333, abs=1e-5)
    assert jaro_winkler("", "a") == 0


def test_similarity_join_equals_all_pairs(spark):
    import random

    rng = random.Random(1)
    sets = [(i, sorted({f"t{rng.randrange(12)}" for _ in range(rng.randrange(1, 8))})) for i in range(60)]
    a = spark.createDataFrame(sets, "x long, runs array<string>")
    got = {(r[0], r[1]) for r in joins.similarity_join(a, a.withColumnRenamed("x", "y"), "x", "y", "runs", 0.6).collect()}
    assert got == {(i, j) for i, s in sets for j, t in sets if len(set(s) & set(t)) >= 0.6 * len(set(s) | set(t)) - 1e-9}


def test_no_cartesian_product_in_the_plan(spark, small):
    p = w.PAIRS["w4"](spark, small)
    sa, sb = signatures.kept_signatures(p.a, p.b, p.qids, select.fixed_combinations(p.combos))
    from reclink.operators.match import scored_pairs

    plan = scored_pairs(sa, sb)._jdf.queryExecution().executedPlan().toString()
    assert "Cartesian" not in plan and "NestedLoop" not in plan


def test_scans_read_the_columns_in_use_only(spark, small):
    p = w.PAIRS["w4"](spark, small)
    plan = signatures.attribute_signatures(p.a, p.qids, select.fixed_combinations([("given", "family")]))._jdf.queryExecution().executedPlan().toString()
    scan = next(line for line in plan.splitlines() if "ReadSchema" in line)
    assert "given" in scan and "family" in scan
    assert not any(c in scan.split("ReadSchema")[1] for c in ("occupation", "parish", "street"))


def test_joining_candidates_filters_before_the_exchange(spark, small):
    """Signatures without all their parts are dropped in the scan's stage, not after a shuffle."""
    p = w.PAIRS["w4"](spark, small)
    sigs = signatures.attribute_signatures(p.a, p.qids, select.fixed_combinations(p.combos))
    assert "Exchange" not in sigs._jdf.queryExecution().executedPlan().toString()


def test_unknown_column_is_refused(spark, small):
    with pytest.raises(ValueError):
        select.select_combinations(views.person(spark, small), [Qid("no")])
