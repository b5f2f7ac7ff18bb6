"""Steps that leave little on disk: slices of signatures, pairs that can match, shuffle files."""

import random

import pytest
from pyspark.sql import functions as F

from reclink.baselines import comparison, prob_signature, probabilistic
from reclink.operators import evaluate, match, pairing, perturb, select, signatures
from reclink.plans.model import Qid, Settings
from reclink.queries import workloads
from reclink.sources import store, views

QIDS = [Qid(a) for a in "xyz"]
COMBOS = select.fixed_combinations([("x", "y"), ("x", "z"), ("y", "z"), ("x", "y", "z")])


def _records(spark, prefix, seed):
    rng = random.Random(seed)
    rows = [(f"{prefix}{i}", *[rng.choice([None, "1", "2", "3", "4"]) for _ in "xyz"]) for i in range(80)]
    return spark.createDataFrame(rows, "record_id string, x string, y string, z string")


def _shuffles(spark):
    files = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
    return {files.apply(i).getName() for i in range(files.size()) if files.apply(i).getName().startswith("shuffle_")}


def test_sliced_signatures_and_reachable_pairs(spark, monkeypatch):
    a, b = _records(spark, "a", 1), _records(spark, "b", 2)
    whole = signatures.kept_signatures(a, b, QIDS, COMBOS)
    monkeypatch.setattr(signatures, "SLICE_BYTES", 1)
    sliced = signatures.kept_signatures(a, b, QIDS, COMBOS)
    rows = lambda df: sorted(tuple(r) for r in df.select("record_id", "combo_id", "sig_hash", "sig_check").collect())
    assert [rows(x) for x in whole] == [rows(x) for x in sliced] and rows(whole[0])
    every = [store.keep(signatures.attribute_signatures(x, QIDS, COMBOS).drop("sig")) for x in (a, b)]
    found = lambda df: sorted((r["a_id"], r["b_id"], r["common"], round(r["s_a"], 9)) for r in df.collect())
    want = found(match.scored_pairs(*every))
    assert found(match.similar_pairs(*every, 0.6)) == [r for r in want if r[3] >= 0.6 - 1e-9]


def test_a_written_step_leaves_no_shuffle_files(spark):
    before = _shuffles(spark)
    kept = store.keep(spark.range(1000).selectExpr("id % 7 AS k").groupBy("k").count())
    assert _shuffles(spark) <= before
    assert kept.count() == 7


def test_pairs_are_compared_and_counted_in_slices(spark, monkeypatch):
    a, b = _records(spark, "a", 1), _records(spark, "b", 2)
    sa, sb = (store.keep(signatures.attribute_signatures(x, QIDS, COMBOS).drop("sig")) for x in (a, b))
    a, b = (x.withColumn("entity_id", F.substring("record_id", 2, 9)) for x in (a, b))
    rows = lambda df: sorted(tuple(r) for r in df.collect())
    levels = store.keep(comparison.compared(a, b, match.candidate_pairs(sa, sb), "xyz"))
    truth = evaluate.truth_of(a, b)
    whole = rows(levels), rows(probabilistic.estimate_mu(levels, truth, "xyz")), rows(evaluate.precision_recall(levels, truth))
    monkeypatch.setattr(store, "SLICE_BYTES", 1)
    monkeypatch.setattr(store, "SLICES", 3)
    a, b = store.keep(a), store.keep(b)
    before = _shuffles(spark)
    sliced = comparison.compared_candidates(a, b, sa, sb, "xyz")
    truth = evaluate.truth_of(a, b)
    counts = probabilistic.estimate_mu(sliced, truth, "xyz"), evaluate.precision_recall(sliced, truth)
    assert _shuffles(spark) <= before
    assert (rows(sliced), *map(rows, counts)) == whole and whole[0]


def test_scores_by_probability_in_slices(spark, monkeypatch):
    a, b = _records(spark, "a", 1), _records(spark, "b", 2)
    combos = COMBOS[3:]
    sa, sb = (store.keep(x.drop("sig")) for x in signatures.kept_signatures(a, b, QIDS, combos))
    held = [{(r["sig_hash"], r["record_id"]) for r in s.collect()} for s in (sa, sb)]
    n = lambda h: max(sum(x[0] == h for x in side) for side in held)
    want = sorted((i, j, round(1 / (1 + 0.2 * 1.2 ** n(h)), 9)) for h, i in held[0] for g, j in held[1] if g == h)
    monkeypatch.setattr(store, "SLICE_BYTES", 1)
    monkeypatch.setattr(store, "SLICES", 3)
    for score in ("max", "noisy_or"):
        got = lambda s_t: sorted((*r[:2], round(r[2], 9)) for r in prob_signature.prob_signature_link(sa, sb, score, Settings(s_t=s_t)).collect())
        assert got(0.1) == want and got(0.75) == [r for r in want if r[2] >= 0.75] != []


def test_sliced_signatures_are_written_once(spark, monkeypatch):
    a, b = store.keep(_records(spark, "a", 1)), store.keep(_records(spark, "b", 2))
    monkeypatch.setattr(signatures, "SLICE_BYTES", 1)
    written, again = signatures.written_signatures(a, b, QIDS, COMBOS, keep=lambda df, name: pytest.fail(f"{name} written twice"))
    assert written.count() and again.count()


def test_both_databases_of_persons_are_one_file_without_wide_shuffles(spark, small, monkeypatch):
    whole = workloads.voter(spark, small, 0.2)
    rows = lambda df: sorted(map(str, df.collect()))
    want = rows(whole.a), rows(whole.b)
    base = views.person(spark, small)
    changed = perturb.rename_ids(perturb.corrupt(perturb.inject_mcar(base, workloads.VOTER, 0.2, 5), workloads.VOTER), "b")
    assert want == tuple(rows(x.select(whole.a.columns)) for x in (base, changed))
    monkeypatch.setattr(store, "SLICE_BYTES", 1)
    monkeypatch.setattr(store, "SLICES", 3)
    sliced = workloads.voter(spark, small, 0.2)
    assert (rows(sliced.a), rows(sliced.b)) == want
    assert set(sliced.a.inputFiles()) == set(sliced.b.inputFiles())


@pytest.mark.parametrize("few", [0, 8 << 20])
def test_true_pairs_are_found_without_joining_the_databases(spark, monkeypatch, few):
    a, b = (store.keep(_records(spark, p, 1).withColumn("entity_id", F.expr("nullif(floor(substring(record_id, 2) / 3), 5)"))) for p in "ab")
    pairs = store.keep(a.select(F.col("record_id").alias("a_id")).join(b.select(F.col("record_id").alias("b_id")), F.expr("substring(a_id, 2) % 7 = substring(b_id, 2) % 5")))
    truth = evaluate.truth_of(a, b)
    want = pairs.join(truth, ["a_id", "b_id"]).count(), truth.count()
    monkeypatch.setattr(store, "SLICE_BYTES", 1)
    monkeypatch.setattr(store, "SLICES", 3)
    monkeypatch.setattr(evaluate, "FEW_BYTES", few)
    monkeypatch.setattr(evaluate, "written_truth", lambda truth: truth if evaluate.sides_of(truth) else pytest.fail("truth is joined"))
    row = evaluate.precision_recall(pairs, truth).first()
    assert (row["tp"], row["truth"]) == want and row["predicted"] == pairs.count() and row["tp"]


def test_signatures_that_meet_few_others(spark, monkeypatch):
    a, b = _records(spark, "a", 1).limit(5), _records(spark, "b", 2)
    sa, sb = (store.keep(signatures.attribute_signatures(x, QIDS, COMBOS).drop("sig")) for x in (a, b))
    rows = lambda df: sorted(tuple(r) for r in df.collect())
    want = rows(match.similar_pairs(sa, sb, 0.3))
    both = match.candidate_pairs(sa, sb).count()
    monkeypatch.setattr(match, "FEW_BYTES", store.read_bytes(sa))
    assert store.read_bytes(sb) > match.FEW_BYTES
    left, right = match.meeting(sa, sb)
    assert left is sa and 0 < right.count() < sb.count() and match.candidate_pairs(left, right).count() == both
    assert rows(match.similar_pairs(sa, sb, 0.3)) == want != []


def test_pairs_are_counted_by_row_numbers(spark, monkeypatch):
    """Slices that share pairs, signatures of many records and those over the cap give the counts
    of the pairs themselves; neither pairs nor all signatures' hashes are written."""
    for name, value in (("HOT", 16), ("LOOK", 2), ("PARTS", 2)):
        monkeypatch.setattr(pairing, name, value)
    records = store.keep(_records(spark, "", 5))
    a, b, rows = workloads.twins(lambda i, n: store.part(records, "record_id", i, n), 2, "xyz", lambda x: perturb.corrupt(perturb.inject_mcar(x, "xyz", 0.3, 2), "xyz"))
    truth, settings, combos = evaluate.truth_of(a, b), Settings(s_t=0.6), COMBOS[1:3]
    written, keep = [], store.keep
    monkeypatch.setattr(store, "keep", lambda df, name="step", **options: written.append((name, df.columns)) or keep(df, name, **options))
    kinds = comparison.compared_kinds(rows, QIDS, combos, "xyz", settings)
    counts = {score: {r["match"]: r["n"] for r in prob_signature.prob_signature_counts(rows, QIDS, combos, score, settings).collect()} for score in ("jaccard", "noisy_or")}
    assert not [x for x in written if {"h", "c", "sig_hash", "a_id"} & set(x[1]) and x[0] != "hot"] and any(name == "known" for name, _ in written)

    sa, sb = signatures.written_signatures(a, b, QIDS, combos, settings)
    levels = comparison.compared_candidates(a, b, sa, sb, "xyz")
    true = truth.select("a_id", "b_id", F.lit(True).alias("t"))
    names = ["match", "l_x", "l_y", "l_z"]
    expected = levels.join(true, ["a_id", "b_id"], "left").withColumn("match", F.coalesce("t", F.lit(False))).groupBy(*names).count()
    assert levels.count() > 80 and rows.count() == 80
    assert sorted(map(tuple, kinds.select(*names, "n").collect())) == sorted(map(tuple, expected.collect()))
    for score, found in counts.items():
        theirs = evaluate.precision_recall(prob_signature.prob_signature_link(sa, sb, score, settings), truth).first()
        assert (sum(found.values()), found.get(True, 0)) == (theirs["predicted"], theirs["tp"]), score


def test_repeated_ids_have_no_row_numbers(spark):
    records = store.keep(_records(spark, "", 5))
    twice = store.keep(records.unionByName(records.limit(1)))
    assert workloads.twins(lambda i, n: store.part(twice, "record_id", i, n), 2, "xyz", lambda x: x)[2] is None
