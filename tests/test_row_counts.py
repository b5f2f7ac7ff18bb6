"""Databases by row numbers: counted pairs and matches are those of the steps that list them."""

import random
from dataclasses import replace

from pyspark.sql import functions as F

from reclink.baselines import prob_signature, simple
from reclink.operators import evaluate, match, pairing, perturb, select, signatures
from reclink.plans.model import Qid, Settings
from reclink.queries import workloads
from reclink.sources import store, views

QIDS, ATTRS = [Qid(a) for a in "xyz"], "xyz"
COMBOS = select.fixed_combinations([("x", "z"), ("y", "z")])


def _twins(spark):
    rng = random.Random(5)
    rows = [(str(i), *[rng.choice([None, "1", "2", "3", "4"]) for _ in ATTRS]) for i in range(80)]
    records = store.keep(spark.createDataFrame(rows, "record_id string, x string, y string, z string"))
    change = lambda x: perturb.corrupt(perturb.inject_mcar(x, ATTRS, 0.3, 2), ATTRS)
    return workloads.twins(lambda i, n: store.part(records, "record_id", i, n), 2, ATTRS, change)


def test_pairs_matches_and_complete_cases_are_counted(spark):
    a, b, rows = _twins(spark)
    truth, settings = evaluate.truth_of(a, b), Settings(s_t=0.6, beta=1.0)
    sa, sb = signatures.written_signatures(a, b, QIDS, COMBOS, settings)
    count = lambda kinds: {r["match"]: r["n"] for r in kinds.collect()}

    def listed(pairs):
        row = evaluate.precision_recall(pairs, truth).first()
        return {k: n for k, n in ((True, row["tp"]), (False, row["predicted"] - row["tp"])) if n}

    pairs = store.keep(match.candidate_pairs(sa, sb))
    found = pairing.pair_counts(rows, QIDS, COMBOS, settings)
    assert count(found) == listed(pairs) and len(count(found)) == 2
    assert evaluate.blocking_of_counts(found, 80, 80, 80).first() == evaluate.blocking_quality(pairs, truth, 80, 80).first()
    assert count(match.link_counts(rows, QIDS, COMBOS, settings)) == listed(match.link(a, b, QIDS, [], COMBOS, settings).pairs)
    whole, _ = simple.complete_case(b, ATTRS)
    some = signatures.written_signatures(a, whole, QIDS, COMBOS, settings)
    counted = prob_signature.prob_signature_counts(simple.complete_rows(rows, ATTRS), QIDS, COMBOS, settings=settings)
    assert count(counted) == listed(prob_signature.prob_signature_link(*some, settings=settings)) and 0 < whole.count() < 80


def test_slices_are_read_by_one_scan(spark):
    """A plan on a step of many slices does not grow with their number."""
    out = store.in_slices(lambda i: spark.range(10 * i, 10 * i + 10), 4, "slice")
    assert out._jdf.queryExecution().optimizedPlan().collectLeaves().size() == 1
    assert sorted(r["id"] for r in out.collect()) == list(range(40)) and len(out._kept) == 4


def test_the_limit_of_methods_is_put_back(spark):
    name = "spark.sql.codegen.hugeMethodLimit"
    before = spark.conf.get(name)
    with store.small_methods(spark):
        assert spark.conf.get(name) == "8000"
    assert spark.conf.get(name) == before


def test_one_database_by_rows_has_the_relations_of_its_records(spark):
    a, b, rows = _twins(spark)
    from reclink.plans.model import Rule

    settings, rules = replace(Settings(), s_t=0.7), [Rule.conj(("x", "y"))]
    theirs = evaluate.precision_recall(match.link(a, b, QIDS, rules, COMBOS, settings, every=False).pairs, evaluate.truth_of(a, b)).first()
    found = match.link(rows.side("a", ATTRS), rows.side("b", ATTRS), QIDS, rules, COMBOS, settings, every=False).pairs
    mine = found.agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("a_id") == F.col("b_id")).alias("tp")).first()
    assert (mine["n"], mine["tp"]) == (theirs["predicted"], theirs["tp"])


def test_phonetic_matches_are_counted_without_pairs(spark, small, monkeypatch):
    """Counts of sliced databases are those of the listed pairs; pairs leave no files."""
    p, names = workloads.PAIRS["w7"](spark, small), (("given", "family"), ("birth",))
    theirs = evaluate.precision_recall(simple.phonetic_link(p.a, p.b, *names), p.truth).first()
    monkeypatch.setattr(store, "SLICE_BYTES", 1)
    monkeypatch.setattr(store, "SLICES", 2)
    slices = workloads.national_slices(spark, small)
    written, keep = [], store.keep
    monkeypatch.setattr(store, "keep", lambda df, name="step", **options: written.append(df.columns) or keep(df, name, **options))
    assert evaluate.accuracy_of_counts(*simple.phonetic_counts(slices, *names)).first() == theirs and theirs["tp"] and len(slices) == 2
    assert not [x for x in written if {"a_id", "record_id"} & set(x)]


def test_relations_of_documents_write_no_words(spark, small):
    """Titles and authors are those of the whole view, without its words as files."""
    heads = views.publication_heads(spark, small)
    theirs = views.publication(spark, small).select(heads.columns)
    rows = lambda df: sorted((r[0], r[1], tuple(r[2])) for r in df.collect())
    assert rows(heads) == rows(theirs) != []
    assert store.read_bytes(heads) * 2 < store.read_bytes(theirs)
