"""Perturbations on awkward values, sizes of record graphs, the planned table function."""

import itertools

import pytest
from pyspark.errors import AnalysisException
from pyspark.sql import functions as F

from reclink.functions import udx
from reclink.operators import graph, perturb, select
from reclink.plans.model import Qid


def test_shifted_dates(spark):
    values = ["2020-02-29", "2021-02-30", "1999", "", None, "no date", "0001-01-15"]
    rows = spark.createDataFrame([(f"r{i}", values[i % 7]) for i in range(700)], "record_id string, birth string")
    found = perturb.shift_dates(rows, ("birth",), share=0.5, most_days=10).withColumnRenamed("birth", "new").join(rows, "record_id")
    assert found.where("birth IN ('2021-02-30', '1999', '', 'no date') AND new <> birth OR (birth IS NULL) <> (new IS NULL)").count() == 0
    days = [r["d"] for r in found.where("birth = '2020-02-29'").select(F.date_diff(F.to_date("new"), F.to_date("birth")).alias("d")).collect()]
    assert 25 < sum(d != 0 for d in days) < 75 and min(days) >= -10 and max(days) <= 10 and min(days) < 0 < max(days)
    assert perturb.shift_dates(rows.limit(0), ("birth",)).count() == 0


def test_picked_attributes(spark):
    """`run` hits neighbours in the list of attributes only, `any` every set of up to three."""
    names = list("abcde")
    rows = spark.range(4000).select(F.col("id").cast("string").alias("record_id"), *[F.lit("v").alias(a) for a in names])
    runs = {frozenset(names[(i + k) % 5] for k in range(c)) for i in range(5) for c in (1, 2, 3)}
    sets = {frozenset(x) for c in (1, 2, 3) for x in itertools.combinations(names, c)}
    for pick, want in (("run", runs), ("any", sets)):
        lost = perturb.inject_mcar(rows, names, 0.5, 3, pick=pick).collect()
        seen = {frozenset(a for a in names if r[a] is None) for r in lost} - {frozenset()}
        assert seen == want
        assert 0.45 < sum(any(r[a] is None for a in names) for r in lost) / 4000 < 0.55


@pytest.mark.parametrize("size", [3, 60])
def test_graph_counts(spark, size):
    """Two groups that share two records: neither edges nor triangles count twice."""
    groups = [(f"r{i}", 0, "x") for i in range(size)] + [(f"r{i}", 0, "y") for i in range(size - 2, 2 * size)]
    members = spark.createDataFrame([(*g, None) for g in groups], "record_id string, rule_id int, group_key string, role string")
    pairs = {p for _, key in ((0, "x"), (0, "y")) for p in itertools.combinations(sorted(r for r, _, k in groups if k == key), 2)}
    near = {}
    for a, b in pairs:
        near.setdefault(a, set()).add(b)
        near.setdefault(b, set()).add(a)
    triangles = sum(len(near[a] & near[b]) for a, b in pairs) // 3
    assert tuple(graph.Stars(members).counts().first()) == (len(pairs), triangles)
    assert tuple(graph.Stars(members.limit(0)).counts().first()) == (0, 0)


def test_counted_groups(spark):
    rows = spark.createDataFrame([("a", "x", None), ("a", "y", "1"), ("b", "x", "1"), ("b", "x", "1")], "p string, q string, r string")
    trace = select.Selection()
    select.select_combinations(rows, [Qid(c) for c in "pqr"], c_t=0.0, trace=trace)
    assert trace.groups == {3: 3, 5: 2, 6: 2, 7: 2}


def test_planned_table_function(spark):
    spark.udtf.register("combination_rows", udx.CombinationRows)
    spark.createDataFrame([(7, "a", None), (8, "b", "c")], "k long, x string, y string").createOrReplaceTempView("v_planned")
    found = spark.sql("SELECT * FROM combination_rows(TABLE(v_planned), 'k', 'x;x,y')")
    assert found.dtypes[0] == ("k", "bigint")
    assert sorted(map(tuple, found.collect())) == [(7, 1, "a"), (8, 1, "b"), (8, 2, "b|c")]
    with pytest.raises(AnalysisException, match="no column z"):
        spark.sql("SELECT * FROM combination_rows(TABLE(v_planned), 'k', 'x,z')").collect()
