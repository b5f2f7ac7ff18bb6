"""Ground truth of the workloads."""

from reclink.queries import compare, workloads


def test_large_groups_of_near_copies_are_true_pairs(spark):
    """60 records on each side share all runs but one of their own."""
    common = [f"run {i}" for i in range(20)]
    side = lambda k: spark.createDataFrame([(f"{k}{i}", [*common, f"{k} own {i // 2}"]) for i in range(60)], "record_id string, runs array<string>")
    assert workloads.papers_truth(side("a"), side("b")).distinct().count() == 3600


def test_methods_are_compared_on_all_workloads(spark, monkeypatch):
    monkeypatch.setattr(compare, "compare_methods", lambda spark, d, name: spark.createDataFrame([(name,)], "workload string"))
    assert sorted(r[0] for r in compare.wl_w9(spark, "").collect()) == ["w1", "w2", "w3", "w4", "w5", "w6"]
