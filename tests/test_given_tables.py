"""Queries whose rows come from given tables and not from literals."""

import pytest

from reclink.queries import ORACLES, QUERIES


@pytest.mark.parametrize("name", ["ev_tukey_stats", "sel_fixed", "sel_random", "sig_probability", "wl_w0"])
def test_files_are_read(spark, small, name):
    assert QUERIES[name](spark, small).inputFiles() and name in ORACLES


def test_python_source_reads_each_row_once(spark, small):
    got = QUERIES["src_python_datasource"](spark, small)
    assert sorted(r["record_id"] for r in got.collect()) == sorted(r[0] for r in spark.read.parquet(f"{small}/customer.parquet").select("c_custkey").collect())
