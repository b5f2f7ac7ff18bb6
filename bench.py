"""Headline queries on $BENCH_SF_DIR with local[$BENCH_CPUS]; prints one JSON line.

Per workload also: seconds of each step, records per second, unique signatures, candidates,
precision and recall (to stderr as a table, and under "workloads" in the line).
"""

from __future__ import annotations

import json
import os
import sys
import time

HERE = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, HERE)

#: Queries that are timed whole.
HEADLINE = ("sel_full", "sig_filter")
#: Workloads that are linked step by step, with the selection, on records that are there.
WORKLOADS = tuple(os.environ.get("BENCH_WORKLOADS", "w2,w4,w6,w7").split(","))
#: The workload that the baselines run on.
BASELINES = os.environ.get("BENCH_BASELINES", "w4")


def session(cpus: str):
    from pyspark.sql import SparkSession

    spark = (
        SparkSession.builder.master(f"local[{cpus}]").appName("bench").config("spark.sql.shuffle.partitions", str(2 * int(cpus) if cpus.isdigit() else 16))
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "8g")).config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def steps(spark, pair) -> dict:
    """A workload with the selection step, each step written before the next begins."""
    from reclink.operators import evaluate, match, signatures

    a, b, truth = pair
    n = a.count() + b.count()
    r = match.link(a, b, pair.qids, pair.rules, None, pair.settings, max_size=3)
    got = evaluate.precision_recall(r.pairs, truth).first()
    both = signatures.attribute_signatures(a, pair.qids, r.combos).unionByName(signatures.attribute_signatures(b, pair.qids, r.combos))
    total = sum(r.timings.values())
    return {
        "records": n, **{k: round(v, 2) for k, v in r.timings.items()}, "total": round(total, 2), "records_per_sec": round(n / total), "combinations": [",".join(c.attrs) for c in r.combos],
        "unique_signatures": both.select("combo_id", "sig_hash").distinct().count(), "candidates": r.scored.count(), "precision": got["precision"], "recall": got["recall"],
    }


class Prepared:
    """A pair whose records and truth are files; making them is not measured."""

    def __init__(self, spark, sf_dir: str, name: str):
        from reclink.queries import workloads as w
        from reclink.sources.store import keep

        pair = w.PAIRS[name](spark, sf_dir)
        self.a, self.b, self.truth = keep(pair.a, "a"), keep(pair.b, "b"), keep(pair.truth, "truth")
        self.qids, self.rules, self.settings, self.attrs, self.combos = pair.qids, pair.rules, pair.settings, pair.attrs, pair.combos

    def __iter__(self):
        return iter((self.a, self.b, self.truth))


def baselines(pair) -> dict:
    """Seconds of the classical probabilistic linkage and of the signature baseline, from
    records to pairs, with the fixed combinations."""
    from reclink.baselines import comparison, prob_signature, probabilistic
    from reclink.operators import match, select, signatures
    from reclink.sources.store import keep

    combos, out = select.fixed_combinations(pair.combos), {}
    for name in ("probabilistic", "signatures"):
        started = time.monotonic()
        sa, sb = (keep(x.drop("sig"), "sig") for x in signatures.kept_signatures(pair.a, pair.b, pair.qids, combos, pair.settings))
        if name == "signatures":
            found = prob_signature.prob_signature_link(sa, sb)
        else:
            levels = keep(comparison.compared(pair.a, pair.b, match.candidate_pairs(sa, sb), pair.attrs), "levels")
            found = probabilistic.probabilistic_link(levels, probabilistic.estimate_mu(levels, pair.truth, pair.attrs))
        found.write.format("noop").mode("overwrite").save()
        out[name] = round(time.monotonic() - started, 2)
    return out


def main() -> None:
    sf_dir = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
    spark = session(os.environ.get("BENCH_CPUS", "8"))
    from reclink.queries import QUERIES

    QUERIES["op_project"](spark, sf_dir).count()  # start-up is not measured
    times = {}
    for name in HEADLINE:
        started = time.monotonic()
        QUERIES[name](spark, sf_dir).write.format("noop").mode("overwrite").save()
        times[name] = round(time.monotonic() - started, 3)
        print(f"{name}: {times[name]}", file=sys.stderr, flush=True)
    workloads = {}
    for name in WORKLOADS if WORKLOADS != ("",) else ():
        pair = Prepared(spark, sf_dir, name)
        workloads[name] = steps(spark, pair)
        if name == BASELINES:
            workloads[name]["baselines"] = baselines(pair)
            times |= {f"{name}_{k}": v for k, v in workloads[name]["baselines"].items()}
        times[f"{name}_link"] = workloads[name]["total"]
        print(f"{name}: {workloads[name]}", file=sys.stderr, flush=True)
    print(json.dumps({"metric": "headline_total", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "sf": os.path.basename(sf_dir.rstrip("/")).removeprefix("sf"), "workloads": workloads}))
    spark.stop()


if __name__ == "__main__":
    main()
