"""Attribute selection on the voter view with a fifth of its records missing values."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F

from reclink.operators import perturb, select
from reclink.plans.model import Qid
from reclink.queries import _sql as s
from reclink.queries._registry import query
from reclink.queries.workloads import VOTER
from reclink.sources import views
from reclink.sources.store import keep

QIDS = [Qid(a) for a in VOTER]
ALPHA, C_T = 0.5, 0.7


def gaps(spark, sf_dir):
    return perturb.inject_mcar(views.person(spark, sf_dir), VOTER, 0.2, 5)


GAPS = s.Ctes(("person", s.PERSON), ("d", s.mcar("person", VOTER, 0.2, 5)))
NAME = s.named(VOTER)


def _scores(low: int = 2, high: int = 6, table: str = "d", masks=None) -> str:
    return s.scores(VOTER, table, low, high, masks, ALPHA)


def _fresh() -> s.Ctes:
    return s.Ctes(*GAPS.parts)


def _levels(c_t: float = C_T, how: str = "apriori") -> s.Ctes:
    return s.passing(_fresh().add("sc", _scores()), c_t, how=how)


SHOWN = f"{NAME} AS attrs, round(s_c, 6) AS s_c, round(s_g, 6) AS s_g, round(score, 6) AS score"
DROP = s.LARGEST
DOMINATED = "NOT EXISTS (SELECT 1 FROM passing o WHERE o.mask <> p.mask AND o.mask & p.mask = p.mask AND o.score >= p.score - 1e-9)"


def _frame(spark, combos):
    rows = [(",".join(c.attrs), round(c.s_c, 6), round(c.s_g, 6), round(c.score, 6)) for c in combos]
    return spark.createDataFrame(rows, "attrs string, s_c double, s_g double, score double")


def _all(spark, sf_dir, **options):
    return _frame(spark, select.select_combinations(keep(gaps(spark, sf_dir)), QIDS, n_a=99, alpha=ALPHA, c_t=C_T, **options))


@query(_fresh().then("SELECT round(avg(CASE WHEN given IS NOT NULL AND family IS NOT NULL THEN 1.0 ELSE 0.0 END), 6) AS s_c FROM d"))
def sel_completeness(spark, sf_dir):
    return select.completeness(gaps(spark, sf_dir), [Qid("given"), Qid("family")]).select(F.round("s_c", 6).alias("s_c"))


@query(_fresh().then("SELECT CAST(" + " + ".join(f"CASE WHEN {a} IS NULL THEN {1 << i} ELSE 0 END" for i, a in enumerate(VOTER)) + " AS INTEGER) AS mask, count(*) AS cnt FROM d GROUP BY 1"))
def sel_null_patterns(spark, sf_dir):
    return select.null_patterns(gaps(spark, sf_dir), QIDS)


@query(_fresh().add("sc", _scores(masks=[5])).then("SELECT round(s_g, 6) AS s_g FROM sc"))
def sel_gini(spark, sf_dir):
    return select.gini(gaps(spark, sf_dir), [Qid("given"), Qid("family")]).select(F.round("s_g", 6).alias("s_g"))


@query(_fresh().add("sc", _scores(high=2)).then(f"SELECT {SHOWN} FROM sc"))
def sel_score_pairs(spark, sf_dir):
    found = select.select_combinations(keep(gaps(spark, sf_dir)), QIDS, n_a=99, alpha=ALPHA, c_t=0.0, max_size=2, subset_policy="keep")
    return _frame(spark, found)


def _grown() -> str:
    """Masks that each level looks at: all pairs, then those all of whose parts passed."""
    seen = [f"SELECT 2 AS level, {NAME} AS attrs FROM sc WHERE k = 2"]
    seen += [f"SELECT {k} AS level, {NAME} AS attrs FROM sc x WHERE k = {k} AND (SELECT count(*) FROM p{k - 1} p WHERE p.mask & x.mask = p.mask) = {k}" for k in range(3, 7)]
    return _levels().then(" UNION ALL ".join(seen))


@query(_grown())
def sel_levels(spark, sf_dir):
    trace = select.Selection()
    select.select_combinations(keep(gaps(spark, sf_dir)), QIDS, alpha=ALPHA, c_t=C_T, trace=trace)
    rows = [(k, ",".join(select.attrs_of(m, QIDS))) for k, level in enumerate(trace.levels, 2) for m in sorted(level)]
    return spark.createDataFrame(rows, "level int, attrs string")


def _counted() -> str:
    c = _levels()
    seen = ["SELECT 2 AS level, mask, s_c FROM sc WHERE k = 2"]
    seen += [f"SELECT {k} AS level, mask, s_c FROM sc x WHERE k = {k} AND (SELECT count(*) FROM p{k - 1} p WHERE p.mask & x.mask = p.mask) = {k}" for k in range(3, 7)]
    groups = []
    for m in (m for m in range(1, 64) if m.bit_count() >= 2):
        own = [a for i, a in enumerate(VOTER) if m >> i & 1]
        groups.append(f"SELECT {m} AS mask, count(*) AS groups FROM (SELECT 1 FROM d WHERE {' AND '.join(f'{a} IS NOT NULL' for a in own)} GROUP BY {', '.join(own)})")
    c.add("seen", " UNION ALL ".join(seen)).add("grouped", " UNION ALL ".join(groups))
    return c.then(f"SELECT level, count(*) AS combinations, CAST(sum(groups) AS BIGINT) AS groups FROM seen JOIN grouped USING (mask) WHERE s_c >= {C_T - 1e-9} GROUP BY level")


@query(_counted())
def ev_counters_levels(spark, sf_dir):
    """Combinations that each level scores, and the groups that it forms for them."""
    trace = select.Selection()
    select.select_combinations(keep(gaps(spark, sf_dir)), QIDS, alpha=ALPHA, c_t=C_T, trace=trace)
    looked = [[m for m in level if m in trace.groups] for level in trace.levels]
    rows = [(k, len(masks), sum(trace.groups[m] for m in masks)) for k, masks in enumerate(looked, 2) if masks]
    return spark.createDataFrame(rows, "level int, combinations long, groups long")


@query(_fresh().add("sc", _scores(low=3, high=3)).then(f"SELECT {NAME} AS attrs, round(s_c, 6) AS s_c FROM sc"))
def sel_level_grouping_sets(spark, sf_dir):
    d = gaps(spark, sf_dir)
    masks = [m for m in range(64) if m.bit_count() == 3]
    sums = select.grouping_sets_sums(d, QIDS, masks)
    name = F.create_map(*[F.lit(x) for m in masks for x in (m, ",".join(select.attrs_of(m, QIDS)))])
    return sums.crossJoin(F.broadcast(d.agg(F.count(F.lit(1)).alias("n")))).select(name[F.col("mask")].alias("attrs"), F.round(F.col("sf") / F.col("n"), 6).alias("s_c"))


@query(_levels().then(f"SELECT {SHOWN} FROM passing"))
def sel_apriori(spark, sf_dir):
    return _all(spark, sf_dir, subset_policy="keep")


@query(_levels(how="none").then(f"SELECT {SHOWN} FROM passing"))
def sel_exhaustive(spark, sf_dir):
    return _all(spark, sf_dir, subset_policy="keep", prune="none")


@query(_levels(how="none").then(f"SELECT {SHOWN} FROM passing"))
def sel_completeness_prune(spark, sf_dir):
    return _all(spark, sf_dir, subset_policy="keep", prune="completeness")


@query(_levels().then(f"SELECT {SHOWN} FROM passing p WHERE {DROP}"))
def sel_subset_removal(spark, sf_dir):
    return _all(spark, sf_dir, subset_policy="drop")


@query(_levels().then(f"SELECT {SHOWN} FROM passing p WHERE {DOMINATED}"))
def sel_subset_dominated(spark, sf_dir):
    return _all(spark, sf_dir, subset_policy="dominated")


@query(_levels().then(f"SELECT {SHOWN} FROM (SELECT *, {NAME} AS nm FROM passing) ORDER BY round(score, 9) DESC, k, nm LIMIT 3"))
def sel_top(spark, sf_dir):
    return _frame(spark, select.select_combinations(keep(gaps(spark, sf_dir)), QIDS, n_a=3, alpha=ALPHA, c_t=C_T, subset_policy="keep"))


@query(_levels().then(f"SELECT {SHOWN} FROM (SELECT *, {NAME} AS nm FROM passing p WHERE {DROP}) ORDER BY round(score, 9) DESC, k, nm LIMIT 5"))
def sel_full(spark, sf_dir):
    return _frame(spark, select.select_combinations(keep(gaps(spark, sf_dir)), QIDS, n_a=5, alpha=ALPHA, c_t=C_T))


def _complete(combos) -> str:
    """Completeness of given combinations."""
    each = [f"SELECT '{','.join(c.attrs)}' AS attrs, round(avg(CASE WHEN {' AND '.join(f'{a} IS NOT NULL' for a in c.attrs)} THEN 1.0 ELSE 0.0 END), 6) AS s_c FROM d" for c in combos]
    return _fresh().then(" UNION ALL ".join(each))


def _completed(spark, sf_dir, combos):
    there = lambda c: F.when(reduce(Column.__and__, [F.col(a).isNotNull() for a in c.attrs]), 1.0).otherwise(0.0)
    shares = gaps(spark, sf_dir).agg(*[F.round(F.avg(there(c)), 6).alias(f"s{i}") for i, c in enumerate(combos)])
    rows = F.array(*[F.struct(F.lit(",".join(c.attrs)).alias("attrs"), F.col(f"s{i}").alias("s_c")) for i, c in enumerate(combos)])
    return shares.select(F.explode(rows).alias("r")).select("r.*")


RANDOM, FIXED = select.random_combinations(QIDS, 5, seed=3), select.fixed_combinations([("given", "family"), ("given", "street")])


@query(_complete(RANDOM))
def sel_random(spark, sf_dir):
    """Combinations drawn at random, with their completeness."""
    return _completed(spark, sf_dir, RANDOM)


@query(_complete(FIXED))
def sel_fixed(spark, sf_dir):
    """Given combinations, with their completeness."""
    return _completed(spark, sf_dir, FIXED)


@query(_fresh().then(" UNION ALL ".join(f"SELECT '{a}' AS attr, round(avg(CASE WHEN {a} IS NULL THEN 1.0 ELSE 0.0 END), 6) AS missing_share FROM d" for a in VOTER)))
def sel_criterion(spark, sf_dir):
    return select.missing_shares(gaps(spark, sf_dir), QIDS).select("attr", F.round("missing_share", 6).alias("missing_share"))


@query()
def sel_gini_ams(spark, sf_dir):
    masks = [m for m in range(64) if m.bit_count() == 2]
    squares = select.estimated_sums(keep(gaps(spark, sf_dir)), QIDS, masks, "ams", 64)
    return spark.createDataFrame([(",".join(select.attrs_of(m, QIDS)), v) for m, v in squares.items()], "attrs string, squares double")


@query()
def sel_gini_sample(spark, sf_dir):
    masks = [m for m in range(64) if m.bit_count() == 2]
    squares = select.estimated_sums(keep(gaps(spark, sf_dir)), QIDS, masks, "sample", 16)
    return spark.createDataFrame([(",".join(select.attrs_of(m, QIDS)), v) for m, v in squares.items()], "attrs string, squares double")


@query(_fresh().add("u", "SELECT * FROM person UNION ALL SELECT * FROM d").add("sc", _scores(high=2, table="u")).then(f"SELECT {SHOWN} FROM sc"))
def sel_scope(spark, sf_dir):
    both = keep(views.person(spark, sf_dir).unionByName(gaps(spark, sf_dir)))
    return _frame(spark, select.select_combinations(both, QIDS, n_a=99, alpha=ALPHA, c_t=0.0, max_size=2, subset_policy="keep"))
