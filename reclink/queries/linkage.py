"""Signatures, relations, matching and the workloads."""

from __future__ import annotations

import dataclasses

from pyspark.sql import functions as F

from reclink.functions import text
from reclink.functions.hashing import salted
from reclink.operators import evaluate, graph, match, perturb, select, signatures
from reclink.plans import planner
from reclink.plans.model import Qid, Rule, Settings
from reclink.queries import _sql as s
from reclink.queries import workloads as w
from reclink.queries._registry import query
from reclink.queries.selection import GAPS, gaps
from reclink.sources import views
from reclink.sources.store import in_slices, keep, slices_of
from reclink.sources.tables import read

VQ = [Qid(a) for a in w.VOTER]
VC = select.fixed_combinations(w.VOTER_COMBOS)


def shown(sig):
    return F.translate(sig, signatures.SEPARATOR, "|")


def _gaps() -> s.Ctes:
    return s.Ctes(*GAPS.parts)


# ---------------------------------------------------------------- signatures
@query(
    s.Ctes(("person", s.PERSON)).then(
        """SELECT record_id, CAST(year(CAST(birth AS DATE)) AS VARCHAR) AS y, substr(given, 1, 3) AS p3, right(given, 3) AS s3, nullif(split_part(family, ' ', 2), '') AS t2,
        nullif(regexp_replace(street, '[^0-9]', '', 'g'), '') AS d, CASE WHEN length(trim(lower(family))) > 0 THEN trim(regexp_replace(lower(family), '\\s+', ' ', 'g')) END AS norm,
        CASE WHEN length(given) < 3 THEN 1 ELSE length(given) - 2 END AS grams FROM person"""
    )
)
def fn_tokens(spark, sf_dir):
    c = F.col
    return views.person(spark, sf_dir).select(
        "record_id", text.year_of(c("birth").cast("date")).alias("y"), text.prefix(3)(c("given")).alias("p3"), text.suffix(3)(c("given")).alias("s3"), text.nth_token(2)(c("family")).alias("t2"),
        text.digits(c("street")).alias("d"), text.normalise(c("family")).alias("norm"), F.size(text.qgrams(3)(c("given"))).alias("grams"),
    )


@query(s.Ctes(("person", s.PERSON), ("d", s.mcar("person", w.VOTER, 0.2, 5))).then("SELECT record_id, given || family || street AS sig FROM d WHERE given IS NOT NULL AND family IS NOT NULL AND street IS NOT NULL"))
def sig_strings(spark, sf_dir):
    sig = signatures.attribute_signature(select.fixed_combinations([("given", "family", "street")])[0], VQ, "plain")
    return gaps(spark, sf_dir).select("record_id", sig.alias("sig")).where("sig IS NOT NULL")


def _sigs(cap):
    return s.signatures(_gaps(), "d", w.VOTER_COMBOS, cap)


@query(_sigs(None).then("SELECT record_id, combo_id, replace(sig, chr(31), '|') AS sig FROM sd"))
def sig_long(spark, sf_dir):
    return signatures.attribute_signatures(gaps(spark, sf_dir), VQ, VC).select("record_id", "combo_id", shown("sig").alias("sig"))


@query(_sigs(None).then("SELECT combo_id, n, count(*) AS sigs FROM (SELECT combo_id, sig, count(*) AS n FROM sd GROUP BY ALL) GROUP BY ALL"))
def sig_counts(spark, sf_dir):
    counts = signatures.signature_counts(signatures.attribute_signatures(gaps(spark, sf_dir), VQ, VC))
    return counts.groupBy("combo_id", "n").agg(F.count(F.lit(1)).alias("sigs"))


@query("SELECT n, round(1 / (1 + pow(1.2, n) * 0.2), 6) AS p, round((1 + 1.2 * 0.2) / (1 + pow(1.2, n) * 0.2), 6) AS p_rel FROM (SELECT DISTINCT count(*) AS n FROM orders GROUP BY o_custkey)")
def sig_probability(spark, sf_dir):
    """The probability of each number of orders that share a customer."""
    n = F.col("n")
    shared = read(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n")).select("n").distinct()
    return shared.select(n, F.round(signatures.signature_probability(n), 6).alias("p"), F.round(signatures.signature_probability(n, mode="relative"), 6).alias("p_rel"))


@query(_sigs(8).then("SELECT record_id, combo_id, replace(sig, chr(31), '|') AS sig FROM sd"))
def sig_filter(spark, sf_dir):
    return signatures.filter_signatures(signatures.attribute_signatures(gaps(spark, sf_dir), VQ, VC)).select("record_id", "combo_id", shown("sig").alias("sig"))


SWEEP = (0.5, 0.6, 0.7, 0.8, 0.9)


def _sweep(mode: str) -> str:
    caps = [planner.n_max(p, mode=mode) for p in SWEEP]
    each = " UNION ALL ".join(f"SELECT CAST({p} AS DOUBLE) AS p_t, CAST(coalesce(sum(n) FILTER (n <= {cap}), 0) AS BIGINT) AS rows_kept, count(*) FILTER (n <= {cap}) AS sigs_kept FROM k" for p, cap in zip(SWEEP, caps))
    return _sigs(None).add("k", "SELECT combo_id, sig, count(*) AS n FROM sd GROUP BY ALL").then(each)


def _swept(spark, sf_dir, mode):
    counts = signatures.signature_counts(signatures.attribute_signatures(gaps(spark, sf_dir), VQ, VC))
    caps = F.explode(F.array(*[F.struct(F.lit(p).alias("p_t"), F.lit(planner.n_max(p, mode=mode)).alias("cap")) for p in SWEEP]))
    rows = counts.select("n", caps.alias("c")).groupBy("c.p_t").agg(F.sum(F.when(F.col("n") <= F.col("c.cap"), F.col("n")).otherwise(0)).alias("rows_kept"), F.count_if(F.col("n") <= F.col("c.cap")).alias("sigs_kept"))
    return rows.select("p_t", "rows_kept", "sigs_kept")


@query(_sweep("literal"))
def sig_filter_sweep(spark, sf_dir):
    return _swept(spark, sf_dir, "literal")


@query(_sweep("relative"))
def sig_filter_relative(spark, sf_dir):
    return _swept(spark, sf_dir, "relative")


@query(_sigs(None).then("SELECT record_id, combo_id, sha256('secret' || sig) AS digest FROM sd"))
def sig_salted(spark, sf_dir):
    return signatures.salted_signatures(signatures.attribute_signatures(gaps(spark, sf_dir), VQ, VC), "secret")


@query("SELECT c_custkey, sha256('k' || c_name) AS digest FROM customer")
def fn_salted(spark, sf_dir):
    return spark.read.parquet(f"{sf_dir}/customer.parquet").select("c_custkey", salted(F.col("c_name"), "k").alias("digest"))


# ---------------------------------------------------------------- relations
def _household(spark, sf_dir):
    return graph.membership(views.person(spark, sf_dir), [Rule.group("household")])


HOME = s.Ctes(("a", s.PERSON))


def _home() -> s.Ctes:
    return s.edges(s.Ctes(*HOME.parts), "a", "w7")


@query(s.Ctes(*HOME.parts).then("SELECT record_id, CAST(0 AS INTEGER) AS rule_id, CAST(household AS VARCHAR) AS group_key FROM a"))
def graph_membership(spark, sf_dir):
    return _household(spark, sf_dir).drop("role")


@query(_home().then("SELECT record_id AS src, neighbour AS dst FROM ea WHERE record_id < neighbour"))
def graph_edges(spark, sf_dir):
    return graph.edges(_household(spark, sf_dir))


def _pairs_by(key: str, table: str = s.PERSON) -> str:
    c = s.Ctes(("a", table), ("k", f"SELECT record_id, {key} AS k FROM a WHERE {key} IS NOT NULL"))
    c.add("m", "SELECT * FROM k SEMI JOIN (SELECT k FROM k GROUP BY k HAVING count(*) >= 2) USING (k)")
    return c.then("SELECT count(*) AS edges FROM (SELECT DISTINCT x.record_id, y.record_id FROM m x JOIN m y ON x.k = y.k AND x.record_id < y.record_id)")


def _edge_count(df, rule):
    return graph.edges(graph.membership(df, [rule])).agg(F.count(F.lit(1)).alias("edges"))


@query(_pairs_by("street"))
def rel_equal(spark, sf_dir):
    return _edge_count(views.person(spark, sf_dir), Rule.equal("street"))


@query(_pairs_by("family || chr(31) || street"))
def rel_conj(spark, sf_dir):
    return _edge_count(views.person(spark, sf_dir), Rule.conj(("family", "street")))


@query(
    s.Ctes(("a", s.PUBLICATION), ("k", "SELECT DISTINCT record_id, unnest(author_list) AS k FROM a"), ("m", "SELECT * FROM k SEMI JOIN (SELECT k FROM k GROUP BY k HAVING count(*) >= 2) USING (k)")).then(
        "SELECT count(*) AS edges FROM (SELECT DISTINCT x.record_id, y.record_id FROM m x JOIN m y ON x.k = y.k AND x.record_id < y.record_id)"
    )
)
def rel_overlap(spark, sf_dir):
    return _edge_count(views.publication(spark, sf_dir), Rule.overlap("author_list"))


@query("SELECT concat_ws('-', conv_id, turn) AS record_id, CAST(conv_id AS VARCHAR) AS group_key, role FROM conversations")
def rel_roles(spark, sf_dir):
    return graph.membership(views.household_turns(spark, sf_dir), [Rule.group_role("household", "role")]).select("record_id", "group_key", "role")


@query(s.Ctes(*HOME.parts).then("SELECT record_id, count(*) OVER (PARTITION BY household) - 1 AS degree FROM a"))
def rel_group(spark, sf_dir):
    return graph.group_sizes(_household(spark, sf_dir))


def _mixed(spark, sf_dir):
    """Two rules over documents' lead words and titles give triangles that are no cliques."""
    return graph.membership(views.publication_heads(spark, sf_dir), [Rule.overlap("author_list"), Rule.equal("title")])


def _mixed_sql() -> s.Ctes:
    c = s.Ctes(("a", s.PUBLICATION), ("k", "SELECT DISTINCT record_id, 'a' || unnest(author_list) AS k FROM a UNION ALL SELECT record_id, 't' || title FROM a"))
    c.add("m", "SELECT * FROM k SEMI JOIN (SELECT k FROM k GROUP BY k HAVING count(*) >= 2) USING (k)")
    return c.add("e", "SELECT DISTINCT x.record_id, y.record_id AS neighbour FROM m x JOIN m y ON x.k = y.k AND x.record_id <> y.record_id")


@query(_mixed_sql().then("SELECT record_id, count(*) AS degree FROM e GROUP BY ALL"))
def feat_degree(spark, sf_dir):
    return graph.Stars(_mixed(spark, sf_dir)).degree()


@query(
    _mixed_sql()
    .add("t", "SELECT x.record_id, count(*) / 2 AS t FROM e x JOIN e y ON x.record_id = y.record_id JOIN e z ON z.record_id = x.neighbour AND z.neighbour = y.neighbour GROUP BY ALL")
    .add("k", "SELECT record_id, count(*) AS k FROM e GROUP BY ALL")
    .then("SELECT record_id, round((k + coalesce(t, 0)) / (k * (k + 1) / 2), 6) AS density FROM k LEFT JOIN t USING (record_id)")
    .replace("k AS MATERIALIZED (SELECT record_id, count", "kk AS MATERIALIZED (SELECT record_id, count")
    .replace("FROM k LEFT JOIN t", "FROM kk LEFT JOIN t")
)
def feat_density(spark, sf_dir):
    return graph.Stars(_mixed(spark, sf_dir)).density().select("record_id", F.round("density", 6).alias("density"))


@query(
    _mixed_sql()
    .add("t", "SELECT count(*) AS n FROM e x JOIN e y ON x.record_id = y.record_id JOIN e z ON z.record_id = x.neighbour AND z.neighbour = y.neighbour")
    .then("SELECT (SELECT count(*) FROM e) // 2 AS edges, (SELECT n FROM t) // 6 AS triangles")
)
def ev_counters_graph(spark, sf_dir):
    return graph.Stars(_mixed(spark, sf_dir)).counts()


def _neighbour_sigs() -> s.Ctes:
    c = s.signatures(s.Ctes(("a", s.PERSON)), "a", w.VOTER_COMBOS, 8)
    return s.edges(c, "a", "w4").add("n", "SELECT DISTINCT e.record_id, s.combo_id, s.sig FROM ea e JOIN sa s ON s.record_id = e.neighbour")


@query(_neighbour_sigs().then("SELECT record_id, count(*) AS sigs FROM n GROUP BY ALL"))
def feat_nbr_sigs(spark, sf_dir):
    n = slices_of(views.person(spark, sf_dir))
    people = in_slices(lambda i: views.person(spark, sf_dir, i, n).select("record_id", *w.VOTER), n, "people")
    kept, _ = signatures.kept_signatures(people, people.limit(0), VQ, VC)
    kept = keep(kept.select("record_id", "sig_hash"), "sigs")
    stars = graph.Stars(graph.membership(people, [Rule.conj(("family", "street"))]), single=True)
    return graph.neighbour_signatures(stars, kept).select("record_id", F.size("nbr_sigs").cast("long").alias("sigs"))


@query(_home().then("SELECT e.record_id, array_to_string(list_sort(list_distinct(list(v))), ';') AS vals FROM ea e JOIN (SELECT record_id AS neighbour, unnest(['given=' || given, 'age=' || age]) AS v FROM a) USING (neighbour) GROUP BY ALL"))
def feat_nbr_values(spark, sf_dir):
    people = views.person(spark, sf_dir)
    return graph.neighbour_values(graph.Stars(_household(spark, sf_dir), single=True), people, ["given", "age"]).select("record_id", F.array_join("nbr_values", ";").alias("vals"))


@query(
    "WITH m AS (SELECT concat_ws('-', conv_id, turn) AS record_id, conv_id, role FROM conversations) "
    "SELECT x.record_id, array_to_string(list_sort(list_distinct(list(x.role || '>' || y.role))), ';') AS roles FROM m x JOIN m y ON x.conv_id = y.conv_id AND x.record_id <> y.record_id GROUP BY ALL"
)
def feat_nbr_roles(spark, sf_dir):
    members = graph.membership(views.household_turns(spark, sf_dir), [Rule.group_role("household", "role")])
    return graph.neighbour_roles(members).select("record_id", F.array_join("roles", ";").alias("roles"))


@query(_mixed_sql().add("d", "SELECT record_id, count(*) AS d FROM e GROUP BY ALL").then("SELECT e.record_id, round(avg(d.d), 6) AS mean_degree FROM e JOIN d ON d.record_id = e.neighbour GROUP BY ALL"))
def feat_misc(spark, sf_dir):
    return graph.Stars(_mixed(spark, sf_dir)).mean_degree().select("record_id", F.round("mean_degree", 6).alias("mean_degree"))


@query(
    _home().then("SELECT e.record_id, CAST(sum(CASE WHEN m.given IS NULL OR m.middle IS NULL THEN 1 ELSE 0 END) AS BIGINT) AS missing_neighbours FROM ea e JOIN m ON m.record_id = e.neighbour GROUP BY ALL").replace("ea AS MATERIALIZED", "m AS MATERIALIZED (" + s.mcar("a", w.VOTER, 0.2, 5) + "),\nea AS MATERIALIZED")
)
def feat_missing_neighbours(spark, sf_dir):
    stars = graph.Stars(_household(spark, sf_dir), single=True)
    return graph.neighbours_with_missing(stars, gaps(spark, sf_dir), ("given", "middle"))


#: Vectors are related if they share a label and a hundred of vec_ids.
CLOSE = "SELECT a.vec_id AS x, b.vec_id AS y, b.embedding AS e FROM embeddings a JOIN embeddings b ON a.label = b.label AND a.vec_id // 100 = b.vec_id // 100 AND a.vec_id <> b.vec_id"


@query(f"SELECT x AS record_id, round(avg(CAST(e[1] AS DOUBLE)), 5) AS c1, round(avg(CAST(e[64] AS DOUBLE)), 5) AS c64 FROM ({CLOSE}) GROUP BY 1")
def feat_embedding_centroid(spark, sf_dir):
    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select(F.col("vec_id").alias("record_id"), F.col("embedding").cast("array<double>").alias("embedding"), F.concat_ws("/", "label", F.floor(F.col("vec_id") / 100)).alias("home"))
    edges = graph.edges(graph.membership(rows, [Rule.group("home")]))
    return graph.neighbour_centroid(edges, rows).select("record_id", F.round(F.get("centroid", F.lit(0)), 5).alias("c1"), F.round(F.get("centroid", F.lit(63)), 5).alias("c64"))


@query(
    _neighbour_sigs()
    .add("deg", "SELECT record_id, count(*) AS degree FROM ea GROUP BY ALL")
    .add("own", "SELECT record_id, count(*) AS own FROM sa GROUP BY ALL")
    .add("nn", "SELECT record_id, count(*) AS near FROM n GROUP BY ALL")
    .then("SELECT record_id, coalesce(own, 0) AS own, coalesce(degree, 0) AS degree, coalesce(near, 0) AS near FROM a LEFT JOIN own USING (record_id) LEFT JOIN deg USING (record_id) LEFT JOIN nn USING (record_id)")
)
def sig_database(spark, sf_dir):
    table = signatures.signature_database(views.person(spark, sf_dir), VQ, VC, [Rule.conj(("family", "street"))], Settings(features=("degree", "nbr_sigs")))
    return table.select("record_id", F.size("attr_sigs").cast("long").alias("own"), F.col("rel.degree").alias("degree"), F.size("rel.nbr_sigs").cast("long").alias("near"))


@query(_mixed_sql().add("r", "SELECT record_id AS v, record_id AS u FROM e UNION SELECT r.v, e.neighbour FROM r JOIN e ON r.u = e.record_id").then("SELECT v AS record_id, min(u) AS component FROM r GROUP BY v", recursive=True).replace("r AS MATERIALIZED", "r AS"))
def graph_components(spark, sf_dir):
    return graph.components(graph.star_edges(_mixed(spark, sf_dir)), keep)


# ---------------------------------------------------------------- matching
def linked(pair: w.Pair, settings: Settings | None = None, **options) -> match.LinkResult:
    return match.link(pair.a, pair.b, pair.qids, pair.rules, select.fixed_combinations(pair.combos), settings or pair.settings, keep=keep, **options)


def _w4(spark, sf_dir):
    return w.PAIRS["w4"](spark, sf_dir)


def kept(spark, sf_dir):
    p = _w4(spark, sf_dir)
    return p, *signatures.written_signatures(p.a, p.b, p.qids, select.fixed_combinations(p.combos), p.settings)


def _cand() -> s.Ctes:
    c = s.PAIRS["w4"]()
    for side in "ab":
        s.signatures(c, side, w.VOTER_COMBOS)
    return s.candidates(c)


@query(_cand().then("SELECT a_id, b_id, common FROM cand"))
def match_candidates(spark, sf_dir):
    _, sa, sb = kept(spark, sf_dir)
    return match.candidate_pairs(sa, sb)


@query(_cand().then("SELECT a_id, b_id, round(s_a, 6) AS s_a FROM scored"))
def match_sim_a(spark, sf_dir):
    _, sa, sb = kept(spark, sf_dir)
    return match.scored_pairs(sa, sb).select("a_id", "b_id", F.round("s_a", 6).alias("s_a"))


@query(_cand().then("SELECT round(avg(2.0 * common / (na + nb)), 6) AS dice, round(avg(CAST(common AS DOUBLE) / least(na, nb)), 6) AS overlap, round(avg(CAST(common AS DOUBLE)), 6) AS shared FROM scored"))
def match_sim_variants(spark, sf_dir):
    _, sa, sb = kept(spark, sf_dir)
    sizes = lambda x, side: x.groupBy(F.col("record_id").alias(f"{side}_id")).agg(F.count(F.lit(1)).alias(f"n{side}"))
    rows = match.candidate_pairs(sa, sb).join(sizes(sa, "a"), "a_id").join(sizes(sb, "b"), "b_id")
    kinds = (("dice", "dice"), ("overlap", "overlap"), ("count", "shared"))
    return rows.agg(*[F.round(F.avg(match.from_counts(F.col("common"), F.col("na"), F.col("nb"), kind)), 6).alias(name) for kind, name in kinds])


@query(s.matched("w4").then("SELECT a_id, b_id, round(s_a, 6) AS s_a FROM matches WHERE stage = 1"))
def match_stage1(spark, sf_dir):
    return linked(_w4(spark, sf_dir)).pairs.where("stage = 1").select("a_id", "b_id", F.round("s_a", 6).alias("s_a"))


@query(s.relational(_cand(), "w4").then("SELECT a_id, b_id, round(s_r, 6) AS s_r FROM with_r"))
def match_sim_r(spark, sf_dir):
    r = linked(_w4(spark, sf_dir))
    return r.relational().select("a_id", "b_id", F.round("s_r", 6).alias("s_r"))


@query(
    s.edges(s.edges(_cand(), "a", "w4"), "b", "w4")
    .add("da", "SELECT record_id AS a_id, count(*) AS da FROM ea GROUP BY ALL")
    .add("db", "SELECT record_id AS b_id, count(*) AS db FROM eb GROUP BY ALL")
    .then("SELECT round(avg(CASE WHEN greatest(x, y) = 0 THEN 1 ELSE 1 - abs(x - y) / CAST(greatest(x, y) AS DOUBLE) END), 6) AS mean_r FROM (SELECT coalesce(da, 0) AS x, coalesce(db, 0) AS y FROM scored LEFT JOIN da USING (a_id) LEFT JOIN db USING (b_id))")
)
def match_sim_r_numeric(spark, sf_dir):
    p = _w4(spark, sf_dir)
    settings = dataclasses.replace(p.settings, features=("degree",))
    r = linked(p, settings)
    return r.relational(settings).agg(F.round(F.avg("s_r"), 6).alias("mean_r"))


FULL = s.matched("w4").then("SELECT a_id, b_id, round(s_a, 6) AS s_a, round(s, 6) AS s, CAST(stage AS INTEGER) AS stage FROM matches")


def _rounded(pairs):
    return pairs.select("a_id", "b_id", F.round("s_a", 6).alias("s_a"), F.round("s", 6).alias("s"), "stage")


@query(FULL)
def match_full(spark, sf_dir):
    r = linked(_w4(spark, sf_dir))
    return _rounded(match.decide(r.scored, r.a, r.b, Settings(), bound=False))


@query(FULL)
def match_bound(spark, sf_dir):
    return _rounded(linked(_w4(spark, sf_dir)).pairs)


@query(s.relational(_cand(), "w4").then(" UNION ALL ".join(f"SELECT CAST({t} AS DOUBLE) AS s_t, count(*) FILTER (s_a >= {t} - 1e-9) AS stage1, count(*) FILTER (s_a >= {t} - 1e-9 OR 0.5 * s_a + 0.5 * s_r >= {t} - 1e-9) AS matches FROM with_r" for t in evaluate.S_T)))
def match_sweep_st(spark, sf_dir):
    r = linked(_w4(spark, sf_dir))
    both = r.relational().select("s_a", "s_r")
    each = both.select("*", F.explode(F.array(*[F.lit(t) for t in evaluate.S_T])).alias("s_t"))
    low = F.col("s_t") - planner.EPSILON
    return each.groupBy("s_t").agg(F.count_if(F.col("s_a") >= low).alias("stage1"), F.count_if((F.col("s_a") >= low) | (0.5 * F.col("s_a") + 0.5 * F.col("s_r") >= low)).alias("matches"))


BETAS = (0.0, 0.25, 0.5, 0.75, 1.0)


@query(s.relational(_cand(), "w4").then(" UNION ALL ".join(f"SELECT CAST({b} AS DOUBLE) AS beta, count(*) FILTER (s_a >= 0.8 - 1e-9 OR {b} * s_a + (1 - {b}) * s_r >= 0.8 - 1e-9) AS matches FROM with_r" for b in BETAS)))
def match_sweep_beta(spark, sf_dir):
    r = linked(_w4(spark, sf_dir))
    both = r.relational().select("s_a", "s_r")
    each = both.select("*", F.explode(F.array(*[F.lit(b) for b in BETAS])).alias("beta"))
    low = 0.8 - planner.EPSILON
    return each.groupBy("beta").agg(F.count_if((F.col("s_a") >= low) | (F.col("beta") * F.col("s_a") + (1 - F.col("beta")) * F.col("s_r") >= low)).alias("matches"))


@query(
    s.relational(_cand(), "w4")
    .add("ca", "SELECT * FROM na_sig SEMI JOIN (SELECT combo_id, sig FROM na_sig GROUP BY ALL HAVING count(*) <= 50) USING (combo_id, sig)")
    .add("cb", "SELECT * FROM nb_sig SEMI JOIN (SELECT combo_id, sig FROM nb_sig GROUP BY ALL HAVING count(*) <= 50) USING (combo_id, sig)")
    .then("SELECT count(*) AS candidates FROM (SELECT a_id, b_id FROM cand UNION SELECT ca.record_id, cb.record_id FROM ca JOIN cb USING (combo_id, sig))")
)
def match_rel_candidates(spark, sf_dir):
    r = linked(_w4(spark, sf_dir))
    sets = [graph.neighbour_signatures(side.stars, kept) for side, kept in ((r.a, r.sig_a), (r.b, r.sig_b))]
    return match.relational_candidates(r.sig_a, r.sig_b, *sets, 50).agg(F.count(F.lit(1)).alias("candidates"))


@query(
    s.matched("w4", s_t=0.5)
    .add("o", "SELECT *, row_number() OVER (PARTITION BY a_id ORDER BY round(s, 9) DESC, b_id) AS ra, row_number() OVER (PARTITION BY b_id ORDER BY round(s, 9) DESC, a_id) AS rb FROM matches")
    .then("SELECT a_id, b_id, round(s, 6) AS s FROM o WHERE ra = 1 AND rb = 1")
)
def match_one_to_one(spark, sf_dir):
    pairs = linked(_w4(spark, sf_dir), Settings(s_t=0.5)).pairs.withColumn("s", F.round("s", 9))
    return match.one_to_one(pairs).select("a_id", "b_id", F.round("s", 6).alias("s"))


@query(s.matched("w4").add("sh", "SELECT x.record_id AS a_id, y.record_id AS b_id, array_to_string(list_sort(list(combo_id)), ',') AS shared FROM sa x JOIN sb y USING (combo_id, sig) GROUP BY ALL").then("SELECT a_id, b_id, CAST(stage AS INTEGER) AS stage, shared FROM matches JOIN sh USING (a_id, b_id)"))
def match_explain(spark, sf_dir):
    r = linked(_w4(spark, sf_dir))
    return match.explain_pairs(r.pairs, r.sig_a, r.sig_b).select("a_id", "b_id", "stage", F.array_join("shared_combos", ",").alias("shared"))


# ---------------------------------------------------------------- workloads
@query(
    s.Ctes(("person", s.PERSON), ("a", "SELECT * FROM person WHERE CAST(role AS INTEGER) % 2 = 1"), ("b", "SELECT * FROM person WHERE CAST(role AS INTEGER) % 2 = 0")).then(
        """SELECT 'household+gender' AS link, a.record_id AS x, b.record_id AS y FROM a JOIN b ON a.household = b.household AND a.gender = b.gender
        UNION ALL SELECT 'household+year+given', a.record_id, b.record_id FROM a JOIN b ON a.household = b.household AND year(CAST(a.birth AS DATE)) = year(CAST(b.birth AS DATE)) AND substr(a.given, 1, 3) = substr(b.given, 1, 3)
        UNION ALL SELECT 'household', x.record_id, y.record_id FROM a x JOIN a y ON x.household = y.household AND x.record_id < y.record_id"""
    )
)
def wl_w0(spark, sf_dir):
    """Members of odd and of even numbers: which of them signatures and relations bring together."""
    rows = views.person(spark, sf_dir).select("record_id", "household", "role", "gender", "given", F.col("birth").cast("date").alias("birth"))
    rows = keep(rows, "people")
    odd = F.col("role").cast("int") % 2 == 1
    a, b = rows.where(odd), rows.where(~odd)
    home = Qid("household")
    out = None
    for name, qids in (("household+gender", [home, Qid("gender")]), ("household+year+given", [home, Qid("birth", text.year_of), Qid("given", text.prefix(3))])):
        combos = select.fixed_combinations([[q.name for q in qids]])
        sa, sb = signatures.attribute_signatures(a, qids, combos), signatures.attribute_signatures(b, qids, combos)
        pairs = match.candidate_pairs(sa, sb).select(F.lit(name).alias("link"), F.col("a_id").alias("x"), F.col("b_id").alias("y"))
        out = pairs if out is None else out.unionByName(pairs)
    edges = graph.edges(graph.membership(a, [Rule.group("household")])).select(F.lit("household").alias("link"), F.col("src").alias("x"), F.col("dst").alias("y"))
    return out.unionByName(edges)


def _workload(name):
    def run(spark, sf_dir):
        pair = w.PAIRS[name](spark, sf_dir)
        return evaluate.precision_recall(linked(pair).pairs, pair.truth)

    return run


for _name in w.PAIRS:
    query(s.matched(_name).then(s.accuracy()), f"wl_{_name}")(_workload(_name))


_IN_WAVE = "SELECT p.wave, count(*) AS {n} FROM {pairs} x JOIN person p ON p.record_id = x.a_id GROUP BY ALL"


@query(
    s.matched("w3").add("pw", _IN_WAVE.format(n="predicted", pairs="matches")).add("tw", _IN_WAVE.format(n="true_pairs", pairs="truth"))
    .add("hw", _IN_WAVE.format(n="tp", pairs="(SELECT a_id, b_id FROM matches SEMI JOIN truth USING (a_id, b_id))"))
    .then("SELECT wave, true_pairs, coalesce(predicted, 0) AS predicted, coalesce(tp, 0) AS tp, round(CAST(tp AS DOUBLE) / predicted, 6) AS precision, round(coalesce(CAST(tp AS DOUBLE), 0) / true_pairs, 6) AS recall FROM tw LEFT JOIN pw USING (wave) LEFT JOIN hw USING (wave)")
)
def wl_w3_waves(spark, sf_dir):
    """Precision and recall of the census linkage in each wave."""
    pair = w.PAIRS["w3"](spark, sf_dir)
    wave = pair.a.select(F.col("record_id").alias("a_id"), "wave")
    one = F.lit(1)
    found = linked(pair).pairs.select("a_id", "b_id", one.alias("p")).join(pair.truth.select("a_id", "b_id", one.alias("t")), ["a_id", "b_id"], "full")
    rows = found.join(wave, "a_id").groupBy("wave").agg(F.count("t").alias("true_pairs"), F.count("p").alias("predicted"), F.count(F.col("t") + F.col("p")).alias("tp"))
    ratio = lambda n: F.round(F.try_divide(F.col("tp").cast("double"), F.col(n)), 6)
    return rows.where("true_pairs > 0").select("*", ratio("predicted").alias("precision"), ratio("true_pairs").alias("recall"))


POLICIES = ("drop", "keep")


def _selected(name):
    """Selection over both sides (n_a=5, c_t=0.6, up to three attributes), then the linkage,
    with and without combinations that are part of another selected one."""

    def run(spark, sf_dir):
        pair = w.PAIRS[name](spark, sf_dir)
        a, b, truth = keep(pair.a, "a"), keep(pair.b, "b"), keep(pair.truth, "truth")
        both = a.select(*pair.attrs).unionByName(b.select(*pair.attrs))
        out = None
        for (_, policy), combos in select.select_many(both, pair.qids, [(0.6, p) for p in POLICIES], 5, max_size=3).items():
            found = match.link(a, b, pair.qids, pair.rules, combos, pair.settings)
            names = ";".join(",".join(c.attrs) for c in combos)
            about = [F.lit(policy).alias("policy"), F.lit(a.count()).alias("records_a"), F.lit(b.count()).alias("records_b"), F.lit(names).alias("combinations")]
            one = evaluate.precision_recall(found.pairs, truth).select(*about, "predicted", "tp", "precision", "recall")
            out = one if out is None else out.unionByName(one)
        return out

    return run


for _name in w.PAIRS:
    query(" UNION ALL ".join(f"SELECT * FROM ({s.selected(_name, policy)})" for policy in POLICIES), f"wl_{_name}_selected")(_selected(_name))


@query()
def wl_w8(spark, sf_dir):
    """Sensitivity: how accuracy at each s_t and the seconds of steps 2 and 3 move with c_t,
    n_a, p_t and random selections.  Settings that give the same job share one run."""
    p = _w4(spark, sf_dir)
    a, b, truth = keep(p.a, "a"), keep(p.b, "b"), keep(p.truth, "truth")
    both = keep(a.select(*p.attrs).unionByName(b.select(*p.attrs)), "union")
    ranked = select.select_many(both, p.qids, [(c, "drop") for c in (0.5, 0.7, 0.9)], 10, max_size=3)
    runs = [("c_t", c, combos[:5], 0.5) for (c, _), combos in ranked.items()]
    runs += [("n_a", n, ranked[0.5, "drop"][:n], 0.5) for n in (1, 2, 5, 10)]
    runs += [("random", i, select.random_combinations(p.qids, 5, i), 0.5) for i in (1, 2, 3)]
    runs += [("p_t", t, select.fixed_combinations(p.combos), t) for t in (0.5, 0.7, 0.9)]
    done, rows = {}, []
    for kind, value, combos, p_t in runs:
        job = (frozenset(c.attrs for c in combos), p_t)
        if job not in done:
            done[job] = (0.0, 0.0, [])
            if combos:
                settings = Settings(p_t=p_t)
                r = match.link(a, b, p.qids, p.rules, combos, settings)
                blend = settings.beta * F.col("s_a") + (1 - settings.beta) * F.col("s_r")
                curve = evaluate.pr_curve(r.relational(settings).select("a_id", "b_id", F.greatest("s_a", blend).alias("s")), truth)
                done[job] = (r.timings["generate"], r.timings["match"], [(x["s_t"], x["predicted"], x["precision"], x["recall"]) for x in curve.collect()])
        generate, matched, curve = done[job]
        found = {x[0]: x for x in curve}
        rows += [(kind, float(value), len(combos), round(generate, 2), round(matched, 2), *found.get(t, (t, 0, None, 0.0))) for t in evaluate.S_T]
    return spark.createDataFrame(rows, "parameter string, value double, combos int, generate_seconds double, match_seconds double, s_t double, predicted long, precision double, recall double")
