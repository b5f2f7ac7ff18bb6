"""Signatures, the frequency rule, relations and matching on the worked example."""

import itertools

import pytest
from pyspark.sql import functions as F

from reclink.functions import text
from reclink.operators import graph, match, select, signatures
from reclink.plans import planner
from reclink.plans.model import Qid, Rule, Settings
from reclink.sources.views import example


@pytest.fixture(scope="module")
def people(spark):
    return example(spark).cache()


def plain(df, *qids):
    combo = select.fixed_combinations([[q.name for q in qids]])[0]
    return {r["record_id"]: r["s"] for r in df.select("record_id", signatures.attribute_signature(combo, qids, "plain").alias("s")).collect()}


def test_signature_strings(people):
    first, last, birth = Qid("first_name"), Qid("last_name"), Qid("birth_date")
    year, street = Qid("birth_date", text.year_of), Qid("street", text.street_name)
    assert plain(people, first, last, year) == {"r1": "PeterSmith1981", "r2": None, "r3": "AnneMiller1991", "r4": "PeterSmith1981", "r5": None}
    assert [plain(people, first, birth)[r] for r in ("r1", "r2", "r4")] == ["Peter1981-11-25"] * 3
    got = plain(people, first, year, street)
    assert got["r2"] == got["r4"] == "Peter1981Skye"


def test_stored_signatures_do_not_run_together(spark):
    rows = spark.createDataFrame([("1", "ab", "c"), ("2", "a", "bc"), ("3", None, "x")], "record_id string, a string, b string")
    found = signatures.attribute_signatures(rows, [Qid("a"), Qid("b")], select.fixed_combinations([("a", "b")])).collect()
    assert len(found) == 2 and len({r["sig"] for r in found}) == 2


@pytest.mark.parametrize(("p_t", "literal", "relative"), [(0.5, 8, 10), (0.6, 6, 9), (0.7, 4, 7), (0.8, 1, 5), (0.9, 0, 3)])
def test_cap(p_t, literal, relative):
    for mode, cap in (("literal", literal), ("relative", relative)):
        assert planner.n_max(p_t, mode=mode) == cap
        assert all((planner.probability(n, mode=mode) >= p_t) == (n <= cap) for n in range(1, 30))


def test_probabilities_fall():
    want = [0.806452, 0.776398, 0.743163, 0.706854, 0.667707, 0.626097, 0.582535, 0.537645, 0.492137]
    assert [planner.probability(n) for n in range(1, 10)] == pytest.approx(want, abs=1e-6)
    assert planner.n_max(0.0) is None and planner.n_max(1.0) == 0


def test_filter_at_the_cap(spark):
    rows = spark.createDataFrame([(f"a{i}", "x") for i in range(8)] + [(f"b{i}", "y") for i in range(9)], "record_id string, v string")
    sigs = signatures.attribute_signatures(rows, [Qid("v")], select.fixed_combinations([("v",)]))
    kept = signatures.filter_signatures(sigs).collect()
    assert {r["record_id"][0] for r in kept} == {"a"} and len(kept) == 8
    assert signatures.filter_signatures(sigs, Settings(p_t=0.9)).count() == 0


def test_relations_of_the_example(people):
    phone = graph.edges(graph.membership(people.where("database = 'A'"), [Rule.equal("phone")]))
    assert [tuple(r) for r in phone.collect()] == [("r2", "r3")]
    street = graph.edges(graph.membership(people.where("database = 'B'"), [Rule.equal("street", text.street_name)]))
    assert [tuple(r) for r in street.collect()] == [("r4", "r5")]


def test_graph_features(spark):
    # a triangle 1-2-3 with a tail 3-4, as groups
    rows = spark.createDataFrame([("1", "t"), ("2", "t"), ("3", "t"), ("3", "u"), ("4", "u"), ("5", "v"), *[(f"h{i}", "hub") for i in range(60)]], "record_id string, g string")
    edges = graph.edges(graph.membership(rows, [Rule.group("g")])).cache()
    hub = edges.where("src LIKE 'h%'")
    assert hub.count() == 60 * 59 // 2
    edges = edges.where("src NOT LIKE 'h%'")
    assert sorted(tuple(r) for r in edges.collect()) == [("1", "2"), ("1", "3"), ("2", "3"), ("3", "4")]
    assert {r[0]: r[1] for r in graph.degree(edges).collect()} == {"1": 2, "2": 2, "3": 3, "4": 1}
    density = {r[0]: r[1] for r in graph.egonet_density(edges).collect()}
    assert density == pytest.approx({"1": 1, "2": 1, "3": 4 / 6, "4": 1})
    assert graph.triangles(edges).count() == 1
    assert {r[0]: r[1] for r in graph.components(edges, lambda df: df.cache()).collect()} == dict.fromkeys("1234", "1")


def test_similarities(spark):
    row = spark.range(1).select(
        *[match.from_counts(F.lit(2), F.lit(3), F.lit(4), k).alias(k) for k in ("jaccard", "dice", "overlap", "count")],
        match.from_counts(F.lit(0), F.lit(0), F.lit(0)).alias("none"), match.number_similarity(F.lit(3.0), F.lit(4.0)).alias("num"), match.number_similarity(F.lit(0.0), F.lit(0.0)).alias("zero"),
    ).first()
    assert tuple(row) == pytest.approx((0.4, 4 / 7, 2 / 3, 2, 0, 0.75, 1))


def plain_link(a, b, combos, rule, cap, s_t, beta):
    """The method from its definitions, on lists of dicts."""
    def sigs(rows):
        every = {r["record_id"]: {(i, tuple(r[c] for c in combo)) for i, combo in enumerate(combos) if all(r[c] is not None for c in combo)} for r in rows}
        count = {}
        for s in itertools.chain.from_iterable(every.values()):
            count[s] = count.get(s, 0) + 1
        return {k: {s for s in v if count[s] <= cap} for k, v in every.items()}

    def near(rows, own):
        key = {r["record_id"]: tuple(r[c] for c in rule) for r in rows if all(r[c] is not None for c in rule)}
        return {k: set().union(*(own[o] for o, g in key.items() if o != k and g == key[k])) if k in key else set() for k in own}

    jaccard = lambda x, y: len(x & y) / len(x | y) if x | y else 0.0
    sa, sb = sigs(a), sigs(b)
    ra, rb = near(a, sa), near(b, sb)
    out = set()
    for x in sa:
        for y in sb:
            if sa[x] & sb[y]:
                s = jaccard(sa[x], sb[y])
                if s >= s_t - 1e-9 or beta * s + (1 - beta) * jaccard(ra[x], rb[y]) >= s_t - 1e-9:
                    out.add((x, y))
    return out


@pytest.fixture(scope="module")
def towns(spark):
    """Households with gaps and errors, small enough to compare with the definitions."""
    rows = []
    for i in range(60):
        home = i // 3
        rows.append((f"r{i:02}", f"n{i % 7}", f"f{home}", f"s{home % 11}", f"b{i % 13}", home))
    a = [tuple(None if (k + j) % 11 == 0 and j else v for j, v in enumerate(r)) for k, r in enumerate(rows)]
    b = [("b" + r[0], *(None if (k * 3 + j) % 7 == 0 and j < 5 else ("e" + v if (k + 2 * j) % 9 == 0 and j < 5 else v) for j, v in enumerate(r[1:], 1))) for k, r in enumerate(rows)]
    b = [(*r[:5], rows[k][5]) for k, r in enumerate(b)]
    a = [(*r[:5], rows[k][5]) for k, r in enumerate(a)]
    schema = "record_id string, given string, family string, street string, birth string, home int"
    return a, b, spark.createDataFrame(a, schema).cache(), spark.createDataFrame(b, schema).cache()


COMBOS = (("given", "family"), ("given", "street"), ("family", "birth"), ("street", "birth"))
COLUMNS = ("record_id", "given", "family", "street", "birth", "home")


@pytest.mark.parametrize(("s_t", "beta"), [(0.5, 0.5), (0.6, 0.5), (0.8, 0.5), (1.0, 0.5), (0.7, 1.0), (0.7, 0.25), (0.4, 0.0)])
def test_link_equals_the_definitions(towns, s_t, beta):
    a, b, da, db = towns
    rows = [[dict(zip(COLUMNS, r)) for r in side] for side in (a, b)]
    want = plain_link(*rows, COMBOS, ("home",), 8, s_t, beta)
    qids = [Qid(c) for c in ("given", "family", "street", "birth")]
    settings = Settings(s_t=s_t, beta=beta)
    r = match.link(da, db, qids, [Rule.group("home")], select.fixed_combinations(COMBOS), settings)
    got = {(x["a_id"], x["b_id"]) for x in r.pairs.collect()}
    assert got == want
    free = match.decide(r.scored, r.a, r.b, settings, bound=False)
    assert {(x["a_id"], x["b_id"]) for x in free.collect()} == want
    first = {(x["a_id"], x["b_id"]) for x in r.pairs.where("stage = 1").collect()}
    assert first <= want
    if s_t == 1.0:
        assert first == want  # the second chance cannot help


def test_one_to_one_and_explanations(towns):
    _, _, da, db = towns
    qids = [Qid(c) for c in ("given", "family", "street", "birth")]
    r = match.link(da, db, qids, [Rule.group("home")], select.fixed_combinations(COMBOS), Settings(s_t=0.5))
    best = match.one_to_one(r.pairs).collect()
    assert len({x["a_id"] for x in best}) == len({x["b_id"] for x in best}) == len(best) > 0
    for x in match.explain_pairs(r.pairs, r.sig_a, r.sig_b).collect():
        assert len(x["shared_combos"]) == x["common"]
    wider = match.link(da, db, qids, [Rule.group("home")], select.fixed_combinations(COMBOS), Settings(s_t=0.5), candidates="attr+rel")
    assert {(x["a_id"], x["b_id"]) for x in r.pairs.collect()} <= {(x["a_id"], x["b_id"]) for x in wider.pairs.collect()}


def test_signature_database_keeps_all_records(people):
    qids = [Qid("first_name"), Qid("last_name"), Qid("birth_date")]
    settings = Settings(features=("degree", "density", "nbr_sigs", "nbr_values"))
    table = signatures.signature_database(people, qids, select.fixed_combinations([("first_name", "last_name")]), [Rule.equal("phone")], settings)
    got = {r["record_id"]: r for r in table.collect()}
    assert set(got) == {"r1", "r2", "r3", "r4", "r5"}
    assert got["r2"]["attr_sigs"] == [] and got["r1"]["rel"]["degree"] == 0 and got["r3"]["rel"]["degree"] == 2


def test_bad_settings():
    for wrong in ({"lam": 1.0}, {"mu": 1.0}, {"mu": 0.0}, {"s_t": 1.1}, {"beta": -0.1}, {"n_a": 0}):
        with pytest.raises(ValueError):
            Settings(**wrong)
    with pytest.raises(ValueError):
        planner.refuse_cartesian(10**9)
