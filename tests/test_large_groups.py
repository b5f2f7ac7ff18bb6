"""Relation groups of more than 50 records."""

import random

import pytest

from reclink.operators import graph, match, select
from reclink.plans.model import Qid, Rule, Settings
from reclink.sources import store


def test_roles_of_a_large_group(spark):
    rows = [(f"h{i:02d}", "big", "head" if i == 0 else "child") for i in range(60)] + [("x", "two", "head"), ("y", "two", "head"), ("z", "one", "head")]
    members = graph.membership(spark.createDataFrame(rows, "record_id string, g string, role string"), [Rule.group_role("g", "role")])
    got = {r["record_id"]: r["roles"] for r in graph.neighbour_roles(members).collect()}
    assert got == {"h00": ["head>child"], **{f"h{i:02d}": ["child>child", "child>head"] for i in range(1, 60)}, "x": ["head>head"], "y": ["head>head"]}


def _plain(groups):
    """Neighbours of each record, from the groups (name -> members)."""
    near = {}
    for members in groups.values():
        for r in members:
            near.setdefault(r, set()).update(x for x in members if x != r)
    return {r: n for r, n in near.items() if n}


def _members(spark, groups):
    rows = [(r, 0, g, None) for g, members in groups.items() for r in members]
    return spark.createDataFrame(rows, "record_id string, rule_id int, group_key string, role string")


def _overlapping(rng):
    names = [f"r{i}" for i in range(90)]
    groups = {f"g{k}": set(rng.sample(names, rng.choice([1, 2, 3, 8]))) for k in range(25)}
    return groups | {"big": set(names[:60]), "wide": set(names[40:88])}


def test_features_of_overlapping_groups(spark):
    """Degree, density, mean degree, sums and held items against plain neighbour sets."""
    rng = random.Random(3)
    groups = _overlapping(rng)
    near = _plain(groups)
    stars = graph.Stars(_members(spark, groups))
    got = lambda df: {r[0]: r[1] for r in df.collect()}
    assert got(stars.degree()) == {r: len(n) for r, n in near.items()}
    t = {r: sum(y in near[x] for x in n for y in n if x < y) for r, n in near.items()}
    assert got(stars.density()) == pytest.approx({r: (len(n) + t[r]) / (len(n) * (len(n) + 1) / 2) for r, n in near.items()})
    assert got(stars.mean_degree()) == pytest.approx({r: sum(len(near[x]) for x in n) / len(n) for r, n in near.items()})
    holds = {f"r{i}": {rng.randrange(12) for _ in range(rng.randrange(3))} for i in range(90)}
    items = spark.createDataFrame([(r, x) for r, have in holds.items() for x in have], "record_id string, item long")
    want = {r: sorted(set().union(*(holds[x] for x in n))) for r, n in near.items()}
    assert got(stars.neighbours_hold(items, "held")) == {r: x for r, x in want.items() if x}
    values = spark.createDataFrame([(r, len(have)) for r, have in holds.items()], "record_id string, v long")
    assert got(stars.sums(values, "v")) == {r: sum(len(holds[x]) for x in n) for r, n in near.items()}
    listed = {(r, x) for r, n in near.items() for x in n if r < x}
    assert {tuple(r) for r in graph.edges(_members(spark, groups), tile=7).collect()} == listed


@pytest.mark.parametrize("size", [60, 5000])
def test_one_large_group(spark, size):
    """A group of any size: every member has all others for neighbours, from one row each."""
    groups = {"all": [f"r{i}" for i in range(size)], "two": ["x", "y"], "one": ["z"]}
    for single in (True, False):
        stars = graph.Stars(_members(spark, groups), single)
        degrees = {r[0]: r[1] for r in stars.degree().collect()}
        assert degrees == {**dict.fromkeys(groups["all"], size - 1), "x": 1, "y": 1}
        assert {r[1] for r in stars.density().collect()} == {1.0}
    parts = graph.components(graph.star_edges(_members(spark, groups)), lambda df: df.cache()).collect()
    assert len(parts) == size + 2 and {r[1] for r in parts} == {"r0", "x"}


def test_long_chain_is_one_component(spark):
    chain = spark.createDataFrame([(f"{i:03d}", f"{i + 1:03d}") for i in range(150)], "src string, dst string")
    assert {r[1] for r in graph.components(chain, store.keep).collect()} == {"000"}


def test_large_families_are_linked_through_their_members(spark):
    """Stage 2 sees relations of more than 50 records: those without own evidence match."""
    people = [(f"{k:03d}", f"n{k}", f"s{k}", "home") for k in range(70)]
    a = spark.createDataFrame(people, "record_id string, given string, street string, home string")
    b = spark.createDataFrame([(f"b{i}", g if k % 7 else f"{g}x", s, h) for k, (i, g, s, h) in enumerate(people)], a.schema)
    qids = [Qid("given"), Qid("street"), Qid("home")]
    combos = select.fixed_combinations([("given", "street"), ("given", "home"), ("street", "home")])
    r = match.link(a, b, qids, [Rule.group("home")], combos, Settings(s_t=0.5))
    stages = {(x["a_id"], x["stage"]) for x in r.pairs.collect()}
    assert {(f"{k:03d}", 1 if k % 7 else 2) for k in range(70)} == stages


def test_repeated_ids_are_refused(spark):
    a = spark.createDataFrame([("1", "x"), ("1", "y")], "record_id string, given string")
    with pytest.raises(ValueError, match="occurs 2 times"):
        match.link(a, a, [Qid("given")], [Rule.group("given")], select.fixed_combinations([("given",)]))


def test_neighbourhoods_are_counted_without_listing_pairs(spark, monkeypatch):
    """Records of many classes in one group: neither pairs nor triples of classes are made."""
    rng = random.Random(5)
    names = [f"r{i}" for i in range(120)]
    groups = {"title": set(names[:100])}
    for name in names:
        for word in rng.sample(range(60), 2):
            groups.setdefault(f"word{word}", set()).add(name)
    near = _plain(groups)
    for name in ("edges", "triangles"):
        monkeypatch.setattr(graph, name, lambda *a, **b: pytest.fail("pairs of classes were listed"))
    stars = graph.Stars(_members(spark, groups))
    got = lambda df: {r[0]: r[1] for r in df.collect()}
    t = {r: sum(y in near[x] for x in n for y in n if x < y) for r, n in near.items()}
    assert got(stars.degree()) == {r: len(n) for r, n in near.items()}
    assert got(stars.mean_degree()) == pytest.approx({r: sum(len(near[x]) for x in n) / len(n) for r, n in near.items()})
    assert got(stars.density()) == pytest.approx({r: (len(n) + t[r]) / (len(n) * (len(n) + 1) / 2) for r, n in near.items()})
    assert tuple(stars.counts().first()) == (sum(len(n) for n in near.values()) // 2, sum(t.values()) // 3)
