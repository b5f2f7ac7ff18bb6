"""SQL texts of the record views, pairs and steps, for a second engine to check against."""

from __future__ import annotations

from collections.abc import Sequence
from itertools import combinations

from reclink.queries import workloads as w

PERSON = """SELECT concat_ws('-', l_orderkey, l_linenumber, l_partkey, l_suppkey, CAST(round(l_extendedprice * 100) AS BIGINT)) AS record_id,
    concat_ws('-', l_orderkey, l_linenumber, l_partkey, l_suppkey, CAST(round(l_extendedprice * 100) AS BIGINT)) AS entity_id,
    l_orderkey AS household, CAST(l_linenumber AS VARCHAR) AS role, p_name AS given, p_type AS middle, h.n_name || ' ' || c_mktsegment AS family,
    strftime(o_orderdate, '%Y-%m-%d') || ' ' || c_name AS street, h.n_name AS city, o_orderpriority AS zip, strftime(l_shipdate, '%Y-%m-%d') AS birth,
    l_returnflag AS gender, CAST(CAST(l_quantity AS INTEGER) AS VARCHAR) AS age, p_brand AS occupation, q.n_name AS parish, CAST(year(o_orderdate) AS INTEGER) AS wave
    FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation h ON c_nationkey = h.n_nationkey
    JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey JOIN nation q ON s_nationkey = q.n_nationkey"""

PUBLICATION = r"""SELECT CAST(doc_id AS VARCHAR) AS record_id, array_to_string(w[1:3], ' ') AS title, array_to_string(list_sort(au), ' ') AS authors, au AS author_list,
    array_to_string(w[greatest(len(w) - 2, 1):len(w)], ' ') AS venue, CAST(1950 + (n_chars // 200) % 70 AS VARCHAR) AS year, lang, source, md5(text) AS entity_id,
    list_distinct(CASE WHEN len(w) >= 3 THEN list_transform(range(1, len(w) - 1), lambda i: array_to_string(w[i:i + 2], ' ')) ELSE [array_to_string(w, ' ')] END) AS runs
    FROM (SELECT *, list_transform(list_sort(list_transform(list_distinct(w), lambda x: {'n': -length(x), 'x': x}))[1:3], lambda s: s.x) AS au
          FROM (SELECT *, list_filter(regexp_split_to_array(lower(text), '[^\p{L}\p{N}_]+'), lambda x: x <> '') AS w FROM documents) WHERE len(w) > 0)"""


def h(key: str, salt: str, modulus: int) -> str:
    return f"(CAST('0x' || substr(md5({key} || '|{salt}'), 1, 8) AS BIGINT) % {modulus})"


def _chosen(key: str, salt: str, most: int, n: int, j: int, pick: str = "run") -> str:
    if pick == "any":
        sets = ["[" + ", ".join(str(sum(1 << i for i in own)) for own in combinations(range(n), k)) + "]" for k in range(1, most + 1)]
        own = f"([{', '.join(sets)}])[1 + {h(key, salt + '-k', most)}]"
        return f"({own}[1 + {h(key, salt + '-o', 1 << 30)} % len({own})] & {1 << j}) > 0"
    return f"(({j} - {h(key, salt + '-o', n)} + {n}) % {n}) < 1 + {h(key, salt + '-k', most)}"


def replace(table: str, changes: dict[str, str], where: str = "") -> str:
    columns = ", ".join(f"{v} AS {k}" for k, v in changes.items())
    return f"SELECT * REPLACE ({columns}) FROM {table}{' WHERE ' + where if where else ''}"


def mcar(table: str, attrs: Sequence[str], share: float, most: int, salt: str = "mcar") -> str:
    n, key = len(attrs), "record_id"
    hit = lambda j: f"{h(key, salt, 1000)} < {round(share * 1000)} AND {_chosen(key, salt, min(most, n), n, j)}"
    return replace(table, {a: f"CASE WHEN NOT ({hit(j)}) THEN {a} END" for j, a in enumerate(attrs)})


def corrupt(table: str, attrs: Sequence[str], share: float = 0.2, most: int = 3, salt: str = "cor", pick: str = "run") -> str:
    n, key, out = len(attrs), "record_id", {}
    for j, a in enumerate(attrs):
        p = f"(1 + {h(key, f'{salt}-p-{a}', 97)} % greatest(length({a}), 1))"
        cases = [
            f"substr({a}, 1, {p} - 1) || substr({a}, {p} + 1)", f"substr({a}, 1, {p}) || 'x' || substr({a}, {p} + 1)", f"substr({a}, 1, {p} - 1) || 'z' || substr({a}, {p} + 1)",
            f"substr({a}, 1, {p} - 1) || substr({a}, {p} + 1, 1) || substr({a}, {p}, 1) || substr({a}, {p} + 2)", f"substr({a}, 1, 1)", f"regexp_replace({a}, ' [^ ]*$', '')", f"translate({a}, 'cgi', 'kjy')",
        ]
        body = " ".join(f"WHEN {i} THEN {c}" for i, c in enumerate(cases))
        hit = f"{h(key, salt, 1000)} < {round(share * 1000)} AND {_chosen(key, salt, min(most, n), n, j, pick)}"
        out[a] = f"CASE WHEN {a} IS NOT NULL AND {hit} THEN CASE {h(key, f'{salt}-op-{a}', 7)} {body} END ELSE {a} END"
    return replace(table, out)


def shift_dates(table: str, attrs: Sequence[str], share: float = 0.2, most_days: int = 31, salt: str = "day") -> str:
    key, out = "record_id", {}
    for a in attrs:
        days = f"CAST(CASE WHEN {h(key, f'{salt}-sign-{a}', 2)} = 0 THEN 1 ELSE -1 END * (1 + {h(key, f'{salt}-n-{a}', most_days)}) AS INTEGER)"
        new = f"CASE WHEN regexp_matches({a}, '^[0-9]{{4}}-[0-9]{{2}}-[0-9]{{2}}$') THEN strftime(TRY_CAST({a} AS DATE) + {days}, '%Y-%m-%d') END"
        out[a] = f"CASE WHEN {h(key, f'{salt}-{a}', 1000)} < {round(share * 1000)} THEN coalesce({new}, {a}) ELSE {a} END"
    return replace(table, out)


def drift(table: str, rates: dict[str, float], donors: int = 1024, salt: str = "drift") -> str:
    pool = f"SELECT {h('record_id', salt + '-donor', donors)} AS bk, " + ", ".join(f"min_by({a}, record_id) AS {a}" for a in rates) + f" FROM {table} GROUP BY 1"
    new = {a: f"CASE WHEN {h('t.record_id', f'{salt}-{a}', 1000)} < {round(r * 1000)} THEN coalesce(p_{a}.{a}, t.{a}) ELSE t.{a} END" for a, r in rates.items()}
    joins = " ".join(f"LEFT JOIN pool p_{a} ON p_{a}.bk = {h('t.record_id', f'{salt}-to-{a}', donors)}" for a in rates)
    return f"WITH pool AS ({pool}) SELECT t.* REPLACE ({', '.join(f'{v} AS {k}' for k, v in new.items())}) FROM {table} t {joins}"


def snapshots(table: str, keep_a: float, keep_b: float, shared: float, salt: str = "snap") -> tuple[str, str]:
    x, m = h("record_id", salt, 1_000_000), 1_000_000
    end, both, alone = round(keep_a * m), round(min(keep_b * shared, keep_a) * m), round(keep_b * (1 - shared) * m)
    return f"SELECT * FROM {table} WHERE {x} < {end}", f"SELECT * FROM {table} WHERE {x} < {both} OR ({x} >= {end} AND {x} < {end + alone})"


class Ctes:
    """A growing WITH list."""

    def __init__(self, *parts: tuple[str, str]):
        self.parts = list(parts)

    def add(self, name: str, sql: str) -> Ctes:
        self.parts.append((name, sql))
        return self

    def then(self, sql: str, recursive: bool = False) -> str:
        return f"WITH {'RECURSIVE ' if recursive else ''}" + ",\n".join(f"{n} AS MATERIALIZED ({s})" for n, s in self.parts) + "\n" + sql


RENAMED = "SELECT * REPLACE ('b' || record_id AS record_id) FROM "
TRUTH = "SELECT a.record_id AS a_id, b.record_id AS b_id FROM a JOIN b USING (entity_id)"


def persons(*steps: tuple[str, str]) -> Ctes:
    c = Ctes(("person", PERSON))
    for name, sql in steps:
        c.add(name, sql)
    return c.add("truth", TRUTH)


def _voter(share: float) -> Ctes:
    return persons(("m", mcar("person", w.VOTER, share, 5)), ("c", corrupt("m", w.VOTER)), ("a", "SELECT * FROM person"), ("b", RENAMED + "c"))


def _census_hist() -> Ctes:
    mar = replace("m", {"street": f"CASE WHEN NOT ({h('record_id', 'mar', 1000)} < CASE gender WHEN 'A' THEN 100 WHEN 'N' THEN 50 ELSE 0 END) THEN street END"})
    return persons(
        ("d", drift("person", w.CENSUS_RATES)), ("m", mcar("d", ("given", "middle", "family", "gender"), 0.24, 4)), ("r", mar),
        ("s", replace("r", {"occupation": "CASE WHEN NOT (CAST(age AS INTEGER) < 16) THEN occupation END"})), ("a", "SELECT * FROM person"), ("b", RENAMED + "s"),
    )


def _snapshot_pair(shares, rates, lose, missing, most) -> Ctes:
    a, b = snapshots("person", *shares)
    return persons(("a0", a), ("b0", b), ("a", mcar("a0", lose, missing[0], most, "mcar-a")), ("b1", drift("b0", rates)), ("b2", mcar("b1", lose, missing[1], most, "mcar-b")), ("b", RENAMED + "b2"))


def _papers(where: str, missing: tuple[float, float]) -> Ctes:
    first = lambda cond: f"SELECT * FROM pub p WHERE ({cond}) AND CAST(record_id AS BIGINT) = (SELECT min(CAST(o.record_id AS BIGINT)) FROM pub o WHERE o.entity_id = p.entity_id AND ({cond.replace('record_id', 'o.record_id').replace('source', 'o.source')}))"
    lose = ("authors", "venue", "year")
    c = Ctes(("pub", PUBLICATION), ("a0", first(where)), ("b0", RENAMED + f"({first(f'NOT ({where})')})"))
    c.add("ga", "SELECT record_id, unnest(runs) AS g FROM a0").add("gb", "SELECT record_id, unnest(runs) AS g FROM b0")
    c.add("common", "SELECT ga.record_id AS a_id, gb.record_id AS b_id, count(*) AS m FROM ga JOIN gb USING (g) GROUP BY ALL")
    c.add("truth", "SELECT a_id, b_id FROM common JOIN (SELECT record_id AS a_id, count(*) AS na FROM ga GROUP BY 1) USING (a_id) JOIN (SELECT record_id AS b_id, count(*) AS nb FROM gb GROUP BY 1) USING (b_id) WHERE 2 * m >= na + nb - m")
    return c.add("a", mcar("a0", lose, missing[0], 2, "mcar-a")).add("b", mcar("b0", lose, missing[1], 2, "mcar-b"))


SOME = ("given", "middle", "city", "zip")
PAIRS = {
    "w1": lambda: _papers(f"{h('record_id', 'w1', 100)} < 4", (0.17, 0.54)),
    "w2": lambda: _papers("CAST(regexp_extract(source, '([0-9]+)$', 1) AS INTEGER) % 2 = 0", (0.2, 0.2)),
    "w3": _census_hist,
    "w4": lambda: _voter(0.2),
    "w5": lambda: _voter(0.5),
    "w6": lambda: _snapshot_pair((0.94, 0.92, 0.89), w.VOTER_RATES, SOME, (0.12, 0.10), 2),
    "w7": lambda: _snapshot_pair((0.997, 0.681, 0.9965), w.NATIONAL_RATES, w.NATIONAL, (0.01, 0.01), 1),
}
COMBOS = {"w1": w.PAPER_COMBOS, "w2": w.PAPER_COMBOS, "w3": w.CENSUS_COMBOS, "w4": w.VOTER_COMBOS, "w5": w.VOTER_COMBOS, "w6": w.VOTER_COMBOS, "w7": w.NATIONAL_COMBOS}
CONJ, HOUSE = "family || chr(31) || street", "CAST(household AS VARCHAR)"
KEYS = {"w3": HOUSE, "w4": CONJ, "w5": CONJ, "w6": CONJ, "w7": HOUSE}


def signatures(c: Ctes, side: str, combos: Sequence[Sequence[str]], cap: int | None = 8, name: str | None = None) -> Ctes:
    """s<side>_all and s<side>: record_id, combo_id, sig."""
    name = name or f"s{side}"
    each = " UNION ALL ".join(f"SELECT record_id, {i} AS combo_id, {' || '.join(f'chr(31) || {x}' for x in combo)} AS sig FROM {side} WHERE {' AND '.join(f'{x} IS NOT NULL' for x in combo)}" for i, combo in enumerate(combos, 1))
    c.add(f"{name}_all", each)
    kept = f"SELECT * FROM {name}_all" if cap is None else f"SELECT s.* FROM {name}_all s JOIN (SELECT combo_id, sig FROM {name}_all GROUP BY ALL HAVING count(*) <= {cap}) USING (combo_id, sig)"
    return c.add(name, kept)


def candidates(c: Ctes) -> Ctes:
    c.add("cand", "SELECT x.record_id AS a_id, y.record_id AS b_id, count(*) AS common FROM sa x JOIN sb y USING (combo_id, sig) GROUP BY ALL")
    c.add("na", "SELECT record_id AS a_id, count(*) AS na FROM sa GROUP BY ALL").add("nb", "SELECT record_id AS b_id, count(*) AS nb FROM sb GROUP BY ALL")
    return c.add("scored", "SELECT a_id, b_id, common, na, nb, CAST(common AS DOUBLE) / (na + nb - common) AS s_a FROM cand JOIN na USING (a_id) JOIN nb USING (b_id)")


def edges(c: Ctes, side: str, pair: str) -> Ctes:
    """e<side>: record_id, neighbour in both directions."""
    if pair in ("w1", "w2"):
        members = f"SELECT record_id, k FROM (SELECT record_id, unnest(list_distinct(author_list)) AS k FROM {side})"
    else:
        members = f"SELECT record_id, {KEYS[pair]} AS k FROM {side}"
    c.add(f"g{side}_0", f"SELECT * FROM ({members}) WHERE k IS NOT NULL")
    c.add(f"m{side}", f"SELECT g.* FROM g{side}_0 g JOIN (SELECT k FROM g{side}_0 GROUP BY k HAVING count(*) >= 2) USING (k)")
    return c.add(f"e{side}", f"SELECT DISTINCT x.record_id, y.record_id AS neighbour FROM m{side} x JOIN m{side} y USING (k) WHERE x.record_id <> y.record_id")


def relational(c: Ctes, pair: str) -> Ctes:
    for side in "ab":
        edges(c, side, pair)
        c.add(f"n{side}_sig", f"SELECT DISTINCT e.record_id, s.combo_id, s.sig FROM e{side} e JOIN s{side} s ON s.record_id = e.neighbour")
        c.add(f"r{side}", f"SELECT record_id AS {side}_id, count(*) AS r{side} FROM n{side}_sig GROUP BY ALL")
    c.add("both_r", "SELECT a_id, b_id, count(*) AS rc FROM (SELECT DISTINCT a_id, b_id FROM scored) p JOIN na_sig x ON x.record_id = a_id JOIN nb_sig y ON y.record_id = b_id AND y.combo_id = x.combo_id AND y.sig = x.sig GROUP BY ALL")
    return c.add("with_r", "SELECT s.*, coalesce(CAST(rc AS DOUBLE) / (ra.ra + rb.rb - rc), 0) AS s_r FROM scored s LEFT JOIN ra USING (a_id) LEFT JOIN rb USING (b_id) LEFT JOIN both_r USING (a_id, b_id)")


def matched(pair: str, s_t: float = 0.8, beta: float = 0.5, cap: int | None = 8, combos=None) -> Ctes:
    """Everything up to `matches`: a_id, b_id, s_a, s_r, s, stage."""
    c = PAIRS[pair]()
    for side in "ab":
        signatures(c, side, combos or COMBOS[pair], cap)
    relational(candidates(c), pair)
    e = 1e-9
    return c.add("matches", f"SELECT a_id, b_id, common, s_a, CASE WHEN s_a < {s_t} - {e} THEN s_r END AS s_r, CASE WHEN s_a >= {s_t} - {e} THEN s_a ELSE {beta} * s_a + (1 - {beta}) * s_r END AS s, CASE WHEN s_a >= {s_t} - {e} THEN 1 ELSE 2 END AS stage FROM with_r WHERE s_a >= {s_t} - {e} OR {beta} * s_a + (1 - {beta}) * s_r >= {s_t} - {e}")


def accuracy(pairs: str = "matches") -> str:
    return f"""SELECT count(*) AS predicted, count(t.a_id) AS tp, (SELECT count(*) FROM truth) AS truth, round(count(t.a_id) / nullif(count(*), 0), 6) AS precision,
        round(count(t.a_id) / nullif((SELECT count(*) FROM truth), 0), 6) AS recall FROM {pairs} m LEFT JOIN truth t ON t.a_id = m.a_id AND t.b_id = m.b_id"""


# ---------------------------------------------------------------- selection
def named(attrs: Sequence[str], mask: str = "mask") -> str:
    return "array_to_string(list_filter([" + ", ".join(f"CASE WHEN {mask} & {1 << i} > 0 THEN '{a}' END" for i, a in enumerate(attrs)) + "], lambda x: x IS NOT NULL), ',')"


def scores(attrs: Sequence[str], table: str, low: int = 2, high: int = 6, masks=None, alpha: float = 0.5) -> str:
    """mask, k, s_c, s_g, score of the combinations of `low` to `high` attributes."""
    parts = []
    for m in masks or [m for m in range(1, 1 << len(attrs)) if low <= m.bit_count() <= high]:
        own = [a for i, a in enumerate(attrs) if m >> i & 1]
        there = " AND ".join(f"{a} IS NOT NULL" for a in own)
        parts.append(f"SELECT {m} AS mask, {m.bit_count()} AS k, coalesce(sum(f), 0) AS sf, coalesce(sum(CAST(f AS DOUBLE) * f), 0) AS sff FROM (SELECT count(*) AS f FROM {table} WHERE {there} GROUP BY {', '.join(own)})")
    return f"SELECT mask, k, sf / n AS s_c, sf / n - sff / (CAST(n AS DOUBLE) * n) AS s_g, {alpha} * sf / n + {1 - alpha} * (sf / n - sff / (CAST(n AS DOUBLE) * n)) AS score FROM ({' UNION ALL '.join(parts)}), (SELECT count(*) AS n FROM {table})"


def passing(c: Ctes, c_t: float, high: int = 6, how: str = "apriori") -> Ctes:
    """passing: rows of sc that reach c_t, grown level by level."""
    c.add("p2", f"SELECT * FROM sc WHERE k = 2 AND score >= {c_t - 1e-9}")
    for k in range(3, high + 1):
        parts = f"(SELECT count(*) FROM p{k - 1} p WHERE p.mask & x.mask = p.mask) = {k}"
        c.add(f"p{k}", f"SELECT * FROM sc x WHERE k = {k} AND score >= {c_t - 1e-9}" + (f" AND {parts}" if how == "apriori" else ""))
    return c.add("passing", " UNION ALL ".join(f"SELECT * FROM p{k}" for k in range(2, high + 1)))


#: Combinations no larger one of which passes.
LARGEST = "NOT EXISTS (SELECT 1 FROM passing o WHERE o.mask <> p.mask AND o.mask & p.mask = p.mask)"


def selected(pair: str, policy: str, n_a: int = 5, c_t: float = 0.6, high: int = 3, cap: int = 8, s_t: float = 0.8) -> str:
    """All three steps: the n_a best combinations of both sides, then linkage and accuracy."""
    attrs, c = ATTRS[pair], PAIRS[pair]()
    c.add("sides", f"SELECT {', '.join(attrs)} FROM a UNION ALL SELECT {', '.join(attrs)} FROM b").add("sc", scores(attrs, "sides", 2, high))
    passing(c, c_t, high)
    c.add("chosen", f"SELECT mask, {named(attrs)} AS nm, row_number() OVER (ORDER BY round(score, 9) DESC, k, {named(attrs)}) AS r FROM passing p" + (f" WHERE {LARGEST}" if policy == "drop" else "") + f" QUALIFY r <= {n_a}")
    for side in "ab":
        each = []
        for m in range(1, 1 << len(attrs)):
            own = [a for i, a in enumerate(attrs) if m >> i & 1]
            if 2 <= len(own) <= high:
                each.append(f"SELECT record_id, {m} AS combo_id, {' || '.join(f'chr(31) || {x}' for x in own)} AS sig FROM {side} WHERE {' AND '.join(f'{x} IS NOT NULL' for x in own)} AND {m} IN (SELECT mask FROM chosen)")
        c.add(f"s{side}_all", " UNION ALL ".join(each))
        c.add(f"s{side}", f"SELECT s.* FROM s{side}_all s JOIN (SELECT combo_id, sig FROM s{side}_all GROUP BY ALL HAVING count(*) <= {cap}) USING (combo_id, sig)")
    relational(candidates(c), pair)
    c.add("matches", f"SELECT a_id, b_id FROM with_r WHERE s_a >= {s_t - 1e-9} OR 0.5 * s_a + 0.5 * s_r >= {s_t - 1e-9}")
    c.add("found", accuracy())
    return c.then(f"SELECT '{policy}' AS policy, (SELECT count(*) FROM a) AS records_a, (SELECT count(*) FROM b) AS records_b, (SELECT string_agg(nm, ';' ORDER BY r) FROM chosen) AS combinations, predicted, tp, precision, recall FROM found")


ATTRS = {"w1": w.PAPERS, "w2": w.PAPERS, "w3": w.CENSUS, "w4": w.VOTER, "w5": w.VOTER, "w6": w.VOTER, "w7": w.NATIONAL}
