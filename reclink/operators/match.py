"""Step 3: candidate pairs, attribute similarity, and the relational second chance."""

from __future__ import annotations

import time
from collections.abc import Callable, Sequence
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from reclink.operators import graph, joins, pairing, signatures
from reclink.operators.select import select_combinations
from reclink.plans.model import Combo, Qid, Rule, Settings
from reclink.plans.planner import EPSILON, relational_bound
from reclink.sources import store


# ---------------------------------------------------------------- similarities
def from_counts(common: Column, na: Column, nb: Column, kind: str = "jaccard") -> Column:
    """Set similarity from the sizes of the sets and of their intersection; 0 for two empty
    sets.  kind: jaccard, dice, overlap or count."""
    if kind == "count":
        return common.cast("double")
    below = {"jaccard": na + nb - common, "dice": na + nb, "overlap": F.least(na, nb)}[kind]
    above = 2 * common if kind == "dice" else common
    return F.coalesce(F.try_divide(above.cast("double"), below), F.lit(0.0))


def set_similarity(a: Column, b: Column, kind: str = "jaccard") -> Column:
    return from_counts(F.size(F.array_intersect(a, b)), F.size(a), F.size(b), kind)


def number_similarity(a: Column, b: Column) -> Column:
    """1 - |a-b| / max(a, b); two zeros are equal."""
    return F.when(F.greatest(a, b) == 0, F.lit(1.0)).otherwise(1 - F.abs(a - b) / F.greatest(a, b))


# ---------------------------------------------------------------- pairs
def candidate_pairs(sa: DataFrame, sb: DataFrame) -> DataFrame:
    """a_id, b_id, common: pairs that share a kept signature.  The frequency cap bounds how
    many pairs a signature can make.  Only hashes are shuffled: two of 64 bits, which stand
    for the string."""
    key = ["combo_id", "sig_hash", "sig_check"]
    left = sa.select(*key, F.col("record_id").alias("a_id"))
    right = sb.select(*key, F.col("record_id").alias("b_id"))
    return left.join(right, key).groupBy("a_id", "b_id").agg(F.count(F.lit(1)).alias("common"))


def scored_pairs(sa: DataFrame, sb: DataFrame, sim_a: str = "jaccard", pairs: DataFrame | None = None) -> DataFrame:
    """Candidates with s_a, from counts alone."""
    sizes = lambda s, side: s.groupBy(F.col("record_id").alias(f"{side}_id")).agg(F.count(F.lit(1)).alias(f"n{side}"))
    pairs = pairs if pairs is not None else candidate_pairs(sa, sb)
    rows = pairs.join(sizes(sa, "a"), "a_id", "left").join(sizes(sb, "b"), "b_id", "left").na.fill(0, ["na", "nb"])
    return rows.select("a_id", "b_id", "common", from_counts(F.col("common"), F.col("na"), F.col("nb"), sim_a).alias("s_a"))


def similar_pairs(sa: DataFrame, sb: DataFrame, least: float) -> DataFrame:
    """Scored pairs (jaccard) with s_a of at least `least` > 0, which needs no frequency cap: a
    record's signatures are ordered by the pairs that they would make, and two records that
    share enough of them share one of the first ones.  Sets travel with these and a pair is
    made at its first common signature, so no pair is shuffled."""
    key = ["combo_id", "sig_hash", "sig_check"]
    sa, sb = meeting(sa, sb, whole=True)
    n = store.slices_of(sa, sb)
    count = lambda rows, x, y, i: store.part(rows, "sig_hash", i, n).select(*key, F.lit(x).alias("x"), F.lit(y).alias("y"))
    made = lambda i: count(sa, 1, 0, i).unionByName(count(sb, 0, 1, i)).groupBy(*key).agg(F.sum("x").alias("x"), F.sum("y").alias("y"))
    # a signature of one side makes no pair, but counts in its record's set
    made = store.in_slices(lambda i: made(i).select(*key, (F.col("x") * F.col("y")).alias("f"), "x", "y"), n, "signature-pairs")

    def ordered(rows: DataFrame, count: str) -> Callable[[int, int], DataFrame]:
        return lambda i, n: joins.hot_join(store.part(rows, "record_id", i, n).select("record_id", *key), made.select(*key, "f", count), key, count)

    left, right = signature_sets(sa, "a", ordered(sa, "x")), signature_sets(sb, "b", ordered(sb, "y"))
    common = F.size("both").cast("long")
    out = meet(left, right, lambda rows: rows.select("a_id", "b_id", common.alias("common"), from_counts(common, F.size("sa"), F.size("sb")).alias("s_a")).where(F.col("s_a") >= least - EPSILON), least)
    store.release(made, *((left, right) if store.is_kept(out) else ()))
    return out


#: Bytes of signature files whose sets are broadcast to the values that go along, or which are
#: broadcast themselves to the signatures of the other side.
FEW_BYTES = 8 << 20


def meeting(sa: DataFrame, sb: DataFrame, whole: bool = False) -> tuple[DataFrame, DataFrame]:
    """Signatures of both sides; where one side has few, of the other only those that it has too
    (whole: all of the records that have such a one, if these are few as well)."""
    key = ["combo_id", "sig_hash", "sig_check"]
    few = lambda rows: store.read_bytes(rows) <= FEW_BYTES

    def met(rows: DataFrame, others: DataFrame) -> DataFrame:
        found = store.keep(rows.join(F.broadcast(others.select(*key)), key, "left_semi"), "meeting")
        if not whole:
            return found
        out = store.keep(rows.join(F.broadcast(found.select("record_id")), "record_id", "left_semi"), "meeting") if few(found) else rows
        store.release(found)
        return out

    if few(sa) == few(sb):
        return sa, sb
    return (sa, met(sb, sa)) if few(sa) else (met(sa, sb), sb)


def signature_sets(sigs: DataFrame, side: str, ordered: Callable[[int, int], DataFrame] | None = None, more: DataFrame | None = None, counted: bool = False) -> DataFrame:
    """{side}_id and s{side}, its signatures as (h, c), in the order of f; `ordered` gives the
    signatures of a slice of records with f.  Columns of `more` (record_id and others) go along;
    counted adds n to a signature.  Written, in slices of records where there are many."""
    names = {"h": "sig_hash", "c": "sig_check"} | ({"n": "n"} if counted else {})
    few = more is not None and store.read_bytes(sigs) <= FEW_BYTES
    n = 1 if few else store.slices_of(sigs, *([more] if more is not None else []))

    def make(i: int) -> DataFrame:
        rows = ordered(i, n) if ordered else store.part(sigs, "record_id", i, n).withColumn("f", F.lit(0))
        sets = rows.groupBy("record_id").agg(F.array_sort(F.collect_list(F.struct("f", *[F.col(c).alias(k) for k, c in names.items()]))).alias("s"))
        sets = sets.select("record_id", F.transform("s", lambda x: F.struct(*[x[k].alias(k) for k in names])).alias(f"s{side}"))
        if more is not None:
            sets = (F.broadcast(sets) if few else sets).join(store.part(more, "record_id", i, n), "record_id")
        return sets.withColumnRenamed("record_id", f"{side}_id")

    return store.in_slices(make, n, "signature-sets")


def meet(left: DataFrame, right: DataFrame, of: Callable[[DataFrame], DataFrame], least: float = 0.0) -> DataFrame:
    """`of` (rows of both sides with both, the signatures that they share) over every pair that
    can reach a jaccard of `least`.  A pair is made at its first common signature, by one slice
    of the signatures; written where there is more than one."""
    n = store.slices_of(left, right)

    def firsts(sets: DataFrame, side: str, i: int) -> DataFrame:
        size = F.size(f"s{side}")
        most = size - F.ceil(size * least - EPSILON).cast("int") + 1
        rows = sets.select("*", F.explode(F.slice(f"s{side}", F.lit(1), most)).alias("k"))
        return rows if n == 1 else rows.where(F.pmod("k.h", F.lit(n)) == i)

    def make(i: int) -> DataFrame:
        met = firsts(left, "a", i).join(firsts(right, "b", i), "k").withColumn("both", F.array_intersect("sa", "sb"))
        return of(met.where(F.get("both", F.lit(0)) == F.col("k")))

    return make(0) if n == 1 else store.in_slices(make, n, "met")


def relational_candidates(sa: DataFrame, sb: DataFrame, ra: DataFrame, rb: DataFrame, cap: int) -> DataFrame:
    """Attribute candidates and pairs whose neighbours share a signature held by at most
    `cap` records' neighbourhoods on each side; common counts attribute signatures."""
    own = lambda r, side: r.select(F.col("record_id").alias(f"{side}_id"), F.explode("nbr_sigs").alias("h"))
    capped = lambda rows: rows.join(rows.groupBy("h").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") <= cap).select("h"), "h", "left_semi")
    more = capped(own(ra, "a")).join(capped(own(rb, "b")), "h").select("a_id", "b_id").distinct().withColumn("common", F.lit(0).cast("long"))
    return candidate_pairs(sa, sb).unionByName(more).groupBy("a_id", "b_id").agg(F.max("common").alias("common"))


# ---------------------------------------------------------------- relational similarity
class Side:
    """A database as stage 2 sees it: its record graph, made when a pair first asks for it."""

    def __init__(self, df: DataFrame, kept: DataFrame, rules: Sequence[Rule], qids: Sequence[Qid], keep: Callable[[DataFrame, str], DataFrame]):
        self.df, self.kept, self.rules, self.qids, self.keep = df, kept, rules, qids, keep
        self._stars: graph.Stars | None = None

    @property
    def members(self) -> DataFrame:
        return graph.membership(self.df, self.rules)

    @property
    def stars(self) -> graph.Stars:
        if self._stars is None:
            self._stars = graph.Stars(self.members, graph.apart(self.rules), self.keep)
        return self._stars

    def items(self, feature: str) -> DataFrame:
        return graph.signature_items(self.kept) if feature == "nbr_sigs" else graph.value_items(self.df, [q.name for q in self.qids])

    def numbers(self, feature: str) -> DataFrame:
        return self.stars.degree() if feature == "degree" else self.stars.density()


def common_items(pairs: DataFrame, a: Side, b: Side, feature: str) -> DataFrame:
    """a_id, b_id, na, nb, common of pairs (a_id, b_id): sizes of the sets that the neighbours
    of both hold, and of what the sets share.

    What the classes of both hold is counted once a pair of classes; what a record alone holds
    in its groups is no neighbour's and is taken off.
    """
    keep = a.keep
    near = pairs.select("a_id", "b_id")
    for side, name in ((a, "a"), (b, "b")):
        near = near.join(side.stars.of.select(F.col("record_id").alias(f"{name}_id"), F.col("cls").alias(f"c{name}")), f"{name}_id", "left")
    near = keep(near, "near")
    held, own = {}, {}
    for side, name in ((a, "a"), (b, "b")):
        wanted = near.select(F.col(f"c{name}").alias("cls")).where("cls IS NOT NULL").distinct()
        items = side.items(feature)
        held[name] = keep(side.stars.around(items, wanted), "around")
        asked = items.join(near.select(F.col(f"{name}_id").alias("record_id")).distinct(), "record_id", "left_semi")
        own[name] = keep(side.stars.alone(asked, held[name]), "alone").select(F.col("record_id").alias(f"{name}_id"), "item")
        held[name] = held[name].select(F.col("cls").alias(f"c{name}"), "item")
    met = near.where("ca IS NOT NULL AND cb IS NOT NULL")
    classes = met.select("ca", "cb").distinct().join(held["a"], "ca").join(held["b"], ["cb", "item"]).groupBy("ca", "cb").agg(F.count(F.lit(1)).alias("both"))
    less = lambda rows, weight: rows.select("a_id", "b_id", F.lit(weight).alias("w"))
    off = less(met.join(own["a"], "a_id").join(held["b"], ["cb", "item"]), -1)
    off = off.unionByName(less(met.join(own["b"], "b_id").join(held["a"], ["ca", "item"]), -1))
    off = off.unionByName(less(met.join(own["a"], "a_id").join(own["b"], ["b_id", "item"]), 1))
    out = near.join(classes, ["ca", "cb"], "left").join(off.groupBy("a_id", "b_id").agg(F.sum("w").alias("w")), ["a_id", "b_id"], "left")
    for name in "ab":
        out = out.join(held[name].groupBy(f"c{name}").agg(F.count(F.lit(1)).alias(f"h{name}")), f"c{name}", "left")
        out = out.join(own[name].groupBy(f"{name}_id").agg(F.count(F.lit(1)).alias(f"o{name}")), f"{name}_id", "left")
    n = lambda c: F.coalesce(c, F.lit(0))
    return out.select("a_id", "b_id", (n("ha") - n("oa")).alias("na"), (n("hb") - n("ob")).alias("nb"), (n("both") + n("w")).alias("common"))


def _feature(pairs: DataFrame, a: Side, b: Side, name: str, kind: str) -> DataFrame:
    """a_id, b_id, and the similarity of the pair's feature."""
    if name in ("nbr_sigs", "nbr_values"):
        return common_items(pairs, a, b, name).select("a_id", "b_id", from_counts(F.col("common"), F.col("na"), F.col("nb"), kind).alias(name))
    out, value = pairs.select("a_id", "b_id"), "roles" if name == "roles" else name
    for side, at in ((a, "a"), (b, "b")):
        table = graph.neighbour_roles(side.members) if name == "roles" else side.numbers(name)
        out = out.join(table.select(F.col("record_id").alias(f"{at}_id"), F.col(value).alias(f"v{at}")), f"{at}_id", "left")
    if name == "roles":
        found = F.coalesce(set_similarity(F.col("va"), F.col("vb"), kind), F.lit(0.0))
    else:
        found = number_similarity(*(F.coalesce(F.col(c).cast("double"), F.lit(0.0)) for c in ("va", "vb")))
    return out.select("a_id", "b_id", found.alias(name))


def relational(pairs: DataFrame, a: Side, b: Side, settings: Settings = Settings()) -> DataFrame:
    """pairs (a_id, b_id and more) with s_r: the mean over the features, of set similarity for
    sets and number similarity for numbers.  Records without neighbours count as empty."""
    out, names = pairs, settings.features
    for name in names:
        out = out.join(_feature(pairs, a, b, name, settings.sim_r), ["a_id", "b_id"], "left")
    mean = sum((F.coalesce(F.col(x), F.lit(0.0)) for x in names), F.lit(0.0)) / len(names)
    return out.withColumn("s_r", mean).drop(*names)


def decide(scored: DataFrame, a: Side, b: Side, settings: Settings = Settings(), bound: bool = True) -> DataFrame:
    """a_id, b_id, common, s_a, s_r, s, stage of the matches.

    Stage 1 takes s_a >= s_t.  Stage 2 blends with the relational similarity; only pairs
    that can still reach s_t fetch their neighbourhoods (bound=False: all).
    """
    first = scored.where(F.col("s_a") >= settings.s_t - EPSILON).select("*", F.lit(None).cast("double").alias("s_r"), F.col("s_a").alias("s"), F.lit(1).alias("stage"))
    low = F.lit(0.0) if not bound else F.lit(relational_bound(settings.s_t, settings.beta))
    rest = scored.where((F.col("s_a") < settings.s_t - EPSILON) & (F.col("s_a") >= low))
    if bound and settings.beta == 1:
        return first  # the blend is s_a alone
    blended = relational(rest, a, b, settings)
    s = settings.beta * F.col("s_a") + (1 - settings.beta) * F.col("s_r")
    second = blended.select("a_id", "b_id", "common", "s_a", "s_r", s.alias("s"), F.lit(2).alias("stage")).where(F.col("s") >= settings.s_t - EPSILON)
    return first.unionByName(second)


def one_to_one(pairs: DataFrame) -> DataFrame:
    """Pairs that are the best of both their records (score, then the other id)."""
    by = lambda own, other: F.row_number().over(Window.partitionBy(own).orderBy(F.desc("s"), other))
    return pairs.withColumn("_a", by("a_id", "b_id")).withColumn("_b", by("b_id", "a_id")).where("_a = 1 AND _b = 1").drop("_a", "_b")


def explain_pairs(matches: DataFrame, sa: DataFrame, sb: DataFrame) -> DataFrame:
    """Matches with the combinations whose signatures they share."""
    left = sa.select("combo_id", "sig_hash", F.col("record_id").alias("a_id"))
    right = sb.select("combo_id", "sig_hash", F.col("record_id").alias("b_id"))
    shared = left.join(right, ["combo_id", "sig_hash"]).join(matches.select("a_id", "b_id"), ["a_id", "b_id"], "left_semi")
    shared = shared.groupBy("a_id", "b_id").agg(F.array_sort(F.collect_list("combo_id")).alias("shared_combos"))
    return matches.join(shared, ["a_id", "b_id"])


# ---------------------------------------------------------------- the whole method
@dataclass
class LinkResult:
    pairs: DataFrame
    combos: list[Combo]
    sig_a: DataFrame
    sig_b: DataFrame
    scored: DataFrame
    a: Side
    b: Side
    timings: dict[str, float] = field(default_factory=dict)

    def relational(self, settings: Settings = Settings()) -> DataFrame:
        """All candidates with s_a and s_r."""
        return relational(self.scored, self.a, self.b, settings)


def refuse_repeated_ids(df: DataFrame) -> None:
    """A record_id names one record: pairs, graphs and counts rest on that."""
    repeated = df.groupBy("record_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").limit(1).collect()
    if repeated:
        raise ValueError(f"record_id {repeated[0]['record_id']!r} occurs {repeated[0]['n']} times")


def link(
    a: DataFrame, b: DataFrame, qids: Sequence[Qid], rules: Sequence[Rule], combos: Sequence[Combo] | None = None, settings: Settings = Settings(),
    keep: Callable[[DataFrame, str], DataFrame] | None = None, candidates: str = "attr", relational_cap: int = 50, every: bool = True, **selection,
) -> LinkResult:
    """All three steps.  Each step is written by `keep` (default: files in the shared folder),
    so it is computed once and timings are of work done; selection goes to
    select_combinations, over both databases.  candidates="attr+rel" adds pairs that share a
    neighbour's signature which at most `relational_cap` neighbourhoods hold.  every=False
    scores only candidates that can still match; the matches are the same."""
    keep = keep or store.keep
    for side in (a, b):
        refuse_repeated_ids(side)
    times, clock = {}, time.monotonic()
    if combos is None:
        names = [q.name for q in qids]
        combos = select_combinations(a.select(*names).unionByName(b.select(*names)), qids, settings.n_a, settings.alpha, settings.c_t, **selection)
    times["select"], clock = time.monotonic() - clock, time.monotonic()
    if not combos:
        raise ValueError("no combination reaches c_t")
    sa, sb = signatures.written_signatures(a, b, qids, combos, settings, keep)
    left, right = (Side(x, s, rules, qids, keep) for x, s in ((a, sa), (b, sb)))
    if settings.beta < 1:
        left.stars, right.stars  # noqa: B018  the record graphs are part of this step
    times["generate"], clock = time.monotonic() - clock, time.monotonic()
    pairs = None
    if candidates == "attr+rel":
        pairs = relational_candidates(sa, sb, graph.neighbour_signatures(left.stars, sa), graph.neighbour_signatures(right.stars, sb), relational_cap)
    least = settings.s_t if settings.beta == 1 else relational_bound(settings.s_t, settings.beta)
    if every or pairs is not None or settings.sim_a != "jaccard" or least <= EPSILON:
        scored = keep(scored_pairs(sa, sb, settings.sim_a, pairs), "scored")
    else:
        scored = similar_pairs(sa, sb, least)
        scored = scored if store.is_kept(scored) else keep(scored, "scored")
    matches = keep(decide(scored, left, right, settings), "matches")
    times["match"] = time.monotonic() - clock
    return LinkResult(matches, list(combos), sa, sb, scored, left, right, times)


def link_counts(rows: pairing.Rows, qids: Sequence[Qid], combos: Sequence[Combo], settings: Settings = Settings()) -> DataFrame:
    """match and n: how many pairs `link` finds that are true, and not, in databases by row
    numbers, where relations have no weight (beta 1); written."""
    if settings.beta != 1 or settings.sim_a != "jaccard" or settings.s_t <= EPSILON:
        raise ValueError("only matches by attributes are counted")
    grouped = pairing.groups(rows, qids, combos, settings, whole=True)
    s_a = from_counts(F.col("common"), F.col("a_n"), F.col("b_n"))

    def decided(pairs: DataFrame) -> DataFrame:
        scored = pairs.select(F.col("a_row").alias("a_id"), F.col("b_row").alias("b_id"), "common", s_a.alias("s_a"))
        return pairing.by_truth(decide(scored, None, None, settings).withColumnsRenamed({"a_id": "a_row", "b_id": "b_row"}))

    found = pairing.similar(rows, grouped, decided)
    out = store.keep(found.groupBy("match").agg(F.sum("n").alias("n")), "tally")
    store.release(grouped)
    return out
