"""Record graphs: membership in star form, and features of a record's neighbourhood.

A relation is kept as (record, group), and records are related that share a group of whatever
size.  Pairs are only listed where a caller asks for them (`edges`).  Features come from
`Stars`: records with the same groups are one class, so what a record's neighbours hold is
counted per class and group and the record's own share is taken off; a group of g records
costs g rows and not g*g.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from reclink.operators.joins import hot_join
from reclink.plans.model import Rule
from reclink.sources import store

GROUP = ["rule_id", "group_key"]
#: Records of a group on a side of a tile.
TILE = 512
#: Shared groups of a record up to which neighbourhoods are counted from sets of groups.
MOST_GROUPS = 6
#: Bytes in shuffle files for a byte of sets that meet, about.
PER_SET = 16


def membership(df: DataFrame, rules: Sequence[Rule]) -> DataFrame:
    """record_id, rule_id, group_key, role; a null key is no relation."""
    parts = []
    for i, rule in enumerate(rules):
        role = F.col(rule.role).cast("string") if rule.role else F.lit(None).cast("string")
        if rule.kind == "overlap":
            part = df.select("record_id", F.explode(F.array_distinct(F.col(rule.columns[0]).cast("array<string>"))).alias("group_key"), role.alias("role"))
            if rule.max_df is not None:
                rare = part.groupBy("group_key").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") <= rule.max_df)
                part = part.join(rare.select("group_key"), "group_key", "left_semi")
        else:
            keys = [rule.fn(F.col(c)).cast("string") for c in rule.columns]
            key = keys[0] if len(keys) == 1 else F.concat(*[x for k in keys for x in (F.lit("\u001f"), k)])
            part = df.select("record_id", key.alias("group_key"), role.alias("role"))
        parts.append(part.where(F.col("group_key").isNotNull()).select("record_id", F.lit(i).alias("rule_id"), "group_key", "role"))
    return reduce(DataFrame.unionByName, parts)


def apart(rules: Sequence[Rule]) -> bool:
    """Whether no record can be in two groups."""
    return len(rules) == 1 and rules[0].kind != "overlap"


def _paired(members: DataFrame, tile: int) -> DataFrame:
    """record_id of all pairs of different members of a group: src < dst, once per group.  A
    group of more than `tile` members is dealt over tiles, each a key of its own."""
    sizes = members.groupBy(*GROUP).agg(F.count(F.lit(1)).alias("g")).where("g > 1")
    blocks = F.ceil(F.col("g") / tile).cast("int")
    rows = hot_join(members.select("record_id", *GROUP), sizes, GROUP, "g", hot=max(tile, 256)).withColumn("block", F.pmod(F.xxhash64("record_id"), blocks).cast("int"))
    dealt = rows.select("record_id", *GROUP, "block", F.explode(F.sequence(F.lit(0), blocks - 1)).alias("other"))
    dealt = dealt.select("record_id", *GROUP, "block", F.least("block", "other").alias("t0"), F.greatest("block", "other").alias("t1"))
    left, right = dealt.withColumnsRenamed({"record_id": "src", "block": "b0"}), dealt.withColumnsRenamed({"record_id": "dst", "block": "b1"})
    met = left.join(right, [*GROUP, "t0", "t1"]).where("src < dst AND (t0 = t1 OR b0 <> b1)")
    return met.select("src", "dst")


def edges(members: DataFrame, tile: int = TILE) -> DataFrame:
    """src < dst, each pair once whatever the number of shared groups and their size."""
    return _paired(members, tile).distinct()


def star_edges(members: DataFrame) -> DataFrame:
    """src < dst: every member of a group with the group's smallest one; as connected as
    `edges` with one edge a record and group."""
    heads = members.groupBy(*GROUP).agg(F.min("record_id").alias("src"), F.count(F.lit(1)).alias("g")).where("g > 1")
    return hot_join(members.select(F.col("record_id").alias("dst"), *GROUP), heads, GROUP, "g").where("src < dst").select("src", "dst").distinct()


def directed(pairs: DataFrame) -> DataFrame:
    """record_id, neighbour: both directions."""
    ends = F.explode(F.array(F.struct(F.col("src").alias("record_id"), F.col("dst").alias("neighbour")), F.struct(F.col("dst").alias("record_id"), F.col("src").alias("neighbour"))))
    return pairs.select(ends.alias("e")).select("e.*")


def degree(pairs: DataFrame) -> DataFrame:
    return directed(pairs).groupBy("record_id").agg(F.count(F.lit(1)).alias("degree"))


def triangles(pairs: DataFrame) -> DataFrame:
    """a, b, c once each: edges are oriented from the lower to the higher degree, so the
    wedges that are looked at stay few even next to hubs."""
    d = degree(pairs)
    rank = F.struct(F.col("ds"), F.col("src")) < F.struct(F.col("dd"), F.col("dst"))
    known = pairs.join(d.select(F.col("record_id").alias("src"), F.col("degree").alias("ds")), "src").join(d.select(F.col("record_id").alias("dst"), F.col("degree").alias("dd")), "dst")
    out = known.select(F.when(rank, F.col("src")).otherwise(F.col("dst")).alias("u"), F.when(rank, F.col("dst")).otherwise(F.col("src")).alias("v"))
    wedges = out.select("u", F.col("v").alias("x")).join(out.select("u", F.col("v").alias("y")), "u").where("x < y")
    return wedges.join(pairs.select(F.col("src").alias("x"), F.col("dst").alias("y")), ["x", "y"]).select(F.col("u").alias("a"), F.col("x").alias("b"), F.col("y").alias("c"))


def egonet_density(pairs: DataFrame) -> DataFrame:
    """(k + t) / (k (k + 1) / 2) for k neighbours with t edges among them."""
    corners = triangles(pairs).select(F.explode(F.array("a", "b", "c")).alias("record_id")).groupBy("record_id").agg(F.count(F.lit(1)).alias("t"))
    rows = degree(pairs).join(corners, "record_id", "left")
    k = F.col("degree")
    return rows.select("record_id", ((k + F.coalesce("t", F.lit(0))) / (k * (k + 1) / 2)).alias("density"))


class Stars:
    """Neighbourhoods of any size.  `of`: record_id, cls (its class); `classes`: cls, n (its
    records) and each of its groups.  `single` says that no record is in two groups; classes
    are then groups and no two of them meet."""

    def __init__(self, members: DataFrame, single: bool = False, keep: Callable[[DataFrame, str], DataFrame] | None = None):
        self.keep, self.single = keep or store.keep, single
        group = F.struct(*GROUP)
        if single:
            each = members.select("record_id", F.array(group).alias("groups"))
        else:
            each = members.groupBy("record_id").agg(F.array_sort(F.collect_set(group)).alias("groups"))
        name = F.struct(F.xxhash64("groups").alias("x"), F.xxhash64(F.lit(1), "groups").alias("y"))
        named = each.withColumn("cls", name)
        self.of = self.keep(named.select("record_id", "cls"), "class-of")
        sizes = named.groupBy("cls").agg(F.count(F.lit(1)).alias("n"), F.any_value("groups").alias("groups"))
        self.classes = self.keep(sizes.select("cls", "n", F.explode("groups").alias("g")).select("cls", "n", "g.*"), "classes")
        self._links: DataFrame | None = None
        self._sets: DataFrame | None = None
        self._few: bool | None = None

    def sizes(self) -> DataFrame:
        return self.classes.select("cls", "n").distinct() if not self.single else self.classes.select("cls", "n")

    def links(self) -> DataFrame:
        """src < dst: classes that share a group; only made where records have many groups."""
        if self._links is None:
            self._links = self.keep(edges(self.classes.select(F.col("cls").alias("record_id"), *GROUP)), "class-links")
        return self._links

    def _shared(self) -> DataFrame:
        """cls, n, sets: all sets of a class's groups that two records share, by two hashes each;
        the set of bits i stands at place i, from 1."""
        if self._few is None:
            totals = self.classes.groupBy(*GROUP).agg(F.sum("n").alias("g"), F.count(F.lit(1)).alias("r")).where("g > 1")
            rows = hot_join(self.classes, totals, GROUP, "r").groupBy("cls", "n").agg(F.array_sort(F.collect_list(F.struct(*GROUP))).alias("groups"))
            rows = self.keep(rows, "shared-groups")
            self._few = (rows.agg(F.max(F.size("groups")).alias("m")).first()["m"] or 0) <= MOST_GROUPS
            if self._few:
                part = lambda i: F.filter("groups", lambda g, j: F.getbit(i, j) == 1)
                name = lambda i: F.struct(F.xxhash64(part(i)).alias("x"), F.xxhash64(F.lit(1), part(i)).alias("y"))
                every = F.sequence(F.lit(1), F.call_function("shiftleft", F.lit(1), F.size("groups")) - 1)
                self._sets = self.keep(rows.select("cls", "n", F.transform(every, name).alias("sets")), "shared-sets")
        return self._sets

    def few(self) -> bool:
        """Whether records have so few shared groups that all sets of them can be counted."""
        if self._few is None:
            self._shared()
        return bool(self._few)

    @staticmethod
    def _sign(bits: Column) -> Column:
        """1 for a set of an odd number of groups, else -1."""
        return F.when(F.bit_count(bits) % 2 == 1, F.lit(1)).otherwise(F.lit(-1))

    def _each_set(self) -> DataFrame:
        rows = self._shared().select("cls", "n", F.posexplode("sets").alias("i", "s"))
        return rows.select("cls", "n", "s", self._sign(F.col("i") + 1).alias("sign"))

    def _beside(self, values: DataFrame) -> DataFrame:
        """cls, x: sum of the values (cls, x) of the classes that share a group with it: over
        the sets of its groups, what the classes with all of a set have, by inclusion and
        exclusion, less its own.  No two classes meet."""
        if self.single:
            return values.where("false").select("cls", "x")
        if self.few():
            each = self._each_set()
            totals = each.join(values.select("cls", "x"), "cls").groupBy("s").agg(F.sum("x").alias("x"), F.count(F.lit(1)).alias("r"))
            united = hot_join(each.select("cls", "s", "sign"), totals, "s", "r").groupBy("cls").agg(F.sum(F.col("sign") * F.col("x")).alias("all"))
            return united.join(values.select("cls", F.col("x").alias("own")), "cls", "left").select("cls", (F.col("all") - F.coalesce("own", F.lit(0))).alias("x"))
        near = directed(self.links()).withColumnsRenamed({"record_id": "cls", "neighbour": "other"})
        return near.join(values.select(F.col("cls").alias("other"), "x"), "other").groupBy("cls").agg(F.sum("x").alias("x"))

    def class_degrees(self) -> DataFrame:
        """cls, n, k: records of a class, and neighbours of each of them."""
        sizes = self.sizes()
        around = self._beside(sizes.withColumnRenamed("n", "x"))
        return sizes.join(around, "cls", "left").select("cls", "n", (F.coalesce("x", F.lit(0)) + F.col("n") - 1).alias("k")).where("k > 0")

    def degree(self) -> DataFrame:
        """record_id, degree of records that have neighbours."""
        return self.of.join(self.class_degrees(), "cls").select("record_id", F.col("k").alias("degree"))

    def _related_around(self) -> DataFrame:
        """cls, q: over all sets t of groups, signed, the square of how many of a record and its
        neighbours have all of t.  Pairs that share a group are (q - their number) / 2.

        How many have t is itself a signed sum, over the sets s of the class's groups, of the
        records that have both; so the squares are sums over pairs of sets (s, z) of a class of
        one weight, which is summed over the t that occur with both, from the shorter list."""
        each = self._each_set().groupBy("s").agg(F.sum("n").alias("c"))
        bits = F.sequence(F.lit(1), F.size("sets"))
        both = F.flatten(F.transform(bits, lambda i: F.transform(bits, lambda j: F.struct(F.get("sets", i - 1).alias("s"), F.get("sets", j - 1).alias("t"), F.get("sets", i.bitwiseOR(j) - 1).alias("u"), i.alias("i"), j.alias("j")))))
        rows = self.keep(self._shared().select("cls", F.explode(both).alias("p")).select("cls", "p.*"), "set-pairs")
        met = rows.groupBy("s", "t").agg(F.any_value("u").alias("u"), self._sign(F.any_value("j")).alias("sign"), F.count(F.lit(1)).alias("r"))
        met = self.keep(met.join(each.withColumnRenamed("s", "u"), "u").select("s", "t", "sign", "c", "r"), "sets-met")
        long = met.groupBy("s").agg(F.count(F.lit(1)).alias("m"))
        pairs = met.where("s <= t").select(F.col("s"), F.col("t").alias("z"), "r")
        pairs = pairs.join(long, "s").join(long.select(F.col("s").alias("z"), F.col("m").alias("mz")), "z")
        less = F.col("m") <= F.col("mz")
        pairs = pairs.select(F.when(less, F.col("s")).otherwise(F.col("z")).alias("s"), F.when(less, F.col("z")).otherwise(F.col("s")).alias("z"), "r")
        pairs = self.keep(pairs, "set-sides")
        n = min(store.SLICES, 1 + PER_SET * store.read_bytes(met) // store.SLICE_BYTES)

        def weigh(i: int) -> DataFrame:
            first = store.part(pairs, "z", i, n).join(met.select("s", "t", "sign", "c"), "s")
            second = first.join(store.part(met.select(F.col("s").alias("z"), "t", F.col("c").alias("cz")), "z", i, n), ["z", "t"])
            found = second.groupBy("s", "z", "r").agg(F.sum(F.col("sign") * F.col("c") * F.col("cz")).alias("w"))
            return found.select(F.least("s", "z").alias("s"), F.greatest("s", "z").alias("t"), "w", "r")

        weights = store.in_slices(weigh, n, "weights")
        store.release(pairs, met)
        asked = rows.where("s <= t").select("cls", "s", "t", (self._sign(F.col("i")) * self._sign(F.col("j")) * F.when(F.col("i") == F.col("j"), 1).otherwise(2)).alias("sign"))
        return hot_join(asked, weights, ["s", "t"], "r").groupBy("cls").agg(F.sum(F.col("sign") * F.col("w")).alias("q"))

    def density(self) -> DataFrame:
        """record_id, density: (k + t) / (k (k + 1) / 2) for k neighbours with t pairs of
        neighbours among them.  Where records have few groups, pairs are counted from sets of
        groups (`_related_around`).  Else within and between two classes such pairs are counted from
        sizes; three classes that share groups pairwise are triangles of `links`."""
        known = self.class_degrees()
        if not self.single and self.few():
            k = F.col("k")
            pairs = (F.col("q") - (k + 1)) / 2
            rows = known.join(self._related_around(), "cls").select("cls", (pairs / (k * (k + 1) / 2)).alias("density"))
            return self.of.join(rows, "cls").select("record_id", "density")
        n = known.select("cls", "n")
        inner = F.col("n") * (F.col("n") - 1) / 2
        # pairs inside a neighbouring class, and of the own class with it (less the record itself)
        inside = self._beside(known.select("cls", inner.alias("x"))).withColumnRenamed("x", "p")
        between = self._beside(known.select("cls", F.col("n").alias("x"))).withColumnRenamed("x", "q")
        rows = known.join(inside, "cls", "left").join(between, "cls", "left")
        corner = F.lit(0.0)
        if not self.single:
            three = triangles(self.links())
            for name in "abc":
                three = three.join(n.select(F.col("cls").alias(name), F.col("n").alias(f"n_{name}")), name)
            each = F.explode(F.array(*[F.struct(F.col(x).alias("cls"), (F.col(f"n_{y}") * F.col(f"n_{z}")).alias("w")) for x, y, z in ("abc", "bac", "cab")]))
            rows = rows.join(three.select(each.alias("e")).select("e.*").groupBy("cls").agg(F.sum("w").alias("w")), "cls", "left")
            corner = F.coalesce("w", F.lit(0.0))
        own = F.col("n") - 1
        t = own * (own - 1) / 2 + F.coalesce("p", F.lit(0.0)) + own * F.coalesce("q", F.lit(0)) + corner
        k = F.col("k")
        return self.of.join(rows.select("cls", ((k + t) / (k * (k + 1) / 2)).alias("density")), "cls").select("record_id", "density")

    def counts(self) -> DataFrame:
        """edges, triangles of the whole graph, in one row, from degrees and densities; no pair
        is listed."""
        k = F.col("degree")
        among = F.round(F.col("density") * k * (k + 1) / 2 - k).cast("long")
        rows = self.degree().join(self.density(), "record_id")
        n = lambda c, part: F.coalesce((F.sum(c) / part).cast("long"), F.lit(0).cast("long"))
        return rows.agg(n(k, 2).alias("edges"), n(among, 3).alias("triangles"))

    def mean_degree(self) -> DataFrame:
        """record_id, mean_degree: mean degree of the neighbours."""
        known = self.class_degrees()
        around = self._beside(known.select("cls", (F.col("n") * F.col("k")).alias("x")))
        total = F.coalesce("x", F.lit(0)) + (F.col("n") - 1) * F.col("k")
        return self.of.join(known.join(around, "cls", "left").select("cls", (total / F.col("k")).alias("mean_degree")), "cls").select("record_id", "mean_degree")

    def sums(self, values: DataFrame, column: str) -> DataFrame:
        """record_id and the sum of a column of values (record_id, column) over its neighbours."""
        rows = self.of.join(values.select("record_id", F.col(column).alias("own")), "record_id", "left").na.fill(0, ["own"])
        totals = rows.groupBy("cls").agg(F.sum("own").alias("x"))
        around = totals.select("cls", F.col("x").alias("all")).join(self._beside(totals), "cls", "left").select("cls", (F.col("all") + F.coalesce("x", F.lit(0))).alias("x"))
        return rows.join(around, "cls").join(self.class_degrees().select("cls"), "cls", "left_semi").select("record_id", (F.col("x") - F.col("own")).alias(column))

    def around(self, items: DataFrame, wanted: DataFrame | None = None) -> DataFrame:
        """cls, item, n: what the records of a class's groups hold, of items (record_id, item)
        without repeats.  n is 1 if one record of the groups alone holds it (a member of the
        class then lacks it among its neighbours if it is that record), and more otherwise.
        wanted (cls) limits the classes."""
        classes = self.classes if wanted is None else self.classes.join(wanted, "cls", "left_semi")
        held = items.join(self.of, "record_id").groupBy("cls", "item").agg(F.count(F.lit(1)).alias("n"))
        if self.single:
            return held if wanted is None else held.join(wanted, "cls", "left_semi")
        counts = self.classes.select("cls", *GROUP)
        if wanted is not None:
            counts = counts.join(classes.select(*GROUP).distinct(), GROUP, "left_semi")
        counts = counts.join(held, "cls").groupBy(*GROUP, "item").agg(F.sum("n").alias("n"))
        return classes.select("cls", *GROUP).join(counts, GROUP).groupBy("cls", "item").agg(F.max("n").alias("n"))

    def alone(self, items: DataFrame, around: DataFrame) -> DataFrame:
        """record_id, item: items of a record that none of its neighbours holds."""
        return items.join(self.of, "record_id").join(around.where("n = 1").select("cls", "item"), ["cls", "item"]).select("record_id", "item")

    def neighbours_hold(self, items: DataFrame, name: str) -> DataFrame:
        """record_id and the sorted distinct items of its neighbours, where there are any."""
        around = self.keep(self.around(items), "around")
        whole = around.groupBy("cls").agg(F.array_sort(F.collect_list("item")).alias("whole"))
        less = self.alone(items, around).groupBy("record_id").agg(F.collect_list("item").alias("less"))
        rows = self.of.join(whole, "cls").join(less, "record_id", "left")
        found = F.when(F.col("less").isNull(), F.col("whole")).otherwise(F.array_except("whole", "less"))
        return rows.select("record_id", found.alias(name)).where(F.size(name) > 0)


def signature_items(kept: DataFrame) -> DataFrame:
    return kept.select("record_id", F.col("sig_hash").alias("item"))


def value_items(df: DataFrame, columns: Sequence[str]) -> DataFrame:
    values = df.select("record_id", F.explode(F.array(*[F.concat(F.lit(f"{c}="), F.col(c).cast("string")) for c in columns])).alias("item"))
    return values.where("item IS NOT NULL")


def neighbour_signatures(stars: Stars, kept: DataFrame) -> DataFrame:
    """Distinct kept signatures of a record's neighbours, sorted."""
    return stars.neighbours_hold(signature_items(kept), "nbr_sigs")


def neighbour_values(stars: Stars, df: DataFrame, columns: Sequence[str]) -> DataFrame:
    return stars.neighbours_hold(value_items(df, columns), "nbr_values")


def neighbour_roles(members: DataFrame) -> DataFrame:
    """Distinct 'own>other' role labels over shared groups of any size: from the roles of the
    group and how many records have each, without the record's own."""
    rows = members.where("role IS NOT NULL")
    counts = rows.groupBy(*GROUP, "role").agg(F.count(F.lit(1)).alias("n"))
    groups = counts.groupBy(*GROUP).agg(F.collect_list(F.struct("role", "n")).alias("others"), F.sum("n").alias("g"))
    each = hot_join(rows.select("record_id", *GROUP, "role"), groups, GROUP, "g").select("record_id", "role", F.explode("others").alias("o"))
    found = each.where((F.col("o.role") != F.col("role")) | (F.col("o.n") > 1))
    return found.groupBy("record_id").agg(F.array_sort(F.collect_set(F.concat_ws(">", "role", "o.role"))).alias("roles"))


def neighbours_with_missing(stars: Stars, df: DataFrame, columns: Sequence[str]) -> DataFrame:
    lacks = F.exists(F.array(*[F.col(c).cast("string") for c in columns]), lambda x: x.isNull()).cast("long")
    return stars.sums(df.select("record_id", lacks.alias("missing_neighbours")), "missing_neighbours")


def neighbour_centroid(pairs: DataFrame, vectors: DataFrame, column: str = "embedding") -> DataFrame:
    """record_id, centroid: mean vector of the neighbours, summed by position."""
    each = vectors.select(F.col("record_id").alias("neighbour"), F.posexplode(column).alias("i", "x"))
    sums = directed(pairs).join(each, "neighbour").groupBy("record_id", "i").agg(F.avg("x").alias("x"))
    ordered = sums.groupBy("record_id").agg(F.array_sort(F.collect_list(F.struct("i", "x"))).alias("c"))
    return ordered.select("record_id", F.transform("c", lambda s: s["x"]).alias("centroid"))


def components(pairs: DataFrame, checkpoint=None) -> DataFrame:
    """record_id, component (smallest id reached): smallest labels with pointer jumping, until
    no label changes.  `checkpoint` writes a frame and reads it back, so lineage stays short."""
    keep = checkpoint or (lambda df: df.checkpoint())
    both = keep(directed(pairs))
    labels = keep(both.groupBy("record_id").agg(F.least(F.col("record_id"), F.min("neighbour")).alias("component")))
    while True:
        near = both.join(labels.select(F.col("record_id").alias("neighbour"), F.col("component").alias("c")), "neighbour").groupBy("record_id").agg(F.min("c").alias("near"))
        lower = labels.join(near, "record_id").select("record_id", F.least("component", "near").alias("m"), F.col("component").alias("old"))
        jump = labels.select(F.col("record_id").alias("m"), F.col("component").alias("jump"))
        after = keep(lower.join(jump, "m", "left").select("record_id", F.least(F.col("m"), F.coalesce("jump", "m")).alias("component"), "old"))
        changed = after.where("component <> old").limit(1).count()
        labels = after.select("record_id", "component")
        if not changed:
            return labels


def group_sizes(members: DataFrame) -> DataFrame:
    """Degree under one rule without making edges: group size less one."""
    return members.select("record_id", (F.count(F.lit(1)).over(Window.partitionBy(*GROUP)) - 1).alias("degree"))
