"""Step 2: attribute signatures, their frequency filter, and the signature database."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from reclink.functions.hashing import salted
from reclink.operators import graph
from reclink.plans.model import Combo, Qid, Rule, Settings
from reclink.plans.planner import n_max
from reclink.sources import store

#: Stands between the parts of a stored signature, so ("ab", "c") and ("a", "bc") differ.
SEPARATOR = "\u001f"
#: Signatures over the cap that are broadcast (20 bytes each), and records from which one
#: counts as hot where they are more.
FREQUENT, HOT = 400_000, 1_000
#: Bytes of a database whose signatures are filtered at once, and slices at most.
SLICE_BYTES, SLICES = 32 << 20, 8


def attribute_signature(combo: Combo, qids: Sequence[Qid], render: str = "stored") -> Column:
    """Tokens of a combination in one string; null if any of them is missing (concat gives
    null for null, unlike concat_ws).  render="plain" has no separator, for display."""
    by_name = {q.name: q for q in qids}
    parts = [by_name[a].token().cast("string") for a in combo.attrs]
    if render == "plain":
        return F.concat(*parts)
    return F.concat(*[x for p in parts for x in (F.lit(SEPARATOR), p)])


def attribute_signatures(df: DataFrame, qids: Sequence[Qid], combos: Sequence[Combo]) -> DataFrame:
    """record_id, combo_id, sig_hash, sig_check, sig: one row per complete combination; narrow.
    The two hashes together stand for the string in joins."""
    each = [F.struct(F.lit(c.combo_id).alias("combo_id"), attribute_signature(c, qids).alias("sig")) for c in combos]
    rows = df.select("record_id", F.explode(F.array(*each)).alias("s")).select("record_id", "s.combo_id", "s.sig")
    return rows.where(F.col("sig").isNotNull()).select("record_id", "combo_id", F.xxhash64("combo_id", "sig").alias("sig_hash"), F.xxhash64("sig", F.lit(1)).alias("sig_check"), "sig")


def salted_signatures(attr_sig: DataFrame, secret: str) -> DataFrame:
    """Signatures as digests under a secret; no raw value is kept."""
    return attr_sig.select("record_id", "combo_id", salted(F.col("sig"), secret).alias("digest"))


def signature_counts(attr_sig: DataFrame) -> DataFrame:
    """combo_id, sig_hash, n: records that share a signature (one per record and combo)."""
    return attr_sig.groupBy("combo_id", "sig_hash").agg(F.count(F.lit(1)).alias("n"))


def signature_probability(n: Column, lam: float = 1.2, mu: float = 0.2, mode: str = "literal") -> Column:
    p = 1 / (1 + F.pow(F.lit(lam), n) * mu)
    return p if mode == "literal" else p * (1 + lam * mu)


def filter_signatures(attr_sig: DataFrame, settings: Settings = Settings(), counted: DataFrame | None = None) -> DataFrame:
    """Drops signatures whose probability is under p_t, as a cap on n.  `counted` gives the
    rows to count over (both databases for count_scope="union").

    Only counts are shuffled, summed before; signatures over the cap are broadcast if they are
    few, and else those of very many records, so that no row travels to be dropped with all
    others of its signature."""
    cap = n_max(settings.p_t, settings.lam, settings.mu, settings.prob_mode)
    if cap is None:
        return attr_sig
    counts = signature_counts(counted if counted is not None else attr_sig)
    over = store.keep(counts.where(F.col("n") > cap).select("combo_id", "sig_hash", "n"), "frequent")
    key = ["combo_id", "sig_hash"]
    if over.limit(FREQUENT + 1).count() <= FREQUENT:
        return attr_sig.join(F.broadcast(over.select(*key)), key, "left_anti")
    hot = over.where(F.col("n") > HOT)
    rest = attr_sig.join(F.broadcast(hot.select(*key)), key, "left_anti") if hot.limit(FREQUENT + 1).count() <= FREQUENT else attr_sig
    return rest.join(over.select(*key), key, "left_anti")


def kept_signatures(a: DataFrame, b: DataFrame, qids: Sequence[Qid], combos: Sequence[Combo], settings: Settings = Settings()) -> tuple[DataFrame, DataFrame]:
    """Filtered signatures of both databases.  Those of a large database are filtered in slices,
    combination by combination and by hashes, each written before the next begins, so that only a
    slice's rows are in shuffle files at a time; a slice reads the attributes of its combination
    anew and holds no strings."""

    def made(rows: DataFrame, of: Sequence[Combo]) -> DataFrame:
        return attribute_signatures(rows, qids, of)

    union = settings.count_scope == "union"
    slices = min(SLICES, 1 + store.read_bytes(a, b) // (2 * SLICE_BYTES))
    if slices == 1 or n_max(settings.p_t, settings.lam, settings.mu, settings.prob_mode) is None:
        sa, sb = made(a, combos), made(b, combos)
        both = sa.unionByName(sb) if union else None
        return filter_signatures(sa, settings, both), filter_signatures(sb, settings, both)
    hashes = -(-slices // len(combos))

    def part(rows: DataFrame, i: int) -> DataFrame:
        found = made(rows, [combos[i // hashes]]).drop("sig")
        return found if hashes == 1 else found.where(F.pmod("sig_hash", F.lit(hashes)) == i % hashes)

    def sliced(rows: DataFrame) -> DataFrame:
        return store.in_slices(lambda i: filter_signatures(part(rows, i), settings, part(a, i).unionByName(part(b, i)) if union else None), hashes * len(combos), "slice")

    return sliced(a), sliced(b)


def written_signatures(a: DataFrame, b: DataFrame, qids: Sequence[Qid], combos: Sequence[Combo], settings: Settings = Settings(), keep: store.Keeper = store.keep) -> tuple[DataFrame, DataFrame]:
    """kept_signatures without strings, written once: slices are files already."""
    found = zip(kept_signatures(a, b, qids, combos, settings), ("sig_a", "sig_b"))
    sa, sb = (x if store.is_kept(x) else keep(x.drop("sig"), name) for x, name in found)
    return sa, sb


def signature_database(df: DataFrame, qids: Sequence[Qid], combos: Sequence[Combo], rules: Sequence[Rule], settings: Settings = Settings()) -> DataFrame:
    """record_id, attr_sigs, rel: every record, also those without signatures.

    rel holds the features asked for: degree, density, nbr_sigs, nbr_values, roles.
    """
    kept = filter_signatures(attribute_signatures(df, qids, combos), settings)
    sigs = kept.groupBy("record_id").agg(F.array_sort(F.collect_set("sig_hash")).alias("attr_sigs"))
    out = df.select("record_id").join(sigs, "record_id", "left")
    members = graph.membership(df, rules)
    stars = graph.Stars(members, graph.apart(rules))
    tables = {
        "degree": stars.degree,
        "density": stars.density,
        "nbr_sigs": lambda: graph.neighbour_signatures(stars, kept),
        "nbr_values": lambda: graph.neighbour_values(stars, df, [q.name for q in qids]),
        "roles": lambda: graph.neighbour_roles(members),
    }
    defaults = {"degree": F.lit(0).cast("long"), "density": F.lit(0.0), "nbr_sigs": F.array().cast("array<long>"), "nbr_values": F.array().cast("array<string>"), "roles": F.array().cast("array<string>")}
    for name in settings.features:
        out = out.join(tables[name](), "record_id", "left")
    rel = F.struct(*[F.coalesce(F.col(name), defaults[name]).alias(name) for name in settings.features])
    return out.select("record_id", F.coalesce("attr_sigs", F.array().cast("array<long>")).alias("attr_sigs"), rel.alias("rel"))
