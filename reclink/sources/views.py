"""Record views over the given tables: what a linkage sees as its databases."""

from __future__ import annotations

import datetime

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from reclink.sources.store import keep
from reclink.sources.tables import read

EXAMPLE_SCHEMA = "database string, record_id string, entity_id string, first_name string, last_name string, birth_date date, street string, city string, phone string"


def example(spark: SparkSession) -> DataFrame:
    """Five records of two databases with missing values; two entities are in both."""
    day, other = datetime.date(1981, 11, 25), datetime.date(1991, 9, 11)
    rows = [
        ("A", "r1", "e1", "Peter", "Smith", day, None, "London", None),
        ("A", "r2", "e2", "Peter", None, day, "43 Skye Pl", "Dublin", "+353 456 785"),
        ("A", "r3", "e3", "Anne", "Miller", other, "43 Skye Plc", None, "+353 456 785"),
        ("B", "r4", "e2", "Peter", "Smith", day, "43 Skye Pl", None, None),
        ("B", "r5", "e3", "Ann", "Myller", None, "43 Skye Place", "Dublin", "+353 456 785"),
    ]
    return spark.createDataFrame(rows, EXAMPLE_SCHEMA)


def person(spark: SparkSession, sf_dir: str, i: int = 0, n: int = 1) -> DataFrame:
    """One person per order line; an order is a household.  Slice i of n, by orders.  Orders
    come last, so that an order's lines leave the join together and their files are small."""
    t = lambda name: read(spark, sf_dir, name)
    mine = lambda name, key: t(name) if n == 1 else t(name).where(F.pmod(F.xxhash64(F.col(key).cast("long")), F.lit(n)) == i)
    home = t("nation").select(F.col("n_nationkey").alias("c_nationkey"), F.col("n_name").alias("home"))
    parish = t("nation").select(F.col("n_nationkey").alias("s_nationkey"), F.col("n_name").alias("parish"))
    orders = mine("orders", "o_orderkey").join(t("customer").join(home, "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    rows = (
        mine("lineitem", "l_orderkey")
        .join(t("part"), F.col("l_partkey") == F.col("p_partkey"))
        .join(t("supplier").join(parish, "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
        .join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    )
    record = F.concat_ws("-", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", F.round(F.col("l_extendedprice") * 100).cast("long"))
    return rows.select(
        record.alias("record_id"), record.alias("entity_id"), F.col("l_orderkey").alias("household"), F.col("l_linenumber").cast("string").alias("role"),
        F.col("p_name").alias("given"), F.col("p_type").alias("middle"), F.concat_ws(" ", "home", "c_mktsegment").alias("family"),
        F.concat(F.date_format("o_orderdate", "yyyy-MM-dd"), F.lit(" "), F.col("c_name")).alias("street"), F.col("home").alias("city"), F.col("o_orderpriority").alias("zip"),
        F.date_format("l_shipdate", "yyyy-MM-dd").alias("birth"), F.col("l_returnflag").alias("gender"), F.col("l_quantity").cast("int").cast("string").alias("age"),
        F.col("p_brand").alias("occupation"), F.col("parish"), F.year("o_orderdate").alias("wave"),
    )


def _split(text: str) -> Column:
    return F.filter(F.split(F.lower(text), r"[^\p{L}\p{N}_]+"), lambda w: F.length(w) > 0)


def _authors(words: Column) -> Column:
    ranked = F.array_sort(F.transform(F.array_distinct(words), lambda x: F.struct((-F.length(x)).alias("n"), x.alias("x"))))
    return F.transform(F.slice(ranked, 1, 3), lambda s: s["x"])


def _title(words: Column) -> Column:
    return F.array_join(F.slice(words, 1, 3), " ")


def publication_heads(spark: SparkSession, sf_dir: str) -> DataFrame:
    """record_id, title and author_list of `publication`; no other words are written."""
    # one value of a list: the optimizer would put the splitting into each use of the words
    head = F.transform(F.array(_split("text")), lambda w: F.struct(_title(w).alias("title"), _authors(w).alias("author_list"), F.size(w).alias("n")))
    rows = read(spark, sf_dir, "documents").select(F.col("doc_id").cast("string").alias("record_id"), F.explode(head).alias("h"))
    return keep(rows.where("h.n > 0").select("record_id", "h.title", "h.author_list"), "heads")


def publication(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents as publications: first words as title, longest words as authors."""
    # written once: the optimizer would put the splitting into each step of the lambdas below
    rows = keep(read(spark, sf_dir, "documents").select("doc_id", "lang", "source", "n_chars", _split("text").alias("w"), F.md5("text").alias("entity_id")), "words").where(F.size("w") > 0)
    authors = _authors(F.col("w"))
    last = F.slice("w", F.greatest(F.size("w") - 2, F.lit(1)), 3)
    return rows.select(
        F.col("doc_id").cast("string").alias("record_id"), _title(F.col("w")).alias("title"), F.array_join(F.array_sort(authors), " ").alias("authors"), authors.alias("author_list"),
        F.array_join(last, " ").alias("venue"), (1950 + F.floor(F.col("n_chars") / 200) % 70).cast("string").alias("year"), "lang", "source", "entity_id",
        F.array_distinct(F.when(F.size("w") >= 3, F.transform(F.sequence(F.lit(1), F.greatest(F.size("w") - 2, F.lit(1))), lambda i: F.array_join(F.slice("w", i, 3), " "))).otherwise(F.array(F.array_join("w", " ")))).alias("runs"),
    )


def household_turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "conversations")
    return rows.select(
        F.concat_ws("-", "conv_id", "turn").alias("record_id"), F.col("conv_id").alias("household"), F.col("turn").alias("seq"), "role",
        F.split_part("text", F.lit(" "), F.lit(1)).alias("name"), F.substring("text", 1, 20).alias("street"),
    )


def page_record(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "pages")
    return rows.select(
        F.col("page_id").alias("record_id"), F.regexp_extract("url", r"^https?://([^/]+)", 1).alias("host"), F.regexp_extract("url", r"^https?://[^/]+/([a-z]+)/", 1).alias("path_lang"),
        F.regexp_extract("html", r"<title>([^<]*)</title>", 1).alias("title"),
    )


def event_record(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read(spark, sf_dir, "events")
    return rows.select(F.col("event_id").alias("record_id"), F.col("ts").cast("timestamp").alias("ts"), F.col("user_id").alias("household"), F.col("event_type").alias("kind"), F.col("value").alias("amount"), F.get_json_object("props", "$.k").cast("int").alias("k"))
