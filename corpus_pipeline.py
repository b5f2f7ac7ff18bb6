"""The corpus pipeline: language ID, near-dedup, decontamination, packing.

Each stage gets all that the one before it kept, as files.  All but the last return the
columns of documents, further ones and any names included; the last gives the packed pieces.

Nulls, repeats, ties and empty tables, stage by stage:

* language ID drops null texts and texts without a letter; repeated rows are judged alike.  A
  document whose best language has a probability under 0.3 goes too (`langid.keep_known`).
* near-dedup keeps the smallest doc_id of a group (null is the largest); of rows that agree in
  doc_id and text one stays.
* decontamination takes benchmark items with a null item_id for items like any other; those
  without words are none.  Repeated documents are judged alike.
* packing gives every row that is left its pieces, each for itself.

An empty table of documents, or one of which nothing is left, gives no rows; an empty benchmark
leaves all documents.  Without labelled texts every document with a letter passes language ID.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from reclink.llm import binpack, decontam, langid, oddsketch
from reclink.llm._common import materialise


#: Similarity, in hundredths, from which near copies are linked.
SIMILAR_PERCENT = 80


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents without a recognisable language; the classifier learns from a bounded
    sample of those that carry a label."""
    return langid.keep_known(docs, langid.train(docs))


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each group of near copies: texts are linked that share 0.8 or
    more of their five-word shingles."""
    return oddsketch.drop_near_copies(docs, SIMILAR_PERCENT)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents of which benchmark passages make up a twentieth or more."""
    return decontam.clean_documents(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs what is left into sequences; with small steps, as the executors still hold what
    the stages before have needed."""
    return binpack.pack_documents(docs, step_bytes=1 << 20, cache_chunks=150_000)


STAGES = [("language ID", language), ("MinHash near-dedup", near_copies), ("benchmark decontamination", decontamination), ("best-fit packing", packing)]

#: SQL has neither the network nor the tokenizer; tests hold run() against plain versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = materialise(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
