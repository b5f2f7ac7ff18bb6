"""A table without any language label."""

from pyspark.sql import functions as F

import corpus_pipeline


def test_without_labels_only_texts_without_a_letter_go(spark, docs):
    bare = docs.withColumn("lang", F.lit(None).cast("string"))
    texts = sorted(r["text"][:12] for r in corpus_pipeline.language(spark, bare, "").collect())
    assert texts == sorted(r["text"][:12] for r in docs.where(F.col("text").rlike(r"\p{L}")).collect())
