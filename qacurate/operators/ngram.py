"""Leak removal by shared word n-grams: the baseline."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from qacurate.functions.text import ngrams, tokens


def ngram_hits(questions: DataFrame, items: DataFrame, n: int = 13) -> DataFrame:
    """(id, n_grams, n_hit) for each question; texts below n words are one run of all their words.

    Questions are (id, text), items (item_id, text). The items' runs join as they are; Spark
    broadcasts them below its size limit and shuffles both sides above it.
    """
    grams = questions.select("id", F.explode(ngrams(tokens("text"), n)).alias("gram"))
    known = items.select(F.explode(ngrams(tokens("text"), n)).alias("gram")).distinct().withColumn("hit", F.lit(1))
    return grams.join(known, "gram", "left").groupBy("id").agg(F.count(F.lit(1)).alias("n_grams"), F.count("hit").alias("n_hit"))


def ngram_decontaminate(questions: DataFrame, items: DataFrame, n: int = 13, min_share: float = 0.0) -> DataFrame:
    """(id) of the questions to remove: any hit, or a share of hits of ``min_share`` or more."""
    return ngram_hits(questions, items, n).where((F.col("n_hit") > 0) & (F.col("n_hit") >= min_share * F.col("n_grams"))).select("id")
