"""Question-answer pairs from chunks, by a strict and a loose standard, and their statistics.

A model lists the pairs of a chunk. Rules stand in for it: a line of some words is a question, the lines behind it
its answer. The strict standard asks for a long question and a full worked answer.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from qacurate.functions.text import n_sentences, n_tokens
from qacurate.models.clients import Model, parsed


@dataclass(frozen=True)
class Standard:
    name: str
    question_words: int
    answer_words: int
    answer_sentences: int
    answer_lines: int


LOW = Standard("low", 6, 6, 0, 1)
HIGH = Standard("high", 40, 250, 20, 5)
STANDARDS = {s.name: s for s in (LOW, HIGH)}


def extract_pairs(chunks: DataFrame, standard: str = "high", model: Model | None = None) -> DataFrame:
    """(qid, book_id, chunk_no, line, standard, question, answer)

    model: lists the pairs of a chunk as JSON; ``line`` is then a pair's place in the list, and a reply that
    does not parse gives none.
    """
    rule = STANDARDS[standard]
    if model is not None:
        asked = model.ask(chunks.select("book_id", "chunk_no", "text"), f"extract_{standard}", "_reply")
        listed = asked.select("book_id", "chunk_no", F.posexplode(parsed(F.col("_reply"), "array<struct<question: string, answer: string>>")).alias("line", "p"))
        return listed.where("p.question is not null and p.answer is not null").select(_qid(rule), "book_id", "chunk_no", "line", F.lit(rule.name).alias("standard"), "p.question", "p.answer")
    lines = chunks.select("book_id", "chunk_no", F.split("text", "\n").alias("lines"))
    each = lines.select("book_id", "chunk_no", "lines", F.posexplode("lines").alias("line", "question"))
    following = F.get("lines", F.col("line") + 1)
    candidate = each.where((n_tokens("question", "space") >= 6) & (n_tokens(following, "space") >= 6))
    made = candidate.select("book_id", "chunk_no", "line", "question", F.array_join(F.slice("lines", F.col("line") + 2, rule.answer_lines), "\n").alias("answer"))
    good = (n_tokens("question", "space") >= rule.question_words) & (n_tokens("answer", "space") >= rule.answer_words) & (n_sentences("answer") >= rule.answer_sentences)
    return made.where(good).select(_qid(rule), "book_id", "chunk_no", "line", F.lit(rule.name).alias("standard"), "question", "answer")


def _qid(rule: Standard) -> Column:
    return F.concat_ws(":", "book_id", "chunk_no", "line", F.lit(rule.name)).alias("qid")


def extract_dual(chunks: DataFrame, model: Model | None = None) -> DataFrame:
    """Both standards; pairs found by both stay twice, as deduplication comes later."""
    return extract_pairs(chunks, "high", model).unionByName(extract_pairs(chunks, "low", model))


def synthesise_questions(chunks: DataFrame, model: Model | None = None) -> DataFrame:
    """The contrast: a question made up about a chunk instead of taken from it."""
    if model is not None:
        asked = model.ask(chunks.select("book_id", "chunk_no", "text"), "synthesise", "question")
        return asked.select(F.concat_ws(":", "book_id", "chunk_no", F.lit("synth")).alias("qid"), "book_id", "chunk_no", "question", F.col("text").alias("answer"))
    head = F.array_join(F.slice(F.split(F.trim("text"), "[ \\n]+"), 1, 8), " ")
    return chunks.select(F.concat_ws(":", "book_id", "chunk_no", F.lit("synth")).alias("qid"), "book_id", "chunk_no", F.concat(F.lit("What follows from: "), head, F.lit("?")).alias("question"), F.col("text").alias("answer"))


def extraction_stats(books: DataFrame, chunks: DataFrame, pairs: DataFrame) -> DataFrame:
    """Per subject and in total: books, chunks, chunks with a pair, pairs by standard.

    A book of two subjects counts under both and once in the total. Counts come down to books first,
    so the roll-up moves a row per book and subject instead of expanding chunks and pairs.
    """
    c = chunks.groupBy("book_id").agg(F.count(F.lit(1)).alias("chunks"))
    by_chunk = pairs.groupBy("book_id", "chunk_no").agg(F.count_if(F.col("standard") == "high").alias("high"), F.count_if(F.col("standard") == "low").alias("low"))
    p = by_chunk.groupBy("book_id").agg(F.count(F.lit(1)).alias("valid"), F.sum("high").alias("high"), F.sum("low").alias("low"))
    per_book = books.select("book_id", "subjects").join(c, "book_id", "left").join(p, "book_id", "left").fillna(0, ["chunks", "valid", "high", "low"])
    shown = F.explode(F.concat("subjects", F.array(F.lit("total"))))
    sums = [F.sum(x).alias(y) for x, y in (("chunks", "n_chunks"), ("valid", "n_valid_chunks"), ("high", "n_pairs_high"), ("low", "n_pairs_low"))]
    return per_book.withColumn("subject", shown).groupBy("subject").agg(F.count(F.lit(1)).alias("n_books"), *sums)


def valid_chunk_rate(stats: DataFrame) -> DataFrame:
    pairs = F.col("n_pairs_high") + F.col("n_pairs_low")
    return stats.select("subject", F.round(F.try_divide(100.0 * F.col("n_valid_chunks"), F.col("n_chunks")), 4).alias("valid_rate"), F.round(F.try_divide(pairs.cast("double"), F.col("n_valid_chunks")), 4).alias("pairs_per_valid"))
