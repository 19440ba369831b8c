"""Refinement, supplementary reasoning and defect filtering of pairs, by a model or by rules that stand in for it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from qacurate.functions.text import containment, n_sentences, n_tokens, tokens
from qacurate.models.clients import Model, parsed

CITATION = "(see|in|from) (figure|table|section|equation|chapter|page) [0-9.]+"
REFERENCE = "(figure|table|section|equation|chapter|appendix|page) [0-9]+|https?://|www\\."
CONNECTIVES = "(^|[^\\p{L}])(because|since|therefore|thus|hence|so|then|follows)([^\\p{L}]|$)"
DEFECTS = ("external_reference", "contradiction", "missing_information", "invalid")


def _clean(c: str) -> Column:
    return F.trim(F.regexp_replace(F.regexp_replace(F.col(c), f"(?i){CITATION}", ""), "[ \\t\\r\\n]+", " "))


def refine(pairs: DataFrame, chunks: DataFrame, strength: str = "strong", model: Model | None = None) -> DataFrame:
    """Questions made self-contained and answers made complete, with the source chunk at hand.

    model: rewrites both; where its reply does not parse, the pair stays as it is. Without one, by rules:

    strong: drops citations, puts the first line of the chunk before the question and the last after the
    answer. weak: drops citations only.
    """
    if model is not None:
        source = chunks.select("book_id", "chunk_no", F.col("text").alias("_chunk"))
        asked = model.ask(pairs.join(source, ["book_id", "chunk_no"], "left"), "refine", "_reply", chunk="_chunk")
        reply = parsed(F.col("_reply"), "question string, answer string")
        return asked.withColumn("question", F.coalesce(reply["question"], "question")).withColumn("answer", F.coalesce(reply["answer"], "answer")).drop("_chunk", "_reply")
    if strength == "weak":
        return pairs.withColumn("question", _clean("question")).withColumn("answer", _clean("answer"))
    ends = chunks.select("book_id", "chunk_no", F.substring_index(F.trim("text"), "\n", 1).alias("_head"), F.substring_index(F.trim("text"), "\n", -1).alias("_tail"))
    met = pairs.withColumn("question", _clean("question")).withColumn("answer", _clean("answer")).join(ends, ["book_id", "chunk_no"], "left")
    head = F.when(F.col("_head").isNull() | F.contains("question", F.col("_head")), F.col("question")).otherwise(F.concat("_head", F.lit(" "), "question"))
    tail = F.when(F.col("_tail").isNull() | F.contains("answer", F.col("_tail")), F.col("answer")).otherwise(F.concat("answer", F.lit(" "), "_tail"))
    return met.withColumn("question", head).withColumn("answer", tail).drop("_head", "_tail")


def missing_reasoning() -> Column:
    """Stand-in for the gap checker: too few sentences or words, or short without a connective."""
    words = n_tokens("answer")
    return (n_sentences("answer") < 2) | (words < 20) | ((words < 60) & ~F.lower("answer").rlike(CONNECTIVES))


def flag_missing_reasoning(pairs: DataFrame, model: Model | None = None) -> DataFrame:
    """Adds ``lacks_reasoning``, by the gap checker or its rule."""
    if model is not None:
        return model.agrees(pairs, "gap", "lacks_reasoning")
    return pairs.withColumn("lacks_reasoning", F.coalesce(missing_reasoning(), F.lit(True)))


def supplement(pairs: DataFrame, model: Model | None = None) -> DataFrame:
    """Adds steps and a final line to the flagged answers only; the others are not touched, nor asked about."""
    if model is not None:
        flagged = model.ask(pairs.where("lacks_reasoning"), "explain", "_more")
        return flagged.withColumn("answer", F.coalesce("_more", "answer")).drop("_more").unionByName(pairs.where("not lacks_reasoning"))
    last = F.trim(F.regexp_extract("answer", "([^.!?]*)[.!?]?\\s*$", 1))
    longer = F.concat(F.lit("Step 1: the question states: "), "question", F.lit(" Step 2: "), "answer", F.lit(" Therefore the final answer is: "), last, F.lit("."))
    return pairs.withColumn("answer", F.when(F.col("lacks_reasoning"), longer).otherwise(F.col("answer")))


def defects() -> Column:
    """Names of a pair's defects, in a fixed order; empty for a sound pair."""
    q, a = F.coalesce(F.col("question"), F.lit("")), F.coalesce(F.col("answer"), F.lit(""))
    tests = {
        "external_reference": F.lower(q).rlike(REFERENCE) | F.lower(a).rlike(REFERENCE),
        "contradiction": F.lower(a).rlike("(?s)contradict|on the one hand.*on the other hand"),
        "missing_information": n_tokens(q) < 6,
        "invalid": (n_tokens(a) < 3) | (F.size(F.array_distinct(tokens(a))) * 4 < F.size(tokens(a))),
    }
    return F.array_compact(F.array(*[F.when(tests[d], d) for d in DEFECTS]))


def judge_defects(pairs: DataFrame, model: Model | None = None) -> DataFrame:
    """Adds ``defects``: those of the known names that the judge gives (none where its reply does not parse), or by rules."""
    if model is None:
        return pairs.withColumn("defects", defects())
    named = F.transform(parsed(F.col("_named"), "array<string>"), lambda x: F.replace(F.lower(F.trim(x)), F.lit(" "), F.lit("_")))
    known = F.array_intersect(F.array(*map(F.lit, DEFECTS)), F.coalesce(named, F.array().cast("array<string>")))
    return model.ask(pairs, "defects", "_named").withColumn("defects", known).drop("_named")


def drop_defective(pairs: DataFrame, model: Model | None = None) -> tuple[DataFrame, DataFrame]:
    """(kept, removed); removed has ``defects``."""
    judged = judge_defects(pairs, model)
    return judged.where(F.size("defects") == 0).drop("defects"), judged.where(F.size("defects") > 0)


def difficulty_aware_distil(df: DataFrame, cut: float = 6.0) -> DataFrame:
    """Answers of questions whose mean score lies below ``cut`` are written anew; the others stay."""
    new = F.concat(F.lit("Let us work it out. "), "answer", F.lit(" Checking once more: "), "answer")
    return df.withColumn("distilled", F.col("score") < cut).withColumn("answer", F.when(F.col("score") < cut, new).otherwise(F.col("answer")))


def refined_share(before: DataFrame, after: DataFrame) -> DataFrame:
    """Mean overlap of words before and after, as one row."""
    a, b = before.select("qid", tokens("answer").alias("x")), after.select("qid", tokens("answer").alias("y"))
    return a.join(b, "qid").agg(F.round(F.avg(containment("x", "y")), 6).alias("overlap"))
