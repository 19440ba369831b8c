"""Annotation, blending and stage accounting."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from qacurate.functions.text import n_tokens
from qacurate.models.clients import Model


@dataclass(frozen=True)
class SourceSpec:
    """A source of the mixture. annotate: its answers are written anew. strategy: how its subset is chosen."""

    name: str
    include: bool = True
    annotate: bool = False
    strategy: str = "all"


#: The sources of the mixture and what is done with each.
SPECS = (SourceSpec("textbook"), SourceSpec("A", annotate=True, strategy="random"), SourceSpec("B", annotate=True, strategy="difficulty"), SourceSpec("C", include=False))


def annotate(df: DataFrame, specs: tuple[SourceSpec, ...] = SPECS, model: Model | None = None) -> DataFrame:
    """Answers of sources marked so become step-by-step solutions, by a model or a template; others stay."""
    names = [s.name for s in specs if s.annotate]
    if model is not None:
        mine = F.coalesce(F.col("dataset").isin(names), F.lit(False))
        asked = model.ask(df.where(mine), "annotate", "_made")
        return asked.withColumn("answer", F.coalesce("_made", "answer")).drop("_made").unionByName(df.where(~mine))
    made = F.concat(F.lit("Step 1: read the question. Step 2: "), "answer", F.lit(" Therefore the final answer is given above."))
    return df.withColumn("answer", F.when(F.col("dataset").isin(names), made).otherwise(F.col("answer")))


def drop_overlong(df: DataFrame, max_tokens: int = 4096, text: str = "answer", kind: str = "space") -> DataFrame:
    """Answers of more than ``max_tokens`` tokens go; exactly as many stay."""
    return df.where(F.coalesce(n_tokens(text, kind), F.lit(0)) <= max_tokens)


def build_mixture(parts: dict[str, DataFrame], specs: tuple[SourceSpec, ...] = SPECS) -> DataFrame:
    """The union of the included sources, tagged with ``dataset``."""
    chosen = [parts[s.name].withColumn("dataset", F.lit(s.name)) for s in specs if s.include and s.name in parts]
    return reduce(lambda x, y: x.unionByName(y, allowMissingColumns=True), chosen)


def stage_counts(stages: list[tuple[str, DataFrame]], by: str) -> DataFrame:
    """(stage_no, stage, <by>, n): rows after each stage by ``by`` and in total."""
    parts = [df.select(F.lit(k).alias("stage_no"), F.lit(name).alias("stage"), F.col(by)) for k, (name, df) in enumerate(stages)]
    every = reduce(DataFrame.unionAll, parts)
    counted = every.groupBy("stage_no", "stage", by).agg(F.count(F.lit(1)).alias("n"))
    total = counted.groupBy("stage_no", "stage").agg(F.sum("n").alias("n")).select("stage_no", "stage", F.lit("total").alias(by), "n")
    return counted.unionByName(total)


def pivot_stages(counts: DataFrame, by: str, stages: list[str]) -> DataFrame:
    return counts.groupBy(by).pivot("stage", stages).agg(F.first("n"))


def to_chat(df: DataFrame) -> DataFrame:
    """(qid, messages): chat records as JSON text."""
    turn = lambda role, c: F.struct(F.lit(role).alias("role"), F.col(c).alias("content"))
    return df.select("qid", F.to_json(F.array(turn("user", "question"), turn("assistant", "answer"))).alias("messages"))


def share_of(part: Column, whole: Column) -> Column:
    return F.round(F.try_divide(100.0 * part, whole), 4)
