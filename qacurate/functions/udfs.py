"""Functions for SQL users, registered by name: scalar, table and aggregate functions, SQL functions."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def balanced(text: str | None, mark: str = "\\boxed{") -> str | None:
    """The inside of the last mark with balanced braces, at any depth."""
    at = -1 if text is None else text.rfind(mark)
    if at < 0:
        return None
    depth, start = 1, at + len(mark)
    for i in range(start, len(text)):
        depth += (text[i] == "{") - (text[i] == "}")
        if depth == 0:
            return text[start:i]
    return None


@F.pandas_udf(T.StringType())
def unwrap_balanced(texts: pd.Series) -> pd.Series:
    return texts.map(balanced)


@F.pandas_udf(T.DoubleType())
def weighted_mean(values: pd.Series, weights: pd.Series) -> float:
    return float((values * weights).sum() / weights.sum()) if weights.sum() else float("nan")


@F.udtf(returnType="chunk_no int, n_tokens int, chunk string")
class ChunkText:
    """Slices of a text of ``size`` words."""

    def eval(self, text: str, size: int) -> Iterator[tuple]:
        words = (text or "").split()
        for k in range(0, len(words), size):
            part = words[k : k + size]
            yield k // size, len(part), " ".join(part)


@F.udtf(returnType="gram string")
class NGrams:
    """Word n-grams of a text, repeats included."""

    def eval(self, text: str, n: int) -> Iterator[tuple]:
        words = (text or "").split()
        for k in range(len(words) - n + 1):
            yield (" ".join(words[k : k + n]),)


JACCARD = "create or replace temporary function set_jaccard(a array<string>, b array<string>) returns double return try_divide(cast(size(array_intersect(a, b)) as double), cast(size(array_union(a, b)) as double))"


def register_all(spark: SparkSession) -> None:
    spark.udf.register("unwrap_balanced", unwrap_balanced)
    spark.udf.register("weighted_mean", weighted_mean)
    spark.udtf.register("chunk_text", ChunkText)
    spark.udtf.register("word_ngrams", NGrams)
    spark.sql(JACCARD)
