"""Proxy for training and evaluating a model on a subset: a linear classifier of labelled quality.

It stands in for a fine-tuned model, so its accuracies compare subsets and mean nothing beyond.
"""

from __future__ import annotations

from pyspark.ml import Pipeline
from pyspark.ml.classification import LogisticRegression
from pyspark.ml.feature import HashingTF
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from qacurate.functions.text import md5_int, tokens
from qacurate.operators.select import select_by_difficulty, select_longest, select_random
from qacurate.staging import stage


def accuracy(train: DataFrame, test: DataFrame, buckets: int = 1 << 12) -> float:
    """Share of test rows (words, quality) that a model fitted on train gets right; 0 without two classes."""
    if train.select("quality").distinct().limit(2).count() < 2:
        return 0.0
    model = Pipeline(stages=[HashingTF(inputCol="words", outputCol="features", numFeatures=buckets), LogisticRegression(labelCol="quality", maxIter=15, regParam=0.01)]).fit(train)
    return model.transform(test).agg(F.avg((F.col("prediction") == F.col("quality")).cast("double"))).first()[0] or 0.0


def subsets(rows: DataFrame, id_: str = "doc_id") -> dict[str, DataFrame]:
    """The subset of each strategy at the size that difficulty gives; rows carry length, total and n."""
    dif = select_by_difficulty(rows)
    n = dif.count()
    return {"all": rows, "difficulty": dif, "length": select_longest(rows, n, id_=id_), "random": select_random(rows, n, id_)}


def compare_strategies(df: DataFrame, proxies: tuple[int, ...] = (1 << 10, 1 << 14)) -> DataFrame:
    """(proxy, strategy, n, accuracy, chosen, tied, agreed): every strategy's subset, by every proxy.

    df: (doc_id, text, quality, length, total, n), with the summed scores of a row's draws. chosen: no other
    strategy does better, keeping all rows included; tied: another does as well; agreed: all proxies choose alike.
    """
    rows = stage(df.select("doc_id", tokens("text").alias("words"), F.col("quality").cast("int").alias("quality"), "length", "total", "n"), "proxy-rows")
    held = md5_int(F.concat(F.lit("t:"), F.col("doc_id").cast("string"))) % 5 == 0
    train, test = rows.where(~held), rows.where(held)
    found = [(p, s, x.count(), round(accuracy(x, test, p), 6)) for s, x in subsets(train).items() for p in proxies]
    best = {p: max(a for q, _, _, a in found if q == p) for p in proxies}
    chosen = {p: frozenset(s for q, s, _, a in found if q == p and a == best[p]) for p in proxies}
    agreed = len(set(chosen.values())) == 1
    out = [(p, s, n, a, s in chosen[p], s in chosen[p] and len(chosen[p]) > 1, agreed) for p, s, n, a in found]
    return df.sparkSession.createDataFrame(out, "proxy int, strategy string, n long, accuracy double, chosen boolean, tied boolean, agreed boolean")
