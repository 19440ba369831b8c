"""Data selection at matched size: by response length, by difficulty, at random."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from qacurate.functions.text import let, md5_fraction, md5_int, n_tokens, token_f1, tokens
from qacurate.models.clients import Model

SMALL = 100_000  # rows up to which the top of an order is kept as it is read


def select_longest(df: DataFrame, n: int, length: str = "length", id_: str = "qid") -> DataFrame:
    """The n longest, ties to the smaller id: for small n a bounded heap per task, else by the histogram."""
    if n <= SMALL:
        return df.orderBy(F.col(length).desc(), id_).limit(n)
    return select_longest_hist(df, n, length, id_)


def select_longest_hist(df: DataFrame, n: int, length: str = "length", id_: str = "qid") -> DataFrame:
    """The same at any size: a histogram of lengths gives the length at the cut, rows above it stay without a
    sort, and only rows of that very length are ordered."""
    counts = df.groupBy(length).agg(F.count(F.lit(1)).alias("_n"))
    above = F.coalesce(F.sum("_n").over(Window.orderBy(F.col(length).desc()).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    cut = counts.select(length, "_n", above.alias("_above")).where((F.col("_above") < n) & (F.col("_above") + F.col("_n") >= n)).first()
    if cut is None:
        return df
    ties = df.where(F.col(length) == cut[length]).orderBy(id_).limit(n - cut["_above"])
    return df.where(F.col(length) > cut[length]).unionByName(ties)


def reference_answers(df: DataFrame) -> DataFrame:
    """Adds ``reference`` by dataset: the last sentence of the refined answer (textbook), the given answer
    (A), what follows the reasoning part of a long answer (B)."""
    last = F.trim(F.regexp_extract("answer", "([^.!?]*[.!?]?)\\s*$", 1))
    rule = F.when(F.col("dataset") == "textbook", last).when(F.col("dataset") == "B", F.trim(F.substring_index("answer", "\n", -1))).otherwise(F.col("answer"))
    return df.withColumn("reference", rule)


def hardness() -> Column:
    """Stand-in for how hard a question is for the sampler: by md5, a little beyond both ends of [0, 1]."""
    return F.lit(1.2) * md5_fraction("h", F.col("qid")) - F.lit(0.1)


def _said(w: Column, k: Column) -> Column:
    """Whether draw k of a question has a word of its reference."""
    return md5_fraction(F.col("qid"), k, w) >= F.col("_hard")


def sample_responses(df: DataFrame, m: int = 16, model: Model | None = None) -> DataFrame:
    """m responses per question: ``k`` and ``response``.

    Without a model a stand-in answers: each draw drops words of the reference by md5, the more the harder
    the question. Some questions are always answered in full, some never.
    """
    each = df.withColumn("k", F.explode(F.sequence(F.lit(1), F.lit(m))))
    if model is not None:
        return model.ask(each, "sample", "response", question="question", k="k")
    kept = F.filter(tokens("reference"), lambda w: _said(w, F.col("k")))
    return each.withColumn("_hard", hardness()).withColumn("response", F.array_join(kept, " ")).drop("_hard")


def mean_scores(df: DataFrame, m: int = 16) -> DataFrame:
    """Adds ``n``, ``total`` and ``mean``: the stand-in's m responses, scored, in one row and without a shuffle.

    The same as ``difficulty`` of ``score_responses`` of ``sample_responses``: a response holds words of the
    reference only, so its overlap is the number of distinct words it has.
    """

    def total(words: Column) -> Column:
        def score(k: Column) -> Column:
            said = F.size(F.filter(words, lambda w: _said(w, k))).cast("double")
            f1 = F.coalesce(F.try_divide(2.0 * said, said + F.size(words).cast("double")), F.lit(0.0))
            return F.floor(f1 * 10 + 0.5).cast("long")

        return F.aggregate(F.transform(F.sequence(F.lit(1), F.lit(m)), score), F.lit(0).cast("long"), lambda s, x: s + x)

    scored = df.withColumn("_hard", hardness()).withColumn("total", let(F.array_distinct(tokens("reference")), total)).drop("_hard")
    return scored.withColumn("n", F.lit(m).cast("long")).withColumn("mean", F.col("total") / F.col("n"))


def score_responses(df: DataFrame, model: Model | None = None) -> DataFrame:
    """Adds ``score``: 0 to 10, by a model (null where its answer holds no number), or ten times the token
    F1 of response and reference, half up."""
    if model is not None:
        found = F.regexp_extract("_score", "([0-9]+)", 1)
        return model.ask(df, "score", "_score", reference="reference", response="response").withColumn("score", F.when(found != "", F.least(found.cast("int"), F.lit(10)))).drop("_score")
    return df.withColumn("score", F.floor(token_f1(tokens("response"), tokens("reference")) * 10 + 0.5).cast("int"))


def difficulty(scores: DataFrame) -> DataFrame:
    """(qid, n, total, mean): the mean score; low is hard. Sums of whole scores compare exactly."""
    return scores.groupBy("qid").agg(F.count(F.lit(1)).alias("n"), F.sum("score").alias("total")).withColumn("mean", F.col("total") / F.col("n"))


def select_by_difficulty(means: DataFrame, low: float = 1, high: float = 9) -> DataFrame:
    """Means from low to high, bounds included: easier is too easy, harder is taken for noise."""
    return means.where((F.col("total") >= low * F.col("n")) & (F.col("total") <= high * F.col("n")))


def hard_subset(means: DataFrame, cut: float = 6) -> DataFrame:
    return means.where(F.col("total") < cut * F.col("n"))


def random_key(id_: str, seed: str = "s") -> Column:
    return md5_int(F.concat_ws(":", F.lit(seed), F.col(id_).cast("string")), 12)


def select_random(df: DataFrame, n: int, id_: str = "qid", seed: str = "s") -> DataFrame:
    """Exactly n rows, those with the smallest md5 keys; the same rows whatever the partitions."""
    keyed = df.withColumn("_key", random_key(id_, seed))
    if n > SMALL:
        # Counts by the key's first 16 bits say in which slice the n-th row lies; only that slice is ranked.
        part = F.shiftrightunsigned("_key", 32).cast("int")
        counts = keyed.groupBy(part.alias("b")).agg(F.count(F.lit(1)).alias("n"))
        edge = counts.withColumn("upto", F.sum("n").over(Window.orderBy("b"))).where(F.col("upto") >= n).orderBy("b").first()
        if edge is None:
            return keyed.drop("_key")
        ties = keyed.where(part == edge["b"]).orderBy("_key", id_).limit(n - (edge["upto"] - edge["n"]))
        return keyed.where(part < edge["b"]).unionByName(ties).drop("_key")
    return keyed.orderBy("_key", id_).limit(n).drop("_key")


def select_stratified(df: DataFrame, by: str, share: float, id_: str = "qid", seed: str = "s") -> DataFrame:
    """ceil(share) of each stratum, by md5 key."""
    keyed = df.withColumn("_key", random_key(id_, seed))
    counts = df.groupBy(by).agg(F.count(F.lit(1)).alias("_n"))
    # Rank within slices of the key, then add the slices before: no stratum meets in one task.
    keyed = keyed.withColumn("_slice", F.substring(F.lpad(F.hex("_key"), 12, "0"), 1, 2))
    before = F.coalesce(F.sum("_m").over(Window.partitionBy(by).orderBy("_slice").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    slices = keyed.groupBy(by, "_slice").agg(F.count(F.lit(1)).alias("_m")).select(by, "_slice", before.alias("_ahead"))
    place = F.row_number().over(Window.partitionBy(by, "_slice").orderBy("_key", id_))
    ranked = keyed.withColumn("_place", place).join(slices, [by, "_slice"]).join(counts, by)
    return ranked.where(F.col("_ahead") + F.col("_place") <= F.ceil(F.col("_n") * share)).select(df.columns)


def lengths(df: DataFrame, text: str = "answer") -> DataFrame:
    return df.withColumn("length", n_tokens(text))
