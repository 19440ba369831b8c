"""Measures over score tables, stages and responses.

Scores are whole hundredths of a per cent (cents), and averages round half up in whole numbers, so no
engine's floating point decides a printed digit.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from qacurate.functions.text import n_tokens, repetition, tokens


def half_up(total: Column, n: Column) -> Column:
    """total / n to the nearest whole number, halves up; for totals of zero or more."""
    return F.floor((2 * total + n) / (2 * n)).cast("long")


def benchmark_accuracy(graded: DataFrame) -> DataFrame:
    """(model, benchmark, n, n_correct, cents) from instance-level rows."""
    out = graded.groupBy("model", "benchmark").agg(F.count(F.lit(1)).alias("n"), F.count_if("correct").alias("n_correct"))
    return out.withColumn("cents", half_up(F.col("n_correct") * 10000, F.col("n")))


def category_averages(scores: DataFrame) -> DataFrame:
    """(system, category, n, cents): unweighted means of benchmarks by category and overall.

    Overall is the mean of all benchmarks, not of the categories.
    """
    g = scores.groupingSets([["system", "category"], ["system"]], "system", "category").agg(F.count(F.lit(1)).alias("n"), F.sum("cents").alias("total"))
    return g.select("system", F.coalesce("category", F.lit("Overall")).alias("category"), "n", half_up(F.col("total"), F.col("n")).alias("cents"))


def best_second(scores: DataFrame) -> DataFrame:
    """Rows with the rank 1 or 2 of their benchmark."""
    rank = F.dense_rank().over(Window.partitionBy("benchmark").orderBy(F.col("cents").desc()))
    return scores.withColumn("rank", rank).where("rank <= 2").select("benchmark", "system", "cents", "rank")


def win_counts(scores: DataFrame) -> DataFrame:
    return best_second(scores).groupBy("system").agg(F.count_if(F.col("rank") == 1).alias("wins"), F.count_if(F.col("rank") == 2).alias("seconds"))


def gain_vs_baseline(scores: DataFrame, baseline: str) -> DataFrame:
    """(system, category, gain): difference of averages to the baseline's, in cents."""
    avg = category_averages(scores)
    base = avg.where(F.col("system") == baseline).select("category", F.col("cents").alias("base"))
    return avg.where(F.col("system") != baseline).join(base, "category").select("system", "category", (F.col("cents") - F.col("base")).alias("gain"))


def scaling_gap(families: DataFrame) -> DataFrame:
    """Gap of the trained over the instruct model by size, and its change to the next smaller size."""
    gap = families.withColumn("gap", F.col("trained") - F.col("instruct"))
    return gap.select("family", "size", "gap", (F.col("gap") - F.lag("gap").over(Window.partitionBy("family").orderBy("size"))).alias("change"))


def ablation_delta(studies: DataFrame, full: str = "full") -> DataFrame:
    base = studies.where(F.col("variant") == full).select("study", F.col("cents").alias("base"))
    return studies.where(F.col("variant") != full).join(base, "study").select("study", "variant", (F.col("cents") - F.col("base")).alias("delta"))


def stage_retention(counts: DataFrame, by: str) -> DataFrame:
    """(by, stage, n, kept): share of the stage before, in ten-thousandths, half up."""
    before = F.lag("n").over(Window.partitionBy(by).orderBy("stage_no"))
    return counts.withColumn("before", before).where("before > 0").select(by, "stage", "n", half_up(F.col("n") * 10000, F.col("before")).alias("kept"))


def response_length(df: DataFrame, by: str, text: str = "answer") -> DataFrame:
    n = n_tokens(text)
    return df.select(by, n.alias("t")).groupBy(by).agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("t"), 6).alias("mean"), F.round(F.var_samp("t"), 4).alias("variance"))


def length_histogram(df: DataFrame, by: str, text: str = "answer", width: int = 50) -> DataFrame:
    """(by, bin, n, share): the density of response lengths."""
    counts = df.select(by, F.floor(n_tokens(text) / width).cast("int").alias("bin")).groupBy(by, "bin").agg(F.count(F.lit(1)).alias("n"))
    return counts.select(by, "bin", "n", F.round(F.col("n") / F.sum("n").over(Window.partitionBy(by)), 6).alias("share"))


def length_quantiles(df: DataFrame, by: str, text: str = "answer") -> DataFrame:
    t = df.select(by, n_tokens(text).alias("t")).groupBy(by)
    return t.agg(*[F.round(F.percentile("t", p), 6).alias(f"p{int(p * 100)}") for p in (0.25, 0.5, 0.75, 0.95)])


def length_score_corr(points: DataFrame) -> DataFrame:
    """Pearson correlation of mean length and score over points (name, length, score)."""
    return points.agg(F.count(F.lit(1)).alias("n"), F.round(F.corr("length", "score"), 6).alias("corr"))


def pareto_front(points: DataFrame) -> DataFrame:
    """Points that no other beats: none is at most as long and scores as much, and better in one."""
    p, o = points.alias("p"), points.select(F.col("name").alias("o"), F.col("length").alias("ol"), F.col("score").alias("os")).alias("q")
    beaten = (F.col("ol") <= F.col("length")) & (F.col("os") >= F.col("score")) & ((F.col("ol") < F.col("length")) | (F.col("os") > F.col("score")))
    return p.join(o, beaten, "left_anti").select("name", "length", "score")


def repetition_rate(df: DataFrame, by: str, text: str, n: int = 3, short: int = 20) -> DataFrame:
    """Mean share of repeated n-grams and share of short responses."""
    r = df.select(by, repetition(tokens(text), n).alias("r"), (n_tokens(text) < short).cast("int").alias("s"))
    return r.groupBy(by).agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("r"), 6).alias("repetition"), F.round(F.avg("s"), 6).alias("short_share"))


def average_ranks(df: DataFrame, column: str, out: str) -> DataFrame:
    """Adds the mean rank of ``column``, ties sharing theirs.

    The rank of a value is worked out over the counts of distinct values, so the rows themselves are
    never sorted in one place.
    """
    counts = df.groupBy(column).agg(F.count(F.lit(1)).alias("_n"))
    upto = F.sum("_n").over(Window.orderBy(column))
    return df.join(counts.select(column, (upto - (F.col("_n") - 1) / 2).alias(out)), column)


def length_difficulty_rank(df: DataFrame) -> DataFrame:
    """Pearson and Spearman correlation of (length, mean)."""
    ranked = average_ranks(average_ranks(df.select("length", "mean"), "length", "rl"), "mean", "rm")
    return ranked.agg(F.count(F.lit(1)).alias("n"), F.round(F.corr("length", "mean"), 6).alias("pearson"), F.round(F.corr("rl", "rm"), 6).alias("spearman"))


def call_budget(counts: dict[str, Column], rows: DataFrame) -> DataFrame:
    """(stage, calls): model calls per stage from one row of counts."""
    return rows.select(F.inline(F.array(*[F.struct(F.lit(k).alias("stage"), v.cast("long").alias("calls")) for k, v in counts.items()])))
