"""Exact copies by distributed most-significant-digit radix partitioning.

All texts start in one group. A round splits every open group by the next bytes of its members (the
digit): members alone with their digit are unique, members whose text ends inside the digit are
equal, the rest go on with the bytes behind it. Digits grow from round to round, so the rounds are
logarithmic in the longest text, and what a round moves shrinks to the texts that still share all
their bytes so far. Equality rests on the bytes themselves, never on a digest.

Counting a digit is a partial aggregate, so a group of copies of any size sends one row per task;
the counts then meet the members in a join whose large partitions Spark splits.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from qacurate.staging import Staged

FIRST_DIGIT, GROWTH = 64, 8
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def normalised() -> F.Column:
    """The text with A-Z in lower case; null is empty."""
    return F.translate(F.coalesce(F.col("text"), F.lit("")), _UPPER, _LOWER)


def _round(state: DataFrame, size: int) -> DataFrame:
    open_ = state.withColumn("digit", F.substring("rest", 1, size))
    groups = Staged(
        open_.groupBy("grp", "digit")
        .agg(F.count(F.lit(1)).alias("members"), F.max("doc_id").alias("largest"))
        .where("members > 1"),
        "radix-groups",
    )
    named = Staged(groups.df.withColumn("next", F.monotonically_increasing_id()), "radix-names")
    groups.drop()
    ends = F.length("digit") < size
    goes_on = F.col("members").isNotNull() & ~ends
    # Merge at every size: a broadcast of small group tables would make the plan depend on the input's size.
    return open_.join(named.df.hint("merge"), ["grp", "digit"], "left").select(
        "doc_id",
        "sha",
        F.when(goes_on, F.col("next")).alias("grp"),
        F.when(goes_on, F.expr(f"substring(rest, {size} + 1)")).alias("rest"),
        F.when(F.col("members").isNull(), F.col("doc_id")).when(ends, F.col("largest")).alias("keep_id"),
        F.when(F.col("members").isNull(), F.lit(1)).when(ends, F.col("members")).cast("long").alias("group_size"),
    )


def exact_classes(docs: DataFrame) -> DataFrame:
    """(doc_id, keep_id, group_size, kept, text_sha256), one row per input row.

    Texts are equal when the same after lower-casing A-Z; of equal texts the row with the largest
    doc_id stays. Null texts are empty texts, and all empty texts are equal. Null ids count in
    group_size but stay only where no equal text has an id; rows that repeat the id that stays all
    stay. Only doc_id and text are read. No rows: no rows.
    """
    state = docs.select(
        "doc_id",
        F.sha2(normalised().cast("binary"), 256).alias("sha"),
        F.lit(0).cast("long").alias("grp"),
        normalised().cast("binary").alias("rest"),
    )
    size, found = FIRST_DIGIT, []
    while True:
        done = Staged(_round(state, size), "radix-round")
        found.append(done.df.where("grp is null").drop("grp", "rest"))
        state = done.df.where("grp is not null").select("doc_id", "sha", "grp", "rest")
        if state.isEmpty():
            break
        size *= GROWTH
    out = found[0]
    for part in found[1:]:
        out = out.unionByName(part)
    return out.select(
        "doc_id",
        "keep_id",
        "group_size",
        F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"),
        F.col("sha").alias("text_sha256"),
    )


def drop_copies(docs: DataFrame) -> DataFrame:
    """The input without the copies; ids are taken to be unique, rows without an id stay."""
    gone = exact_classes(docs).where("not kept and doc_id is not null").select("doc_id")
    return docs.join(gone, "doc_id", "left_anti").select(docs.columns)


ORACLE = f"""
with t as (
  select doc_id, translate(coalesce(text, ''), '{_UPPER}', '{_LOWER}') as t from documents
), g as (select t, max(doc_id) as keep_id, count(*) as n from t group by t)
select doc_id, keep_id, n::bigint as group_size, doc_id = keep_id as kept, sha256(t) as text_sha256
from t join g using (t)
"""
