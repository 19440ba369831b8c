"""Line deduplication by pairwise alignment.

A block can only be cut where two documents share a run of adjacent lines with enough words. The
shortest such runs from each line on, and up to each line, cover every line of any such block, so their
hashes find all pairs that matter. A run of few documents (rare) pairs them all; a run of more documents
pairs each with the first that has it. Where that alignment leaves lines of the run, the document meets
all earlier holders of the run as well. The result is that of aligning all pairs that share a line.
Whole copies are settled by the first copy. Each pair is aligned by patience diff over line hashes, and
the blocks that align are cut from the later document.
"""

from __future__ import annotations

import bisect
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from qacurate.llm.text import free_names
from qacurate.staging import Staged, bound_batches

_LAST = (1 << 63) - 1
RARE = 8


def _unique_matches(a: list[int], b: list[int]) -> list[tuple[int, int]]:
    """Lines found once in both, as the longest run of pairs that rises in both (patience sorting)."""
    once = Counter(a), Counter(b)
    at = {x: j for j, x in enumerate(b) if once[1][x] == 1}
    pairs = [(i, at[x]) for i, x in enumerate(a) if once[0][x] == 1 and x in at]
    tops, piles, back = [], [], []
    for k, (_, j) in enumerate(pairs):
        p = bisect.bisect_left(tops, j)
        if p == len(tops):
            tops.append(j)
            piles.append(k)
        else:
            tops[p], piles[p] = j, k
        back.append(piles[p - 1] if p else -1)
    out, k = [], piles[-1] if piles else -1
    while k >= 0:
        out.append(pairs[k])
        k = back[k]
    return out[::-1]


def align(a: list[int], b: list[int]) -> list[tuple[int, int]]:
    """Rising pairs of equal lines of a and b: equal ends first, then unique lines, then what lies between them."""
    out, todo = [], [(0, len(a), 0, len(b))]
    while todo:
        a0, a1, b0, b1 = todo.pop()
        while a0 < a1 and b0 < b1 and a[a0] == b[b0]:
            out.append((a0, b0))
            a0, b0 = a0 + 1, b0 + 1
        while a0 < a1 and b0 < b1 and a[a1 - 1] == b[b1 - 1]:
            a1, b1 = a1 - 1, b1 - 1
            out.append((a1, b1))
        if a0 == a1 or b0 == b1:
            continue
        marks = [(a0 + i, b0 + j) for i, j in _unique_matches(a[a0:a1], b[b0:b1])]
        if not marks:
            continue
        out += marks
        edges = [(a0 - 1, b0 - 1), *marks, (a1, b1)]
        todo += [(i + 1, k, j + 1, m) for (i, j), (k, m) in zip(edges, edges[1:], strict=False)]
    return sorted(out)


def cut_lines(a: list[int], b: list[int], words: list[int], least_words: int) -> list[int]:
    """Lines of b in aligned blocks (runs without a gap in a or b) of ``least_words`` words or more."""
    out, block = [], []
    for i, j in [*align(a, b), (-9, -9)]:
        if block and (i, j) != (block[-1][0] + 1, block[-1][1] + 1):
            if sum(words[m] for _, m in block) >= least_words:
                out += [m for _, m in block]
            block = []
        block.append((i, j))
    return out


def line_tables(docs: DataFrame) -> DataFrame:
    """(id, same, lines, words): hash and word count of every line that has a word, in order."""
    text = F.coalesce(F.col("text"), F.lit(""))
    blanks = "[\\\\x20\\\\x09-\\\\x0D]"
    kept = F.filter(F.transform(F.split(text, "\n", -1), lambda x: F.trim(x, F.lit(" \t\x0b\x0c\r"))), lambda x: x != "")
    rows = docs.select(F.coalesce("doc_id", F.lit(_LAST)).alias("id"), F.unhex(F.md5(text.cast("binary"))).alias("same"), kept.alias("kept"))
    return rows.select("id", "same", F.transform("kept", lambda x: F.xxhash64(x)).alias("lines"), F.expr(f"transform(kept, x -> size(split(x, '{blanks}+')))").alias("words"))


def candidate_pairs(tables: DataFrame, rare: int = RARE) -> DataFrame:
    """(a, b), a < b: documents that share a line. At most ``rare`` rows of a line are ever paired among each other."""
    rows = tables.select("id", F.explode(F.array_distinct("lines")).alias("h")).distinct()
    known = Staged(rows.groupBy("h").agg(F.count(F.lit(1)).alias("n"), F.min("id").alias("first")).where("n > 1"), "shared-lines").df
    met = rows.join(known, "h")
    common = met.where((F.col("n") > rare) & (F.col("id") != F.col("first"))).select(F.col("first").alias("a"), F.col("id").alias("b"))
    few = met.where(F.col("n") <= rare).groupBy("h").agg(F.sort_array(F.collect_list("id")).alias("ids"))
    each = few.select(F.explode(F.expr("flatten(transform(ids, (x, i) -> transform(slice(ids, i + 2, size(ids)), y -> struct(x as a, y as b))))")).alias("p"))
    return common.union(each.select("p.a", "p.b")).distinct()


def least_runs(lines: list[int], words: list[int], least_words: int) -> set[tuple[int, int]]:
    """(first, last line) of the shortest runs of ``least_words`` words from each line on and up to each line."""
    ends, out = np.cumsum([0, *words]), set()
    for i in range(len(lines)):
        k = int(np.searchsorted(ends, ends[i] + least_words))
        if k <= len(lines):
            out.add((i, max(k - 1, i)))
        k = int(np.searchsorted(ends, ends[i + 1] - least_words, side="right")) - 1
        if k >= 0:
            out.add((min(k, i), i))
    return out


def line_runs(tables: DataFrame, least_words: int) -> DataFrame:
    """(h, id, at, to): hash and place of the ``least_runs`` of every row of (id, lines, words)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for i, lines, words in zip(*(batch.column(c).to_pylist() for c in ("id", "lines", "words")), strict=True):
                raw = np.array(lines, np.int64).tobytes()
                for a, b in least_runs(lines, words, least_words):
                    h = xxhash.xxh3_64_intdigest(raw[8 * a : 8 * b + 8])
                    out.append((h - (1 << 64) if h >> 63 else h, i, a, b))
            columns = zip(*out, strict=True) if out else ([], [], [], [])
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (pa.int64(), pa.int64(), pa.int32(), pa.int32()), strict=True)], names=["h", "id", "at", "to"])

    return tables.select("id", "lines", "words").mapInArrow(run, "h long, id long, at int, to int")


def _shared_runs(own: DataFrame, least_words: int) -> DataFrame:
    """(h, id, at, to, n, first) of the runs that several documents hold."""
    runs = Staged(line_runs(own, least_words), "line-runs").df
    known = Staged(runs.select("h", "id").distinct().groupBy("h").agg(F.count(F.lit(1)).alias("n"), F.min("id").alias("first")).where("n > 1"), "shared-runs").df
    return Staged(runs.join(known, "h"), "met-runs").df


def _run_pairs(met: DataFrame, rare: int) -> DataFrame:
    common = met.where((F.col("n") > rare) & (F.col("id") != F.col("first"))).select(F.col("first").alias("a"), F.col("id").alias("b"))
    few = met.where(F.col("n") <= rare).groupBy("h").agg(F.sort_array(F.collect_set("id")).alias("ids"))
    each = few.select(F.explode(F.expr("flatten(transform(ids, (x, i) -> transform(slice(ids, i + 2, size(ids)), y -> struct(x as a, y as b))))")).alias("p"))
    return common.union(each.select("p.a", "p.b")).distinct()


def _left_pairs(met: DataFrame, cut: DataFrame, rare: int) -> DataFrame:
    """Pairs of documents that keep lines of a common run with the run's other earlier holders."""
    common = met.where(F.col("n") > rare)
    later = common.where("id <> first").join(cut, "id", "left")
    whole = F.size(F.array_intersect(F.sequence("at", "to"), F.coalesce("cut", F.array().cast("array<int>")))) > F.col("to") - F.col("at")
    left = Staged(later.where(~whole).select("h", F.col("id").alias("b")).distinct(), "left-runs").df
    held = common.where("id <> first").select("h", F.col("id").alias("a")).distinct()
    return left.join(held, "h").where("a < b").select("a", "b").distinct()


def align_lines(docs: DataFrame, least_words: int = 20, rare: int | None = None) -> DataFrame:
    """(doc_id, n_lines, n_removed, words_removed, removed): positions, among the lines with a word, that are cut.

    One row per input row. Of copies of a whole text the smallest doc_id keeps its lines and the others
    lose all, if the text has ``least_words`` words. Lines are equal after trimming ASCII blanks; pairs
    are judged on the input. With ``rare`` given, only the pairs of ``candidate_pairs`` are aligned;
    without it the result is that of all pairs. Null texts have no lines. A null doc_id counts as larger than any; rows
    that repeat a doc_id are one document: what is cut by its id is cut in each. Only doc_id and text
    are read.
    """
    bound_batches(docs.sparkSession)
    tables = Staged(line_tables(docs), "lines").df
    # Written before the join, whose large partitions (a group of copies) Spark then splits.
    first = Staged(tables.groupBy("same").agg(F.min("id").alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1").select("same", "first"), "first-copies").df
    met = tables.join(first, "same", "left")
    copy = F.coalesce(F.col("id") != F.col("first"), F.lit(False)) & (F.aggregate("words", F.lit(0), lambda x, y: x + y) >= least_words)
    marked = Staged(met.select("id", "lines", "words", copy.alias("copy")), "marked-lines").df
    own = marked.where("not copy").select("id", "lines", "words")
    one = own.dropDuplicates(["id"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, at = [], []
            for b, la, lb, words in zip(*(batch.column(c).to_pylist() for c in ("b", "la", "lb", "words")), strict=True):
                got = cut_lines(la, lb, words, least_words)
                ids += [b] * len(got)
                at += got
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(np.array(at, np.int32))], names=["id", "at"])

    def cut_by(pairs: DataFrame) -> DataFrame:
        both = pairs.join(one.select(F.col("id").alias("a"), F.col("lines").alias("la")), "a").join(one.select(F.col("id").alias("b"), F.col("lines").alias("lb"), "words"), "b")
        return both.select("b", "la", "lb", "words").mapInArrow(run, "id long, at int")

    def gathered(cuts: DataFrame) -> DataFrame:
        return cuts.groupBy("id").agg(F.sort_array(F.collect_set("at")).alias("cut"))

    if rare is not None:
        cut = gathered(cut_by(candidate_pairs(own, rare)))
    else:
        one = Staged(one, "own-lines").df
        met = _shared_runs(one, least_words)
        cuts = Staged(cut_by(_run_pairs(met, RARE)), "cuts").df
        more = cut_by(_left_pairs(met, Staged(gathered(cuts), "cut-lines").df, RARE))
        cut = gathered(cuts.union(more))
    all_ = F.sequence(F.lit(0), F.size("lines") - 1)
    none = F.array().cast("array<int>")
    out = marked.join(cut, "id", "left").withColumn("removed", F.when(F.size("lines") == 0, none).when(F.col("copy"), all_).otherwise(F.coalesce(F.filter("cut", lambda x: x < F.size("lines")), none)))
    return out.select(
        F.when(F.col("id") != _LAST, F.col("id")).alias("doc_id"),
        F.size("lines").cast("long").alias("n_lines"),
        F.size("removed").cast("long").alias("n_removed"),
        F.expr("aggregate(removed, 0L, (s, k) -> s + words[k])").alias("words_removed"),
        "removed",
    )


def apply_cuts(docs: DataFrame, cuts: DataFrame) -> DataFrame:
    """The documents with the cut lines gone; cuts as ``align_lines`` returns them. Lines without a word stay."""
    id_, removed, lines = free_names(docs, "_id", "_removed", "_lines")
    gone = cuts.where("n_removed > 0").select(F.col("doc_id").alias(id_), F.col("removed").alias(removed))
    kept = F.expr(
        f"aggregate({lines}, struct(0 as n, cast(array() as array<string>) as out), (s, x) -> "
        "if(trim(' \t\x0b\x0c\r' from x) = '', struct(s.n as n, array_append(s.out, x) as out), "
        f"struct(s.n + 1 as n, if(array_contains({removed}, s.n), s.out, array_append(s.out, x)) as out)), s -> array_join(s.out, '\n'))"
    )
    met = docs.join(gone, F.col("doc_id") == F.col(id_), "left").withColumn(lines, F.split("text", "\n", -1))
    return met.withColumn("text", F.when(F.col(removed).isNotNull(), kept).otherwise(F.col("text"))).select(docs.columns)
