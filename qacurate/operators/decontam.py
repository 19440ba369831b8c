"""Leak removal: search for the most similar benchmark items, then judge each pair.

Questions are (id, text); long texts are cut into windows first, and a text goes if any window is
judged a paraphrase of any of its k items. The judge's stand-in compares word sets.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from qacurate.functions.text import containment, let, md5_fraction, tokens
from qacurate.models.clients import Model
from qacurate.operators.knn import Best, checked

WIDTH, JUDGE_CUT, JUDGE_WORDS = 256, 0.7, 8


def benchmark_pool(*sets: tuple[str, DataFrame]) -> DataFrame:
    """(benchmark, item_id, text) of all the sets."""
    out = None
    for name, df in sets:
        part = df.select(F.lit(name).alias("benchmark"), "item_id", "text")
        out = part if out is None else out.unionByName(part)
    return out


def windows(df: DataFrame, id_: str, text: str = "text", size: int = 32, stride: int = 16) -> DataFrame:
    """(doc_id, win_no, id, words): runs of ``size`` words, one every ``stride``; the last may be short."""

    def cut(w: Column) -> Column:
        count = F.greatest(F.ceil((F.size(w) - size) / F.lit(stride)) + 1, F.lit(1)).cast("int")
        parts = F.transform(F.sequence(F.lit(0), count - 1), lambda i: F.slice(w, i * stride + 1, size))
        return F.when(F.size(w) > 0, parts).otherwise(F.array().cast("array<array<string>>"))

    return df.select(F.col(id_).alias("doc_id"), F.posexplode(let(tokens(text), cut)).alias("win_no", "words"))


def _code(word: Column) -> Column:
    """Twelve bits of md5: the first eight are the bucket, the ninth the sign."""
    return F.conv(F.substring(F.md5(word), 1, 3), 16, 10).cast("int")


def sparse_embeddings(df: DataFrame, keys: list[str], words: str = "words") -> DataFrame:
    """(keys, bucket, weight): signed feature hashing into 256 buckets; weights are whole numbers."""
    each = df.select(*keys, F.explode(words).alias("word"))
    coded = each.select(*keys, _code(F.col("word")).alias("c"))
    sign = F.when(F.col("c") % 16 >= 8, 1).otherwise(-1)
    summed = coded.select(*keys, F.shiftright("c", 4).alias("bucket"), sign.alias("s")).groupBy(*keys, "bucket").agg(F.sum("s").alias("weight"))
    return summed.where("weight <> 0")


def codes(words: str = "words") -> Column:
    return F.transform(words, _code)


def _dense(column: pa.Array) -> np.ndarray:
    """The embeddings as a matrix of whole numbers, from lists of codes."""
    offsets, flat = column.offsets.to_numpy(), column.values.to_numpy()
    rows = np.repeat(np.arange(len(column)), np.diff(offsets))
    flat = flat[offsets[0] : offsets[-1]]
    return np.bincount(rows * WIDTH + flat // 16, np.where(flat % 16 >= 8, 1.0, -1.0), len(column) * WIDTH).reshape(len(column), WIDTH)


def hashed_words(words: str = "words") -> Column:
    """The distinct words as 64-bit hashes: small to move and quick to intersect."""
    return F.transform(F.array_distinct(words), lambda w: F.xxhash64(w))


def _lists(tile: np.ndarray) -> list[tuple[int, np.ndarray, np.ndarray]]:
    """The inverted lists of a tile of items: bucket, places and weights."""
    return [(b, at, tile[at, b]) for b in range(WIDTH) if len(at := np.flatnonzero(tile[:, b]))]


def _by_matrix(q: np.ndarray, tile: np.ndarray) -> tuple[np.ndarray, None]:
    return (q.astype(np.float32) @ tile.T).astype(np.float64), None


def _by_lists(q: np.ndarray, lists: tuple[int, list]) -> tuple[np.ndarray, np.ndarray]:
    """Dot products bucket by bucket, and whether question and item share one."""
    n, by_bucket = lists
    dots, met = np.zeros((len(q), n)), np.zeros((len(q), n), bool)
    for b, at, weights in by_bucket:
        rows = np.flatnonzero(q[:, b])
        cells = np.ix_(rows, at)
        dots[cells] += q[rows, b][:, None] * weights
        met[cells] = True
    return dots, met


def _searched(questions: DataFrame, items: DataFrame, keep: list[str], k: int, lists: bool) -> DataFrame:
    """The questions' columns ``keep`` and ``found``: item_id, rank, similarity of the k best items.

    Questions and items have ``words``. The words become codes in the JVM; a batch is compared with the items,
    whose bytes are checked before they go to every executor, tile by tile. No question is moved. Sums are whole
    numbers, so the similarity does not depend on their order. Where there is no similarity, nothing is found.
    """
    rows = checked(items, 4 * WIDTH).select("item_id", codes().alias("c")).orderBy("item_id").collect()
    # Whole numbers below 2^24, so that single precision holds every product exactly.
    matrix = _dense(pa.array([r.c for r in rows], pa.list_(pa.int32()))).astype(np.float32)
    shared = questions.sparkSession.sparkContext.broadcast((np.array([r.item_id for r in rows], np.int64), matrix, (matrix.astype(np.float64) ** 2).sum(axis=1)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, m, norms = shared.value
        tiles = {at: m[at : at + 4096] for at in range(0, len(ids), 4096)}
        if lists:
            tiles = {at: (len(t), _lists(t.astype(np.float64))) for at, t in tiles.items()}
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                q = _dense(pa.concat_arrays([part.column("_codes")]))
                mine, best = (q**2).sum(axis=1), Best(part.num_rows, k)
                for tile, held in tiles.items():
                    both = np.sqrt(mine[:, None] * norms[None, tile : tile + 4096])
                    dots, met = (_by_lists if lists else _by_matrix)(q, held)
                    best.add(np.divide(dots, both, out=np.full(both.shape, -2.0), where=both > 0 if met is None else met), tile)
                top, s = best.found()
                real, rest = s > -2, part.drop_columns(["_codes"])
                places = np.broadcast_to(np.arange(1, top.shape[1] + 1, dtype=np.int32), top.shape)
                ends = np.concatenate([[0], np.cumsum(real.sum(axis=1))]).astype(np.int32)
                found = pa.ListArray.from_arrays(pa.array(ends), pa.StructArray.from_arrays([pa.array(ids[top[real]]), pa.array(places[real]), pa.array(s[real])], names=["item_id", "rank", "similarity"]))
                yield pa.RecordBatch.from_arrays([*rest.columns, found], names=[*rest.schema.names, "found"])

    asked = questions.select(*keep, codes().alias("_codes"))
    found = T.ArrayType(T.StructType([T.StructField("item_id", T.LongType()), T.StructField("rank", T.IntegerType()), T.StructField("similarity", T.DoubleType())]))
    return asked.mapInArrow(run, T.StructType([*asked.schema.fields[:-1], T.StructField("found", found)]))


def topk_hashed(questions: DataFrame, items: DataFrame, keep: list[str], k: int = 5) -> DataFrame:
    """The questions' columns ``keep`` and ``found``, by matrix products; see ``_searched``."""
    return _searched(questions, items, keep, k, lists=False)


def topk_text(questions: DataFrame, items: DataFrame, k: int = 5, keep: tuple[str, ...] = ("id",)) -> DataFrame:
    """Top-k by sparse vectors: the questions' columns ``keep``, item_id, rank, similarity of items that share a bucket.

    The items' inverted lists by bucket take the questions' weights; for comparison with ``topk_hashed``. A row is
    made for each of the k best only, not for each pair that shares a bucket.
    """
    return _searched(questions, items, [*keep], k, lists=True).select(*keep, F.inline("found"))


def judge_pairs(found: DataFrame, items: DataFrame, words: Column) -> DataFrame:
    """The pairs that were found, with the words of their item as ``item``; words: the column that the judge reads."""
    return found.join(items.select("item_id", words.alias("item")), "item_id")


def judge(pairs: DataFrame, cut: float = JUDGE_CUT, least: int = JUDGE_WORDS, model: Model | None = None) -> DataFrame:
    """Adds ``paraphrase``: a model's yes, or enough distinct words on both sides and enough of the smaller side shared."""
    if model is not None:
        texts = pairs.withColumns({"_q": F.array_join("question", " "), "_i": F.array_join("item", " ")})
        return model.agrees(texts, "paraphrase", "paraphrase", question="_q", item="_i").drop("_q", "_i")
    long_ = (F.size(F.array_distinct("question")) >= least) & (F.size(F.array_distinct("item")) >= least)
    return pairs.withColumn("paraphrase", long_ & (F.coalesce(containment("question", "item"), F.lit(0.0)) >= cut))


def window_questions(df: DataFrame, id_: str, size: int = 32, stride: int = 16) -> DataFrame:
    """(doc_id, id, words): a question per window; ids are text and number, so that texts of any length keep theirs apart."""
    return windows(df, id_, size=size, stride=stride).select("doc_id", F.concat_ws(":", "doc_id", "win_no").alias("id"), "words")


def judged_pairs(questions: DataFrame, items: DataFrame, k: int = 5, search: str = "block", model: Model | None = None) -> DataFrame:
    """(doc_id, id, item_id, rank, question, item) of the k best items of each question; search: block or text.

    Words travel as hashes, but for a model, which reads them.
    """
    read = (lambda: F.col("words")) if model is not None else hashed_words
    asked, keep = questions.withColumn("question", read()), ["doc_id", "id", "question"]
    if search == "block":
        found = topk_hashed(asked, items, keep, k).select(*keep, F.inline("found"))
    else:
        found = topk_text(asked, items, k, tuple(keep))
    return judge_pairs(found, items, read())


def decontaminate(questions: DataFrame, items: DataFrame, k: int = 5, cascade: bool = False, search: str = "block", model: Model | None = None) -> DataFrame:
    """(doc_id, item_id, rank): evidence, the best-ranked paraphrase of each leaked text.

    questions: (doc_id, id, words); items: (item_id, words). cascade judges rank by rank and stops
    asking about a text once it is settled: the same texts go, with fewer calls.
    """
    pairs = judged_pairs(questions, items, k, search, model)
    if not cascade:
        hits = judge(pairs, model=model).where("paraphrase")
        return hits.groupBy("doc_id").agg(F.min(F.struct("rank", "item_id")).alias("e")).select("doc_id", F.col("e.item_id").alias("item_id"), F.col("e.rank").alias("rank"))
    out, settled = None, None
    for r in range(1, k + 1):
        asked = pairs.where(F.col("rank") == r)
        if settled is not None:
            asked = asked.join(settled, "doc_id", "left_anti")
        now = judge(asked, model=model).where("paraphrase").groupBy("doc_id").agg(F.min("item_id").alias("item_id")).withColumn("rank", F.lit(r))
        out = now if out is None else out.unionByName(now)
        settled = out.select("doc_id")
    return out


def embedding_decontaminate(questions: DataFrame, items: DataFrame, threshold: float = 0.72) -> DataFrame:
    """(doc_id): the baseline without a judge, similarity of the best item at or above a threshold."""
    best = topk_hashed(questions, items, ["doc_id"], 1)
    return best.where(F.get("found", 0)["similarity"] >= threshold).select("doc_id").distinct()


def leakage_report(removed: DataFrame, population: DataFrame, by: str) -> DataFrame:
    """Leaked rows, rows and share (percent) by ``by`` and in total."""
    marked = population.join(removed.select("doc_id").distinct().withColumn("leak", F.lit(1)), "doc_id", "left")
    out = marked.rollup(by).agg(F.count("leak").alias("n_leaked"), F.count(F.lit(1)).alias("n"), F.grouping(by).alias("g"))
    return out.select(F.when(F.col("g") == 1, "total").otherwise(F.col(by)).alias(by), "n_leaked", "n", F.round(100.0 * F.col("n_leaked") / F.col("n"), 4).alias("share"))


REWRITES = ("verbatim", "case", "drop", "swap", "reverse")


def planted_leaks(items: DataFrame) -> DataFrame:
    """(id, doc_id, item_id, kind, words, text): items rewritten in known ways; ids are item_id * 10 + kind."""
    w = items.select("item_id", "words")
    raw = F.col("words")
    forms = {
        "verbatim": raw,
        "case": F.transform(raw, lambda x: F.upper(x)),
        "drop": F.filter(F.transform(raw, lambda x, i: F.when(md5_fraction(F.col("item_id"), i.cast("string"), x) >= 0.1, x)), lambda x: x.isNotNull()),
        "swap": F.transform(raw, lambda x, i: F.when((i % 5 == 0) & (i + 1 < F.size(raw)), F.get(raw, i + 1)).when((i % 5 == 1), F.get(raw, i - 1)).otherwise(x)),
        "reverse": F.reverse(raw),
    }
    rows = [F.struct(F.lit(k).alias("kind"), F.lit(n).alias("no"), forms[k].alias("words")) for n, k in enumerate(REWRITES)]
    each = w.select("item_id", F.explode(F.array(*rows)).alias("r"))
    made = each.select("item_id", (F.col("item_id") * 10 + F.col("r.no")).alias("id"), F.col("r.kind").alias("kind"), F.transform("r.words", lambda x: F.lower(x)).alias("words"), F.array_join("r.words", " ").alias("text"))
    return made.withColumn("doc_id", F.col("id"))


def detector_recall(items: DataFrame, n_sizes: tuple[int, ...] = (5, 8, 13), threshold: float = 0.72) -> DataFrame:
    """(kind, n, judge, embedding, ngram_<n> ...): planted rewrites that each detector finds."""
    from qacurate.operators.ngram import ngram_decontaminate

    planted = planted_leaks(items)
    texts = items.select("item_id", F.array_join("words", " ").alias("text"))
    found = {"judge": decontaminate(planted, items).select("doc_id"), "embedding": embedding_decontaminate(planted, items, threshold)}
    for n in n_sizes:
        found[f"ngram_{n}"] = ngram_decontaminate(planted.select("id", "text"), texts, n).select(F.col("id").alias("doc_id"))
    out = planted.select("doc_id", "kind")
    for name, df in found.items():
        out = out.join(df.distinct().withColumn(name, F.lit(1)), "doc_id", "left")
    return out.groupBy("kind").agg(F.count(F.lit(1)).alias("n"), *[F.count(name).alias(name) for name in found])
