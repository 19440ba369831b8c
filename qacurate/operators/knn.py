"""Top-k neighbours: exact by a scan of the items, by blocks, by shards of items; approximate by planes or lists.

All take questions (id, vec) and items (item_id, vec) and return (id, item_id, rank, similarity):
cosine, rounded to six digits, ties by item id. Item tables are broadcast only below a checked size;
the scan sends the questions in bounded parts instead, and the shards strategy moves both sides.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from qacurate.functions.text import cosine

BROADCAST_ROWS, BROADCAST_BYTES = 200_000, 256 << 20  # of items, at most, on each executor
QUESTION_BYTES = 32 << 20  # of questions that go to each executor for a pass over the items
SCHEMA = "id long, item_id long, rank int, similarity double"


def _ranked(scored: DataFrame, k: int) -> DataFrame:
    place = F.row_number().over(Window.partitionBy("id").orderBy(F.col("similarity").desc(), "item_id"))
    return scored.withColumn("rank", place).where(F.col("rank") <= k).select("id", "item_id", "rank", "similarity")


def topk_exact(questions: DataFrame, items: DataFrame, k: int = 5) -> DataFrame:
    """Every question against every item, where the items lie; see ``_scanned``."""
    return _ranked(_scanned(questions, items, k), k)


def checked(items: DataFrame, row_bytes: int = 0, most: int = BROADCAST_ROWS) -> DataFrame:
    """The items, if they are few enough to go to every executor, by rows and by bytes."""
    most = min(most, BROADCAST_BYTES // row_bytes) if row_bytes else most
    if items.limit(most + 1).count() > most:
        raise ValueError(f"more than {most} items: use the shards strategy")
    return items


def _matrix(column: pa.Array) -> np.ndarray:
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(column), -1) if len(column) else np.empty((0, 1))


class Best:
    """The k best items of each question, tile by tile: by similarity in millionths, then by place."""

    def __init__(self, n: int, k: int) -> None:
        self.k, self.keys = k, np.empty((n, 0), np.int64)

    def add(self, similarity: np.ndarray, first: int) -> None:
        """Similarities (-2 where there is none) of a tile of items that begins at place ``first``."""
        place = first + np.arange(similarity.shape[1])
        keys = (np.round(similarity, 6) * 1e6).round().astype(np.int64) * (1 << 40) - place
        if keys.shape[1] > self.k:
            keys = -np.partition(-keys, self.k - 1, axis=1)[:, : self.k]
        self.keys = np.concatenate([self.keys, keys], axis=1)
        self.keys = -np.sort(-self.keys, axis=1)[:, : self.k]

    def found(self) -> tuple[np.ndarray, np.ndarray]:
        """Places and similarities, the best first."""
        micro = -((-self.keys) >> 40)
        return micro * (1 << 40) - self.keys, micro / 1e6


def _best(q: np.ndarray, m: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Item ids and similarities of the k best items of each question; ties by id, as m is in order of id."""
    best, mine, other = Best(len(q), k), np.linalg.norm(q, axis=1), np.linalg.norm(m, axis=1)
    for at in range(0, len(m), 4096):
        norms = mine[:, None] * other[None, at : at + 4096]
        best.add(np.divide(q @ m[at : at + 4096].T, norms, out=np.full(norms.shape, -2.0), where=norms > 0), at)
    places, s = best.found()
    return ids[places], s


def topk_block(questions: DataFrame, items: DataFrame, k: int = 5) -> DataFrame:
    """A matrix product per Arrow batch against the items on every executor, tile by tile; moves no question."""
    width = items.select(F.size("vec")).first()
    rows = checked(items, 8 * max(width[0] if width else 1, 1)).orderBy("item_id").collect()
    ids = np.array([r.item_id for r in rows], np.int64)
    vectors = np.array([r.vec for r in rows], np.float64)
    shared = questions.sparkSession.sparkContext.broadcast((ids, vectors))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, vectors = shared.value
        for whole in batches:
            for at in range(0, whole.num_rows if len(ids) else 0, 512):
                batch = whole.slice(at, 512)
                found, sims = _best(_matrix(batch.column("vec")), vectors, ids, k)
                got = found.shape[1]
                mine = np.repeat(batch.column("id").to_numpy(), got)
                yield pa.RecordBatch.from_arrays([pa.array(mine), pa.array(found.ravel()), pa.array(np.tile(np.arange(1, got + 1, dtype=np.int32), batch.num_rows)), pa.array(sims.ravel())], names=["id", "item_id", "rank", "similarity"])

    return questions.select("id", "vec").mapInArrow(run, SCHEMA)


def topk_sharded(questions: DataFrame, items: DataFrame, k: int = 5, shard_rows: int = 20_000, block_rows: int = 5_000) -> DataFrame:
    """Items dealt into shards of some ``shard_rows``; each question meets each shard, and the shards' lists merge.

    Questions are dealt into blocks of some ``block_rows``, so a group is one block and one shard whatever
    the tables' sizes. Questions move once per shard and items once per block.
    """
    import pandas as pd

    shards = -(-max(items.count(), 1) // shard_rows)
    blocks = -(-max(questions.count(), 1) // block_rows)
    dealt = items.withColumn("shard", F.pmod(F.xxhash64("item_id"), F.lit(shards)).cast("int"))
    asked = questions.select("id", "vec", F.explode(F.sequence(F.lit(0), F.lit(shards - 1))).alias("shard"))
    asked = asked.withColumn("block", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int"))
    spread = dealt.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))

    def run(q: pd.DataFrame, m: pd.DataFrame) -> pd.DataFrame:
        m = m.sort_values("item_id")
        if not len(q) or not len(m):
            return pd.DataFrame({"id": [], "item_id": [], "similarity": []}).astype({"id": "int64", "item_id": "int64"})
        found, sims = _best(np.stack(q.vec.to_numpy()).astype(np.float64), np.stack(m.vec.to_numpy()).astype(np.float64), m.item_id.to_numpy(), k)
        return pd.DataFrame({"id": np.repeat(q.id.to_numpy(), found.shape[1]), "item_id": found.ravel(), "similarity": sims.ravel()})

    lists = asked.groupBy("shard", "block").cogroup(spread.groupBy("shard", "block")).applyInPandas(run, "id long, item_id long, similarity double")
    return _ranked(lists, k)


_NONE, _PART = -(1 << 62), 2048  # a key below all others; rows of items that are compared at once


def _scanned(questions: DataFrame, items: DataFrame, k: int, cells: Callable[[np.ndarray], np.ndarray] | None = None) -> DataFrame:
    """(id, item_id, similarity): the k best items of each question in each task of the items; null without a cosine.

    The questions go to every executor, ``QUESTION_BYTES`` of them at once; more take further passes over the items,
    which never move. A task keeps k items a question. cells: the cell of each vector in each of some tables, an
    array (tables, vectors); only items that share a cell with a question are compared with it.
    """
    few = questions.agg(F.count(F.lit(1)), F.max(F.size("vec"))).first()
    chunks = max(1, -(-few[0] * 8 * (few[1] or 1) // QUESTION_BYTES))
    vectors = items.select("item_id", F.col("vec").cast("array<double>").alias("vec"))
    found = [_scan(questions.where(F.pmod(F.xxhash64("id"), F.lit(chunks)) == c) if chunks > 1 else questions, vectors, k, cells) for c in range(chunks)]
    return reduce(DataFrame.union, found)


def _scan(questions: DataFrame, items: DataFrame, k: int, cells: Callable[[np.ndarray], np.ndarray] | None) -> DataFrame:
    asked = questions.select(F.col("id").cast("long").alias("id"), F.col("vec").cast("array<double>").alias("vec")).toArrow().combine_chunks()
    q = _matrix(pa.concat_arrays(asked.column("vec").chunks)) if asked.num_rows else np.empty((0, 1))
    table = cells or (lambda v: np.zeros((1, len(v)), np.int64))
    places = [{int(c): np.flatnonzero(row == c) for c in np.unique(row)} for row in table(q)] if len(q) else []
    shared = questions.sparkSession.sparkContext.broadcast((asked.column("id").to_numpy(), q, np.linalg.norm(q, axis=1), places))

    def best(part: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
        """Similarities in millionths and ids of the k best items of a part."""
        _, q, mine, places = shared.value
        ids = part.column("item_id").to_numpy()
        order = np.argsort(ids, kind="stable")
        ids, m = ids[order], _matrix(part.column("vec"))[order]
        other, keys = np.linalg.norm(m, axis=1), np.full((len(q), k), _NONE, np.int64)
        for row, by_cell in zip(table(m), places, strict=True):
            for c in np.unique(row):
                at = np.flatnonzero(row == c)
                met = by_cell.get(int(c), np.empty(0, np.int64))
                for i in range(0, len(met), 1024):
                    who = met[i : i + 1024]
                    norms = mine[who][:, None] * other[at][None, :]
                    s = np.divide(q[who] @ m[at].T, norms, out=np.full(norms.shape, -2.0), where=norms > 0)
                    new = (np.round(s, 6) * 1e6).round().astype(np.int64) * _PART - at
                    if new.shape[1] > k:
                        new = -np.partition(-new, k - 1, axis=1)[:, :k]
                    new = -np.sort(-np.concatenate([keys[who], new], axis=1), axis=1)
                    if len(places) > 1:  # an item that was met in another table
                        item = -new % _PART
                        for j in range(1, new.shape[1]):
                            new[(item[:, :j] == item[:, j : j + 1]).any(axis=1), j] = _NONE
                        new = -np.sort(-new, axis=1)
                    keys[who] = new[:, :k]
        return -(-keys // _PART), ids[-keys % _PART % len(ids)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        asked = shared.value[0]
        micro, ids = np.full((len(asked), k), _NONE, np.int64), np.zeros((len(asked), k), np.int64)
        for batch in batches:
            for at in range(0, batch.num_rows if len(asked) else 0, _PART):
                new, item = best(batch.slice(at, _PART))
                micro, ids = np.concatenate([micro, new], axis=1), np.concatenate([ids, item], axis=1)
                order = np.lexsort((ids, -micro), axis=1)[:, :k]
                micro, ids = np.take_along_axis(micro, order, axis=1), np.take_along_axis(ids, order, axis=1)
        real = micro > _NONE // _PART // 2
        for at in range(0, len(asked), 4096):
            kept = real[at : at + 4096]
            s = micro[at : at + 4096][kept]
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(asked[at : at + 4096], kept.sum(axis=1))), pa.array(ids[at : at + 4096][kept]), pa.array(s / 1e6, mask=s < -1_500_000)], names=["id", "item_id", "similarity"])

    return items.mapInArrow(run, "id long, item_id long, similarity double")


def topk_lsh(questions: DataFrame, items: DataFrame, k: int = 5, planes: int = 3, tables: int = 16, width: int = 64) -> DataFrame:
    """Random hyperplanes: items in the same cell of some table are compared exactly.

    The fewer planes, the larger the cells. The defaults suit vectors without clusters, where neighbours
    are hardly nearer than other items; clustered vectors are found with many planes (see the tests). Cells are
    compared by matrix products where the items lie, so no row is made for each pair that meets.
    """
    normals = np.random.default_rng(7).standard_normal((tables, planes, width))

    def cells(v: np.ndarray) -> np.ndarray:
        side = (v @ normals.reshape(-1, width).T > 0).reshape(len(v), tables, planes)
        return (side @ (1 << np.arange(planes))).astype(np.int64).T

    return _ranked(_scanned(questions, items, k, cells), k)


def topk_ivf(questions: DataFrame, items: DataFrame, k: int = 5, lists: int = 8, probes: int = 6) -> DataFrame:
    """Coarse centres by k-means over the items; a question looks into the lists of its nearest centres.

    Vectors without clusters need most lists for a high recall; clustered ones a fraction (see the tests).
    """
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    featured = items.select("item_id", F.col("vec").cast("array<double>").alias("vec"), array_to_vector(F.col("vec").cast("array<double>")).alias("features"))
    model = KMeans(k=lists, seed=7, maxIter=10).fit(featured)
    centres = F.array(*[F.array(*[F.lit(float(x)) for x in c]) for c in model.clusterCenters()])
    near = F.slice(F.array_sort(F.transform(centres, lambda c, i: F.struct((-cosine("vec", c)).alias("d"), i.alias("cell")))), 1, probes)
    asked = questions.select("id", F.col("vec").cast("array<double>").alias("vec")).select("id", "vec", F.explode(near).alias("p")).select("id", "vec", F.col("p.cell").alias("cell"))
    held = model.transform(featured).select("item_id", F.col("vec").alias("other"), F.col("prediction").alias("cell"))
    return _ranked(asked.join(held, "cell").select("id", "item_id", F.round(cosine("vec", "other"), 6).alias("similarity")), k)


def recall_at_k(found: DataFrame, truth: DataFrame) -> DataFrame:
    n = truth.agg(F.count(F.lit(1)).alias("n_true"))
    hit = found.join(truth, ["id", "item_id"], "left_semi").agg(F.count(F.lit(1)).alias("n_hit"))
    return n.crossJoin(hit).select("n_true", "n_hit", F.round(F.try_divide(F.col("n_hit").cast("double"), F.col("n_true")), 6).alias("recall"))
