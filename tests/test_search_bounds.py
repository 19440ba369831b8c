"""Search by tiles: ties, limits, memory, and approximate search where vectors have clusters."""

import resource

import numpy as np
import pytest
from pyspark.sql import functions as F

from qacurate.operators import decontam as D
from qacurate.operators import knn


def test_tiles_keep_ties_in_order():
    rng = np.random.default_rng(3)
    s = rng.integers(-3, 4, (40, 500)) / 3
    best = knn.Best(40, 7)
    for at in range(0, 500, 61):
        best.add(s[:, at : at + 61], at)
    places, found = best.found()
    want = np.argsort(-np.round(s, 6), axis=1, kind="stable")[:, :7]
    assert (places == want).all() and (found == np.take_along_axis(np.round(s, 6), want, axis=1)).all()


def test_memory_of_a_search_is_bounded():
    rng = np.random.default_rng(1)
    items, questions = rng.standard_normal((200_000, 64)), rng.standard_normal((512, 64))
    before = resource.getrusage(resource.RUSAGE_SELF).ru_maxrss
    found, _ = knn._best(questions, items, np.arange(200_000), 5)
    assert resource.getrusage(resource.RUSAGE_SELF).ru_maxrss - before < 200_000  # KB; one matrix of all pairs has 800 MB
    some = questions[:3] @ items.T / np.linalg.norm(items, axis=1)
    assert (found[:3, 0] == some.argmax(axis=1)).all()


def test_large_items_are_refused(spark, monkeypatch):
    items = spark.range(50).select(F.col("id").alias("item_id"), F.array(F.lit(1.0), F.col("id").cast("double")).alias("vec"))
    monkeypatch.setattr(knn, "BROADCAST_BYTES", 16 * 49)
    with pytest.raises(ValueError, match="shards"):
        knn.topk_block(items.withColumnRenamed("item_id", "id"), items)


def test_shards_follow_the_tables(spark):
    rng = np.random.default_rng(5)
    rows = [(i, [float(x) for x in rng.standard_normal(8)]) for i in range(300)]
    q = spark.createDataFrame(rows[:70], "id long, vec array<double>")
    m = spark.createDataFrame(rows, "item_id long, vec array<double>")
    want = {tuple(r) for r in knn.topk_exact(q, m).collect()}
    assert {tuple(r) for r in knn.topk_sharded(q, m, shard_rows=40, block_rows=30).collect()} == want


def test_few_lists_find_clustered_vectors(spark):
    rng = np.random.default_rng(2)
    centres = rng.standard_normal((32, 32)) * 3
    rows = [(i, [float(x) for x in centres[i % 32] + rng.standard_normal(32) * 0.5]) for i in range(640)]
    m = spark.createDataFrame(rows, "item_id long, vec array<double>")
    q = m.where("item_id % 16 = 0").withColumnRenamed("item_id", "id")
    truth = knn.topk_exact(q, m)
    assert knn.recall_at_k(knn.topk_ivf(q, m, lists=16, probes=4), truth).first().recall >= 0.9
    assert knn.recall_at_k(knn.topk_lsh(q, m, planes=6, tables=16, width=32), truth).first().recall >= 0.9


def test_windows_of_long_texts_have_ids_of_their_own(spark):
    df = spark.createDataFrame([(1, "w " * 2000), (11, "v " * 40)], "doc_id long, text string")
    rows = D.window_questions(df, "doc_id", size=2, stride=1).select("id").collect()
    assert len({r.id for r in rows}) == len(rows) == 1999 + 39
