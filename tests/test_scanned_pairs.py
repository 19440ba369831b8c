"""Exact joins by sketches: frequent words make no rows, and the ML library's own join gives the same pairs."""

import random

from pyspark.sql import functions as F

from qacurate.operators import minhash as M
from qacurate.queries.common import word_sets


def _sets(spark):
    rng = random.Random(3)
    rows, words = [], [f"w{i}" for i in range(60)]
    for i in range(240):  # few words, so that each is in many sets and many pairs lie near the threshold
        rows.append((i, rng.sample(words, rng.choice([0, 1, 2, 5, 20, 33, 40, 55]))))
    rows += [(1000 + i, [f"x{j}" for j in range(i, 90 + 9 * i)]) for i in range(12)]
    rows += [(2000, [f"z{j}" for j in range(10)]), (2001, [f"z{j}" for j in range(6)])]  # 0.6 to the digit
    return spark.createDataFrame(rows, "id long, set array<string>")


def test_join_equals_brute_force_in_bounded_parts(spark, monkeypatch):
    sets = _sets(spark)
    want = {(r.a, r.b) for r in M.jaccard_bruteforce(sets).collect()}
    assert (2000, 2001) in want and len(want) > 100
    for size in (1 << 20, 2000):
        monkeypatch.setattr(M, "SKETCH_BYTES", size)
        got = [(r.a, r.b) for r in M.exact_similarity_join(sets).collect()]
        assert len(got) == len(set(got)) and set(got) == want


def test_frequent_words_make_no_rows(spark):
    plan = M.scanned_pairs(_sets(spark).select("id", M.hash_set().alias("hset")), 0.6)._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and "Generate" not in plan


def test_the_librarys_own_join_gives_the_same(spark, sf):
    from pyspark.ml.feature import HashingTF, MinHashLSH

    for sets, tables in ((word_sets(spark, sf), 64), (_sets(spark), 3)):
        sets = sets.localCheckpoint()
        vectors = HashingTF(inputCol="set", outputCol="features", numFeatures=1 << 18, binary=True).transform(sets.where(F.size("set") > 0))
        model = MinHashLSH(inputCol="features", outputCol="hashes", numHashTables=tables, seed=7).fit(vectors)
        found = model.approxSimilarityJoin(vectors, vectors, 0.4 + 1e-9, "distance").select(F.col("datasetA.id").alias("a"), F.col("datasetB.id").alias("b"), (1 - F.col("distance")).alias("s")).where("a < b")
        want = {(r.a, r.b, round(r.s, 9)) for r in found.collect()}
        assert want and {(r.a, r.b, round(r.similarity, 9)) for r in M.ml_minhash(sets, tables=tables).collect()} == want
