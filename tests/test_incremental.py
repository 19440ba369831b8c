"""Streams that keep their state in tables: what is emitted when, and no join that pairs a bucket's rows."""

import datetime

from oracle import difference

from qacurate.operators import minhash as M
from qacurate.queries import REGISTRY
from qacurate.streaming import streams as S


def _scores(spark, rows):
    at = datetime.datetime(2024, 1, 1)
    return spark.createDataFrame([(q, s, at + datetime.timedelta(minutes=m)) for q, s, m in rows], "qid string, score int, ts timestamp")


def test_scores_are_emitted_when_full_or_when_the_wait_is_over(spark):
    x = S.IncrementalScores(spark, full=3, wait="1 hour")
    out = lambda k: sorted(tuple(r) for r in spark.read.parquet(f"{x.out}/batch={k}").collect())
    x.add(_scores(spark, [("a", 1, 0), ("a", 2, 1), ("b", 5, 0), ("c", 7, 2), ("c", 1, 3), ("c", 1, 4), ("c", 9, 5)]), 0)
    assert out(0) == [("c", 3, 9)]
    x.add(_scores(spark, [("a", 4, 30), ("a", 8, 31), ("c", 9, 32), ("b", 6, 70)]), 1)
    assert out(1) == [("a", 3, 7)]
    x.add(_scores(spark, [("d", 1, 200), ("d", 9, 20)]), 2)  # 20 is behind the watermark of 60
    assert out(2) == []
    x.add(_scores(spark, [("d", 3, 210)]), 3)  # the watermark of 190 ends b, and forgets a and c
    assert out(3) == [("b", 2, 11)]
    x.add(_scores(spark, [("d", 3, 210)]), 3)  # once more: the same
    assert out(3) == [("b", 2, 11)]
    x.add(_scores(spark, [("a", 9, 205), ("d", 3, 211)]), 4)
    assert sorted(r.qid for r in spark.read.parquet(f"{x.state}/batch=4").collect()) == ["a", "d"] and out(4) == [("d", 3, 7)]


def test_old_rows_do_not_meet_each_other(spark):
    rows = [(i, [f"w{j}" for j in range(20)], i % 2 == 0) for i in range(40)]
    t = spark.createDataFrame(rows, "id long, set array<string>, old boolean")
    sets = t.select("id", M.hash_set().alias("hset"))
    banded = t.selectExpr("id", "0 as band", "'k' as key", "old")
    for tile in (512, 7):
        got = {(r.a, r.b) for r in M.sketched_pairs(banded, sets, 0.6, tile).collect()}
        assert got == {(a, b) for a in range(40) for b in range(a + 1, 40) if a % 2 or b % 2}


def test_a_later_row_goes_whatever_its_id(spark, monkeypatch):
    monkeypatch.setattr(M, "candidate_pairs", None)
    x = S.IncrementalDedup(spark)
    words = " ".join(f"w{i}" for i in range(30))
    x.add(spark.createDataFrame([(10, words), (12, words + " more"), (20, "quite another text of its own")], "id long, text string"), 0)
    x.add(spark.createDataFrame([(5, words + " last"), (15, words + " again")], "id long, text string"), 1)
    assert {(r.id, r.keep_id) for r in spark.read.parquet(x.out).collect()} == {(10, 10), (12, 10), (20, 20), (5, 10), (15, 5)}


def test_streams_give_what_their_sql_gives(spark, sf):
    for name in ("stream_minhash", "stream_difficulty"):
        assert difference(REGISTRY.queries[name](spark, sf), REGISTRY.oracles[name], sf) == ""
