"""Behaviour of the other methods: selection bounds, leaks, extraction, plans, published arithmetic."""

import pytest
from pyspark.sql import functions as F

from qacurate.functions import published as P
from qacurate.functions.udfs import balanced
from qacurate.models.clients import EchoClient, ReplayClient, call_model, prompt
from qacurate.operators import answers as A
from qacurate.operators import decontam as D
from qacurate.operators import ingest, knn, measures, select
from qacurate.queries import REGISTRY
from qacurate.queries.decontam import items
from qacurate.staging import fresh_path


def test_published_averages(spark):
    got = {(r.system, r.category): r.cents for r in measures.category_averages(P.scores(spark)).collect()}
    assert got["mixture", "Overall"] == 6101 and got["instruct", "Overall"] == 5880
    assert got["textbook", "General"] == 3958 and got["B", "Specific"] == 6756 and got["C", "Math"] == 7618
    wins = {r.system: (r.wins, r.seconds) for r in measures.win_counts(P.scores(spark)).collect()}
    assert wins["mixture"] == (7, 3)
    gains = {(r.system, r.category): r.gain for r in measures.gain_vs_baseline(P.scores(spark), "instruct").collect()}
    assert gains["mixture", "Overall"] == 221
    assert sum(x[4] for x in P.EXTRACTION) == 25483 and sum(x[5] for x in P.EXTRACTION) == 920200
    assert [sum(r[k] for r in P.FUNNEL) for k in (1, 2, 3, 4)] == [945683, 767893, 728767, 651840]


def test_detectors_on_rewrites(spark, sf):
    got = {r.kind: r for r in D.detector_recall(items(spark, sf).select("item_id", "words")).collect()}
    assert got["verbatim"].ngram_13 == got["verbatim"].judge == got["verbatim"].n
    assert got["reverse"].judge == got["reverse"].n and got["reverse"].ngram_5 == 0
    assert got["swap"].ngram_13 < got["swap"].n // 4 < got["swap"].judge


def test_search_strategies_agree(spark, sf):
    e = spark.read.parquet(f"{sf}/embeddings.parquet")
    q = e.where("vec_id % 5 <> 0").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"))
    m = e.where("vec_id % 5 = 0").select(F.col("vec_id").alias("item_id"), F.col("embedding").alias("vec"))
    a, b, c = ({tuple(r) for r in f(q, m).collect()} for f in (knn.topk_exact, knn.topk_block, knn.topk_sharded))
    assert a == b == c
    for approximate in (knn.topk_lsh, knn.topk_ivf):
        assert knn.recall_at_k(approximate(q, m), knn.topk_exact(q, m)).first().recall >= 0.9


def test_search_forms_agree(spark, sf):
    q = D.window_questions(spark.read.parquet(f"{sf}/documents.parquet"), "doc_id")
    both = [{tuple(r) for r in D.decontaminate(q, items(spark, sf), search=s).collect()} for s in ("block", "text")]
    assert both[0] == both[1]


def test_random_selection_is_stable(spark, monkeypatch):
    df = spark.range(5000).withColumnRenamed("id", "qid")
    small = {r.qid for r in select.select_random(df, 700).collect()}
    monkeypatch.setattr(select, "SMALL", 10)
    assert {r.qid for r in select.select_random(df.repartition(9), 700).collect()} == small
    longest = df.withColumn("length", F.col("qid") % 40)
    want = sorted(((-(i % 40), i) for i in range(5000)))[:333]
    assert {r.qid for r in select.select_longest(longest, 333).collect()} == {i for _, i in want}


def test_chunks_join_to_text(spark):
    text = "a b\n\nc  d e\n" * 50 + "tail"
    df = spark.createDataFrame([(1, text), (2, ""), (3, None)], "book_id long, text string")
    parts = ingest.chunk(df, 7).orderBy("book_id", "chunk_no").collect()
    assert "".join(r.text for r in parts) == text and {r.book_id for r in parts} == {1}
    assert max(r.n_tokens for r in parts) == 7
    assert ingest.chunk(df, 100, 50).count() == -(-(len(text.split()) - 50) // 50)


@pytest.mark.parametrize(("text", "qtype", "answer", "rule"), [
    ("x\nThe final answer is \\boxed{42}.", "computational", "42", "r1"),
    ("x\nThe answer is 7", "computational", "7", "r2"),
    ("so \\boxed{\\mathrm{9}} ok", "computational", "9", "r3"),
    ("x\nwe get $12$", "computational", "12", "r4"),
    ("pick (C)", "choice", "C", "r5"),
    ("it is not true", "truefalse", "false", "r7"),
    ("makes 15 m", "computational", "15 m", "r8"),
    ("nothing", "choice", None, "r9"),
])
def test_rules(spark, text, qtype, answer, rule):
    df = spark.createDataFrame([(text, qtype, {"A": "north pole", "B": "south pole"})], "response string, qtype string, options map<string,string>")
    r = A.extract_answer(df).first()
    assert (r.answer, r.rule) == (answer, rule)


def test_balanced():
    assert balanced("a \\boxed{x{y{z}}} b") == "x{y{z}}"
    assert balanced("\\boxed{open") is None and balanced(None) is None


def test_model_calls_are_cached(spark, sf):
    cache = fresh_path(spark, "cache")
    b = spark.read.parquet(f"{sf}/benchmark.parquet")
    first = call_model(b, "classify", prompt("classify"), EchoClient(), cache)
    assert first.where("answer like 'echo %'").count() == b.count()
    again = call_model(b, "classify", prompt("classify"), ReplayClient("echo-1"), cache)
    assert again.where("answer is null").count() == 0
    with pytest.raises(Exception, match="no stored answer"):
        call_model(b, "refine", prompt("classify"), ReplayClient("echo-1"), cache)


def test_recipe_shrinks(spark, sf):
    rows = REGISTRY.queries["textbook_recipe"](spark, sf).where("subject = 'total'").orderBy("stage_no").collect()
    assert [r.stage for r in rows] == ["pairs", "dedup", "filter", "decontaminate"]
    assert all(a.n >= b.n for a, b in zip(rows, rows[1:], strict=False))


def test_plans(spark, sf):
    plan = lambda df: df._jdf.queryExecution().toString()
    assert "CartesianProduct" not in plan(REGISTRY.queries["dedup_minhash"](spark, sf))
    assert "PushedFilters: [IsNotNull(n_chars), GreaterThan(n_chars,500)]" in plan(REGISTRY.queries["scan_parquet"](spark, sf))
    assert "WindowGroupLimit" in plan(REGISTRY.queries["topk_exact"](spark, sf))
    assert "BroadcastHashJoin" in plan(REGISTRY.queries["join_broadcast"](spark, sf))
