"""Operators that ask a model: replies from a table, then the same from the stored answers alone."""

import json

import pytest
from pyspark.sql import functions as F

from qacurate.models.clients import PROMPTS, Model, ReplayClient, TableClient, prompt, usage
from qacurate.operators import decontam, extract, ingest, mixture, refine, select
from qacurate.plans.recipe import Recipe, run_textbook
from qacurate.staging import fresh_path


def filled(role, **fields):
    return PROMPTS[role].format(**fields)


class Asked:
    """A model with replies by role, and the same without a client."""

    def __init__(self, spark, replies, other="no"):
        self.cache = fresh_path(spark, "answers")
        self.model = Model(TableClient(tuple(replies), other), self.cache)
        self.replay = Model(ReplayClient("table-1"), self.cache)

    def both(self, run):
        first, again = (sorted(map(str, run(m).collect())) for m in (self.model, self.replay))
        assert first == again
        return run(self.replay)


def pairs(spark):
    return spark.createDataFrame([("q1", 1, 0, "what is it", "short"), ("q2", 1, 0, "why is it", "a long answer"), ("q3", 2, 0, "when", None)], "qid string, book_id long, chunk_no int, question string, answer string")


def test_extraction_by_a_model(spark):
    chunks = spark.createDataFrame([(1, 0, "one"), (1, 1, "two"), (2, 0, None)], "book_id long, chunk_no int, text string")
    listed = json.dumps([{"question": "a?", "answer": "b"}, {"question": "c?"}, {"question": "d?", "answer": "e"}])
    asked = Asked(spark, [(filled("extract_high", text="one"), listed), (filled("extract_low", text="two"), listed), (filled("extract_low", text="one"), "no json {")])
    got = {(r.qid, r.question, r.answer) for r in asked.both(lambda m: extract.extract_dual(chunks, m)).collect()}
    assert got == {("1:0:0:high", "a?", "b"), ("1:0:2:high", "d?", "e"), ("1:1:0:low", "a?", "b"), ("1:1:2:low", "d?", "e")}


def test_refinement_by_a_model(spark):
    chunks = spark.createDataFrame([(1, 0, "source"), (2, 0, "other")], "book_id long, chunk_no int, text string")
    new = json.dumps({"question": "what is the thing", "answer": "a full answer"})
    asked = Asked(spark, [(filled("refine", chunk="source", question="what is it", answer="short"), new)])
    got = {r.qid: (r.question, r.answer) for r in asked.both(lambda m: refine.refine(pairs(spark), chunks, model=m)).collect()}
    assert got == {"q1": ("what is the thing", "a full answer"), "q2": ("why is it", "a long answer"), "q3": ("when", None)}


def test_gap_and_supplement_by_a_model(spark):
    asked = Asked(spark, [(filled("gap", question="what is it", answer="short"), "Yes, it does."), (filled("explain", question="what is it", answer="short"), "longer")])
    out = asked.both(lambda m: refine.supplement(refine.flag_missing_reasoning(pairs(spark), m), m))
    assert {r.qid: (r.answer, r.lacks_reasoning) for r in out.collect()} == {"q1": ("longer", True), "q2": ("a long answer", False), "q3": (None, False)}
    counts = {r.role: r.calls for r in usage(spark, asked.cache).collect()}
    assert counts == {"gap": 3, "explain": 1}


def test_defects_by_a_model(spark):
    asked = Asked(spark, [(filled("defects", question="why is it", answer="a long answer"), '["Contradiction", "missing information", "unknown"]')], "[]")
    kept, gone = refine.drop_defective(pairs(spark), asked.model)
    assert {r.qid for r in kept.collect()} == {"q1", "q3"}
    assert [list(r.defects) for r in gone.collect()] == [["contradiction", "missing_information"]]


def test_judge_by_a_model(spark):
    q = spark.createDataFrame([(1, "1:0", ["red", "fox"]), (2, "2:0", ["blue", "sky"])], "doc_id long, id string, words array<string>")
    items = spark.createDataFrame([(7, ["fox", "red"]), (8, ["green"])], "item_id long, words array<string>")
    asked = Asked(spark, [(filled("paraphrase", question="red fox", item="fox red"), "yes")])
    for cascade in (False, True):
        assert {(r.doc_id, r.item_id) for r in decontam.decontaminate(q, items, 2, cascade, model=asked.model).collect()} == {(1, 7)}
    assert usage(spark, asked.cache).first().calls == 4


def test_sampler_and_scorer_by_a_model(spark):
    rows = pairs(spark).where("qid <> 'q3'").withColumn("reference", F.col("answer"))
    replies = [(filled("sample", question="what is it", k=k), f"draw {k}") for k in (1, 2)] + [(filled("score", reference="short", response="draw 1"), "Score: 7"), (filled("score", reference="short", response="draw 2"), "12")]
    asked = Asked(spark, replies, "none")
    got = asked.both(lambda m: select.score_responses(select.sample_responses(rows, 2, m), m))
    assert {(r.qid, r.k, r.score) for r in got.collect()} == {("q1", 1, 7), ("q1", 2, 10), ("q2", 1, None), ("q2", 2, None)}


def test_other_roles_by_a_model(spark):
    rows = pairs(spark).withColumn("dataset", F.when(F.col("qid") == "q2", "B").otherwise("textbook"))
    asked = Asked(spark, [(filled("annotate", question="why is it", answer="a long answer"), "Step 1"), (filled("digitise", page="ref:1"), "page one"), (filled("classify", text="t"), '{"subjects": ["physics"], "level": "university"}')], "x")
    assert {r.qid: r.answer for r in mixture.annotate(rows, model=asked.model).collect()} == {"q1": "short", "q2": "Step 1", "q3": None}
    scans = spark.createDataFrame([(1, "ref:1")], "page_id long, html string")
    assert ingest.digitise(scans, "scan", model=asked.model).first().text == "page one"
    with pytest.raises(ValueError, match="no backend"):
        ingest.digitise(scans, "scan")
    books = spark.createDataFrame([(1, "t"), (2, "u")], "book_id long, text string")
    assert {r.book_id: (list(r.subjects), r.level) for r in ingest.classify(books, asked.model).collect()} == {1: (["physics"], "university"), 2: ([], None)}


def test_recipe_asks_its_model(spark):
    books = spark.createDataFrame([(1, ["physics"])], "book_id long, subjects array<string>")
    chunks = spark.createDataFrame([(1, 0, "one")], "book_id long, chunk_no int, text string")
    items = spark.createDataFrame([(7, ["unlike"])], "item_id long, words array<string>")
    listed = json.dumps([{"question": "a b c d", "answer": "e f g"}])
    asked = Asked(spark, [(filled("extract_low", text="one"), listed)], "no")
    last = run_textbook(books, chunks, items, Recipe(model=asked.model))[-1]
    assert last[0] == "decontaminate" and [(r.qid, r.answer) for r in last[1].collect()] == [("1:0:0:low", "e f g")]
    assert {r.role for r in usage(spark, asked.cache).collect()} == {"extract_high", "extract_low", "refine", "gap", "defects", "paraphrase"}


def test_prompts_take_any_text(spark):
    df = spark.createDataFrame([("{x} $1",), (None,)], "text string")
    assert [r[0] for r in df.select(prompt("classify")).collect()] == [PROMPTS["classify"].replace("{text}", t) for t in ("{x} $1", "")]
