"""Queries that once made their data up read the given tables; the fixed cases of answers and chat records stay as tests."""

import json

import pytest
from pyspark.sql import functions as F

from qacurate.operators import answers as A
from qacurate.queries import REGISTRY
from qacurate.sources import tables as T

READS = {
    "part": ("ablation_delta", "answer_indicator", "answer_unwrap", "best_second", "category_averages", "eval_registry", "gain_vs_baseline"),
    "conversations": ("chat_source",),
    "documents": ("decontam_delta", "overlong_bounds"),
}
#: Texts and what each step makes of them.
CASES = (
    ("The final answer is \\boxed{42}.", "\\boxed{42}.", "42"),
    ("Hence the correct answer is **B**", "**B**", "B"),
    ("First the answer is 3.\nThen the final answer is 4.", "4.", "4"),
    ("Answer: $\\mathrm{12 kg}$", "$\\mathrm{12 kg}$", "12 kg"),
    ("The final answer to this question is (C).", "(C).", "(C)"),
    ("The answer is \\boxed{\\mathbf{7/2}}", "\\boxed{\\mathbf{7/2}}", "7/2"),
    ("Nothing here", None, None),
)


@pytest.mark.parametrize(("table", "name"), [(t, n) for t, names in READS.items() for n in names])
def test_reads_its_table(spark, sf, table, name):
    assert any(f"/{table}.parquet" in x for x in REGISTRY.queries[name](spark, sf).inputFiles())


def test_overlong_bounds_has_both_sides(spark, sf):
    got = {(r.n, r.kept) for r in REGISTRY.queries["overlong_bounds"](spark, sf).collect()}
    assert {(4096, True), (4097, False)} <= got and all(kept == (n <= 4096) for n, kept in got)


def test_answer_cases(spark):
    said = A.find_indicator(F.col("text"))
    got = spark.createDataFrame([(k, x) for k, (x, _, _) in enumerate(CASES)], "k int, text string").select("k", said.alias("said"), A.unwrap(said).alias("value"))
    assert {(r.k, r.said, r.value) for r in got.collect()} == {(k, b, c) for k, (_, b, c) in enumerate(CASES)}


def test_chat_source_of_hand_made_records(spark):
    spark.dataSource.register(T.ChatSource)
    records = [json.dumps({"qid": "q1", "messages": [{"role": "user", "content": "Why?"}, {"role": "assistant", "content": "Because."}]}), json.dumps({"qid": "q2", "messages": [{"role": "user", "content": "How?"}]})]
    want = {("q1", 0, "user", "Why?"), ("q1", 1, "assistant", "Because."), ("q2", 0, "user", "How?")}
    assert {tuple(r) for r in spark.read.format("chat").option("records", json.dumps(records)).load().collect()} == want
    assert {tuple(r) for r in T.read_records(spark.createDataFrame([(x,) for x in records], "record string")).collect()} == want
