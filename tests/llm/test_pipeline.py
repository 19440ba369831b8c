"""The pipeline against plain Python on the smallest tables."""

from collections import Counter

import corpus_pipeline
import numpy as np
from pyspark.sql import functions as F
from test_llm_operators import check_packed
from test_near_jaccard import groups_brute

from qacurate.llm import quality_crf


def test_stages_by_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    texts = {r.doc_id: r.text for r in docs.collect()}
    model = quality_crf.fit(docs, spark.read.parquet(f"{sf}/labels.parquet"))
    good = {}
    for i, t in texts.items():
        own, sizes = quality_crf.line_features((t or "").encode())
        if len(sizes) and model.scores(own, sizes, np.array([0, len(sizes)]))[0] < 0.3:
            continue
        good[i] = t
    low = {}
    for i in sorted(good, reverse=True):
        low.setdefault("".join(c.lower() if "A" <= c <= "Z" else c for c in good[i] or ""), i)
    unique = {i: good[i] for i in low.values()}
    want = {i: unique[i] for i in set(groups_brute(unique.items()).values())}
    assert check_packed(corpus_pipeline.run(spark, sf).collect(), sorted(want.items())) == 0


def test_stage_columns_and_edges(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").limit(60)
    odd = docs.withColumns({"extra": F.lit(1), "id": F.lit("x"), "slot": F.lit(2)}).unionByName(spark.createDataFrame([(None, None, None, None, None, 1, "x", 2), (-1, "", None, None, None, 1, "x", 2)], "doc_id long, text string, lang string, source string, n_chars long, extra int, id string, slot int"))
    for table in (odd, odd.limit(0)):
        kept = table
        for _, step in corpus_pipeline.STAGES[:-1]:
            kept = step(spark, kept, sf)
            assert kept.columns == odd.columns
        assert kept.count() <= table.count()
    name, last = corpus_pipeline.STAGES[-1]
    assert name == "pack" and last(spark, odd.limit(0), sf).count() == 0
    mixed = dict(corpus_pipeline.STAGES)["mix"](spark, docs, sf)
    assert Counter(r.doc_id for r in mixed.collect()) == Counter(r.doc_id for r in docs.collect())
