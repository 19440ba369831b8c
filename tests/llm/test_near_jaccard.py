"""The pipeline's near stage against all pairs of the table."""

import itertools
import random

import corpus_pipeline
import pytest
from pyspark.sql import functions as F

from qacurate.llm import near_jaccard


def groups_brute(rows, threshold=0.8, width=5):
    sets = {}
    for i, t in rows:
        words = (t or "").encode().lower().split()
        sets[i] = frozenset(tuple(words[k : k + width]) for k in range(max(1, len(words) - width + 1)))
    name = {i: i for i in sets}

    def find(x):
        while name[x] != x:
            x = name[x]
        return x

    for a, b in itertools.combinations(sorted(sets), 2):
        if abs(len(sets[a]) - len(sets[b])) <= 0.2 * max(len(sets[a]), len(sets[b])) and len(sets[a] & sets[b]) >= threshold * len(sets[a] | sets[b]) - 1e-12:
            x, y = find(a), find(b)
            name[max(x, y)] = min(x, y)
    return {i: find(i) for i in sets}


def test_near_stage_has_every_pair(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    want = groups_brute([(r.doc_id, r.text) for r in docs.collect()])
    assert sum(i != g for i, g in want.items()) > 9
    kept = dict(corpus_pipeline.STAGES)["near"](spark, docs, "")
    assert kept.columns == docs.columns and {r.doc_id for r in kept.select("doc_id").collect()} == set(want.values())


@pytest.mark.parametrize("most", [2, 8])
def test_large_groups_and_edges(spark, most):
    rng = random.Random(3)
    base = [f"w{rng.randrange(900)}" for _ in range(300)]
    rows = [(0, None), (1, ""), (2, " \n"), (3, "one"), (4, "ONE "), (5, "a b c"), (6, "c b a")]
    for i in range(10, 90):
        words = list(base)
        for _ in range(rng.choice((1, 3, 6, 12))):
            words[rng.randrange(300)] = f"x{i}"
        rows.append((i, " ".join(words)))
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumns({c: F.lit(7) for c in ("id", "same", "band", "key", "rep")}).repartition(3)
    want = groups_brute(rows)
    assert {r.doc_id: r.component_id for r in near_jaccard.near_groups(df, most=most).collect()} == want
    kept = near_jaccard.drop_near_copies(df.union(df.limit(1).withColumn("doc_id", F.lit(None).cast("long"))))
    assert {r.doc_id for r in kept.collect()} == set(want.values()) | {None}
    assert near_jaccard.near_groups(df.limit(0)).count() == 0
