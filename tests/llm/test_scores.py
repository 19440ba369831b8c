"""Scores of the line model and of the chain, worked out again by plain loops, and awkward rows."""

import itertools
import math
from collections import Counter

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from qacurate.llm import quality_crf, toxicity_chain

CLASH = ("score", "held_out", "p_rude", "predicted", "buckets", "label")
TEXTS = ["one line of plain words here", "first line of it\nand a second\n\n  \nthird, with 7 marks!", "$$$ ### 12 34\nBUY NOW !!!\nbuy now !!!", "vile words\nmore vile words", "long " * 30_000, "", None, " \n\t"]


def awkward_rows(spark):
    rows = [(i, t) for i, t in enumerate(TEXTS)] + [(None, TEXTS[1]), (None, None), (3, TEXTS[3]), (3, TEXTS[3]), (90, TEXTS[0])]
    return rows, spark.createDataFrame(rows, "doc_id long, text string").withColumns({c: F.lit("x") for c in CLASH}).repartition(3)


def line_model():
    rng = np.random.default_rng(4)
    good = [("the river runs past the old mill and on to the sea " * 2 + "\n") * k for k in range(1, 9)]
    bad = ["$$ ## 99 !!\n" * k + "CLICK CLICK\n" for k in range(1, 9)]
    rows = [quality_crf.line_features(t.encode()) for t in good + bad]
    bounds = np.concatenate([[0], np.cumsum([len(s) for _, s in rows])])
    own = np.concatenate([a for a, _ in rows])
    return quality_crf.train(own + rng.normal(0, 0.05, own.shape), np.concatenate([s for _, s in rows]), bounds, np.array([1.0] * 8 + [0.0] * 8), rounds=60)


def score_brute(text, model):
    own, sizes = quality_crf.line_features((text or "").encode())
    if not len(own):
        mean = 0.5
    else:
        none = np.zeros_like(own[0])
        emit = []
        for k in range(len(own)):
            x = np.concatenate([own[k], own[k - 1] if k else none, own[k + 1] if k + 1 < len(own) else none, [k == 0, k + 1 == len(own), 1]])
            emit.append(float(((x - model.mean) / model.scale) @ model.weight))
        weights = {w: math.exp(sum(e * y for e, y in zip(emit, w, strict=True)) + sum(model.trans[x, y] for x, y in zip(w, w[1:], strict=False))) for w in itertools.product((0, 1), repeat=len(own))}
        whole = sum(weights.values())
        good = [sum(v for w, v in weights.items() if w[k]) / whole for k in range(len(own))]
        mean = sum(s * g for s, g in zip(sizes, good, strict=True)) / sum(sizes)
    mean = min(max(mean, 1e-6), 1 - 1e-6)
    return 1 / (1 + math.exp(-(model.slope * math.log(mean / (1 - mean)) + model.shift)))


def test_quality_by_enumeration(spark):
    rows, df = awkward_rows(spark)
    model = line_model()
    got = quality_crf.score(df, model).collect()
    want = Counter((i, round(score_brute(t, model), 6)) for i, t in rows)
    assert Counter((r.doc_id, round(r.score, 6)) for r in got) == want
    assert all(r.predicted == (r.score >= 0.3) and (r.doc_id is not None or not r.held_out) for r in got)
    assert {r.score for r in got if r.doc_id in (5, 6, 7)} == {score_brute("", model)} or len({round(r.score, 9) for r in got if r.doc_id in (5, 6, 7)}) == 1
    kept = quality_crf.keep_good(df, model)
    assert kept.columns == df.columns
    assert Counter(r.doc_id for r in kept.collect()) == Counter(r.doc_id for r in got if r.predicted)
    assert quality_crf.score(df.limit(0), model).count() == quality_crf.keep_good(df.limit(0), model).count() == 0


def chain():
    f = toxicity_chain.Features()
    texts = [f"word{i} other{i % 7} " + ("vile " if i % 3 == 0 else "kind ") + ("threat" if i % 6 == 0 else "calm") for i in range(240)]
    labels = np.array([[int(i % 3 == 0), int(i % 6 == 0)] for i in range(240)])
    return toxicity_chain.train([f.of(t.encode()) for t in texts], labels, ("rude", "severe"))


def chain_brute(text, links):
    buckets = set()
    for word in (text or "").encode().split():
        w = word.lower().strip(b".,;:!?\"'()[]{}<>|*#-_")
        if w:
            parts = [b"w" + w] + [b"p" + w[:n] for n in (4, 5, 6) if len(w) > n]
            buckets |= {xxhash.xxh32_intdigest(p) >> (32 - toxicity_chain.BITS) for p in parts}
    odds = []
    for link in links:
        odds.append(sum(float(link.weight[b]) for b in buckets) + sum(float(e) * o for e, o in zip(link.earlier, odds, strict=True)) + link.shift)
    return [1 / (1 + math.exp(-min(max(o, -40), 40))) for o in odds]


def test_chain_by_plain_loops(spark):
    rows, df = awkward_rows(spark)
    fitted = chain()
    got = toxicity_chain.score(df, fitted, ("rude", "severe"), "severe").collect()
    want = Counter((i, *(round(p, 5) for p in chain_brute(t, fitted.links))) for i, t in rows)
    assert Counter((r.doc_id, round(r.p_rude, 5), round(r.p_severe, 5)) for r in got) == want
    assert all(r.score == r.p_severe and r.predicted == (r.score >= 0.5) for r in got)
    assert toxicity_chain.score(df.limit(0), fitted, ("rude", "severe"), "severe").count() == 0
    assert fitted.links[1].earlier.shape == (1,) and fitted.links[1].earlier[0] != 0


@pytest.mark.parametrize("rows", [[], [(None, 1)], [(1, None)]])
def test_labels_that_say_nothing(spark, rows):
    _, df = awkward_rows(spark)
    labels = spark.createDataFrame(rows, "doc_id long, quality int")
    assert quality_crf.fit(df, labels) is None
    assert toxicity_chain.fit(df, labels.withColumnRenamed("quality", "rude"), ("rude",)) is None
