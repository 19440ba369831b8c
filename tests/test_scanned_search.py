"""Searches that scan the items: no row for each pair, any number of items and questions, the cells that planes make."""

import numpy as np
from oracle import difference

from qacurate.operators import knn
from qacurate.queries import REGISTRY


def _plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def _tables(spark, n=400, width=8):
    rng = np.random.default_rng(4)
    v = rng.integers(-2, 3, (n, width)).astype(float)  # whole numbers: many ties, and some vectors of zeros
    v[5] = 0
    rows = [(i, [float(x) for x in v[i]]) for i in range(n)]
    m = spark.createDataFrame(rows[::-1], "item_id long, vec array<double>").repartition(3)
    return v, spark.createDataFrame(rows[: n // 4], "id long, vec array<double>"), m


def _want(v, n, k, may):
    norms = np.linalg.norm(v, axis=1)
    with np.errstate(invalid="ignore"):
        s = np.round((v[:n] @ v.T) / (norms[:n, None] * norms[None]), 6)
    out = set()
    for i in range(n):
        order = sorted((j for j in range(len(v)) if may[i, j]), key=lambda j: (-s[i, j] if s[i, j] == s[i, j] else 9, j))[:k]
        out |= {(i, j, r + 1) for r, j in enumerate(order)}
    return out


def _got(df):
    return {(r.id, r.item_id, r["rank"]) for r in df.collect()}


def test_scan_meets_all_items_in_bounded_parts(spark, monkeypatch):
    v, q, m = _tables(spark)
    monkeypatch.setattr(knn, "BROADCAST_ROWS", 10)  # that many items at most went to every executor
    monkeypatch.setattr(knn, "QUESTION_BYTES", 8 * 8 * 30)
    monkeypatch.setattr(knn, "_PART", 64)
    found = knn.topk_exact(q, m, 7)
    assert "Join" not in _plan(found) and _got(found) == _want(v, 100, 7, np.ones((100, 400), bool))


def test_planes_compare_the_items_of_their_cells(spark):
    v, q, m = _tables(spark)
    normals = np.random.default_rng(7).standard_normal((4, 5, 8))
    cell = (np.einsum("tpw,nw->ntp", normals, v) > 0) @ (1 << np.arange(5))
    found = knn.topk_lsh(q, m, 7, planes=5, tables=4, width=8)
    assert "Join" not in _plan(found) and _got(found) == _want(v, 100, 7, (cell[:100, None] == cell[None]).any(axis=2))


def test_no_questions_find_nothing(spark):
    _, q, m = _tables(spark)
    assert knn.topk_exact(q.limit(0), m).count() == knn.topk_lsh(q, m.limit(0), width=8).count() == 0


def test_topk_exact_gives_what_its_sql_gives(spark):
    sf = "/root/testdata/sf0.01"
    assert difference(REGISTRY.queries["topk_exact"](spark, sf), REGISTRY.oracles["topk_exact"], sf) == ""
