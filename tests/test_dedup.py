"""Deduplication: keep-rules, components, band solver, recall, edge cases."""

import hashlib
import itertools
import random

import pytest
from pyspark.sql import functions as F

from qacurate.functions.text import shingles
from qacurate.operators import minhash as M
from qacurate.operators.graph import components


def _components(pairs):
    parent = {}

    def find(x):
        parent.setdefault(x, x)
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in pairs:
        x, y = find(a), find(b)
        parent[max(x, y)] = min(x, y)
    return {x: find(x) for x in list(parent)}


@pytest.mark.parametrize("edges", [[(1, 2), (2, 3), (5, 4)], [(i, i + 1) for i in range(60)], [(0, i) for i in range(1, 50)], []])
def test_components(spark, edges):
    df = spark.createDataFrame([*edges, *[(a, a) for a, _ in edges[:1]]], "a long, b long")
    got = {r.node: r.component for r in components(df).collect()}
    assert got == _components(edges)


def test_components_random(spark):
    rng = random.Random(3)
    edges = [(rng.randrange(200), rng.randrange(200)) for _ in range(150)]
    got = {r.node: r.component for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    want = _components([e for e in edges if e[0] != e[1]])
    assert got == want


def test_greedy_is_insertion_order(spark):
    edges = [(1, 2, 1.0), (2, 3, 1.0), (3, 4, 1.0), (2, 9, 1.0), (5, 6, 1.0)]
    got = {r.keep for r in M.greedy_cover(spark.createDataFrame(edges, "a long, b long, similarity double")).collect()}
    kept = []
    adjacent = {(a, b) for a, b, _ in edges}
    for i in range(1, 10):
        if not any((k, i) in adjacent for k in kept):
            kept.append(i)
    assert got == {b for _, b, _ in edges if b not in kept}


def test_bands():
    bands, rows = M.solve_bands(0.6, 128)
    assert bands * rows <= 128 and abs((1 / bands) ** (1 / rows) - 0.6) < 0.1
    assert M.candidate_probability(0.6) > 0.98 and M.candidate_probability(0.3) < 0.25


def test_edge_texts(spark):
    rows = [(1, None), (2, ""), (3, "one"), (4, "..."), (5, "One!"), *[(k, "same words in every one of these rows here") for k in range(10, 40)], (50, "w " * 20000)]
    df = spark.createDataFrame(rows, "id long, text string")
    got = {r.id: r.keep_id for r in M.minhash_dedup(df, "id", "text").collect()}
    assert len(got) == len(rows)
    assert got[5] == 3 and got[2] == 1 and got[4] == 1 and got[50] == 50
    assert {got[k] for k in range(10, 40)} == {10}
    assert M.minhash_dedup(df.limit(0), "id", "text").count() == 0


def test_partition_count_does_not_matter(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select(F.col("doc_id").alias("id"), "text")
    runs = [{(r.id, r.keep_id) for r in M.minhash_dedup(docs.repartition(n), "id", "text").collect()} for n in (1, 7)]
    assert runs[0] == runs[1]


def test_exact_join_equals_brute_force(spark):
    rng = random.Random(1)
    rows = [(i, " ".join(rng.sample("abcdefghij", rng.randint(1, 8)))) for i in range(80)]
    sets = spark.createDataFrame(rows, "id long, text string").select("id", shingles("text").alias("set"))
    words = {i: set(t.split()) for i, t in rows}
    want = {(a, b) for a, b in itertools.combinations(sorted(words), 2) if len(words[a] & words[b]) / len(words[a] | words[b]) >= 0.6}
    assert {(r.a, r.b) for r in M.exact_similarity_join(sets).collect()} == want
    assert {(r.a, r.b) for r in M.jaccard_bruteforce(sets).collect()} == want


def test_large_buckets_keep_their_components(spark):
    rng = random.Random(4)
    rows = []
    for g in range(3):
        base = [f"g{g}w{k}" for k in range(60)]
        for i in range(60):
            words = [w if rng.random() > 0.12 else f"n{g}.{i}.{w}" for w in base]
            rows.append((g * 100 + i, " ".join(words)))
    df = spark.createDataFrame(rows, "id long, text string")
    runs = [{(r.id, r.keep_id) for r in M.minhash_dedup(df, "id", "text", most=m).collect()} for m in (2, 5, 10_000)]
    assert runs[0] == runs[1] == runs[2] and len({k for _, k in runs[0]}) < 60


def test_greedy_reaches_the_end_of_a_long_chain(spark):
    edges = spark.createDataFrame([(i, i + 1) for i in range(40)], "a long, b long")
    assert {r.keep for r in M.greedy_cover(edges).collect()} == set(range(1, 41, 2))
    assert M.greedy_cover(edges.limit(0)).count() == 0


def test_large_bucket_of_rows_that_are_not_alike(spark):
    """One bucket of 3,000 rows with 5 near copies in it: found, and hardly any other pair is made."""
    rng = random.Random(6)
    rows = [(i, [rng.randrange(1 << 40) for _ in range(30)] + [7]) for i in range(3000)]
    for k in range(5):
        rows.append((5000 + k, [*rows[100 * k][1][:-2], rng.randrange(1 << 40), 7]))
    sets = spark.createDataFrame(rows, "id long, hset array<long>")
    banded = sets.select("id", F.lit(0).alias("band"), F.lit("k").alias("key"))
    assert {(r.a, r.b) for r in M.linking_edges(banded, sets, 0.8, 64).collect()} == {(100 * k, 5000 + k) for k in range(5)}
    assert M.prefix_candidates(sets, 0.8).count() < 50


def test_signatures_do_not_depend_on_batches(spark):
    rng = random.Random(2)
    rows = [(i, [f"w{rng.randrange(5000)}" for _ in range(rng.choice((0, 1, 7, 9000)))]) for i in range(40)] + [(90, None)]
    df = spark.createDataFrame(rows, "id long, set array<string>")
    got = {r.id: r.signature for r in M.minhash(df, num_perm=8).collect()}
    pairs = M.coefficients(8)
    for i, words in rows:
        if not words:
            assert got[i] is None
            continue
        codes = [(int(hashlib.md5(w.encode()).hexdigest()[:8], 16) & M.PRIME) % M.PRIME for w in words]
        assert got[i] == [min((a * x + b) % M.PRIME for x in codes) for a, b in pairs]


def test_sketches_drop_what_cannot_reach_the_threshold_only(spark):
    """A bucket of sets of 1 to 900 members, in one tile and in many: no pair at the threshold is lost, few others are left."""
    rng = random.Random(5)
    rows = [(0, [])]
    for g in range(12):
        base = [rng.randrange(-(1 << 62), 1 << 62) for _ in range((1, 2, 5, 30, 200, 900)[g % 6])]
        for k in range(8):
            rows.append((len(rows), [x if rng.random() > 0.04 * k else rng.randrange(1 << 62) for x in base]))
    sets = spark.createDataFrame(rows, "id long, hset array<long>")
    banded = sets.select("id", F.lit(0).alias("band"), F.lit("k").alias("key"))
    for threshold in (0.3, 0.6, 0.8):
        want = {(a, b) for (a, x), (b, y) in itertools.combinations(rows[1:], 2) if len({*x} & {*y}) >= threshold * len({*x} | {*y})}
        for tile in (10, 512):
            got = {(r.a, r.b) for r in M.sketched_pairs(banded, sets, threshold, tile).collect()}
            assert want <= got
            assert threshold < 0.6 or len(got) < 2 * len(want) + 50 < len(rows) ** 2 / 4


def test_planted_curve_moves_no_words(spark, sf):
    """One pass over the planted copies: no join carries their words, and the curve rises as expected."""
    from qacurate.queries import REGISTRY

    df = REGISTRY.queries["planted_curve"](spark, sf)
    assert "Join" not in df._jdf.queryExecution().optimizedPlan().toString()
    rows = {r.bin: r for r in df.collect()}
    assert rows[max(rows)].found == 1.0 and rows[min(rows)].found < 0.5
