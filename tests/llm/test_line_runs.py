"""Line alignment against all pairs that share a line."""

import random

from hypothesis import given, settings
from hypothesis import strategies as st
from test_llm_operators import aligned_brute

from qacurate.llm import line_alignment


@given(st.lists(st.integers(1, 25), max_size=12), st.integers(0, 11), st.integers(1, 12))
@settings(max_examples=200, deadline=None)
def test_runs_cover_every_block(words, start, n):
    block = range(start, min(start + n, len(words)))
    if len(block) and sum(words[k] for k in block) >= 20:
        runs = [r for r in line_alignment.least_runs(words, words, 20) if r[0] in block and r[1] in block]
        assert {k for a, b in runs for k in range(a, b + 1)} == set(block)
    assert all(sum(words[a : b + 1]) >= 20 for a, b in line_alignment.least_runs(words, words, 20))


def test_common_lines_miss_no_block(spark):
    rng = random.Random(4)
    pool = [" ".join(f"v{rng.randrange(60)}" for _ in range(rng.choice((3, 8, 15, 22)))) for _ in range(12)]
    rows = [(i, "\n".join(rng.choice(pool) if rng.random() < 0.6 else f"own {i} {k} words" for k in range(rng.randint(1, 14))), "s") for i in range(120)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(3)
    got = {r.doc_id: list(r.removed) for r in line_alignment.align_lines(df, 20).collect()}
    want = aligned_brute(rows, 20, 10**9)
    assert got == want and aligned_brute(rows, 20, line_alignment.RARE) != want
