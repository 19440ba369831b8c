"""How the plan of a block is made: solved combinations, few cuts, and their effect on whole tables."""

import random
from collections import Counter, defaultdict

from qacurate.llm import packing
from qacurate.llm.queries import LLM


def test_ways_can_fill_a_window():
    ways = packing.ways_of(16, 3)
    assert (1, 16) in ways and (5, 6, 7) in ways and (8, 8) not in ways and all(1 < len(w) <= 3 for w in ways)


def test_a_sequence_cuts_one_tail_at_most():
    rng = random.Random(1)
    sizes = [rng.choice((3, 90, 700, 2047, 2048, 5000)) + rng.randrange(400) for _ in range(700)]
    out, rest = packing.plan(sizes, 2048, 32, packing.ways_of(64, 3))
    parts = defaultdict(list)
    for _, s in out:
        assert sum(p[2] for p in s) == 2048
        assert sum(at + n != sizes[d] and at % 2048 + n < 2048 for d, at, n in s) <= 1
        for d, at, n in s:
            parts[d].append((at, n))
    for d, at, n in rest:
        parts[d].append((at, n))
    for d, n in enumerate(sizes):
        at = 0
        for a, k in sorted(parts[d]):
            assert a == at
            at += k
        assert at == n
    assert sum(p[2] for p in rest) < 2048
    made = Counter(k for k, _ in out)
    assert made["combination"] > 20


def test_fewer_pieces_than_by_laying_end_to_end(spark):
    rows = LLM.queries["op4_pack_nnls"](spark, "/root/testdata/sf0.1").select("doc_id", "length", "doc_tokens", "made", "sequence_id").collect()
    size = {r.doc_id: r.doc_tokens for r in rows}
    least = sum(-(-n // 2048) for n in size.values())
    plain = len(size) + sum(size.values()) // 2048
    assert len(rows) < least + 0.1 * (plain - least)
    assert max(Counter(r.doc_id for r in rows if r.doc_tokens < 2048).values()) < 8
    made = Counter(k for k, _ in {(r.made, r.sequence_id) for r in rows})
    assert made["combination"] > 0.2 * sum(made.values())
