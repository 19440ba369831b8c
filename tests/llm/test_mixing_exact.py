"""The mixture against its target weights, over many times 1,000 slots."""

from collections import Counter, defaultdict
from fractions import Fraction

import pyarrow.parquet as pq
import pytest
from pyspark.sql import functions as F

from qacurate.llm import mixing


@pytest.mark.parametrize("weights", [{"a": 1.0, "b": 1.0, "c": 1.0}, {"a": 0.7, "b": 0.0001, "c": 0.1, "d": 0.3}, {"a": 5000**0.5, "b": 7**0.5}])
def test_schedule_stays_within_a_block_of_the_weights(weights):
    blocks = {s: max(1, int(12_000 * w / sum(weights.values()))) for s, w in weights.items()}
    names, table = mixing.exact_schedule(weights, blocks)
    total = sum(map(Fraction, weights.values()))
    done, last = Counter(), -1
    for k, j, slot, release, deadline in table.tolist():
        w = Fraction(weights[names[k]]) / total
        assert release == j // w and deadline == -(-(j + 1) // w) and last < slot and release <= slot < deadline and j == done[k]
        done[k] += 1
        last = slot
        for i, s in enumerate(names):
            if done[i] < blocks[s]:
                assert abs(done[i] - (slot + 1) * Fraction(weights[s]) / total) < 1
    assert {names[k]: n for k, n in done.items()} == blocks


def test_mix_stays_within_a_block_of_the_weights(spark):
    docs = spark.range(9000).select(F.col("id").alias("doc_id"), F.concat(F.lit("s"), F.col("id") % 3).alias("source"))
    rows = mixing.mix(docs, dict.fromkeys(("s0", "s1", "s2"), 1.0), block=2).collect()
    assert len(rows) == 9000 and max(r.slot for r in rows) == 4499
    assert all(r.block_no == r.slot // 3 and (r.release_slot, r.deadline_slot) == (3 * r.block_no, 3 * r.block_no + 3) for r in rows)


def test_sources_without_weight_come_last(spark):
    names, table = mixing.exact_schedule({"a": 1.0, "b": 0.0, "c": 0.0}, {"a": 3, "b": 1, "c": 1})
    assert [names[k] for k in table[:, 0]] == ["a", "a", "a", "b", "c"]
    with pytest.raises(ValueError):
        mixing.whole_weights({"a": -1.0})


def test_files_follow_the_schedule(spark, tmp_path):
    docs = spark.range(6000).select(F.col("id").alias("doc_id"), F.concat(F.lit("s"), F.col("id") % 3).alias("source"), F.concat(F.lit("text "), "id").alias("text")).repartition(5)
    docs = docs.union(spark.createDataFrame([(None, "s1", "x"), (None, "s1", "y"), (7, "s1", "z"), (7, "s1", "z")], "doc_id long, source string, text string"))
    weights = {"s0": 4.0, "s1": 2.0, "s2": 1.0}
    mixing.interleave(docs, weights, block=4).write.parquet(str(tmp_path / "mixed"))
    order = [r for f in sorted((tmp_path / "mixed").glob("part-*.parquet")) for r in pq.read_table(f).to_pylist()]
    assert Counter((r["doc_id"], r["text"]) for r in order) == Counter((r.doc_id, r.text) for r in docs.collect())
    placed = mixing.mix(docs, weights, block=4).collect()
    at = defaultdict(set)
    for r in placed:
        at[r.doc_id].add((r.slot, r.in_block))
    known = [next(iter(at[r["doc_id"]])) for r in order if len(at[r["doc_id"]]) == 1]
    assert known == sorted(known) and len(known) > 5990
    on = [r.source for r in placed if r.on_target]
    share = Counter(on)
    assert len(on) > 3000 and all(abs(share[s] / len(on) - w / 7) < 0.005 for s, w in weights.items())
    assert all(r.source == "s2" for r in placed if r.slot > max(x.slot for x in placed if x.source != "s2"))


def test_query_has_uneven_targets(spark, sf):
    from qacurate.llm.queries import LLM, TARGETS

    assert len(set(TARGETS.values())) > 1
    rows = LLM.queries["op1_mix_pfair"](spark, sf).where("on_target").collect()
    slots = {(r.source, r.slot) for r in rows}
    done = Counter(s for s, _ in slots)
    total = sum(TARGETS[s] for s in {r.source for r in rows})
    assert all(abs(done[s] - len(slots) * TARGETS[s] / total) < 1 + 1e-9 for s in done)
