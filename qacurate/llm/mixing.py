"""Mixing sources to target weights by Pfair scheduling.

A source's documents are dealt into blocks. Block j of a source of weight w may be placed from slot
floor(j / w), its release, and before slot ceil((j + 1) / w), its deadline. Taking in every slot the
released block with the earliest deadline keeps each source within one block of its share at any time.

Weights are exact rationals, and releases and deadlines follow from them over the whole length of the
schedule: nothing is rounded that would add up. The driver schedules the blocks that exist, one step per
block of ``block`` documents; an ended source takes no steps. Windows of the blocks that remain are met as
before, since leaving blocks out of a schedule by earliest deadline delays no other. ``on_target`` marks the
slots before a source's first missing block is released: up to there the mixture has the target weights,
behind it those of the sources that remain. A document's block follows from its rank within its source. The rank is a count over hash buckets of a source plus a position
within a bucket, so a source with any share of the rows never meets in one task.

A caller may ask for a repeated schedule instead: weights are then rounded to fractions k / K with one K,
and the schedule of K slots repeats. Its deviation from the weights grows with the number of periods.
"""

from __future__ import annotations

import heapq
from collections.abc import Mapping
from fractions import Fraction
from math import lcm

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

RANK_BUCKETS = 4096
MOST_SOURCES = 10_000
BROADCAST_BLOCKS = 1_000_000
MOST_BLOCKS = 20_000_000


def fractions(weights: Mapping[str, float], period: int) -> dict[str, int]:
    """Whole numbers, 1 at least, in proportion to the weights; they sum up to ``period``."""
    names = sorted(weights)
    total = sum(weights[s] for s in names)
    exact = {s: (weights[s] / total if total > 0 else 1 / len(names)) * period for s in names}
    out = {s: max(1, int(exact[s])) for s in names}
    order = sorted(names, key=lambda s: (out[s] - exact[s], s))
    k = 0
    while (gap := period - sum(out.values())) != 0:
        s = order[k % len(order)] if gap > 0 else max(names, key=lambda n: (out[n] - exact[n] if out[n] > 1 else -period, n))
        out[s] += 1 if gap > 0 else -1
        k += 1
    return out


def schedule(shares: Mapping[str, int], period: int) -> list[tuple[str, int, int, int, int]]:
    """(source, block of the period, slot, release, deadline) of one period, by earliest deadline first."""
    coming = sorted((j * period // k, -((-(j + 1) * period) // k), s, j) for s, k in shares.items() for j in range(k))
    ready: list[tuple[int, str, int, int]] = []
    out, at = [], 0
    for slot in range(period):
        while at < len(coming) and coming[at][0] <= slot:
            release, deadline, s, j = coming[at]
            heapq.heappush(ready, (deadline, s, j, release))
            at += 1
        deadline, s, j, release = heapq.heappop(ready)
        out.append((s, j, slot, release, deadline))
    return out


def whole_weights(weights: Mapping[str, float]) -> dict[str, int]:
    """Whole numbers in exactly the proportions of the weights."""
    exact = {s: Fraction(w) for s, w in weights.items()}
    if min(exact.values(), default=0) < 0:
        raise ValueError("a weight is below zero")
    scale = lcm(*(w.denominator for w in exact.values()))
    return {s: int(w * scale) for s, w in exact.items()}


def exact_schedule(weights: Mapping[str, float], blocks: Mapping[str, int]) -> tuple[list[str], np.ndarray]:
    """(sources, rows of (source's number, block, slot, release, deadline)) of all blocks, by earliest deadline first.

    Sources without weight follow after the last slot of the others, in equal shares.
    """
    names = sorted(weights)
    whole = whole_weights(weights)
    out = np.empty((sum(blocks[s] for s in names), 5), np.int64)
    n = start = 0
    for part in ([k for k, s in enumerate(names) if whole[s]], [k for k, s in enumerate(names) if not whole[s]]):
        own = {k: whole[names[k]] or 1 for k in part}
        total = sum(own.values())
        coming = [(0, k, 0) for k in part if blocks[names[k]]]
        ready: list[tuple[int, int, int, int]] = []
        slot = 0
        while coming or ready:
            if not ready:
                slot = max(slot, coming[0][0])
            while coming and coming[0][0] <= slot:
                release, k, j = heapq.heappop(coming)
                heapq.heappush(ready, (-(-(j + 1) * total // own[k]), k, j, release))
            deadline, k, j, release = heapq.heappop(ready)
            out[n] = k, j, start + slot, start + release, start + deadline
            n, slot = n + 1, slot + 1
            if j + 1 < blocks[names[k]]:
                heapq.heappush(coming, ((j + 1) * total // own[k], k, j + 1))
        start += slot
    return names, out


def target_slots(weights: Mapping[str, float], blocks: Mapping[str, int]) -> int:
    """The slots in which no source of a weight lacks a released block."""
    whole = whole_weights(weights)
    total = sum(whole.values())
    return min((blocks[s] * total // w for s, w in whole.items() if w), default=0)


def mix(docs: DataFrame, weights: Mapping[str, float] | None = None, temper: float = 0.5, block: int = 64, period: int | None = None) -> DataFrame:
    """(doc_id, source, block_no, in_block, slot, release_slot, deadline_slot, on_target) of every row.

    weights: target weight of each source; a source that is not named has the least weight given.
    Without weights they are the sources' row counts to the power ``temper``. Every document keeps a
    place: where a source has ended its slots stay empty and the others go on. period: slots of a
    schedule to repeat, by rounded weights; without it the weights hold exactly. A null source is a
    source of its own, shown as null. Rows that repeat an id have a rank each, in no fixed order among
    themselves; null ids rank first. Only doc_id and source are read. No rows: no rows.
    """
    return _mixed(docs, weights, temper, block, period)[0]


def _mixed(docs: DataFrame, weights: Mapping[str, float] | None, temper: float, block: int, period: int | None, whole: bool = False) -> tuple[DataFrame, int]:
    """What ``mix`` returns, and the number of places of its blocks. whole: with each block's place among those that
    exist, ``place_no``, and the rows themselves as the struct ``row``."""
    spark = docs.sparkSession
    carried = [F.struct(*docs.columns).alias("row")] if whole else []
    ties = [F.xxhash64("row.text")] if whole and "text" in docs.columns else []
    rows = docs.select("doc_id", *carried, F.coalesce(F.concat(F.lit("="), "source"), F.lit("")).alias("name"), F.pmod(F.xxhash64("doc_id"), F.lit(RANK_BUCKETS)).alias("bucket"))
    counts = rows.groupBy("name", "bucket").agg(F.count(F.lit(1)).alias("n"))
    sources = {r.name: r.n for r in counts.groupBy("name").agg(F.sum("n").alias("n")).limit(MOST_SOURCES + 1).collect()}
    if len(sources) > MOST_SOURCES:
        raise ValueError(f"more than {MOST_SOURCES} sources: group them first")
    if sum(sources.values()) > MOST_BLOCKS * block:
        raise ValueError(f"more than {MOST_BLOCKS} blocks for the driver to schedule: choose larger blocks")
    if weights is None:
        target = {s: n**temper for s, n in sources.items()}
    else:
        least = min(weights.values(), default=1.0)
        target = {s: weights.get(s[1:], least) if s else least for s in sources}

    before = F.sum("n").over(Window.partitionBy("name").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1))
    offsets = counts.select("name", "bucket", F.coalesce(before, F.lit(0)).alias("ahead"))
    place = F.row_number().over(Window.partitionBy("name", "bucket").orderBy("doc_id", *ties)) - 1
    held = ["doc_id", "name", *["row"] * whole]
    ranked = rows.select(*held, "bucket", place.alias("place")).join(offsets, ["name", "bucket"])
    ranked = ranked.select(*held, (F.col("ahead") + F.col("place")).alias("rank"))
    dealt = ranked.select(*held, F.expr(f"rank div {block}").alias("block_no"), (F.col("rank") % block).alias("in_block"))
    blocks = {s: -(-n // block) for s, n in sources.items()}
    if period is None:
        slots, upto, size = _slots(spark, target, blocks)
        placed = dealt.join(slots, ["name", "block_no"])
    else:
        placed, upto, size = _repeated(dealt, target, blocks, max(period, 4 * len(sources)))
    out = placed.select(
        "doc_id",
        F.when(F.col("name") != "", F.expr("substring(name, 2)")).alias("source"),
        "block_no",
        "in_block",
        "slot",
        "release_slot",
        "deadline_slot",
        (F.col("slot") < upto).alias("on_target"),
        *["place_no", "row"] * whole,
    )
    return out, size


def _slots(spark: SparkSession, target: Mapping[str, float], blocks: Mapping[str, int]) -> tuple[DataFrame, int, int]:
    names, table = exact_schedule(target, blocks)
    keys = pa.DictionaryArray.from_arrays(pa.array(table[:, 0]), pa.array(names, pa.string())).cast(pa.string())
    columns = dict(zip(("block_no", "slot", "release_slot", "deadline_slot"), (pa.array(c) for c in table[:, 1:].T), strict=True))
    slots = spark.createDataFrame(pa.table({"name": keys, **columns, "place_no": pa.array(np.arange(len(table)))}))
    return F.broadcast(slots) if len(table) <= BROADCAST_BLOCKS else slots, target_slots(target, blocks), len(table)


def _repeated(dealt: DataFrame, target: Mapping[str, float], blocks: Mapping[str, int], period: int) -> tuple[DataFrame, int, int]:
    spark = dealt.sparkSession
    shares = fractions(target, period) if target else {}
    table = schedule(shares, period) if target else []
    slots = F.broadcast(spark.createDataFrame([(s, shares[s], *x) for s, *x in table], "name string, own int, turn long, slot0 long, release0 long, deadline0 long"))
    own = F.broadcast(spark.createDataFrame(list(shares.items()), "name string, own int"))
    met = dealt.join(own, "name").withColumns({"turn": F.expr("block_no % own"), "from": F.expr(f"block_no div own * {period}")})
    placed = met.join(slots.drop("own"), ["name", "turn"]).withColumns({b: F.col("from") + F.col(a) for a, b in (("slot0", "slot"), ("release0", "release_slot"), ("deadline0", "deadline_slot"))})
    placed = placed.withColumn("place_no", F.col("slot"))
    periods = max((-(-n // shares[s]) for s, n in blocks.items()), default=0)
    return placed, target_slots(shares, blocks), periods * period


def interleave(docs: DataFrame, weights: Mapping[str, float] | None = None, temper: float = 0.5, block: int = 64, period: int | None = None) -> DataFrame:
    """The input in mixed order: partition k holds the k-th run of blocks, sorted, so that files in the order
    of their names are the schedule and as large as each other. Options and edge cases are those of ``mix``; every row stays, once.
    """
    placed, size = _mixed(docs, weights, temper, block, period, whole=True)
    n = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    part = F.floor(F.col("place_no") * n / F.lit(max(size, 1))).cast("int")
    return placed.select("place_no", "slot", "in_block", "row").repartitionById(n, part).sortWithinPartitions("slot", "in_block").select("row.*")
