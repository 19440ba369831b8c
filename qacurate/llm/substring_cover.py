"""Repeated word windows, found by difference-cover anchors.

A difference cover D modulo p holds, for any two positions, a shift below p that puts both into D. So
two equal windows of ``width`` words share an equal sub-window of ``width - p + 1`` words that starts at
a position in D in both documents. Only those sub-windows, the anchors, are hashed and dealt out
(4 of 13 positions). Anchors found twice are then extended: every full window around one is compared
with all equal windows by two 64-bit hashes over the same 64-bit hashes of its words, and the earliest of
them stays. Two words of one hash would thus count as equal, in otherwise equal windows.

Rows dealt out are bounded by the words read: nothing pairs documents. Copies of a whole document, by
md5 of the text, are settled by their first copy. A window or anchor that occurs everywhere sends one row per slice of text.
"""

from __future__ import annotations

import hashlib
import itertools
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from qacurate.llm.text import WordHashes, docs_of, slices, texts, window_hashes
from qacurate.staging import Staged, bound_batches

#: Perfect difference covers by period.
COVERS = {7: (0, 1, 3), 13: (0, 1, 3, 9)}
_BASES = (0x9E3779B97F4A7C15, 0xD1B54A32D192ED03, 0x8CB92BA72F3D8DD7)
_LAST = (1 << 63) - 1
BUCKET_BYTES = 8 << 20
SCHEMA = "doc_id long, n_words long, n_removed long, kept_sha256 string, cut_from array<int>, cut_to array<int>"
_NAMES = ["doc_id", "n_words", "n_removed", "kept_sha256", "cut_from", "cut_to"]
_OUT = pa.schema(list(zip(_NAMES, [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.list_(pa.int32()), pa.list_(pa.int32())], strict=True)))


def _anchors(x: np.ndarray, place: np.ndarray, room: np.ndarray, width: int, period: int) -> tuple[np.ndarray, np.ndarray]:
    """Positions and hashes of the anchors; place: of a word in its document; room: words from there to its end."""
    short = width - period + 1
    hashes = window_hashes(x, short, _BASES[0])
    n = len(hashes)
    at = np.flatnonzero(np.isin(np.arange(period), COVERS[period])[place[:n] % period] & (room[:n] >= short))
    return at, hashes[at]


def _layout(sizes: list[int]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Document number, place and room of every word."""
    sizes_ = np.array(sizes, np.int64)
    doc = np.repeat(np.arange(len(sizes)), sizes_)
    place = np.arange(len(doc)) - np.repeat(np.cumsum(sizes_) - sizes_, sizes_)
    return doc, place, np.repeat(sizes_, sizes_) - place


def _emit_anchors(width: int, period: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = WordHashes(1)
        for batch in slices(batches):
            words = [t.split() for t in texts(batch.column("text"))]
            long_ = [i for i, w in enumerate(words) if len(w) >= width]
            doc, place, room = _layout([len(words[i]) for i in long_])
            x = known.of(list(itertools.chain.from_iterable(words[i] for i in long_)))
            at, h = _anchors(x, place, room, width, period)
            bucket = batch.column("bucket").to_numpy()[long_][doc[at]] if len(at) else np.empty(0, np.int32)
            order = np.lexsort((bucket, h))
            h, bucket = h[order], bucket[order]
            new = np.ones(len(h), bool)
            new[1:] = (h[1:] != h[:-1]) | (bucket[1:] != bucket[:-1])
            starts = np.flatnonzero(new)
            many = np.diff(np.append(starts, len(h))) > 1
            yield pa.RecordBatch.from_arrays([pa.array(h[starts].view(np.int64)), pa.array(bucket[starts].astype(np.int32)), pa.array(many)], names=["h", "bucket", "many"])

    return run


def _found_twice(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of rows sorted by h, those whose h occurs again."""
    held = np.empty(0, np.int64), np.empty(0, np.int32), np.empty(0, bool)
    open_ = False  # the held row's h occurred before
    for batch in itertools.chain(batches, [None]):
        if batch is not None:
            now = [batch.column(c).to_numpy(zero_copy_only=False) for c in ("h", "bucket", "many")]
            h, bucket, many = (np.concatenate(x) for x in zip(held, now, strict=True))
        else:
            h, bucket, many = held
        if not len(h):
            continue
        same = h[1:] == h[:-1]
        again = many.copy()
        again[1:] |= same
        again[:-1] |= same
        again[0] |= open_
        end = len(h) if batch is None else len(h) - 1
        open_ = bool(same[-1]) if len(same) else open_
        held = h[end:], bucket[end:], many[end:]
        keep = np.flatnonzero(again[:end])
        yield pa.RecordBatch.from_arrays([pa.array(bucket[keep]), pa.array(h[keep])], names=["bucket", "id"])


_STEP = pa.schema([("kind", pa.int8()), ("doc_id", pa.int64()), ("start", pa.int32()), ("w1", pa.int64()), ("w2", pa.int64()), ("text", pa.binary()), ("starts", pa.binary()), ("n_words", pa.int64()), ("n_removed", pa.int64()), ("kept_sha256", pa.string())])
_STEP_DDL = "kind tinyint, doc_id long, start int, w1 long, w2 long, text binary, starts binary, n_words long, n_removed long, kept_sha256 string"


def _step(n: int, **columns) -> pa.RecordBatch:
    arrays = [pa.array(columns[f.name], f.type) if f.name in columns else pa.nulls(n, f.type) for f in _STEP]
    return pa.RecordBatch.from_arrays(arrays, schema=_STEP)


def _extend(width: int, period: int):
    """Streams buckets: their repeated anchors, then their copies, then their texts in order of id."""

    def one(batch: pa.RecordBatch, anchors: np.ndarray, copies: set[int], known: WordHashes) -> Iterator[pa.RecordBatch]:
        ids, words = batch.column("id").to_pylist(), [t.split() for t in texts(batch.column("text"))]
        raw = batch.column("text").cast(pa.binary()).to_pylist()
        read = [i for i, w in enumerate(words) if len(w) >= width and ids[i] not in copies]
        doc, place, room = _layout([len(words[i]) for i in read])
        x = known.of(list(itertools.chain.from_iterable(words[i] for i in read)))
        at, h = _anchors(x, place, room, width, period)
        at = at[np.isin(h, anchors)] if len(anchors) else at[:0]
        change = np.zeros(len(x) + 1, np.int32)  # a window may start up to period - 1 words before an anchor
        np.add.at(change, at - np.minimum(place[at], period - 1), 1)
        np.add.at(change, at + 1, -1)
        start = np.flatnonzero((np.cumsum(change)[:-1] > 0) & (room >= width))
        touched: dict[int, list[np.ndarray]] = {}
        if len(start):
            w1, w2 = window_hashes(x, width, _BASES[1])[start], window_hashes(x, width, _BASES[2])[start]
            order = np.lexsort((start, w2, w1))
            first = np.ones(len(order), bool)
            first[1:] = (w1[order][1:] != w1[order][:-1]) | (w2[order][1:] != w2[order][:-1])
            place_of, id_of = place[start[order]], np.array([ids[i] for i in read], np.int64)[doc[start[order]]]
            head = np.flatnonzero(first)[np.cumsum(first) - 1]
            later = (place_of != place_of[head]) | (id_of != id_of[head])  # a row that repeats an id is no later one
            kept, gone = np.sort(order[first]), np.sort(start[order[later]])
            s = start[kept]
            yield _step(len(s), kind=np.zeros(len(s), np.int8), doc_id=np.array([ids[i] for i in read], np.int64)[doc[s]], start=place[s].astype(np.int32), w1=w1[kept].view(np.int64), w2=w2[kept].view(np.int64))
            for d in np.unique(doc[start]).tolist():
                touched[read[d]] = place[gone[np.searchsorted(gone, np.searchsorted(doc, d)) : np.searchsorted(gone, np.searchsorted(doc, d, side="right"))]]
        some = sorted(touched)
        if some:
            yield _step(len(some), kind=np.ones(len(some), np.int8), doc_id=[ids[i] for i in some], text=[raw[i] for i in some], starts=[touched[i].astype("<i4").tobytes() for i in some])
        rest = [i for i in range(len(ids)) if i not in touched]
        whole = [len(words[i]) if ids[i] in copies and len(words[i]) >= width else 0 for i in rest]
        digests = [hashlib.sha256(b"" if gone_ else b" ".join(words[i])).hexdigest() for i, gone_ in zip(rest, whole, strict=True)]
        yield _step(len(rest), kind=np.full(len(rest), 2, np.int8), doc_id=[ids[i] for i in rest], n_words=[len(words[i]) for i in rest], n_removed=whole, kept_sha256=digests)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, bucket = WordHashes(1), None
        parts: list[np.ndarray] = []
        anchors, copies = np.empty(0, np.uint64), set()
        for batch in batches:
            bs, kinds = batch.column("bucket").to_numpy(), batch.column("kind").to_numpy()
            cut = [0, *(np.flatnonzero((bs[1:] != bs[:-1]) | (kinds[1:] != kinds[:-1])) + 1).tolist(), len(bs)]
            for a, b in zip(cut, cut[1:], strict=False):
                part = batch.slice(a, b - a)
                if bs[a] != bucket:
                    bucket, parts, anchors, copies = bs[a], [], np.empty(0, np.uint64), set()
                if kinds[a] == 0:
                    parts.append(np.unique(part.column("id").to_numpy()))
                elif kinds[a] == 1:
                    copies.update(part.column("id").to_pylist())
                else:
                    if parts:
                        anchors, parts = np.unique(np.concatenate(parts)).view(np.uint64), []
                    for piece in slices(iter([part]), most=2 << 20):
                        yield from one(piece, anchors, copies, known)

    return run


def _not_first(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of rows sorted by window, document and start: those that are not the earliest of their window."""
    last = None
    for batch in batches:
        w1, w2, doc, start = (batch.column(c).to_numpy() for c in ("w1", "w2", "doc_id", "start"))
        if not len(w1):
            continue
        new = np.ones(len(w1), bool)
        new[1:] = (w1[1:] != w1[:-1]) | (w2[1:] != w2[:-1])
        if last is not None and (w1[0], w2[0]) == last[:2]:
            new[0] = False
        head = np.flatnonzero(new)
        run = np.cumsum(new) - 1  # -1: goes on from the batch before
        low_doc, low_start = (np.append(v[head], last[k] if last else 0) for k, v in ((2, doc), (3, start)))
        gone = np.flatnonzero(~new & ((doc != low_doc[run]) | (start != low_start[run])))
        last = (w1[-1], w2[-1], low_doc[run[-1]], low_start[run[-1]])
        yield pa.RecordBatch.from_arrays([pa.array(doc[gone]), pa.array(start[gone])], names=["doc_id", "start"])


def _finish(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            rows = []
            for text, own, more in zip(texts(batch.column("text")), batch.column("starts").to_pylist(), batch.column("more").to_pylist(), strict=True):
                words = text.split()
                starts = np.concatenate([np.frombuffer(own or b"", "<i4"), np.array(more or [], np.int64)]).astype(np.int64)
                change = np.zeros(len(words) + 1, np.int64)
                np.add.at(change, starts, 1)
                np.add.at(change, np.minimum(starts + width, len(words)), -1)
                keep = np.cumsum(change)[:-1] == 0
                edge = np.flatnonzero(np.diff(np.concatenate([[True], keep, [True]]).astype(np.int8)))
                kept = b" ".join(itertools.compress(words, keep.tolist()))
                rows.append((len(words), int((~keep).sum()), hashlib.sha256(kept).hexdigest(), edge[0::2].tolist(), edge[1::2].tolist()))
            columns = zip(*rows, strict=True) if rows else ([] for _ in _NAMES[1:])
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(list(c), f.type) for c, f in zip(columns, list(_OUT)[1:], strict=True))], schema=_OUT)

    return run


def remove_repeats(docs: DataFrame, width: int = 20, period: int = 13, bucket_bytes: int = BUCKET_BYTES) -> DataFrame:
    """One row per input row: word counts, digest of the words that stay, and the word spans cut out.

    A word goes if a window of ``width`` words that covers it also starts earlier: in a smaller doc_id,
    or before in the same document; windows are judged on the input. Null texts have no words. A null
    doc_id counts as larger than any. A doc_id names one document: rows that repeat it are the same
    document, and what is cut by its id is cut in each of them. Only doc_id and text are read.
    """
    spark = docs.sparkSession
    bound_batches(spark)
    source = docs_of(docs, "doc_id", "text").withColumn("id", F.coalesce("doc_id", F.lit(_LAST)))
    base = Staged(source.select("id", F.unhex(F.md5(F.col("text").cast("binary"))).alias("same"), F.octet_length("text").alias("size")), "substring-base").df
    total = base.agg(F.sum("size")).first()[0] or 0
    bucket = F.pmod(F.xxhash64("id"), F.lit(math.ceil(total / bucket_bytes) or 1)).cast("int").alias("bucket")

    # Written before the join, whose large partitions (a group of copies) Spark then splits.
    first = Staged(base.groupBy("same").agg(F.min("id").alias("first"), F.count(F.lit(1)).alias("n")).where("n > 1"), "first-copies").df
    copies = base.join(first, "same").where("id <> first").select("id")
    dealt = source.select("id", "text", bucket).mapInArrow(_emit_anchors(width, period), "h long, bucket int, many boolean")
    twice = dealt.repartition("h").sortWithinPartitions("h").mapInArrow(_found_twice, "bucket int, id long")

    none = F.lit(None).cast("binary").alias("text")
    kinds = [
        twice.select("bucket", F.lit(0).cast("byte").alias("kind"), "id", none),
        copies.select(bucket, F.lit(1).cast("byte").alias("kind"), "id", none),
        source.select(bucket, F.lit(2).cast("byte").alias("kind"), "id", F.col("text").cast("binary").alias("text")),
    ]
    met = kinds[0].union(kinds[1]).union(kinds[2]).repartition("bucket").sortWithinPartitions("bucket", "kind", "id")
    step = Staged(met.mapInArrow(_extend(width, period), _STEP_DDL), "substring-step").df

    windows = step.where("kind = 0").select("w1", "w2", "doc_id", "start")
    later = windows.repartition("w1", "w2").sortWithinPartitions("w1", "w2", "doc_id", "start").mapInArrow(_not_first, "doc_id long, start int")
    starts = later.groupBy("doc_id").agg(F.collect_list("start").alias("more"))
    open_ = step.where("kind = 1").select("doc_id", "text", "starts").join(starts, "doc_id", "left")
    cut = open_.select("doc_id", "text", "starts", "more").mapInArrow(_finish(width), SCHEMA)
    spans = [F.when(F.col("n_removed") > 0, F.array(x.cast("int"))).otherwise(F.array().cast("array<int>")).alias(n) for n, x in (("cut_from", F.lit(0)), ("cut_to", F.col("n_removed")))]
    done = step.where("kind = 2").select("doc_id", "n_words", "n_removed", "kept_sha256", *spans)
    return done.unionByName(cut).withColumn("doc_id", F.when(F.col("doc_id") != _LAST, F.col("doc_id")))


ORACLE = r"""
with w as (
  select doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') as ws from documents
), s as (
  select doc_id, i, list_slice(ws, i + 1, i + 20) as win from w, unnest(range(0, greatest(len(ws) - 19, 0))) as u(i)
), d as (
  select doc_id, i from s qualify row_number() over (partition by win order by doc_id, i) > 1
), c as (
  select distinct doc_id, i + j as p from d, unnest(range(0, 20)) as u(j)
), g as (select doc_id, list(p) as gone from c group by doc_id)
select w.doc_id, len(ws)::bigint as n_words, coalesce(len(gone), 0)::bigint as n_removed,
  sha256(coalesce(array_to_string(list_filter(ws, lambda x, k: not list_contains(coalesce(gone, []), k - 1)), ' '), '')) as kept_sha256
from w left join g using (doc_id)
"""
