"""Near copies by SimHash fingerprints and covering locality-sensitive hashing.

Bit i of a fingerprint gets a vector m(i) of radius + 1 bits. Table v (any such vector but zero)
looks at the bits i whose m(i) has an odd overlap with v. The vectors of up to ``radius`` differing
bits cannot span all dimensions, so some v overlaps evenly with all of them: in that table the two
fingerprints agree. Every pair within the radius thus meets in some table, with certainty.

Equal fingerprints are one class from the start. A bucket emits the spanning links of its classes,
not its pairs. A bucket of more than ``most`` classes is split by masks over the bits that its mask left
free, which again loses no pair within the radius. Each split halves the free bits, and classes of f free
bits are 2^f at most: for a radius of 4, buckets of the third level hold 2^8 classes at most, so that the
memory of a task is bounded whatever the fingerprints are. A split deals every row of the bucket out to 31
tables, so the cost of many dense buckets is time and disk, not memory.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from qacurate.llm.text import docs_of, slices, texts
from qacurate.operators.graph import components
from qacurate.staging import Staged, bound_batches

BITS, SEED = 64, 42
_ALL = (1 << BITS) - 1


def fingerprint(text: bytes, width: int = 4) -> int:
    """Majority bits over the hashes of all word shingles, repeats included; no words: zero."""
    words = text.lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = np.concatenate([[0], ends[:-1] + 1])
    ends = ends[min(width, len(words)) - 1 :]
    digest = xxhash.xxh64_intdigest
    n = len(ends)
    hashes = np.fromiter((digest(joined[a:b], SEED) for a, b in zip(starts[:n].tolist(), ends.tolist(), strict=True)), np.uint64, n)
    return majority(hashes)


def majority(hashes: np.ndarray) -> int:
    """The bits that are set in over half of the hashes; no hashes: zero."""
    counts = np.zeros(BITS, np.int64)
    for at in range(0, len(hashes), 8192):
        bits = np.unpackbits(hashes[at : at + 8192].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
        counts += bits.sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * counts > len(hashes), bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, width: int = 4) -> DataFrame:
    """(doc_id, fp) of every row, fp as a signed long."""
    bound_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            got = np.array([fingerprint(t, width) for t in texts(batch.column("text"))], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(got)], names=["doc_id", "fp"])

    return docs_of(docs, "doc_id", "text").mapInArrow(run, "doc_id long, fp long")


def masks(radius: int, free: int = _ALL) -> list[int]:
    """The tables' bit masks over the free bits.

    Odd vectors are dealt out first: any 2^radius of them meet every v in half their number at least, so
    that few free bits are split as well as many; of f free bits a mask holds f - 2^(radius - 1) at least.
    """
    top = (1 << (radius + 1)) - 1
    order = [*range(1, top + 1, 2), *range(2, top + 1, 2)]
    vectors = [(i, order[k % top]) for k, i in enumerate(i for i in range(BITS) if free >> i & 1)]
    return [sum(1 << i for i, m in vectors if (m & v).bit_count() % 2) for v in range(1, top + 1)]


def spanning(fp: np.ndarray, rep: np.ndarray, radius: int, block: int = 2048) -> list[tuple[int, int]]:
    """Links of a spanning forest of the fingerprints within ``radius``, each to the smallest id of its tree."""
    left, links = np.arange(len(fp)), []
    while len(left):
        tree, edge = [left[:1]], left[:1]
        left = left[1:]
        while len(edge) and len(left):
            near = np.zeros(len(left), bool)
            for at in range(0, len(edge), 64):
                part = fp[edge[at : at + 64]]
                for to in range(0, len(left), block):
                    near[to : to + block] |= (np.bitwise_count(part[:, None] ^ fp[left[to : to + block]][None]) <= radius).any(axis=0)
            edge, left = left[near], left[~near]
            tree.append(edge)
        ids = rep[np.concatenate(tree)]
        low = ids.min()
        links += [(int(x), int(low)) for x in ids if x != low]
    return links


def _linker(radius: int, most: int):
    """Streams rows sorted by bucket: links of small buckets, the rows of larger ones for the next level."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray]] = []
        key, size, spilt = None, 0, False
        out: list[tuple] = []

        def close() -> None:
            if not spilt and size > 1:
                fp, rep = (np.concatenate(x) for x in zip(*held, strict=True))
                out.extend((a, b, None, None, None, None) for a, b in spanning(fp, rep, radius))

        for batch in batches:
            g, t, k = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("g", "t", "k"))
            free = batch.column("free").to_numpy()
            fp, rep = batch.column("fp").to_numpy().view(np.uint64), batch.column("rep").to_numpy()
            cut = np.flatnonzero((t[1:] != t[:-1]) | (k[1:] != k[:-1]) | (g[1:] != g[:-1])) + 1
            starts, ends = np.concatenate([[0], cut]), np.concatenate([cut, [len(t)]])
            inner = ends - starts > 1
            inner[[0, -1]] = True  # these may go on in the neighbouring batch
            for a, b in zip(starts[inner].tolist(), ends[inner].tolist(), strict=True):
                here = (g[a], t[a], k[a])
                if here != key:
                    close()
                    held, key, size, spilt = [], here, 0, False
                held.append((fp[a:b], rep[a:b]))
                size += b - a
                # A bucket of so few free bits is small, and splitting it might leave all of them free.
                spilt = spilt or (size > most and (int(free[a]) & _ALL).bit_count() > 1 << max(radius - 1, 0))
                if spilt:
                    name = f"{here[0]}/{here[1]}:{here[2]}"
                    left = int(free[a])
                    out.extend((None, None, name, left, x, y) for f, r in held for x, y in zip(f.view(np.int64).tolist(), r.tolist(), strict=True))
                    held = []
            if len(out) > 20_000:
                yield _rows(out)
                out = []
        close()
        yield _rows(out)

    return run


def _dealer(radius: int):
    """Rows of split buckets, once for each mask over the bits that are free; ``free`` is what each mask leaves."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known: dict[int, np.ndarray] = {}
        for batch in batches:
            for at in range(0, batch.num_rows, 4096):
                part = batch.slice(at, 4096)
                free = part.column("free").to_numpy().view(np.uint64)
                for f in np.unique(free).tolist():
                    if f not in known:
                        known[f] = np.array(masks(radius, f), np.uint64)
                table = np.array([known[f] for f in free.tolist()])
                n, width = table.shape
                rows = np.repeat(np.arange(n), width)
                fp = part.column("fp").to_numpy().view(np.uint64)
                dealt = part.select(["g", "fp", "rep"]).take(pa.array(rows))
                yield pa.RecordBatch.from_arrays([*dealt.columns, pa.array(np.tile(np.arange(width, dtype=np.int32), n)), pa.array((table & fp[:, None]).ravel().view(np.int64)), pa.array((free[:, None] & ~table).ravel().view(np.int64))], names=["g", "fp", "rep", "t", "k", "free"])

    return run


_LINKS = pa.schema([("a", pa.int64()), ("b", pa.int64()), ("g", pa.string()), ("free", pa.int64()), ("fp", pa.int64()), ("rep", pa.int64())])


def _rows(out: list[tuple]) -> pa.RecordBatch:
    columns = zip(*out, strict=True) if out else ([] for _ in _LINKS)
    return pa.RecordBatch.from_arrays([pa.array(list(c), f.type) for c, f in zip(columns, _LINKS, strict=True)], schema=_LINKS)


def links(classes: DataFrame, radius: int = 4, most: int = 2048) -> DataFrame:
    """(a, b): enough links between the ``rep`` of classes (fp, rep) to connect all within the radius."""
    keys = F.array(*[F.struct(F.lit(t).alias("t"), F.col("fp").bitwiseAND(F.lit(_signed(m))).alias("k"), F.lit(_signed(_ALL & ~m)).alias("free")) for t, m in enumerate(masks(radius))])
    dealt, found = classes.select(F.lit("").alias("g"), "fp", "rep", F.inline(keys)), []
    for level in range(BITS):
        near = dealt.repartition("g", "t", "k").sortWithinPartitions("g", "t", "k")
        out = Staged(near.select("g", "t", "k", "free", "fp", "rep").mapInArrow(_linker(radius, most), "a long, b long, g string, free long, fp long, rep long"), f"links-{level}").df
        found.append(out.where("a is not null").select("a", "b"))
        rows = out.where("g is not null").select("g", "free", "fp", "rep")
        if rows.isEmpty():
            break
        dealt = rows.mapInArrow(_dealer(radius), "g string, fp long, rep long, t int, k long, free long")
    all_ = found[0]
    for part in found[1:]:
        all_ = all_.union(part)
    return all_


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def near_classes(docs: DataFrame, radius: int = 4, width: int = 4) -> DataFrame:
    """(doc_id, fingerprint, component_id): the smallest doc_id reachable by links of ``radius`` bits or fewer.

    One row per input row. Null and empty texts have the fingerprint zero and link like others. Rows
    without an id have a fingerprint, take the component of their class and name none. Only doc_id
    and text are read.
    """
    prints = Staged(fingerprints(docs, width), "fingerprints").df
    classes = Staged(prints.groupBy("fp").agg(F.min("doc_id").alias("rep")), "classes").df
    found = components(links(classes.where("rep is not null"), radius))
    named = classes.join(found, F.col("rep") == F.col("node"), "left").select("fp", F.coalesce("component", "rep").alias("component_id"))
    return prints.join(named, "fp", "left").select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def drop_near_copies(docs: DataFrame, radius: int = 4, width: int = 4) -> DataFrame:
    """The input with the smallest id of each group; ids are taken to be unique, rows without one stay."""
    gone = near_classes(docs, radius, width).where("doc_id <> component_id").select("doc_id")
    return docs.join(gone, "doc_id", "left_anti").select(docs.columns)
