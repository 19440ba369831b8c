"""Near copies by covering SimHash, checked and completed by the Jaccard similarity of word shingles.

Candidates come from two sources, and an exact Jaccard of the shingles decides about each. The covering
tables of ``simhash_cover`` give every pair of fingerprints within their radius. A similarity of 0.8 lets
some 10 of 64 bits differ, though, and tables that cover so many bits would hold too few bits each to part
anything. MinHash finds those pairs: 32 bands of 4 least values, which a pair of similarity s misses with
probability (1 - s^4)^32, 5e-8 at 0.8 and less above it. Large buckets are linked without pairing them
(``linking_edges``). Texts of equal words are one class from the start. Shingles move only for rows that
are in a candidate pair.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from qacurate.llm.simhash_cover import links, majority
from qacurate.llm.text import WordHashes, docs_of, mix, slices, texts, window_hashes
from qacurate.operators.graph import components
from qacurate.operators.minhash import linking_edges, verify
from qacurate.staging import Staged, bound_batches

BANDS, ROWS, BASE = 32, 4, 0x9E3779B97F4A7C15
MOST_WORDS = 50_000  # whose hashes a task holds; a Python worker keeps none between tasks
_RNG = np.random.default_rng(20)
_TIMES = _RNG.integers(0, 1 << 64, (BANDS * ROWS, 1), np.uint64) | np.uint64(1)
_PLUS = _RNG.integers(0, 1 << 64, (BANDS * ROWS, 1), np.uint64)


def shingles(words: list[bytes], width: int = 5, known: WordHashes | None = None) -> np.ndarray:
    """Hashes of the runs of ``width`` words, repeats included; fewer words are one run. known: hashes met before."""
    if not words:
        return np.empty(0, np.uint64)
    known = WordHashes() if known is None else known
    return window_hashes(known.of(words), min(width, len(words)), BASE)


def band_keys(shingles: np.ndarray) -> np.ndarray:
    low = np.full(BANDS * ROWS, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(shingles), 512):
        np.minimum(low, (shingles[None, at : at + 512] * _TIMES + _PLUS).min(axis=1), out=low)
    key = np.zeros(BANDS, np.uint64)
    for column in low.reshape(BANDS, ROWS).T:
        key = mix(key * np.uint64(BASE) + column)
    return key


def _signed(docs: DataFrame, width: int) -> DataFrame:
    """(id, same, fp, keys): digest of the words, fingerprint and band keys of every row with an id."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = WordHashes(most=MOST_WORDS)
        for batch in slices(batches):
            split = [t.lower().split() for t in texts(batch.column("text"))]
            same = [xxhash.xxh3_128_digest(b" ".join(w)) for w in split]
            prints, keys = np.zeros(len(split), np.uint64), []
            for k, w in enumerate(split):
                runs = shingles(w, width, known)
                prints[k] = majority(runs)
                keys.append(band_keys(np.unique(runs)).view(np.int64) if w else [])
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(same, pa.binary()), pa.array(prints.view(np.int64)), pa.array(keys, pa.list_(pa.int64()))], names=["id", "same", "fp", "keys"])
        pa.default_memory_pool().release_unused()

    return docs_of(docs, "doc_id", "text").where("doc_id is not null").mapInArrow(run, "id long, same binary, fp long, keys array<long>")


def _sets(docs: DataFrame, width: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = WordHashes(most=MOST_WORDS)
        for batch in slices(batches):
            sets = [np.unique(shingles(t.lower().split(), width, known)).view(np.int64) for t in texts(batch.column("text"))]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(sets, pa.list_(pa.int64()))], names=["id", "hset"])
        pa.default_memory_pool().release_unused()

    return docs.mapInArrow(run, "id long, hset array<long>")


def _covering_pairs(own: DataFrame, radius: int) -> DataFrame:
    """(a, b): spanning links of the rows whose fingerprints are equal or within the radius."""
    prints = Staged(own.groupBy("fp").agg(F.min("id").alias("rep")), "near-prints").df
    equal = own.select("id", "fp").join(prints, "fp").where("id <> rep").select(F.col("rep").alias("a"), F.col("id").alias("b"))
    return equal.union(links(prints, radius).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")))


def near_groups(docs: DataFrame, threshold: float = 0.8, width: int = 5, most: int = 8, radius: int = 4) -> DataFrame:
    """(doc_id, component_id) of every row with an id: the smallest doc_id reachable by links of ``threshold`` or more.

    Words are lower-cased in ASCII. Texts without a word (null ones too) are one group. ids are taken to be
    unique. most: rows of a bucket that are paired among each other. radius: of the covering tables.
    """
    bound_batches(docs.sparkSession)
    signed = Staged(_signed(docs, width), "near-signatures").df
    classes = Staged(signed.groupBy("same").agg(F.min("id").alias("rep")), "near-classes").df
    own = signed.join(classes.select(F.col("rep").alias("id")), "id", "left_semi").where(F.size("keys") > 0)
    banded = Staged(own.select("id", F.posexplode("keys").alias("band", "key")), "near-bands").df
    shared = banded.groupBy("band", "key").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    met = Staged(banded.join(shared, ["band", "key"], "left_semi"), "near-buckets").df
    covered = Staged(_covering_pairs(own, radius), "near-covered").df
    asked = met.select(F.col("id").alias("doc_id")).union(covered.select("a")).union(covered.select("b")).distinct()
    sets = Staged(_sets(docs_of(docs, "doc_id", "text").join(asked, "doc_id", "left_semi"), width), "near-sets").df
    edges = linking_edges(met, sets, threshold, most).union(verify(covered, sets, threshold).select("a", "b"))
    found = components(edges)
    named = Staged(classes.join(found, F.col("rep") == F.col("node"), "left").select("same", F.coalesce("component", "rep").alias("component_id")), "near-names").df
    return signed.join(named, "same").select(F.col("id").alias("doc_id"), "component_id")


def drop_near_copies(docs: DataFrame, threshold: float = 0.8, width: int = 5) -> DataFrame:
    """The input with the smallest id of each group; ids are taken to be unique, rows without one stay."""
    gone = near_groups(docs, threshold, width).where("doc_id <> component_id").select("doc_id")
    return docs.join(gone, "doc_id", "left_anti").select(docs.columns)
