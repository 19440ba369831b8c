"""Byte-level text helpers that run inside Arrow batches.

Words are runs of bytes other than the six ASCII blanks (space and 0x09-0x0D), which is exactly what
``bytes.split()`` does; ``bytes.lower()`` changes A-Z only. Null texts count as empty.
"""

from __future__ import annotations

import sys
from collections.abc import Callable, Iterator
from typing import TypeVar

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

T = TypeVar("T")
BLANKS = b" \t\n\x0b\x0c\r"


def texts(column: pa.Array) -> list[bytes]:
    return [b"" if t is None else t for t in column.cast(pa.binary()).to_pylist()]


def docs_of(df: DataFrame, *columns: str) -> DataFrame:
    """The named columns only: ``text`` with nulls as empty, ``doc_id`` as long; extra columns never reach Python."""
    shape = {"text": F.coalesce(F.col("text"), F.lit("")).alias("text"), "doc_id": F.col("doc_id").cast("long").alias("doc_id")}
    return df.select(*[shape.get(c, F.col(c)) for c in columns])


def free_names(df: DataFrame, *names: str) -> list[str]:
    """The names, lengthened by underscores until the table has none of them."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out


def per_process(name: str, make: Callable[[], T]) -> T:
    """What ``make`` makes, once for all tasks of a Python worker. For caches: results must not depend on it."""
    held = sys.__dict__.setdefault("_held_per_process", {})
    if name not in held:
        held[name] = make()
    return held[name]


class WordHashes(dict):
    """Word to 64-bit hash, remembered; forgets everything when it has grown to ``most`` words."""

    def __init__(self, seed: int = 0, most: int = 400_000) -> None:
        self.seed, self.most = seed, most

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.most:
            self.clear()
        h = self[word] = xxhash.xxh64_intdigest(word, self.seed)
        return h

    def of(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), dtype=np.uint64, count=len(words))


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit reaches every output bit."""
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xFF51AFD7ED558CCD)
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


def window_hashes(words: np.ndarray, width: int, base: int) -> np.ndarray:
    """A hash of every run of ``width`` consecutive word hashes."""
    n = len(words) - width + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    out, step = np.zeros(n, np.uint64), np.uint64(base | 1)
    for j in range(width):
        out *= step
        out += words[j : j + n]
    return mix(out)


def slices(batches: Iterator[pa.RecordBatch], column: str = "text", most: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """Cuts batches so that one slice holds about ``most`` bytes of text at most, or one row."""
    for batch in batches:
        size = batch.column(column).cast(pa.binary()).nbytes
        rows = max(1, batch.num_rows * most // max(size, 1))
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)
