"""Quality rules by compression: zstandard ratios over whole documents and fixed chunks.

A text that compresses far better than prose of its length repeats itself; one that hardly
compresses is noise or encoded data. Short texts compress worse, so the limits depend on length.
"""

from __future__ import annotations

import bisect
import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame

from qacurate.llm.text import BLANKS, docs_of, slices, texts
from qacurate.staging import bound_batches

_SYMBOLS = b"#*$%&|<>"
_NOT_FIRST = bytes(range(0x80, 0xC0))
#: Bytes, least ratio, largest ratio at that length; between two lengths the limits follow the logarithm
#: of the length. The least ratios lie 0.02 to 0.04 below those of labelled good texts of the given tables.
BANDS = (
    (128, 0.50, 1.20),
    (256, 0.49, 0.95),
    (512, 0.48, 0.86),
    (1024, 0.455, 0.78),
    (2048, 0.435, 0.72),
    (4096, 0.42, 0.68),
    (8192, 0.40, 0.66),
    (16384, 0.385, 0.65),
    (32768, 0.37, 0.65),
    (65536, 0.36, 0.65),
    (1048576, 0.28, 0.65),
)
SCHEMA = (
    "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, "
    "base_failed boolean, kept boolean, n_bytes long, ratio double, n_chunks long, bad_chunk_share double"
)


@dataclass(frozen=True)
class Bands:
    """level: of zstandard. chunk: bytes. most_bad: share of bytes in chunks outside their band from which a text goes."""

    bands: tuple[tuple[int, float, float], ...] = BANDS
    level: int = 3
    chunk: int = 4096
    most_bad: float = 0.3

    def limits(self, size: int) -> tuple[float, float]:
        """The least and the largest ratio of a text of so many bytes; below the first length of the bands any ratio will do."""
        at = bisect.bisect_right(self.bands, size, key=lambda x: x[0])
        if at == 0:
            return 0.0, math.inf
        least, low, high = self.bands[at - 1]
        if at == len(self.bands):
            return low, high
        upto, low2, high2 = self.bands[at]
        share = math.log(size / least) / math.log(upto / least)
        return low + share * (low2 - low), high + share * (high2 - high)

    def within(self, size: int, ratio: float) -> bool:
        low, high = self.limits(size)
        return low <= ratio <= high


def repeated_words(words: list[bytes]) -> int:
    """Words that lie in a run of three words found twice or more."""
    runs = list(zip(words, words[1:], words[2:], strict=False))
    if len(set(runs)) == len(runs):
        return 0
    seen = Counter(runs)
    total = end = 0
    for i, run in enumerate(runs):
        if seen[run] > 1:
            total += i + 3 - max(end, i)
            end = i + 3
    return total


def measures(text: bytes, rule: Bands, packer: zstandard.ZstdCompressor) -> tuple:
    words = text.split()
    lines = [x for x in text.split(b"\n") if x.strip()]
    repeated = repeated_words(words)
    n, size = len(words), len(text)
    failed = n < 50 or 100 * repeated > 50 * n
    ratio = len(packer.compress(text)) / size if size else 0.0
    chunks = [text[i : i + rule.chunk] for i in range(0, size, rule.chunk)]
    bad = sum(len(c) for c in chunks if not rule.within(len(c), len(packer.compress(c)) / len(c))) if size > rule.chunk else 0
    share = bad / size if size else 0.0
    return (
        n,
        len(text.translate(None, BLANKS + _NOT_FIRST)),
        size - len(text.translate(None, _SYMBOLS)),
        len(lines) - len(set(lines)),
        repeated,
        failed,
        not failed and rule.within(size, ratio) and share < rule.most_bad,
        size,
        ratio,
        len(chunks),
        share,
    )


def compression_bands(docs: DataFrame, rule: Bands = Bands()) -> DataFrame:
    """One row per input row: the counts, whether the base rules fail, and whether the text is kept.

    Null and empty texts have no words, so they fail the base rules. Repeated rows give repeated rows;
    a null doc_id stays null; further columns of the input are not read. No shuffle: each text is
    judged alone, so the cost is one scan whatever the keys.
    """
    bound_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packer = zstandard.ZstdCompressor(level=rule.level)
        for batch in slices(batches):
            columns = zip(*(measures(t, rule, packer) for t in texts(batch.column("text"))), strict=True)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *map(pa.array, columns)], names=NAMES)

    return docs_of(docs, "doc_id", "text").mapInArrow(run, SCHEMA)


NAMES = [x.split()[0] for x in SCHEMA.split(", ")]
