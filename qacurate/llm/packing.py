"""Sequence packing by non-negative least squares over a histogram of lengths.

Documents are tokenised and packed block by block: a block holds up to ``block`` tokens, so memory
does not grow with the input and no text is shuffled. Whole windows of a document fill sequences of
their own. The tails are counted by length class; combinations of up to ``depth`` classes whose members
may fill a window are enumerated, and non-negative least squares finds how often to use each so that the
histogram is used up. Counts are rounded down; each use takes members whose exact lengths sum up to the
window, so nothing is cut. Tails left over are packed greedily, the longest first, and a sequence that no
tails fill to the last token cuts one of them. What does not fill a window goes on to the next block; at
a partition's end it is cut into sequences whose lengths are powers of two.
"""

from __future__ import annotations

import os
import zlib
from array import array
from collections import deque
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from qacurate.llm.text import docs_of, per_process, slices, texts
from qacurate.staging import bound_batches

SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, `offset` long, made string"
_NAMES = ["doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset", "made"]
Piece = tuple[int, int, int]  # document of the block, start, length


_TAIL = b".,;:!?"
_PLAIN = frozenset(b"abcdefghijklmnopqrstuvwxyz0123456789")


class WordIds:
    """Token ids of texts, word by word: the vocabulary ignores case and never joins what a blank parts,
    nor a letter or digit with the punctuation behind it.

    Ids are remembered in two generations of ``most`` words: words met again move to the newer one, and
    the older one is dropped when the newer is full.
    """

    def __init__(self, path: str, most: int = 500_000) -> None:
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer, self.most = Tokenizer.from_file(path), most
        vocabulary = self.tokenizer.get_vocab()
        self.ends = np.zeros(max(vocabulary.values()) + 1, bool)
        self.ends[[i for t, i in vocabulary.items() if t.endswith("</w>")]] = True
        self.known: dict[bytes, bytes] = {}
        self.older: dict[bytes, bytes] = {}

    def _encode(self, words: list[bytes]) -> list[bytes]:
        """Ids of each word. Words of letters alone go through the tokenizer many at a time, as each of
        them ends in one token that marks an end; should the marks not be as many as the words, and for
        all other words, each is encoded alone.
        """
        texts_ = [w.decode("utf-8", "replace") for w in words]
        out: list[bytes | None] = [None] * len(words)
        plain = [i for i, t in enumerate(texts_) if t.isalpha()]
        groups = [plain[at : at + 256] for at in range(0, len(plain), 256)]
        for at in range(0, len(groups), 32):
            some = groups[at : at + 32]
            for group, e in zip(some, self.tokenizer.encode_batch_fast([" ".join(map(texts_.__getitem__, g)) for g in some], add_special_tokens=False), strict=True):
                ids = np.array(e.ids, "<u4")
                ends = ((np.flatnonzero(self.ends[ids]) + 1) * 4).tolist()
                if len(ends) == len(group):
                    packed = ids.tobytes()
                    for i, x, y in zip(group, [0, *ends], ends, strict=False):
                        out[i] = packed[x:y]
        rest = [i for i, ids in enumerate(out) if ids is None]
        for at in range(0, len(rest), 4096):
            part = rest[at : at + 4096]
            for i, e in zip(part, self.tokenizer.encode_batch_fast([texts_[i] for i in part], add_special_tokens=False), strict=True):
                out[i] = array("I", e.ids).tobytes()
        return out

    def _learn(self, words: set[bytes]) -> None:
        new = words.difference(self.known)
        if len(self.known) + len(new) > self.most:
            self.known, self.older = {}, self.known
            new = words
        known, older = self.known, self.older
        again = new.intersection(older)
        known.update(zip(again, map(older.__getitem__, again), strict=True))
        split: list[tuple[bytes, bytes, bytes]] = []
        whole: set[bytes] = set()
        for w in new.difference(again):
            core = w.rstrip(_TAIL)
            if core and len(core) < len(w) and core[-1] in _PLAIN:
                tail = w[len(core) :]
                split.append((w, core, tail))
                whole.add(core)
                whole.add(tail)
            else:
                whole.add(w)
        parts = list(whole.difference(known))
        known.update(zip(parts, self._encode(parts), strict=True))
        for w, core, tail in split:
            known[w] = known[core] + known[tail]

    def of(self, batch: list[bytes]) -> list[np.ndarray]:
        # Special tokens are found by their exact case, so texts that might hold one are encoded whole.
        words = [[] if b"<|" in t else t.lower().split() for t in batch]
        self._learn(set().union(*words))
        return [np.frombuffer(self._encode([t])[0] if b"<|" in t else b"".join(map(self.known.__getitem__, w)), "<u4") for t, w in zip(batch, words, strict=True)]


def combinations(classes: int, depth: int) -> tuple[tuple[int, ...], ...]:
    """Ascending classes, ``depth`` of them at most, that sum up to ``classes``."""

    def grow(left: int, least: int, room: int) -> Iterator[tuple[int, ...]]:
        if left >= least:
            yield (left,)
        if room > 1:
            for c in range(least, left // 2 + 1):
                for more in grow(left - c, c, room - 1):
                    yield (c, *more)

    return tuple(grow(classes, 1, depth))


def nnls(a: np.ndarray, b: np.ndarray, rounds: int = 400) -> np.ndarray:
    """The x >= 0 with the least |ax - b|, by active sets."""
    x, active = np.zeros(a.shape[1]), np.zeros(a.shape[1], bool)
    for _ in range(rounds):
        pull = a.T @ (b - a @ x)
        pull[active] = -np.inf
        best = int(pull.argmax())
        if pull[best] <= 1e-8 * max(1.0, float(np.abs(b).max(initial=0))):
            break
        active[best] = True
        while True:
            at = np.flatnonzero(active)
            z = np.linalg.lstsq(a[:, at], b, rcond=None)[0]
            if (z > 1e-10).all():
                x[:] = 0
                x[at] = z
                break
            low = z <= 1e-10
            step = np.min(x[at][low] / np.maximum(x[at][low] - z[low], 1e-300))
            x[at] += step * (z - x[at])
            active[at[x[at] <= 1e-10]] = False
            x[~active] = 0
            if not active.any():
                break
    return x


def ways_of(classes: int, depth: int) -> tuple[tuple[int, ...], ...]:
    """Combinations of 2 to ``depth`` classes whose members may fill a window to the last token.

    A class holds the lengths up to its number times the unit, so k pieces that fill a window have
    classes that sum up to between 1 and k - 1 more than the window's (unless all are whole units).
    """
    found = (w for more in range(1, depth) for w in combinations(classes + more, depth))
    return tuple(w for w in found if len(w) > sum(w) - classes and w[-1] <= classes)


class Tails:
    """Pieces shorter than a window, by their exact length."""

    def __init__(self, window: int) -> None:
        self.of: list[list[Piece]] = [[] for _ in range(window)]
        self.n = np.zeros(window, np.int64)
        self.total = 0

    def add(self, piece: Piece) -> None:
        self.of[piece[2]].append(piece)
        self.n[piece[2]] += 1
        self.total += piece[2]

    def take(self, length: int) -> Piece:
        self.n[length] -= 1
        self.total -= length
        return self.of[length].pop()

    def largest(self, most: int) -> int:
        """The largest length up to ``most`` that is there; 0 if there is none."""
        at = np.flatnonzero(self.n[1 : most + 1])
        return int(at[-1]) + 1 if len(at) else 0

    def exact(self, room: int) -> list[int]:
        """The lengths of one or two pieces that fill the room; empty if no such pieces are there."""
        if self.n[room]:
            return [room]
        half = room // 2
        at = np.flatnonzero((self.n[1 : half + 1] > 0) & (self.n[room - half : room][::-1] > 0)) + 1
        return next(([room - a, a] for a in at.tolist() if 2 * a < room or self.n[a] > 1), [])

    def members(self, way: tuple[int, ...], unit: int) -> list[int]:
        """Lengths of one piece of each class of the way that fill a window together; empty if there are none."""
        window, sums, owns = len(self.n), np.zeros(1, np.int64), []
        for c in way[:-1]:
            owns.append(np.flatnonzero(self.n[(c - 1) * unit + 1 : c * unit + 1]) + (c - 1) * unit + 1)
            sums = (sums[:, None] + owns[-1]).ravel()
        last = window - sums
        fits = np.flatnonzero((last > (way[-1] - 1) * unit) & (last <= min(way[-1] * unit, window - 1)))
        for i in fits[self.n[last[fits]] > 0].tolist():
            at = np.unravel_index(i, [len(x) for x in owns])
            found = [*(int(x[k]) for x, k in zip(owns, at, strict=True)), int(last[i])]
            if all(found.count(x) <= self.n[x] for x in found):
                return found
        return []


def plan(sizes: list[int], window: int, unit: int, ways: tuple[tuple[int, ...], ...]) -> tuple[list[tuple[str, list[Piece]]], list[Piece]]:
    """Full sequences over documents of these sizes, each with how it was made, and pieces that are left.

    ways: combinations of classes. What is left does not fill a window. A sequence cuts one tail at most.
    """
    out = [("window", [(d, at, window)]) for d, n in enumerate(sizes) for at in range(0, n - window + 1, window)]
    classes, tails = window // unit, Tails(window)
    for d, n in enumerate(sizes):
        if tail := n % window:
            tails.add((d, n - tail, tail))
    ends = np.arange(classes + 1) * unit
    upto = np.cumsum(tails.n)[np.minimum(ends, window - 1)]
    counts = np.diff(upto).astype(float)
    matrix = np.zeros((classes, len(ways)))
    for k, way in enumerate(ways):
        for c in way:
            matrix[c - 1, k] += 1
    weight = np.sqrt(np.arange(1, classes + 1))[:, None]  # long tails are the harder ones to place later
    for way, times in zip(ways, np.floor(nnls(matrix * weight, counts * weight[:, 0]) + 1e-6).astype(int).tolist(), strict=True):
        for _ in range(times):
            found = tails.members(way, unit)
            if not found:
                break
            out.append(("combination", [tails.take(x) for x in found]))
    while tails.total >= window:
        out.append(("greedy", _greedy(tails, window)))
    return out, [p for own in reversed(tails.of) for p in own]


def _greedy(tails: Tails, window: int) -> list[Piece]:
    """A full sequence: the longest tails that fit, up to where one or two fill it; else the longest is cut."""
    sequence, room = [tails.take(tails.largest(window - 1))], 0
    while room := window - sum(p[2] for p in sequence):
        lengths = tails.exact(room)
        if not lengths and (most := tails.largest(room)):
            lengths = [most]
        if lengths:
            sequence += [tails.take(x) for x in lengths]
            continue
        d, at, n = tails.take(tails.largest(window - 1))
        sequence.append((d, at, room))
        tails.add((d, at + room, n - room))
    return sequence


def _fill(sequence: list[Piece], window: int, rest: deque[Piece]) -> None:
    room = window - sum(p[2] for p in sequence)
    while room:
        d, at, n = rest.popleft()
        sequence.append((d, at, min(n, room)))
        if n > room:
            rest.appendleft((d, at + room, n - room))
        room -= min(n, room)


def powers_of_two(pieces: list[Piece]) -> list[list[Piece]]:
    """Sequences, the longest first, whose lengths are the powers of two that sum up to the pieces."""
    total, rest, out = sum(p[2] for p in pieces), deque(pieces), []
    for k in range(total.bit_length() - 1, -1, -1):
        if total >> k & 1:
            s: list[Piece] = []
            _fill(s, 1 << k, rest)
            out.append(s)
    return out


def pack(docs: DataFrame, tokenizer: str, end_id: int = 1, window: int = 2048, unit: int = 32, depth: int = 3, block: int = 1 << 21, with_ids: bool = False) -> DataFrame:
    """One row per piece: where it lies in its document and in its sequence; with_ids adds its token ids.

    tokenizer: path of the vocabulary on every node. Null and empty texts have the end id alone. Rows
    that repeat an id are documents of their own; a null doc_id stays null. Only doc_id and text are
    read. Sequence ids hold the number of the partition, so a lost task makes the same ids again. made:
    window (a whole window of one document), combination (a solved one), greedy, or remainder.
    """
    bound_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, ways, sequence = per_process(f"ids of {tokenizer}", lambda: WordIds(tokenizer)), ways_of(window // unit, depth), TaskContext.get().partitionId() << 36
        ids: list[int | None] = []
        tokens: list[np.ndarray] = []  # of the documents of the block
        base: list[tuple[int, int]] = []  # ids before what a document of the block holds, and all it has
        held = 0

        def rows(sequences: list[tuple[str, list[Piece]]]) -> pa.RecordBatch:
            nonlocal sequence
            out: list[list] = [[] for _ in range(8 + with_ids)]
            for made, s in sequences:
                offset = 0
                for d, at, n in s:
                    part = tokens[d][at : at + n]
                    row = (ids[d], base[d][0] + at, n, zlib.crc32(part.tobytes()), base[d][1], sequence, offset, made)
                    for column, value in zip(out, (*row, part) if with_ids else row, strict=True):
                        column.append(value)
                    offset += n
                sequence += 1
            arrays = [*(pa.array(c, pa.int64()) for c in out[:7]), pa.array(out[7], pa.string())]
            return pa.RecordBatch.from_arrays(arrays + ([pa.array(out[8], pa.list_(pa.int32()))] if with_ids else []), names=_NAMES + ["ids"] * with_ids)

        def close() -> tuple[pa.RecordBatch, tuple]:
            full, rest = plan([len(t) for t in tokens], window, unit, ways)
            left = ([ids[d] for d, _, _ in rest], [tokens[d][a : a + n].copy() for d, a, n in rest], [(base[d][0] + a, base[d][1]) for d, a, _ in rest])
            return rows(full), left

        for batch in slices(batches):
            for doc, got in zip(batch.column("doc_id").to_pylist(), encoder.of(texts(batch.column("text"))), strict=True):
                ids.append(doc)
                tokens.append(np.append(got, np.uint32(end_id)).astype("<u4"))
                base.append((0, len(got) + 1))
                held += len(got) + 1
            if held >= block:
                made, (ids, tokens, base) = close()
                held = sum(map(len, tokens))
                yield made
        made, (ids, tokens, base) = close()
        yield made
        yield rows([("remainder", s) for s in powers_of_two([(d, 0, len(t)) for d, t in enumerate(tokens)])])

    return docs_of(docs, "doc_id", "text").mapInArrow(run, SCHEMA + (", ids array<int>" if with_ids else ""))
