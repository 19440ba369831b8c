"""Pairs of lines by the rules, without a table of their texts: what deduplication needs of a question, and how a recipe judges a pair.

The stand-ins of ``extract``, ``refine`` and ``decontam`` look at one chunk at a time. So what they find of a pair is
worked out where the chunk is read, batch by batch, and only ids, hashes and verdicts move. Regular expressions are
those of the operators, by the engine of the Arrow library.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from qacurate.operators import decontam, refine
from qacurate.operators.extract import STANDARDS, Standard
from qacurate.operators.graph import components
from qacurate.operators.knn import Best, checked
from qacurate.operators.minhash import PRIME, coefficients, linked
from qacurate.staging import Staged

STEP = 128  # chunks that are worked on at once
Pair = tuple[int, int, str, str, str]  # place of the chunk, line, standard, question, answer

_WORD = re.compile(r"[^\W_]+")
_LONG_BLANKS = re.compile(r"[\t\r\n]|  ")


def rules(standard: str) -> list[Standard]:
    """In order of the ids they give to one line."""
    return sorted(STANDARDS.values(), key=lambda s: s.name) if standard == "dual" else [STANDARDS[standard]]


def lowered(texts: list[str]) -> list[str]:
    return pc.utf8_lower(pa.array(texts, pa.string())).to_pylist()


def words(lower: str) -> list[str]:
    """Runs of letters and digits of a text in lower case."""
    return _WORD.findall(lower)


def pairs_of(texts: pa.Array, wanted: list[Standard]) -> Iterator[Pair]:
    """What ``extract.extract_pairs`` finds, line by line. Words and sentences are counted over the bytes of all texts at once."""
    texts = pa.concat_arrays([texts.cast(pa.string())])
    off = np.frombuffer(texts.buffers()[1], np.int32)[texts.offset : texts.offset + len(texts) + 1].astype(np.int64)
    if off[-1] == off[0]:
        return
    raw = memoryview(texts.buffers()[2])[off[0] : off[-1]]
    b, off = np.frombuffer(raw, np.uint8), off - off[0]
    dark = ~((b == 32) | (b == 9) | (b == 10) | (b == 13))
    begins = dark.copy()
    begins[1:] &= ~dark[:-1]
    edges = off[:-1][off[:-1] < off[1:]]
    begins[edges] = dark[edges]
    ends_here = np.ones(len(b), bool)  # a sentence ends at a mark before a blank, a line's end or the text's
    ends_here[:-1] = (b[1:] == 32) | (b[1:] == 10)
    ends_here[off[1:][off[1:] > off[:-1]] - 1] = True
    ends_here &= (b == 46) | (b == 33) | (b == 63)
    count = lambda mask: np.concatenate([[0], np.cumsum(mask, dtype=np.int64)])
    n_words, n_sentences = count(begins), count(ends_here)
    breaks = np.flatnonzero(b == 10)
    starts, ends = np.sort(np.concatenate([off[:-1], breaks + 1])), np.sort(np.concatenate([breaks, off[1:]]))
    per_text = 1 + np.diff(np.searchsorted(breaks, off))
    row = np.repeat(np.arange(len(texts)), per_text)
    first = np.cumsum(per_text) - per_text
    last = (first + per_text - 1)[row]
    k = np.arange(len(row))
    n = n_words[ends] - n_words[starts]
    following = np.minimum(k + 1, len(row) - 1)
    open_ = (k < last) & (n >= 6) & (n[following] >= 6)
    for line in np.flatnonzero(open_).tolist():
        start = starts[line + 1]
        for rule in wanted:
            end = ends[min(line + rule.answer_lines, last[line])]
            if n[line] >= rule.question_words and n_words[end] - n_words[start] >= rule.answer_words and n_sentences[end] - n_sentences[start] >= rule.answer_sentences:
                at = int(row[line])
                yield at, line - int(first[at]), rule.name, str(raw[starts[line] : ends[line]], "utf-8"), str(raw[start:end], "utf-8")


def _qid(book: int, chunk: int, line: int, standard: str) -> str:
    return f"{book}:{chunk}:{line}:{standard}"


def _slices(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for at in range(0, batch.num_rows, STEP):
            yield batch.slice(at, STEP)


def question_lines(chunks: DataFrame, standard: str = "dual") -> DataFrame:
    """(id, key, hset): for each line that is a question, the smallest id of its pairs, a digest of its words in order and
    the distinct words as 64 bits of md5. Pairs of one line ask the same, so deduplication keeps that id at most."""
    wanted = rules(standard)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        code: dict[str, int] = {}
        for part in _slices(batches):
            book, chunk = part.column("book_id").to_pylist(), part.column("chunk_no").to_pylist()
            asked: dict[tuple[int, int], tuple[str, str]] = {}
            for at, line, name, question, _ in pairs_of(part.column("text"), wanted):
                asked.setdefault((at, line), (_qid(book[at], chunk[at], line, name), question))
            ids, keys, sets = [], [], []
            for (id_, _), lower in zip(asked.values(), lowered([q for _, q in asked.values()]), strict=True):
                found = words(lower)
                ids.append(id_)
                keys.append(hashlib.md5(" ".join(found).encode()).digest())
                mine = []
                for w in dict.fromkeys(found):
                    if (h := code.get(w)) is None:
                        h = code[w] = int.from_bytes(hashlib.md5(w.encode()).digest()[:8], "big", signed=True)
                    mine.append(h)
                sets.append(mine)
            if len(code) > 1 << 19:
                code.clear()
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.string()), pa.array(keys, pa.binary()), pa.array(sets, pa.list_(pa.int64()))], names=["id", "key", "hset"])

    return chunks.select("book_id", "chunk_no", "text").mapInArrow(run, "id string, key binary, hset array<bigint>")


def band_rows(sets: DataFrame, first: int, upto: int, rows: int = 4, num_perm: int = 128) -> DataFrame:
    """(id, band, key) of the bands from ``first`` up to ``upto``: the bands of ``minhash.minhash``, as the first 32 of the 64 bits
    are its hashes. A word that a batch holds often is permuted once."""
    pairs = np.array(coefficients(num_perm)[first * rows : upto * rows], np.uint64)
    a, b, prime = pairs[None, :, 0], pairs[None, :, 1], np.uint64(PRIME)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                n = np.diff(part.column("hset").offsets.to_numpy())
                part, n = part.filter(pa.array(n > 0)), n[n > 0]
                if not len(n):
                    continue
                flat = (part.column("hset").flatten().to_numpy(zero_copy_only=False).view(np.uint64) >> np.uint64(32) & prime) % prime
                known, place = np.unique(flat, return_inverse=True)
                value = a * known[:, None] + b
                for _ in range(2):  # 2^31 counts as 1; what is left is PRIME at most, which counts as 0
                    value = (value & prime) + (value >> np.uint64(31))
                value[value == prime] = 0
                low = np.minimum.reduceat(value.astype(np.uint32)[place], np.cumsum(n) - n, axis=0).astype(np.uint64).reshape(len(n), upto - first, rows)
                key = np.zeros(low.shape[:2], np.uint64)
                for r in range(rows):  # 64 bits that stand for a band's numbers
                    key = (key ^ low[:, :, r]) * np.uint64(0x9E3779B97F4A7C15)
                    key ^= key >> np.uint64(29)
                bands = np.tile(np.arange(first, upto, dtype=np.int32), len(n))
                yield pa.RecordBatch.from_arrays([part.column("id").take(pa.array(np.repeat(np.arange(len(n)), upto - first))), pa.array(bands), pa.array(key.ravel().view(np.int64))], names=["id", "band", "key"])

    return sets.select("id", "hset").mapInArrow(run, T.StructType([sets.schema["id"], T.StructField("band", T.IntegerType()), T.StructField("key", T.LongType())]))


def kept_questions(lines: DataFrame, threshold: float = 0.6, bands: int = 32, at_once: int = 8) -> DataFrame:
    """(qid): what ``minhash_dedup`` keeps of ``question_lines``.

    Most bands of a short question are its own. So bands are made from the sets ``at_once`` at a time and are gone before the
    next ones are made: what stays of them is the pairs that sketches allow. No signature is stored.
    """
    reps = Staged(lines.groupBy("key").agg(F.min("id").alias("qid"), F.first("hset").alias("hset")).select("qid", "hset", F.monotonically_increasing_id().alias("id")), "questions")
    names = Staged(reps.df.select("id", "qid"), "question-ids").df
    parts = (Staged(band_rows(reps.df, first, min(first + at_once, bands)), "some-bands") for first in range(0, bands, at_once))
    links = linked(parts, reps.df.select("id", "hset"), threshold, dense=True)
    reps.drop()
    named = Staged(components(links), "question-components").df
    best = named.join(names, F.col("node") == F.col("id")).groupBy("component").agg(F.min("qid").alias("qid")).select("qid")
    lone = names.join(named.select(F.col("node").alias("id")), "id", "left_anti").select("qid")
    return Staged(best.union(lone), "kept-questions").df


# How a recipe judges a pair.


def cleaned(texts: list[str]) -> list[str]:
    """``refine``'s rule: without citations, one blank between words, none around."""
    out = pc.replace_substring_regex(pa.array(texts, pa.string()), f"(?i){refine.CITATION}", "").to_pylist()
    return [(re.sub("[ \t\r\n]+", " ", t) if _LONG_BLANKS.search(t) else t).strip(" ") for t in out]


def _sentences(t: str) -> int:
    return sum(t.count(m + x) for m in ".!?" for x in " \n") + t.endswith((".", "!", "?"))


def _final(t: str) -> str:
    """The words behind the last mark, or before it where only blanks follow."""
    at = max(map(t.rfind, ".!?"))
    if at >= 0 and not t[at + 1 :].strip(" \t\n\f\r"):
        return t[max(t.rfind(m, 0, at) for m in ".!?") + 1 : at].strip(" ")
    return t[at + 1 :].strip(" ")


class Judged:
    """Texts of a batch, each looked at once: words, gaps of reasoning and defects."""

    def __init__(self) -> None:
        self.known: dict[str, tuple[int, bool, bool, bool, bool]] = {}
        self.tokens: dict[str, list[str]] = {}

    def add(self, questions: Iterable[str], answers: Iterable[str]) -> None:
        """known: number of words, whether one word in four at most is new, reference, contradiction, gap."""
        q = list(dict.fromkeys(x for x in questions if x not in self.tokens))
        a = list(dict.fromkeys(x for x in answers if x not in self.known))
        for text, lower in zip(q, lowered(q), strict=True):
            self.tokens[text] = words(lower)
        lower = lowered(a)
        refers = pc.match_substring_regex(pa.array(lower, pa.string()), refine.REFERENCE).to_pylist()
        links = iter(())
        found = [(len(w := words(x)), len(set(w)) * 4 < len(w)) for x in lower]
        asked = [i for i, (n, _) in enumerate(found) if 20 <= n < 60]
        if asked:
            links = iter(pc.match_substring_regex(pa.array([lower[i] for i in asked], pa.string()), refine.CONNECTIVES).to_pylist())
        linked = dict(zip(asked, links, strict=False))
        for i, text in enumerate(a):
            n, repeats = found[i]
            at = lower[i].find("on the one hand")
            contradicts = "contradict" in lower[i] or (at >= 0 and lower[i].find("on the other hand", at + 15) >= 0)
            self.known[text] = (n, repeats, refers[i], contradicts, n < 20 or _sentences(text) < 2 or not linked.get(i, True))

    def refers(self, questions: list[str]) -> dict[str, bool]:
        q = list(dict.fromkeys(questions))
        return dict(zip(q, pc.match_substring_regex(pa.array(lowered(q), pa.string()), refine.REFERENCE).to_pylist(), strict=True))


class Pool:
    """Benchmark items. ``leaks`` judges first, which few windows pass, and searches for those only."""

    def __init__(self, items: list[tuple[int, list[str]]]) -> None:
        items = sorted(items)
        self.ids = np.array([i for i, _ in items], np.int64)
        self.sets = [set(w) for _, w in items]
        self.sizes = np.array([len(s) for s in self.sets], np.int64)
        self.codes: dict[str, int] = {}
        self.matrix = self._dense([w for _, w in items])
        self.norms = (self.matrix**2).sum(axis=1)
        self.tiles = []
        for at in range(0, len(items), 256):
            mine = self.sets[at : at + 256]
            vocabulary = {w: i for i, w in enumerate(sorted(set().union(*mine)))}
            holds = np.zeros((len(vocabulary) + 1, len(mine)), np.uint8)  # the last row is that of words no item has
            for j, s in enumerate(mine):
                holds[[vocabulary[w] for w in s], j] = 1
            self.tiles.append((at, vocabulary, holds))

    def _dense(self, texts: list[list[str]]) -> np.ndarray:
        for w in set().union(*texts) - self.codes.keys() if texts else ():
            self.codes[w] = int(hashlib.md5(w.encode()).hexdigest()[:3], 16)
        lists = pa.array([[self.codes[w] for w in t] for t in texts], pa.list_(pa.int32()))
        out = decontam._dense(lists)
        if len(self.codes) > 1 << 19:
            self.codes.clear()
        return out

    def leaks(self, asked: list[list[str]], k: int, size: int = 32, stride: int = 16) -> np.ndarray:
        """Whether a window of each question is judged a paraphrase of one of its k items; see ``decontam.decontaminate``."""
        out = np.zeros(len(asked), bool)
        owner, windows = [], []
        for i, w in enumerate(asked):
            for at in range(0, max(-(-(len(w) - size) // stride) + 1, 1) * stride if w else 0, stride):
                owner.append(i)
                windows.append(w[at : at + size])
        hits: dict[int, list[int]] = {}
        for first, vocabulary, holds in self.tiles:
            none, known = len(vocabulary), vocabulary.get
            for start in range(0, len(windows), 2048):
                part = windows[start : start + 2048]
                place = np.full((size, len(part)), none, np.int32)
                for j, w in enumerate(part):
                    place[: len(w), j] = [known(x, none) for x in w]
                met = np.zeros((len(part), holds.shape[1]), np.uint8)
                for row in place:  # repeats count too, so this is at least what is shared
                    met += holds[row]
                for j in np.flatnonzero(met.max(axis=1) >= decontam.JUDGE_CUT * decontam.JUDGE_WORDS - 1e-9).tolist():
                    mine = set(part[j])
                    if len(mine) < decontam.JUDGE_WORDS:
                        continue
                    sizes = self.sizes[first : first + holds.shape[1]]
                    for c in np.flatnonzero((met[j] >= decontam.JUDGE_CUT * np.minimum(sizes, len(mine)) - 1e-9) & (sizes >= decontam.JUDGE_WORDS)).tolist():
                        other = self.sets[first + c]
                        if len(mine & other) / min(len(mine), len(other)) >= decontam.JUDGE_CUT:
                            hits.setdefault(start + j, []).append(first + c)
        some = list(hits)
        for at in range(0, len(some), 512):
            part = some[at : at + 512]
            q = self._dense([windows[j] for j in part])
            best, mine = Best(len(part), k), (q**2).sum(axis=1)
            for tile in range(0, len(self.ids), 4096):
                m = self.matrix[tile : tile + 4096]
                both = np.sqrt(mine[:, None] * self.norms[None, tile : tile + 4096])
                best.add(np.divide(q @ m.T, both, out=np.full(both.shape, -2.0), where=both > 0), tile)
            places, s = best.found()
            for j, top, real in zip(part, places, s > -2, strict=True):
                if set(top[real].tolist()) & set(hits[j]):
                    out[owner[j]] = True
        return out


def verdicts(chunks: DataFrame, items: DataFrame, recipes: list) -> DataFrame:
    """(qid, subjects, m0, m1 ...): of each pair, and each recipe, whether the pair as the recipe makes it is ``sound`` and a
    ``leak``, its answer's number of ``words`` and whether it ``lacks`` reasoning. The recipes mine by one standard, without a model.
    """
    wanted = rules(recipes[0].standard)
    pool = [(r.item_id, list(r.words)) for r in checked(items, 4 * decontam.WIDTH).select("item_id", "words").collect()]
    shared = chunks.sparkSession.sparkContext.broadcast(pool)
    kinds = [(r.strength if r.refine else None, r.supplement, r.k if r.decontaminate else None) for r in recipes]

    def made(kind: str | None, pairs: list[Pair], heads: list[str], tails: list[str]) -> tuple[list[str], list[str]]:
        q, a = [p[3] for p in pairs], [p[4] for p in pairs]
        if kind is None:
            return q, a
        q, a = cleaned(q), cleaned(a)
        if kind == "weak":
            return q, a
        return [x if heads[p[0]] in x else f"{heads[p[0]]} {x}" for p, x in zip(pairs, q, strict=True)], [x if tails[p[0]] in x else f"{x} {tails[p[0]]}" for p, x in zip(pairs, a, strict=True)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        items_ = Pool(shared.value)
        for part in _slices(batches):
            book, chunk = part.column("book_id").to_pylist(), part.column("chunk_no").to_pylist()
            pairs = list(pairs_of(part.column("text"), wanted))
            trimmed = [t.strip(" ") for t in part.column("text").to_pylist()]
            heads, tails = [t.split("\n", 1)[0] for t in trimmed], [t.rsplit("\n", 1)[-1] for t in trimmed]
            judged, forms, columns = Judged(), {}, []
            for kind in {k for k, _, _ in kinds}:
                forms[kind] = q, a = made(kind, pairs, heads, tails)
                judged.add(q, a)
            refers = judged.refers([x for q, _ in forms.values() for x in q])
            leaky = {}
            for k in {k for _, _, k in kinds if k is not None}:
                asked = list(dict.fromkeys(x for (kind, _, mine) in kinds if mine == k for x in forms[kind][0]))
                leaky[k] = dict(zip(asked, items_.leaks([judged.tokens[x] for x in asked], k).tolist(), strict=True))
            for kind, more, k in kinds:
                q, a = forms[kind]
                if more:
                    a = [f"Step 1: the question states: {x} Step 2: {y} Therefore the final answer is: {_final(y)}." if judged.known[y][4] else y for x, y in zip(q, a, strict=True)]
                    judged.add((), a)
                rows = []
                for x, y in zip(q, a, strict=True):
                    n, repeats, reference, contradicts, gap = judged.known[y]
                    rows.append((not (reference or contradicts or repeats or n < 3 or refers[x] or len(judged.tokens[x]) < 6), n, gap, k is not None and leaky[k][x]))
                columns.append(pa.StructArray.from_arrays([pa.array([r[i] for r in rows], t) for i, t in enumerate((pa.bool_(), pa.int32(), pa.bool_(), pa.bool_()))], names=["sound", "words", "lacks", "leak"]))
            ids = pa.array([_qid(book[p[0]], chunk[p[0]], p[1], p[2]) for p in pairs], pa.string())
            yield pa.RecordBatch.from_arrays([ids, part.column("subjects").take(pa.array([p[0] for p in pairs], pa.int64())), *columns], names=["qid", "subjects", *[f"m{i}" for i in range(len(kinds))]])

    mark = T.StructType([T.StructField(c, t) for c, t in (("sound", T.BooleanType()), ("words", T.IntegerType()), ("lacks", T.BooleanType()), ("leak", T.BooleanType()))])
    schema = T.StructType([T.StructField("qid", T.StringType()), chunks.schema["subjects"], *[T.StructField(f"m{i}", mark) for i in range(len(kinds))]])
    return chunks.select("book_id", "chunk_no", "subjects", "text").mapInArrow(run, schema)
