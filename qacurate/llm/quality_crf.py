"""Line quality by a linear-chain conditional random field, summed up to a score of the document.

Every line with a word is a position of the chain, labelled bad (0) or good (1). Its features are
those of the line itself and of the lines before and after it. Labels exist for documents only, so
each line takes its document's label in training. A document's score is the mean of the lines'
forward-backward marginals of "good", weighted by line length, put through a logistic calibration
fitted on the same sample.

Training sees a bounded sample: at most ``sample`` labelled rows (those whose id has the smallest
hash) of at most ``sample_chars`` characters. Only line features of the sample reach the driver.
"""

from __future__ import annotations

import operator
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from qacurate.llm.text import docs_of, slices, texts
from qacurate.staging import bound_batches

_UPPER = b"ABCDEFGHIJKLMNOPQRSTUVWXYZ"
_DIGITS = b"0123456789"
_MARKS = b"!|#*$%&<>=_~^{}[]\\/@+"
_STOPS = b".,;:"
N_LINE = 13
N_ALL = 3 * N_LINE + 3


def line_features(text: bytes) -> tuple[np.ndarray, np.ndarray]:
    """A row of features and a length for each line that has a word."""
    rows, sizes, seen = [], [], set()
    for line in text.split(b"\n"):
        words = line.split()
        if not words:
            continue
        n, size = len(words), len(line)
        pairs = len(set(zip(words, words[1:], strict=False)))
        rows.append(
            (
                np.log1p(n),
                len(set(words)) / n,
                sum(map(operator.eq, words, words[1:])) / n,
                1 - pairs / (n - 1) if n > 1 else 0.0,
                (size - len(line.translate(None, _UPPER))) / size,
                (size - len(line.translate(None, _DIGITS))) / size,
                (size - len(line.translate(None, _MARKS))) / size,
                (size - len(line.translate(None, _STOPS))) / size,
                words.count(b"|") / n,
                size / n / 10,
                float(words[-1][-1:] in b".!?:;\"'"),
                float(line in seen),
                float(n < 4),
            )
        )
        sizes.append(size)
        seen.add(line)
    return np.array(rows, np.float64).reshape(-1, N_LINE), np.array(sizes, np.float64)


def with_neighbours(own: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Features of each line, of the line before and of the line after; bounds: first line of each document, and the end."""
    before, after = np.zeros_like(own), np.zeros_like(own)
    first, last = np.zeros(len(own)), np.zeros(len(own))
    before[1:], after[:-1] = own[:-1], own[1:]
    starts, ends = bounds[:-1], bounds[1:] - 1
    some = ends >= starts
    before[starts[some]], after[ends[some]] = 0, 0
    first[starts[some]], last[ends[some]] = 1, 1
    return np.column_stack([own, before, after, first, last, np.ones(len(own))])


def marginals(emit: np.ndarray, trans: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Probability of each label at each line, and the summed probability of each pair of labels.

    All chains advance together, the longest first, so a step touches the chains that still run.
    """
    size = np.diff(bounds)
    order = np.argsort(-size, kind="stable")
    order = order[size[order] > 0]
    starts, size = bounds[:-1][order], size[order]
    running = [int(np.searchsorted(-size, -t, side="left")) for t in range(int(size[0]) if len(size) else 0)]
    peak = emit.max(axis=1, keepdims=True)
    local, jump = np.exp(emit - peak), np.exp(trans - trans.max())
    alpha, beta = np.zeros_like(local), np.ones_like(local)
    for t, k in enumerate(running):
        at = starts[:k] + t
        a = local[at] if t == 0 else (alpha[at - 1] @ jump) * local[at]
        alpha[at] = a / a.sum(axis=1, keepdims=True)
    for t in range(len(running) - 2, -1, -1):
        at = starts[: running[t + 1]] + t
        b = (local[at + 1] * beta[at + 1]) @ jump.T
        beta[at] = b / b.sum(axis=1, keepdims=True)
    prob = alpha * beta
    prob /= prob.sum(axis=1, keepdims=True)
    inner = np.ones(len(emit), bool)
    inner[starts] = False
    at = np.flatnonzero(inner)
    pair = alpha[at - 1][:, :, None] * jump[None] * (local[at] * beta[at])[:, None, :]
    pair /= pair.sum(axis=(1, 2), keepdims=True)
    return prob, pair.sum(axis=0)


@dataclass(frozen=True)
class Model:
    mean: np.ndarray
    scale: np.ndarray
    weight: np.ndarray  # difference of the two labels' weights
    trans: np.ndarray
    slope: float
    shift: float

    def good(self, own: np.ndarray, bounds: np.ndarray) -> np.ndarray:
        x = (with_neighbours(own, bounds) - self.mean) / self.scale
        emit = np.zeros((len(own), 2))
        emit[:, 1] = x @ self.weight
        return marginals(emit, self.trans, bounds)[0][:, 1]

    def scores(self, own: np.ndarray, sizes: np.ndarray, bounds: np.ndarray) -> np.ndarray:
        return _sigmoid(self.slope * _logit(weighted(self.good(own, bounds), sizes, bounds)) + self.shift)


def weighted(good: np.ndarray, sizes: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    """Length-weighted mean of the lines of each document; 0.5 where there are none."""
    total, part = np.concatenate([[0], np.cumsum(sizes)]), np.concatenate([[0], np.cumsum(sizes * good)])
    whole = total[bounds[1:]] - total[bounds[:-1]]
    return np.where(whole > 0, (part[bounds[1:]] - part[bounds[:-1]]) / np.maximum(whole, 1), 0.5)


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))


def _logit(p: np.ndarray) -> np.ndarray:
    p = np.clip(p, 1e-6, 1 - 1e-6)
    return np.log(p / (1 - p))


def train(own: np.ndarray, sizes: np.ndarray, bounds: np.ndarray, labels: np.ndarray, rounds: int = 150, rate: float = 0.1, ridge: float = 1e-3) -> Model:
    """Maximises the conditional likelihood of the lines' labels by Adam, then fits the calibration."""
    x = with_neighbours(own, bounds)
    mean, scale = x.mean(axis=0), x.std(axis=0)
    mean[-1], scale[scale < 1e-9] = 0, 1
    x = (x - mean) / scale
    y = np.repeat(labels, np.diff(bounds))
    share = max(y.mean(), 1e-3), max(1 - y.mean(), 1e-3)
    cost = np.where(y > 0, 0.5 / share[0], 0.5 / share[1])  # both labels weigh the same
    pairs = np.zeros((2, 2))
    inner = np.ones(len(y), bool)
    inner[bounds[:-1][np.diff(bounds) > 0]] = False
    np.fill_diagonal(pairs, [(inner & (y == 0)).sum(), (inner & (y == 1)).sum()])
    w, trans = np.zeros(x.shape[1]), np.zeros((2, 2))
    m, v = np.zeros(len(w) + 4), np.zeros(len(w) + 4)
    for step in range(1, rounds + 1):
        emit = np.zeros((len(y), 2))
        emit[:, 1] = x @ w
        prob, expected = marginals(emit, trans, bounds)
        g = np.concatenate([x.T @ (cost * (y - prob[:, 1])) / len(y) - ridge * w, ((pairs - expected) / len(y)).ravel() - ridge * trans.ravel()])
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        move = rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
        w, trans = w + move[:-4], trans + move[-4:].reshape(2, 2)
    model = Model(mean, scale, w, trans, 1.0, 0.0)
    z = _logit(weighted(model.good(own, bounds), sizes, bounds))
    a, b = 1.0, 0.0
    for _ in range(200):  # Newton steps of a ridged logistic fit in two numbers
        p = _sigmoid(a * z + b)
        r, h = p - labels, np.maximum(p * (1 - p), 1e-9)
        grad = np.array([(r * z).sum() + 1e-2 * (a - 1), r.sum() + 1e-2 * b])
        hess = np.array([[(h * z * z).sum() + 1e-2, (h * z).sum()], [(h * z).sum(), h.sum() + 1e-2]])
        a, b = np.array([a, b]) - 0.5 * np.linalg.solve(hess, grad)
    return Model(mean, scale, w, trans, float(a), float(b))


def held_out() -> F.Column:
    return F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0, F.lit(False))


def labelled_sample(docs: DataFrame, labels: DataFrame, target: str | list[str], sample: int, sample_chars: int) -> DataFrame:
    """Whole texts of at most ``sample`` training rows that have a label, none of them held out.

    The ids come from the label table alone, smallest hash first, and are few enough to broadcast by
    construction; twice as many ids are drawn as rows are wanted, since over-long texts are passed over.
    """
    targets = [target] if isinstance(target, str) else target
    ids = (
        labels.where(F.col("doc_id").isNotNull() & ~held_out())
        .where(" and ".join(f"{t} is not null" for t in targets))
        .groupBy("doc_id")
        .agg(*[F.max(t).cast("int").alias(t) for t in targets])
        .orderBy(F.xxhash64("doc_id"), "doc_id")
        .limit(2 * sample)
    )
    texts_ = docs_of(docs, "doc_id", "text").where(F.length("text") <= sample_chars).join(F.broadcast(ids), "doc_id")
    return texts_.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)


def fit(docs: DataFrame, labels: DataFrame, sample: int = 3000, sample_chars: int = 20_000) -> Model | None:
    """None if the labels hold fewer than two kinds."""
    bound_batches(docs.sparkSession)

    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            rows = [line_features(t) for t in texts(batch.column("text"))]
            yield pa.RecordBatch.from_arrays(
                [batch.column("quality"), pa.array([a.astype("<f4").tobytes() for a, _ in rows]), pa.array([b.astype("<f4").tobytes() for _, b in rows])],
                names=["quality", "own", "sizes"],
            )

    drawn = labelled_sample(docs, labels, "quality", sample, sample_chars)
    rows = drawn.select("text", "quality").mapInArrow(features, "quality int, own binary, sizes binary").collect()
    rows = [r for r in rows if len(r.sizes)]
    if len({r.quality for r in rows}) < 2:
        return None
    own = np.concatenate([np.frombuffer(r.own, "<f4").reshape(-1, N_LINE) for r in rows]).astype(np.float64)
    sizes = [np.frombuffer(r.sizes, "<f4") for r in rows]
    bounds = np.concatenate([[0], np.cumsum([len(s) for s in sizes])])
    return train(own, np.concatenate(sizes).astype(np.float64), bounds, np.array([float(r.quality > 0) for r in rows]))


def _scores(texts_: list[bytes], model: Model | None) -> np.ndarray:
    rows = [line_features(t) for t in texts_]
    if model is None or not rows:
        return np.full(len(rows), 0.5)
    bounds = np.concatenate([[0], np.cumsum([len(s) for _, s in rows])]).astype(np.int64)
    return model.scores(np.concatenate([a for a, _ in rows]), np.concatenate([s for _, s in rows]), bounds)


def keep_good(docs: DataFrame, model: Model | None, cut: float = 0.3) -> DataFrame:
    """The rows whose text scores ``cut`` or more, with all columns; judged where they are read, without shuffle."""
    bound_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            yield batch.filter(pa.array(_scores(texts(batch.column("text")), model) >= cut))

    return docs.mapInArrow(run, docs.schema)


def score(docs: DataFrame, model: Model | None, cut: float = 0.3) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every row; a scan without shuffle.

    Texts without a word have the score of an even marginal. Without a model every score is 0.5.
    Repeated rows give repeated rows; a null doc_id is not held out. Only doc_id and text are read,
    and only the text enters the score.
    """
    bound_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in slices(batches):
            out = _scores(texts(batch.column("text")), model)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(out)], names=["doc_id", "score"])

    scored = docs_of(docs, "doc_id", "text").mapInArrow(run, "doc_id long, score double")
    return scored.select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= cut).cast("int").alias("predicted"))
