"""Toxicity by a classifier chain: one linear model per category, each fed by those before it.

Models read hashed words and word beginnings. A later model has the probabilities of the earlier
categories as features; in training these come from out-of-fold predictions, so that it learns from
probabilities as wrong as those it will meet. The order of ``categories`` is the order of the chain.

Training sees at most ``sample`` labelled rows (smallest hash of the id) of at most
``sample_chars`` characters; only their hashed features reach the driver.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from qacurate.llm.quality_crf import held_out, labelled_sample
from qacurate.llm.text import docs_of, slices, texts
from qacurate.staging import bound_batches

BITS = 18
_EDGE = b".,;:!?\"'()[]{}<>|*#-_"


class Features(dict):
    """Buckets of a word: the word in lower case, and its beginnings of 4 to 6 bytes."""

    def __init__(self, most: int = 400_000) -> None:
        self.most = most

    def __missing__(self, word: bytes) -> tuple[int, ...]:
        if len(self) >= self.most:
            self.clear()
        w = word.lower().strip(_EDGE)
        parts = [b"w" + w] + [b"p" + w[:n] for n in (4, 5, 6) if len(w) > n]
        got = self[word] = tuple(xxhash.xxh32_intdigest(p) >> (32 - BITS) for p in parts) if w else ()
        return got

    def of(self, text: bytes) -> np.ndarray:
        """The distinct buckets of a whole text."""
        got: set[int] = set()
        for word in set(text.split()):
            got.update(self[word])
        return np.fromiter(got, np.int32, len(got))


@dataclass(frozen=True)
class Link:
    """Weights of a category: of the buckets, of the earlier probabilities (as log odds), and the constant."""

    weight: np.ndarray
    earlier: np.ndarray
    shift: float


@dataclass(frozen=True)
class Chain:
    categories: tuple[str, ...]
    links: tuple[Link, ...]

    def predict(self, buckets: list[np.ndarray]) -> np.ndarray:
        sparse = Sparse(buckets)
        odds = np.empty((len(buckets), 0))
        for link in self.links:
            odds = np.column_stack([odds, sparse.times(link.weight) + odds @ link.earlier + link.shift])
        return _sigmoid(odds)


class Sparse:
    """Rows of distinct buckets, each of value 1."""

    def __init__(self, rows: list[np.ndarray]) -> None:
        self.n, self.width = len(rows), 1 << BITS
        self.column = np.concatenate([*rows, np.empty(0, np.int32)]).astype(np.int64)
        self.row = np.repeat(np.arange(self.n), [len(r) for r in rows])

    def times(self, weight: np.ndarray) -> np.ndarray:
        return np.bincount(self.row, weight[self.column], self.n)

    def back(self, of_rows: np.ndarray) -> np.ndarray:
        return np.bincount(self.column, of_rows[self.row], self.width)

    def only(self, columns: np.ndarray) -> Sparse:
        """The same rows with these columns, numbered anew."""
        place = np.full(self.width, -1)
        place[columns] = np.arange(len(columns))
        out, at = Sparse([]), place[self.column]
        out.n, out.width, out.column, out.row = self.n, len(columns), at[at >= 0], self.row[at >= 0]
        return out


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -40, 40)))


def evidence(x: Sparse, y: np.ndarray, least: int = 4) -> np.ndarray:
    """Log ratio of a bucket's document share in both classes; 0 for buckets of fewer than ``least`` documents."""
    yes, no = x.back(y), x.back(1 - y)
    ratio = np.log((yes + 0.5) / (y.sum() + 1)) - np.log((no + 0.5) / ((1 - y).sum() + 1))
    return np.where(yes + no >= least, ratio, 0.0)


def fit_link(buckets: list[np.ndarray], odds: np.ndarray, y: np.ndarray, rounds: int = 80, rate: float = 0.02, ridge: float = 1e-3) -> Link:
    """Logistic regression by Adam on whole passes, each bucket scaled by its evidence; both labels weigh the same.

    The scaling keeps the many buckets that say nothing from being used to learn the sample by heart.
    """
    x, n = Sparse(buckets), max(len(y), 1)
    share = min(max(y.mean() if len(y) else 0.5, 1e-3), 1 - 1e-3)
    cost = np.where(y > 0, 0.5 / share, 0.5 / (1 - share))
    full = evidence(x, y)
    kept = np.flatnonzero(full)
    x, scale, k = x.only(kept), full[kept], len(kept)
    w = np.zeros(k + odds.shape[1] + 1)
    m, v = np.zeros_like(w), np.zeros_like(w)
    for step in range(1, rounds + 1):
        r = cost * (_sigmoid(x.times(w[:k] * scale) + odds @ w[k:-1] + w[-1]) - y) / n
        g = np.concatenate([x.back(r) * scale, odds.T @ r, [r.sum()]])
        g[:-1] += ridge * w[:-1]
        m, v = 0.9 * m + 0.1 * g, 0.999 * v + 0.001 * g * g
        w = w - rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-6)
    weight = np.zeros(1 << BITS, np.float32)
    weight[kept] = w[:k] * scale
    return Link(weight, w[k:-1], float(w[-1]))


def train(buckets: list[np.ndarray], labels: np.ndarray, categories: tuple[str, ...], folds: int = 5) -> Chain:
    """labels: a column of 0 and 1 for each category. Folds follow the rows' order, which is that of a hash of the id."""
    fold = np.arange(len(buckets)) % folds
    odds, links = np.empty((len(buckets), 0)), []
    for k in range(len(categories)):
        y, out = labels[:, k].astype(float), np.zeros(len(buckets))
        links.append(fit_link(buckets, odds, y))
        if k + 1 < len(categories):
            for f in range(folds):
                known, other = np.flatnonzero(fold != f), np.flatnonzero(fold == f)
                link = fit_link([buckets[i] for i in known], odds[known], y[known])
                out[other] = Sparse([buckets[i] for i in other]).times(link.weight) + odds[other] @ link.earlier + link.shift
            odds = np.column_stack([odds, np.clip(out, -40, 40)])
    return Chain(categories, tuple(links))


def fit(docs: DataFrame, labels: DataFrame, categories: tuple[str, ...], sample: int = 6000, sample_chars: int = 20_000) -> Chain | None:
    """labels: doc_id and a 0/1 column for each category. None without labelled rows."""
    bound_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        features = Features()
        for batch in slices(batches):
            got = pa.array([features.of(t).astype("<i4").tobytes() for t in texts(batch.column("text"))], pa.binary())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *[batch.column(c) for c in categories], got], names=["doc_id", *categories, "buckets"])

    drawn = labelled_sample(docs, labels, list(categories), sample, sample_chars)
    schema = "doc_id long, " + ", ".join(f"`{c}` int" for c in categories) + ", buckets binary"
    rows = sorted(drawn.mapInArrow(run, schema).collect(), key=lambda r: xxhash.xxh64_intdigest(str(r.doc_id)))
    if not rows:
        return None
    return train([np.frombuffer(r.buckets, "<i4") for r in rows], np.array([[int(r[c] > 0) for c in categories] for r in rows]), categories)


def score(docs: DataFrame, chain: Chain | None, categories: tuple[str, ...], verdict: str, cut: float = 0.5) -> DataFrame:
    """(doc_id, held_out, p_<category> ..., score, predicted) of every row; a scan without shuffle.

    ``score`` is the probability of the category ``verdict``. Null and empty texts have no feature and
    take the models' constants; without a chain all probabilities are 0. Repeated rows give repeated rows.
    """
    bound_batches(docs.sparkSession)
    # The weights' size is fixed by BITS and the number of categories: they travel once per executor.
    shared = docs.sparkSession.sparkContext.broadcast([(x.weight, x.earlier, x.shift) for x in chain.links] if chain else [])
    names = [f"p_{c}" for c in categories]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        features, known = Features(), Chain(categories, tuple(Link(*x) for x in shared.value))
        for batch in slices(batches):
            rows = [features.of(t) for t in texts(batch.column("text"))]
            prob = known.predict(rows) if known.links else np.zeros((len(rows), len(names)))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *[pa.array(prob[:, k]) for k in range(len(names))]], names=["doc_id", *names])

    schema = "doc_id long, " + ", ".join(f"`{n}` double" for n in names)
    scored = docs_of(docs, "doc_id", "text").mapInArrow(run, schema)
    value = F.col(f"`p_{verdict}`")
    return scored.select("doc_id", held_out().alias("held_out"), *[F.col(f"`{n}`") for n in names], value.alias("score"), (value >= cut).cast("int").alias("predicted"))
