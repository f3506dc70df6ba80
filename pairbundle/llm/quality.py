"""Quality scores: random-indexing word vectors pooled per document, then a two-layer network with calibrated temperature.

Every word falls into one of ``buckets``; each bucket has a fixed sparse vector of signs. A word's vector is the sum of the sparse
vectors of the words around it, over the whole corpus: each task adds up its own table, which is bounded by buckets times dimensions,
and tables are summed by bucket. A document is the mean and spread of its words' vectors
and of the likeness of neighbours. The network is fitted on
a bounded sample of labelled rows (``most_labelled``), its temperature on a part of them that the weights never saw.

Null texts count as empty; an empty text has a vector of zeros and a score like any other. Repeated rows score each. With no labels, or
labels of one class alone, the score is that class's smoothed share. An empty table gives an empty table. Whole texts are read.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pairbundle.llm.common import doc_text, documents
from pairbundle.llm.sampling import held_out, labels_of, training_rows
from pairbundle.llm.tokens import text_batches

WORD = r"\w+|[^\w\s]+"


class _Buckets(dict):
    """The bucket of a word; forgets all words when it holds too many."""

    def __init__(self, buckets: int):
        self.buckets = buckets

    def __missing__(self, word):
        import zlib

        self[word] = k = zlib.crc32(word.encode("utf-8", "surrogatepass")) % self.buckets
        return k

    def trim(self, most: int = 300_000) -> None:
        if len(self) > most:
            self.clear()


def _word_rows(texts: list[str], table: _Buckets) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of all words of all texts, and the number of words of each text."""
    find, get, rows = re.compile(WORD).findall, table.__getitem__, []
    for text in texts:
        rows.append(np.fromiter(map(get, find(text.lower())), np.int64))
    table.trim()
    return np.concatenate(rows) if rows else np.zeros(0, np.int64), np.array([len(r) for r in rows], np.int64)


def sparse_signs(buckets: int, dimensions: int, nonzero: int = 4, seed: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Positions and signs of each bucket's index vector."""
    random = np.random.default_rng(seed)
    return random.integers(0, dimensions, (buckets, nonzero)), random.choice([-1, 1], (buckets, nonzero))


def word_vectors(docs: DataFrame, buckets: int, dimensions: int, window: int = 2) -> np.ndarray:
    """A vector of unit length for each bucket, weighted by how rare the bucket is; corpus-wide sums by bucket."""
    names = ["bucket", "n", *(f"v{k}" for k in range(dimensions))]

    def run(batches):
        places, signs = sparse_signs(buckets, dimensions)
        table, total, seen = _Buckets(buckets), np.zeros(buckets * dimensions), np.zeros(buckets, np.int64)
        for batch in batches:
            texts = batch.column(0).to_pylist()
            for a, b in text_batches(texts, 1_000_000):
                words, n = _word_rows(texts[a:b], table)
                owner = np.repeat(np.arange(len(n)), n)
                seen += np.bincount(words, minlength=buckets)
                for gap in range(1, window + 1):
                    same = owner[gap:] == owner[:-gap]
                    left, right = words[:-gap][same], words[gap:][same]
                    for to, other in ((left, right), (right, left)):
                        for k in range(places.shape[1]):
                            total += np.bincount(to * dimensions + places[other, k], weights=signs[other, k], minlength=len(total))
        found = np.flatnonzero(seen)
        sums = total.reshape(buckets, dimensions)[found].astype(np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(found), pa.array(seen[found]), *(pa.array(sums[:, k]) for k in range(dimensions))], names)

    parts = docs.select("text").mapInArrow(run, ", ".join(f"{n} long" for n in names))
    rows = np.array(parts.groupBy("bucket").agg(*[F.sum(n).alias(n) for n in names[1:]]).collect(), np.float64).reshape(-1, dimensions + 2)
    out = np.zeros((buckets, dimensions))
    at, n, sums = rows[:, 0].astype(int), rows[:, 1], rows[:, 2:]
    rare = np.log1p(n.sum() / np.maximum(n, 1))
    out[at] = sums / np.maximum(np.linalg.norm(sums, axis=1, keepdims=True), 1e-9) * (rare / rare.max() if len(rare) else rare)[:, None]
    return out.astype(np.float32)


def pooled(texts: list[str], vectors: np.ndarray, table: _Buckets, group: int = 64) -> np.ndarray:
    """Mean and spread of each text's word vectors, how alike neighbours are (mean, spread, share of equal ones), and whether it has
    words at all. Means come from counts of buckets, some texts at a time; only neighbours need a vector for every word."""
    words, n = _word_rows(texts, table)
    d = vectors.shape[1]
    both = np.concatenate([vectors, vectors * vectors], 1)
    out = np.zeros((len(n), 2 * d + 4), np.float32)
    ends = np.cumsum(n)
    for a in range(0, len(n), group):
        size = n[a : a + group]
        own = words[ends[a] - n[a] : ends[a + len(size) - 1]]
        counts = np.bincount(np.repeat(np.arange(len(size)), size) * len(vectors) + own, minlength=len(size) * len(vectors)).reshape(len(size), -1)
        sums = counts.astype(np.float32) @ both / np.maximum(size, 1)[:, None]
        out[a : a + group, :d] = sums[:, :d]
        out[a : a + group, d : 2 * d] = np.sqrt(np.maximum(sums[:, d:] - sums[:, :d] ** 2, 0))
    for k in np.flatnonzero(n > 1).tolist():
        own = words[ends[k] - n[k] : ends[k]]
        v = vectors[own]
        alike = np.einsum("ij,ij->i", v[1:], v[:-1])
        out[k, 2 * d : 2 * d + 3] = alike.mean(), alike.std(), (own[1:] == own[:-1]).mean()
    out[n > 0, 2 * d + 3] = 1
    return out


@dataclass
class Network:
    """Two layers: scaled inputs, tanh units, one logit divided by the temperature."""

    shift: np.ndarray
    scale: np.ndarray
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: float
    temperature: float = 1.0

    def logits(self, x: np.ndarray) -> np.ndarray:
        return np.tanh((x - self.shift) / self.scale @ self.w1 + self.b1) @ self.w2 + self.b2

    def scores(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.logits(x) / self.temperature, -40, 40)))


def fit_network(x: np.ndarray, y: np.ndarray, hidden: int = 32, epochs: int = 60, batch: int = 256, rate: float = 0.004, decay: float = 1e-4, seed: int = 11) -> Network:
    """Adam on cross-entropy over five sixths of the rows; the temperature minimises it on the others."""
    share = (y.sum() + 1) / (len(y) + 2)
    if len(y) < 12 or y.min() == y.max():
        return Network(np.zeros(x.shape[1]), np.ones(x.shape[1]), np.zeros((x.shape[1], 1)), np.zeros(1), np.zeros(1), float(np.log(share / (1 - share))))
    random = np.random.default_rng(seed)
    order = random.permutation(len(y))
    check, fit = order[: len(y) // 6], order[len(y) // 6 :]
    shift, scale = x[fit].mean(0), x[fit].std(0) + 1e-3
    z, t = (x - shift) / scale, y.astype(float)
    p = [random.normal(0, 1 / np.sqrt(x.shape[1]), (x.shape[1], hidden)), np.zeros(hidden), random.normal(0, 1 / np.sqrt(hidden), hidden), np.zeros(1)]
    m, v, k = [np.zeros_like(a) for a in p], [np.zeros_like(a) for a in p], 0
    for _ in range(epochs):
        for rows in np.array_split(random.permutation(fit), max(1, len(fit) // batch)):
            h = np.tanh(z[rows] @ p[0] + p[1])
            g = (1 / (1 + np.exp(-np.clip(h @ p[2] + p[3], -40, 40))) - t[rows]) / len(rows)
            back = np.outer(g, p[2]) * (1 - h * h)
            k += 1
            for i, grad in enumerate((z[rows].T @ back + decay * p[0], back.sum(0), h.T @ g + decay * p[2], np.array([g.sum()]))):
                m[i] = 0.9 * m[i] + 0.1 * grad
                v[i] = 0.999 * v[i] + 0.001 * grad * grad
                p[i] = p[i] - rate * (m[i] / (1 - 0.9**k)) / (np.sqrt(v[i] / (1 - 0.999**k)) + 1e-8)
    net = Network(shift, scale, p[0], p[1], p[2], float(p[3][0]))
    logits, labels = net.logits(x[check]), t[check]
    losses = {s: np.logaddexp(0, -np.where(labels > 0, 1, -1) * logits / s).mean() for s in np.geomspace(0.25, 8, 60)}
    net.temperature = float(min(losses, key=losses.get))
    return net


def score_quality(docs: DataFrame, labels: DataFrame, modulus: int = 4, remainder: int = 2, most_labelled: int = 20_000, buckets: int = 4096, dimensions: int = 32, accept: float = 0.7) -> DataFrame:
    """doc_id, held_out, score, predicted of every row."""
    rows = doc_text(docs)
    vectors = word_vectors(rows, buckets, dimensions)

    def features(batches):
        table = _Buckets(buckets)
        for b in batches:
            texts = b.column(1).to_pylist()
            x = np.concatenate([pooled(texts[a:e], vectors, table) for a, e in text_batches(texts, 1_000_000)]) if texts else np.zeros((0, 2 * dimensions + 4))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(x.tolist(), pa.list_(pa.float32()))], ["y", "x"])

    sample = training_rows(docs, labels, "quality", modulus, remainder, most_labelled)
    data = sample.orderBy("doc_id").select("y", "text").mapInArrow(features, "y int, x array<float>").toPandas()
    net = fit_network(np.array(data["x"].tolist(), np.float64).reshape(len(data), -1), data["y"].to_numpy(np.int64)) if len(data) else fit_network(np.zeros((0, 2 * dimensions + 4)), np.zeros(0))

    def score(batches):
        table = _Buckets(buckets)
        for b in batches:
            texts, found = b.column(1).to_pylist(), []
            for a, e in text_batches(texts, 1_000_000):
                found.append(net.scores(pooled(texts[a:e], vectors, table).astype(np.float64)))
            s = np.concatenate(found) if found else np.zeros(0)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(s)], ["doc_id", "score"])

    scored = rows.select("doc_id", "text").mapInArrow(score, "doc_id long, score double")
    return scored.select("doc_id", held_out(modulus, remainder).alias("held_out"), "score", (F.col("score") >= accept).cast("int").alias("predicted"))


def op3_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_quality(documents(spark, sf_dir), labels_of(spark, sf_dir))
