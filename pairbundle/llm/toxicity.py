"""Toxicity: gradient-boosted trees over dense features, with isotonic calibration.

Features of a text: densities of a lexicon in the words, in disguised words and close to the second person, rates of capitals,
punctuation, digits and repeated letters, and lengths. The lexicon holds words and beginnings of words that a bounded sample of
labelled rows (``most_labelled``) shows far more often in toxic texts; the sample alone bounds it. Trees and calibration are
fitted on the driver from the sample's features alone.

Null texts count as empty; an empty text has features of zero and a score like any other. Repeated rows score each. With no labels, or
of one class alone, the score is that class's smoothed share. An empty table gives an empty table. Whole texts are read.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pairbundle.llm.common import doc_text, documents
from pairbundle.llm.sampling import held_out, labels_of, training_rows

#: Words that address somebody, in the corpus's languages.
SECOND_PERSON = ("you", "your", "yours", "yourself", "u", "ur", "tu", "te", "toi", "ton", "vous", "votre", "du", "dich", "dir", "dein", "deine", "ihr", "tú", "ti", "usted", "ustedes", "vosotros")

#: Characters that stand for letters in disguised words.
DISGUISES = {"@": "a", "4": "a", "3": "e", "1": "i", "!": "i", "|": "i", "0": "o", "$": "s", "5": "s", "7": "t", "+": "t", "*": "", "_": "", "-": "", ".": ""}

SHORTEST, LONGEST = 4, 7


def terms_of(words):
    """A word's terms: itself, and its beginnings of some lengths, marked by an asterisk."""
    return [words, *(words[:k] + "*" for k in range(SHORTEST, LONGEST + 1) if len(words) > k)]


def learn_lexicon(sample: DataFrame, least_rows: int = 3, strength: float = 2.5) -> dict[str, float]:
    """Terms and their log-odds. Rows that hold a term are counted in Spark by class; the driver gets every term with enough rows and
    odds. A term goes if one of its own beginnings weighs as much: a word's weight is the greatest of its terms, so none changes."""
    totals = {r["y"]: r["n"] for r in sample.groupBy("y").agg(F.count("*").alias("n")).collect()}
    bad, good = totals.get(1, 0), totals.get(0, 0)
    if not bad or not good:
        return {}
    words = F.array_distinct(F.filter(F.split(F.lower("text"), r"[^\p{L}]+"), lambda w: F.length(w) > 2))
    begin = lambda k: F.transform(F.filter(words, lambda w: F.length(w) > k), lambda w: F.concat(F.substring(w, 1, k), F.lit("*")))
    starts = [begin(k) for k in range(SHORTEST, LONGEST + 1)]
    each = sample.select("y", F.explode(F.array_distinct(F.concat(words, *starts))).alias("term"))
    counts = each.groupBy("term").agg(F.sum("y").alias("bad"), F.count("*").alias("rows"))
    odds = F.log((F.col("bad") + 0.5) / (bad + 1)) - F.log((F.col("rows") - F.col("bad") + 0.5) / (good + 1))
    lead = counts.where(F.col("bad") >= least_rows).withColumn("odds", odds).where(F.col("odds") >= strength).select("term", "odds")
    found = {r["term"]: float(r["odds"]) for r in lead.collect()}
    shorter = lambda t: (t[:k] + "*" for k in range(SHORTEST, LONGEST + 1) if k < len(t.rstrip("*")))
    return {t: w for t, w in found.items() if all(found.get(s, 0.0) < w for s in shorter(t))}


class _Weights(dict):
    """A word's lexicon weight: the greatest of its terms; second person -1."""

    def __init__(self, lexicon: dict[str, float]):
        self.lexicon = lexicon
        self.second = frozenset(SECOND_PERSON)

    def __missing__(self, word):
        w = max(self.lexicon.get(t, 0.0) for t in terms_of(word))
        self[word] = w = w if w > 0 else -1.0 if word in self.second else 0.0
        return w


NAMES = ("hits", "density", "weight", "weight_density", "top", "distinct", "near_second", "second", "disguised", "disguised_hits", "capitals", "shouted", "punctuation", "exclaimed", "digits", "stretched", "repeats", "words", "mean_length")


def features(text: str, weights: _Weights) -> list[float]:
    """The values of NAMES for one text."""
    words = re.findall(r"[^\W\d_]+", text.lower())
    if not text:
        return [0.0] * len(NAMES)
    w = np.fromiter(map(weights.__getitem__, words), np.float64, len(words))
    if len(weights) > 150_000:
        weights.clear()
    n, chars = max(1, len(words)), len(text)
    hit, second = np.flatnonzero(w > 0), np.flatnonzero(w < 0)
    near = 0
    if len(hit) and len(second):
        after = np.searchsorted(second, hit)
        gap = np.minimum(np.abs(second[np.minimum(after, len(second) - 1)] - hit), np.abs(hit - second[np.maximum(after - 1, 0)]))
        near = int((gap <= 5).sum())
    masked = re.findall(r"(?<!\S)[^\W\d_]+[@$!|*+0-9_.-]+[^\W\d_]+(?!\S)", text) if re.search(r"[^\W\d_][@$!|*+0-9_.-]+[^\W\d_]", text) else []
    table = str.maketrans(DISGUISES)
    masked_hits = sum(weights[m.lower().translate(table)] > 0 for m in masked)
    capitals = sum(map(str.isupper, text)) if not text.islower() else 0
    shouted = len(re.findall(r"\b[^\W\d_a-z]{3,}\b", text))
    punctuation = len(re.findall(r"[^\w\s]", text))
    stretched = len(re.findall(r"([^\W\d_])\1\1", text))
    same = sum(a == b for a, b in zip(words, words[1:]))
    total = float(w[hit].sum())
    return [float(len(hit)), len(hit) / n, total, total / n, float(w.max()) if len(hit) else 0.0, float(len({words[k] for k in hit})), near / n, len(second) / n, len(masked) / n, float(masked_hits), capitals / chars, shouted / n, punctuation / chars, text.count("!") / chars, sum(map(str.isdigit, text)) / chars if any(map(text.__contains__, "0123456789")) else 0.0, stretched / n, same / n, float(np.log1p(len(words))), chars / n]


@dataclass
class Trees:
    """Boosted regression trees on binned features, each an array of nodes of one full tree, and a calibration by steps."""

    edges: list = field(default_factory=list)
    base: float = 0.0
    trees: list = field(default_factory=list)
    xs: np.ndarray = field(default_factory=lambda: np.zeros(0))
    ys: np.ndarray = field(default_factory=lambda: np.zeros(0))

    def bins(self, x: np.ndarray) -> np.ndarray:
        return np.stack([np.searchsorted(e, x[:, k], side="left") for k, e in enumerate(self.edges)], 1) if len(x) else np.zeros((0, len(self.edges)), np.int64)

    def logits(self, x: np.ndarray) -> np.ndarray:
        b, out = self.bins(x), np.full(len(x), self.base)
        for which, cut, leaf in self.trees:
            at = np.zeros(len(x), np.int64)
            while (at < len(which)).any():
                at = 2 * at + 1 + (b[np.arange(len(x)), which[at]] > cut[at])
            out += leaf[at - len(which)]
        return out

    def scores(self, x: np.ndarray) -> np.ndarray:
        raw = 1 / (1 + np.exp(-np.clip(self.logits(x), -40, 40)))
        return np.clip(np.interp(raw, self.xs, self.ys), 0, 1) if len(self.xs) else raw


def _tree(b: np.ndarray, g: np.ndarray, h: np.ndarray, depth: int, bins: int, least: float, ridge: float):
    """One full tree of given depth by histograms of gradients; nodes without a gain send all rows left."""
    inner = 2**depth - 1
    which, cut = np.zeros(inner, np.int64), np.full(inner, bins, np.int64)
    at = np.zeros(len(b), np.int64)
    for level in range(depth):
        first, width = 2**level - 1, 2**level
        node = at - first
        best = np.full(width, 1e-9)
        for f in range(b.shape[1]):
            slot = node * bins + b[:, f]
            gl = np.bincount(slot, g, width * bins).reshape(width, bins).cumsum(1)
            hl = np.bincount(slot, h, width * bins).reshape(width, bins).cumsum(1)
            gt, ht = gl[:, -1:], hl[:, -1:]
            gain = gl**2 / (hl + ridge) + (gt - gl) ** 2 / (ht - hl + ridge) - gt**2 / (ht + ridge)
            gain[(hl < least) | (ht - hl < least)] = 0
            c = gain.argmax(1)
            top = gain[np.arange(width), c]
            better = top > best
            best[better] = top[better]
            which[first : first + width][better] = f
            cut[first : first + width][better] = c[better]
        at = 2 * at + 1 + (b[np.arange(len(b)), which[at]] > cut[at])
    leaf = at - inner
    gs, hs = np.bincount(leaf, g, inner + 1), np.bincount(leaf, h, inner + 1)
    return which, cut, -gs / (hs + ridge), leaf


def isotonic(raw: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Steps of the non-decreasing fit: pools of adjacent violators, as (mean raw score, smoothed share)."""
    order = np.argsort(raw, kind="stable")
    pools: list[list[float]] = []
    for r, t in zip(raw[order].tolist(), y[order].tolist()):
        pools.append([r, float(t), 1.0])
        while len(pools) > 1 and pools[-2][1] * pools[-1][2] >= pools[-1][1] * pools[-2][2]:
            r2, t2, n2 = pools.pop()
            pools[-1] = [pools[-1][0] + r2, pools[-1][1] + t2, pools[-1][2] + n2]
    return np.array([p[0] / p[2] for p in pools]), np.array([(p[1] + 0.02) / (p[2] + 0.04) for p in pools])


def fit_trees(x: np.ndarray, y: np.ndarray, apart: np.ndarray | None = None, trees: int = 60, depth: int = 3, rate: float = 0.15, bins: int = 64, least: float = 0.5, ridge: float = 1.0, seed: int = 3) -> Trees:
    """Boosting on the rows that are not ``apart``, calibration on those that are; by default a quarter of the rows by chance."""
    share = (y.sum() + 0.5) / (len(y) + 1)
    if len(y) < 20 or y.min() == y.max():
        return Trees([np.zeros(0)] * x.shape[1], float(np.log(share / (1 - share))))
    if apart is None:
        apart = np.random.default_rng(seed).random(len(y)) < 0.25
    check, fit = np.flatnonzero(apart), np.flatnonzero(~apart)
    if not len(fit):
        check, fit = check[:0], check
    edges = [np.unique(np.quantile(x[fit, k], np.linspace(0, 1, bins - 1))) for k in range(x.shape[1])]
    model = Trees(edges, float(np.log(share / (1 - share))))
    b, t = model.bins(x[fit]), y[fit].astype(float)
    f = np.full(len(fit), model.base)
    for _ in range(trees):
        p = 1 / (1 + np.exp(-f))
        which, cut, leaf, at = _tree(b, p - t, p * (1 - p) + 1e-6, depth, bins + 1, least, ridge)
        model.trees.append((which, cut, rate * leaf))
        f += rate * leaf[at]
    raw = 1 / (1 + np.exp(-model.logits(x[check])))
    model.xs, model.ys = isotonic(raw, y[check])
    if len(model.xs) and len(np.unique(y[check])) > 1:
        model.xs, model.ys = np.append(np.insert(model.xs, 0, 0.0), 1.0), np.append(np.insert(model.ys, 0, model.ys[0]), model.ys[-1])
    else:
        model.xs, model.ys = np.zeros(0), np.zeros(0)
    return model


def fit_toxicity(docs: DataFrame, labels: DataFrame, modulus: int = 5, remainder: int = 0, most_labelled: int = 20_000) -> tuple[dict[str, float], Trees]:
    """The lexicon and the calibrated trees from the bounded sample. A quarter of it, by the texts' hash, is kept for the calibration:
    neither the lexicon nor the trees learn from it."""
    sample = training_rows(docs, labels, "toxic", modulus, remainder, most_labelled).withColumn("apart", F.pmod(F.xxhash64("text"), F.lit(4)) == 0)
    lexicon = learn_lexicon(sample.where("NOT apart"))

    def measured(batches):
        weights = _Weights(lexicon)
        for b in batches:
            x = [features(t, weights) for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(x, pa.list_(pa.float64())), b.column(2)], ["y", "x", "apart"])

    data = sample.orderBy("doc_id").select("y", "text", "apart").mapInArrow(measured, "y int, x array<double>, apart boolean").toPandas()
    if not len(data):
        return lexicon, fit_trees(np.zeros((0, len(NAMES))), np.zeros(0))
    return lexicon, fit_trees(np.array(data["x"].tolist(), np.float64).reshape(len(data), len(NAMES)), data["y"].to_numpy(np.int64), data["apart"].to_numpy(bool))


def scorer(lexicon: dict[str, float], model: Trees):
    """texts -> scores, to be called in tasks."""
    weights = _Weights(lexicon)
    return lambda texts: model.scores(np.array([features(t or "", weights) for t in texts], np.float64).reshape(-1, len(NAMES)))


def score_toxicity(docs: DataFrame, labels: DataFrame, modulus: int = 5, remainder: int = 0, accept: float = 0.5, **options) -> DataFrame:
    """doc_id, held_out, score, predicted of every row."""
    lexicon, model = fit_toxicity(docs, labels, modulus, remainder, **options)

    def score(batches):
        judge = scorer(lexicon, model)
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(judge(b.column(1).to_pylist()))], ["doc_id", "score"])

    scored = doc_text(docs).select("doc_id", "text").mapInArrow(score, "doc_id long, score double")
    return scored.select("doc_id", held_out(modulus, remainder).alias("held_out"), "score", (F.col("score") >= accept).cast("int").alias("predicted"))


def toxic_rows(docs: DataFrame, labels: DataFrame, keep: bool, accept: float = 0.5, **options) -> DataFrame:
    """The rows, with all their columns, that are not toxic (``keep``) or that are. Rows are filtered where they lie."""
    lexicon, model = fit_toxicity(docs, labels, **options)
    place = docs.columns.index("text")

    def choose(batches):
        judge = scorer(lexicon, model)
        for b in batches:
            yield b.filter(pa.array((judge(b.column(place).to_pylist()) < accept) == keep))

    return docs.mapInArrow(choose, docs.schema)


def op8_toxicity_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return score_toxicity(documents(spark, sf_dir), labels_of(spark, sf_dir))
