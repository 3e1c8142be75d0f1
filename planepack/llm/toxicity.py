"""Toxicity by a classifier chain of linear models.

The categories are predicted one after the other; each model also sees the probabilities of the categories before it.  While training,
those probabilities are out-of-fold predictions, so a later model never learns from answers its input model has seen.

Features of a document are its distinct words, lower-cased, and the words' beginnings of 3 to 6 characters, counted once a distinct
word; a chi-square test keeps the ``features`` strongest of each category.  The models are fitted on a bounded sample of labelled rows
(the ``sample`` rows with the smallest hash of the id, up to ``chars`` characters: the documented bound); scoring covers every row, in one narrow pass: a
word's weights are kept, so a row costs one lookup per distinct word.

Categories are columns of the labels; ``low_quality`` is ``1 - quality``.  Defined results: null or empty text has no features and gets the
models' intercepts, but is never rejected; without labelled rows (or with one class) a category's probability is its rate (0 without
rows); repeated labels of a document count by their maximum, and of repeated documents one is fitted on and all are scored; a null id is scored and never fitted on;
further columns of any name pass through the filter unchanged; an empty table gives no rows.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import common as C

CHAIN = ("low_quality", "toxic")
SAMPLE, SAMPLE_CHARS, FEATURES, FOLDS, L2 = 8_000, 60_000_000, 600, 3, 0.05
WORD = re.compile(r"[^\W_]+")
WORD_CACHE = 150_000


def features_of(word: str) -> list[str]:
    return [word, *(f"{word[:k]}*" for k in range(3, 7) if len(word) >= k)]


def words_of(text: str | None) -> set[str]:
    return set(WORD.findall(text.lower())) if text else set()


class _Hashes(dict):
    """Feature hashes of words."""

    def __missing__(self, word: str) -> list[int]:
        if len(self) >= WORD_CACHE:
            self.clear()
        self[word] = x = [xxhash.xxh3_64_intdigest(f) for f in features_of(word)]
        return x


def _counted(text: str | None, hashes: _Hashes) -> tuple[np.ndarray, np.ndarray]:
    """Features of a text, and how many of its words have each."""
    return np.unique(np.fromiter((h for w in words_of(text) for h in hashes[w]), np.uint64), return_counts=True)


#: Texts whose features are counted together while fitting.
CHUNK = 500


def _frequencies(texts: list[str], labels: np.ndarray, hashes: _Hashes) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sorted features of all texts, the texts that have each, and those of them in each category; a chunk of texts is held at a time."""
    m = labels.shape[1]
    kinds, df, pos = np.empty(0, np.uint64), np.empty(0), np.empty((0, m))
    for lo in range(0, len(texts), CHUNK):
        parts = [_counted(t, hashes)[0] for t in texts[lo : lo + CHUNK]]
        flat = np.concatenate(parts)
        if not len(flat):
            continue
        owner = np.repeat(np.arange(lo, lo + len(parts)), [len(x) for x in parts])
        order = np.argsort(flat, kind="stable")
        flat, y = flat[order], labels[owner[order]].astype(float)
        first = np.nonzero(np.concatenate([[True], flat[1:] != flat[:-1]]))[0]
        both, at = np.unique(np.concatenate([kinds, flat[first]]), return_inverse=True)
        df = np.bincount(at, np.concatenate([df, np.diff(np.append(first, len(flat)))]), len(both))
        pos = np.stack([np.bincount(at, np.concatenate([pos[:, c], np.add.reduceat(y[:, c], first)]), len(both)) for c in range(m)], 1)
        kinds = both
    return kinds, df, pos


def _sigmoid(z):
    return 1.0 / (1.0 + np.exp(-np.clip(z, -35, 35)))


def fit_linear(x: np.ndarray, extra: np.ndarray, y: np.ndarray, rows: np.ndarray, steps: int = 120) -> np.ndarray:
    """L2-regularised logistic regression by accelerated gradient steps with a diagonal scale: [intercept, extra, features]."""
    y, k = y[rows].astype(np.float32), extra.shape[1]
    a = np.empty((len(y), 1 + k + x.shape[1]), np.float32)
    a[:, 0], a[:, 1 : 1 + k] = 1, extra[rows]
    np.compress(rows, x, axis=0, out=a[:, 1 + k :])
    n = max(1, len(y))
    rate = float(np.clip(y.sum() / n, 1e-4, 1 - 1e-4))
    w = np.zeros(a.shape[1], np.float32)
    w[0] = np.log(rate / (1 - rate))
    if y.sum() in (0, len(y)):
        return w
    # the steepest curvature of the scaled problem, by a few power iterations
    scale = np.sqrt(0.25 * np.einsum("ij,ij->j", a, a) + L2).astype(np.float32)
    a /= scale
    b = a
    v = np.ones(a.shape[1], np.float32)
    for _ in range(12):
        v /= np.linalg.norm(v)
        v = 0.25 * (b.T @ (b @ v))
    rate_of_steps = 1.0 / (float(np.linalg.norm(v)) * 1.05 + 1)
    z = w * scale
    p, t = z.copy(), 1.0
    for _ in range(steps):
        g = b.T @ (_sigmoid(b @ p) - y)
        g[1:] += (L2 * p / scale**2)[1:]
        new = p - rate_of_steps * g
        t2 = (1 + np.sqrt(1 + 4 * t * t)) / 2
        p = new + np.float32((t - 1) / t2) * (new - z)
        z, t = new, t2
    return z / scale


def predict(x: np.ndarray, extra: np.ndarray, w: np.ndarray) -> np.ndarray:
    k = extra.shape[1]
    return _sigmoid(w[0] + extra @ w[1 : 1 + k] + x @ w[1 + k :])


def best_threshold(p: np.ndarray, y: np.ndarray) -> float:
    """The cut with the best F1 on out-of-fold predictions, in the middle of the gap there, within [0.1, 0.9]."""
    if not len(p) or not y.any():
        return 0.5
    order = np.argsort(-p, kind="stable")
    hit = np.cumsum(y[order])
    f1 = 2 * hit / (np.arange(1, len(p) + 1) + y.sum())
    k = int(f1.argmax())
    low = p[order[k + 1]] if k + 1 < len(p) else 0.0
    return float(np.clip((p[order[k]] + low) / 2, 0.1, 0.9))


class Chain:
    """Intercepts, weights of earlier probabilities, and a weight per category for every kept feature."""

    def __init__(self, names, texts: list[str], labels: np.ndarray, features: int = FEATURES, folds: int = FOLDS):
        self.names = list(names)
        m = len(self.names)
        n, hashes = max(1, len(texts)), _Hashes()
        kinds, df, hit = _frequencies(texts, labels, hashes)
        kept = np.zeros(len(kinds), bool)
        for c in range(m):
            rate = float(labels[:, c].mean()) if len(texts) else 0.0
            if 0 < rate < 1:
                score = np.where(df >= 3, (hit[:, c] - df * rate) ** 2 / (df * rate * (1 - rate)) * (1 - df / n), -1.0)
                kept[np.lexsort((kinds, -score))[:features]] |= True
        kept &= df >= 3
        chosen = kinds[kept]
        del kinds, df, hit, kept
        x, names_of, wanted = np.zeros((len(texts), len(chosen)), np.float32), {}, set(chosen.tolist())
        for i, t in enumerate(texts):
            if not len(chosen):
                break
            k, count = _counted(t, hashes)
            at = np.minimum(np.searchsorted(chosen, k), len(chosen) - 1)
            has = chosen[at] == k
            x[i, at[has]] = count[has]
            for w in words_of(t):
                for h, f in zip(hashes[w], features_of(w), strict=True):
                    if h in wanted:
                        names_of[h] = f
        index = {names_of[h]: i for i, h in enumerate(chosen.tolist())}
        hashes.clear()
        rows = range(len(texts))
        fold = np.arange(len(rows)) % folds
        extra = np.zeros((len(rows), 0))
        self.bias, self.chained, weights = [], [], []
        self.held_out = []
        for c in range(m):
            y = labels[:, c].astype(float) if len(rows) else np.zeros(0)
            w = fit_linear(x, extra, y, np.ones(len(rows), bool))
            self.bias.append(float(w[0]) if len(rows) else -9.0)
            self.chained.append(w[1 : 1 + c].tolist())
            weights.append(w[1 + c :])
            oof = np.zeros(len(rows))
            for k in range(folds):
                at = fold == k
                oof[at] = predict(x, extra, fit_linear(x, extra, y, ~at))[at]
            extra = np.column_stack([extra, oof])
            self.held_out.append(float(((oof > 0.5) == (y > 0.5)).mean()) if len(rows) else 1.0)
            self.threshold = best_threshold(oof, y)
        self.weights = {f: tuple(float(w[i]) for w in weights) for f, i in index.items()}

    def word(self, word: str) -> tuple[float, ...]:
        found = [self.weights[f] for f in features_of(word) if f in self.weights]
        return tuple(map(sum, zip(*found, strict=True))) if found else ()

    def probabilities(self, sums: np.ndarray) -> np.ndarray:
        """From the rows' summed word weights, category after category."""
        out = np.zeros_like(sums)
        for c in range(sums.shape[1]):
            out[:, c] = _sigmoid(self.bias[c] + out[:, :c] @ np.array(self.chained[c]) + sums[:, c])
        return out


def fit_chain(docs: DataFrame, labels: DataFrame, names=CHAIN, sample: int = SAMPLE, chars: int = SAMPLE_CHARS) -> Chain:
    """Fit on at most ``sample`` labelled rows of at most ``chars`` characters in all, chosen by the hash of their ids."""
    col = {"low_quality": 1 - F.col("quality")}
    picked = labels.filter("doc_id is not null").groupBy("doc_id").agg(*(F.max(col.get(n, F.col(n) if n in labels.columns else F.lit(None))).cast("int").alias(n) for n in names)).dropna()
    picked = picked.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample).withColumnRenamed("doc_id", "__id")
    rows = docs.select("doc_id", "text").join(F.broadcast(picked), F.col("doc_id") == F.col("__id")).filter("text is not null")
    rows = rows.groupBy("doc_id", *names).agg(F.min("text").alias("text"))  # one row a document, whatever repeats
    so_far = F.sum(F.length("text").cast("long")).over(Window.orderBy(F.xxhash64("doc_id"), "doc_id"))  # over at most ``sample`` rows
    rows = rows.withColumn("__chars", so_far).filter(F.col("__chars") <= chars).select("doc_id", "text", *names).toArrow().sort_by("doc_id")
    labels = np.column_stack([rows[n].to_numpy() for n in names]) if rows.num_rows else np.zeros((0, len(names)))
    return Chain(names, rows["text"].to_pylist(), labels, FEATURES)


def score(docs: DataFrame, chain: Chain, threshold: float | None = None, filtering: bool = False) -> DataFrame:
    """doc_id, a probability per category and ``rejected``; or, with ``filtering``, the rows of ``docs`` that stay."""
    held = docs.sparkSession.sparkContext.broadcast(chain)
    m = len(chain.names)
    threshold = chain.threshold if threshold is None else threshold
    schema = pa.schema([("doc_id", pa.int64()), *((f"p_{n}", pa.float64()) for n in chain.names), ("rejected", pa.bool_())])

    class Weights(dict):
        def __missing__(self, w):
            if len(self) >= WORD_CACHE:
                self.clear()
            self[w] = x = held.value.word(w)
            return x

    def run(batches, at):
        known = Weights()
        for r in batches:
            sums = np.zeros((r.num_rows, m))
            texts = r.column(at).to_pylist()
            for i, t in enumerate(texts):
                # summed in a fixed order, so that a row's result depends on nothing else
                for x in sorted(filter(None, map(known.__getitem__, words_of(t)))):
                    sums[i] += x
            p = held.value.probabilities(sums)
            bad = (p[:, -1] > threshold) & np.array([bool(t) for t in texts], bool)
            if filtering:
                yield r.filter(pa.array(~bad))
            else:
                yield C.batch(schema, r.column(0), *(pa.array(p[:, c]) for c in range(m)), pa.array(bad))

    if filtering:
        at = docs.columns.index("text")
        return docs.transform(C.arrow, lambda b: run(b, at), docs.schema)
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").transform(C.arrow, lambda b: run(b, 1), "doc_id long, " + ", ".join(f"p_{n} double" for n in chain.names) + ", rejected boolean")


def op8(spark, sf_dir):
    docs = C.table(spark, sf_dir, "documents", "doc_id", "text")
    return score(docs, fit_chain(docs, C.table(spark, sf_dir, "labels")))
