"""Quality classifier: a support vector machine on n-gram indicators scaled by naive Bayes log-count ratios.

A document's features are indicators of its words, and of n-grams over word forms, as in prose, with its open vocabulary,
single words say little. A form keeps what a word looks like (case, digits, punctuation, whether the word repeats one just
before) and drops which letters it has. Each indicator is scaled by the log ratio of its smoothed class frequencies; on
these a linear hinge-loss model is fitted by dual coordinate descent, interpolated towards the plain Bayes weights, and its
margins are calibrated to probabilities on out-of-fold margins.

The fit uses a bounded sample of labelled rows outside the held-out fold (`train_rows`); scoring covers every whole text.
An empty or null text has only the bias feature, so its score is that of a featureless text. Repeated rows get equal scores;
a repeated label row counts once, as the greatest of its labels; an empty table of documents gives an empty result, and one
of labels (or labels of one class) the smoothed rate for every row. Equal scores stay equal: nothing is ranked. Columns
other than those named aren't read, whatever their names.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_arrow, slices, text_function, words_of
from .linear import fold, labelled_sample, platt

ORDER = 3
RUNS = re.compile(r"([A-Z]+)|([a-z]+)|([0-9]+)|([^\W\d_]+)|(.)", re.S)


def form(word: bytes) -> str:
    """Runs of a word's character classes, the longer runs of one punctuation mark shortened to two."""
    out = []
    for m in RUNS.finditer(word.decode("utf-8", "replace")):
        if m[1]:
            out.append("A" if len(m[1]) == 1 else "AA")
        elif m[2]:
            out.append("a")
        elif m[3]:
            out.append("0")
        elif m[4]:
            c = "a" if m[4].islower() else "A" if len(m[4]) == 1 else "AA"
            if not out or out[-1] != c:
                out.append(c)
        elif len(out) < 2 or out[-1] != m[5] or out[-2] != m[5]:
            out.append(m[5])
    return "".join(out)


class Forms(dict):
    """Words' forms; long words, which are rare, aren't remembered."""

    def __missing__(self, word: bytes) -> str:
        f = form(word)
        if len(word) <= 256:
            if len(self) > 300_000:
                self.clear()
            self[word] = f
        return f


def ngrams(words: list[bytes], forms: Forms) -> set[tuple]:
    """The distinct words of a text, and n-grams of its forms and of its repeat marks."""
    f = [*map(forms.__getitem__, words)]
    f.append("$")
    out = set(zip(words))
    out.update(zip(f))
    out.update(zip(f, f[1:]))
    out.update(zip(f, f[1:], f[2:]))
    same = [a == b for a, b in zip(words, words[1:])]
    if True in same:
        out.add(("=",))
        if any(map(all, zip(same, same[1:]))):
            out.add(("=", "="))
    n, distinct = len(words), len(set(words))
    out.add(("variety", str(10 * distinct // max(1, n)), str(n.bit_length() // 2)))
    windows = n - 2
    if windows > 0:
        out.add(("repeats", str(10 * len(set(zip(words, words[1:], words[2:]))) // windows)))
    return out


def key(gram: tuple) -> int:
    """A feature's number: words are bytes, and forms text."""
    if isinstance(gram[0], bytes):
        return xxhash.xxh64_intdigest(gram[0], 1) >> 1
    return xxhash.xxh64_intdigest("\x01".join(gram)) >> 1


@dataclass
class NbSvm:
    """Scaled weights by feature key, and what normalises and calibrates a margin."""

    keys: np.ndarray
    ratio: np.ndarray
    weight: np.ndarray
    bias: float
    a: float = 1.0
    b: float = 0.0


def fit_hinge(rows: list[np.ndarray], values: list[np.ndarray], y: np.ndarray, dim: int, cost: np.ndarray, rounds: int = 30, seed: int = 7) -> np.ndarray:
    """Dual coordinate descent for the hinge loss; the last weight is the bias."""
    w, alpha = np.zeros(dim), np.zeros(len(y))
    q = np.array([float(v @ v) for v in values])
    rng = np.random.default_rng(seed)
    for _ in range(rounds):
        worst = 0.0
        for i in rng.permutation(len(y)):
            if q[i] == 0:
                continue
            k, v = rows[i], values[i]
            g = y[i] * float(w[k] @ v) - 1
            new = min(max(alpha[i] - g / q[i], 0.0), cost[i])
            step = new - alpha[i]
            if step:
                w[k] += step * y[i] * v
                alpha[i] = new
                worst = max(worst, abs(step))
        if worst < 1e-3:
            break
    return w


def _fit(rows: list[np.ndarray], label: np.ndarray, dim: int, cost: float, beta: float) -> tuple[np.ndarray, np.ndarray]:
    """Log-count ratios and interpolated weights (with bias) from rows of feature numbers."""
    pos, neg = np.ones(dim), np.ones(dim)
    for k, t in zip(rows, label):
        (pos if t else neg)[k] += 1
    n_pos, n_neg = 2 + label.sum(), 2 + (1 - label).sum()
    ratio = np.log(pos / n_pos) - np.log(neg / n_neg)
    scaled, at = [], []
    for k in rows:
        v = ratio[k]
        norm = np.sqrt(v @ v) or 1.0
        scaled.append(np.append(v / norm, 1.0))
        at.append(np.append(k, dim))
    share = np.where(label == 1, 0.5 / max(1, label.sum()), 0.5 / max(1, (1 - label).sum())) * len(label)
    w = fit_hinge(at, scaled, 2.0 * label - 1, dim + 1, cost * share)
    mean = np.abs(w[:-1]).mean()
    return ratio, np.append((1 - beta) * mean + beta * w[:-1], w[-1])


def _margins(rows: list[np.ndarray], ratio: np.ndarray, w: np.ndarray) -> np.ndarray:
    out = []
    for k in rows:
        v = ratio[k]
        out.append(float(v @ w[k]) / (np.sqrt(v @ v) or 1.0) + w[-1])
    return np.array(out)


def train(features: list[np.ndarray], label: np.ndarray, *, least_df: int = 3, cost: float = 1.0, beta: float = 0.9, folds: int = 4) -> NbSvm:
    """Fit on each row's feature keys; calibrate on margins of rows left out in turn."""
    keys, df = np.unique(np.concatenate([*features, np.zeros(0, np.int64)]), return_counts=True)
    keys = keys[df >= least_df]
    rows = []
    for f in features:
        at = np.searchsorted(keys, f)
        at = at[at < len(keys)] if len(keys) else at[:0]
        rows.append(at[np.isin(keys[at], f)])
    label = label.astype(np.int64)
    if not len(label) or label.min() == label.max():
        p = (label.sum() + 1) / (len(label) + 2)
        return NbSvm(keys[:0], np.zeros(0), np.zeros(0), 0.0, 0.0, float(np.log(p / (1 - p))))
    left = np.zeros(len(label))
    for k in range(folds):
        out = np.arange(len(label)) % folds == k
        if label[~out].min() == label[~out].max():
            continue
        r, w = _fit([rows[i] for i in np.flatnonzero(~out)], label[~out], len(keys), cost, beta)
        left[out] = _margins([rows[i] for i in np.flatnonzero(out)], r, w)
    ratio, w = _fit(rows, label, len(keys), cost, beta)
    a, b = platt(left, label)
    return NbSvm(keys, ratio, w[:-1], float(w[-1]), max(a, 0.0), b)


class Scorer:
    def __init__(self, model: NbSvm):
        self.model, self.forms = model, Forms()
        self.at = {int(k): (float(r), float(r * w)) for k, r, w in zip(model.keys, model.ratio, model.weight)}
        self.seen: dict[tuple, tuple[float, float] | None] = {}

    def score(self, text: str) -> float:
        total = norm = 0.0
        seen = self.seen
        if len(seen) > 300_000:
            seen.clear()
        for gram in ngrams(words_of(text), self.forms):
            if gram not in seen:
                seen[gram] = self.at.get(key(gram))
            if x := seen[gram]:
                norm += x[0] * x[0]
                total += x[1]
        m = total / (norm**0.5 or 1.0) + self.model.bias
        return float(1 / (1 + np.exp(-np.clip(self.model.a * m + self.model.b, -30, 30))))


def fit_quality(docs: DataFrame, labels: DataFrame, *, label: str = "quality", folds: int = 4, held_out: int = 2, train_rows: int = 6000, id_col: str = "doc_id", text_col: str = "text") -> NbSvm:
    sample = labelled_sample(docs, labels, label, folds=folds, held_out=held_out, rows=train_rows, id_col=id_col, text_col=text_col)

    def featured(batches):
        forms = Forms()
        for batch in slices(batches):
            texts, found = batch.column("_text").to_pylist(), batch.column("_label")
            yield {"id": batch.column(id_col).cast(pa.string()), "label": found, "features": [[key(g) for g in ngrams(words_of(t or ""), forms)] for t in texts]}

    got = map_arrow(sample, featured, "id string, label int, features array<bigint>").toArrow().combine_chunks()
    order = np.argsort(np.array(got["id"].to_pylist(), object).astype(str), kind="stable")
    arrays = [np.unique(np.asarray(got["features"][int(i)].values)) for i in order] if got.num_rows else []
    return train(arrays, np.array(got["label"].to_pylist(), np.int64)[order] if got.num_rows else np.zeros(0))


def score_quality(docs: DataFrame, labels: DataFrame, *, threshold: float = 0.7, folds: int = 4, held_out: int = 2, train_rows: int = 6000, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, held_out, score, predicted."""
    model = fit_quality(docs, labels, folds=folds, held_out=held_out, train_rows=train_rows, id_col=id_col, text_col=text_col)

    def make():
        scorer = Scorer(model)
        return lambda texts: [{"score": scorer.score(t)} for t in texts]

    made = docs.select(F.col(id_col), (fold(id_col, folds) == held_out).alias("held_out"), text_function(make, "score double")(F.col(text_col)).alias("_r"))
    return made.select(id_col, "held_out", F.col("_r.score").alias("score"), (F.col("_r.score") >= threshold).cast("int").alias("predicted"))
