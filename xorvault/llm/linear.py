"""Labelled samples and the calibration that the learned operators share."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def fold(id_col: str, folds: int) -> Column:
    """crc32 of the id as text, modulo folds."""
    return F.crc32(F.col(id_col).cast("string").cast("binary")) % folds


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, *, folds: int, held_out: int, rows: int, id_col: str, text_col: str) -> DataFrame:
    """(text, label) of at most `rows` labelled documents outside the held-out fold, chosen by a hash of their ids.

    The chosen ids are at most `rows`, which bounds their broadcast; a label that is null is no label.
    """
    usable = labels.where(F.col(label).isNotNull() & F.col(id_col).isNotNull() & (fold(id_col, folds) != held_out))
    chosen = usable.groupBy(id_col).agg(F.max(label).cast("int").alias("_label")).orderBy(F.xxhash64(id_col), id_col).limit(rows)
    return docs.select(id_col, text_col).join(F.broadcast(chosen), id_col).select(id_col, F.col(text_col).alias("_text"), "_label")


def platt(margin: np.ndarray, label: np.ndarray, rounds: int = 100) -> tuple[float, float]:
    """a, b of 1 / (1 + exp(-(a m + b))) by Newton steps on smoothed targets."""
    pos, neg = label.sum(), (1 - label).sum()
    t = np.where(label == 1, (pos + 1) / (pos + 2), 1 / (neg + 2))
    a, b = 1.0, float(np.log((pos + 1) / (neg + 1)))
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(a * margin + b, -30, 30)))
        g = np.array([((p - t) * margin).sum() + 1e-3 * a, (p - t).sum()])
        w = np.maximum(p * (1 - p), 1e-9)
        h = np.array([[(w * margin * margin).sum() + 1e-3, (w * margin).sum()], [(w * margin).sum(), w.sum() + 1e-6]])
        step = np.linalg.solve(h, g)
        step *= min(1.0, 5 / max(1e-9, np.abs(step).max()))
        a, b = a - step[0], b - step[1]
        if np.abs(step).max() < 1e-8:
            break
    return float(a), float(b)


def isotonic(x: np.ndarray, y: np.ndarray, weight: float = 2.0, prior: float = 0.5) -> tuple[np.ndarray, np.ndarray]:
    """Pool-adjacent-violators fit: knots x and non-decreasing levels, each level shrunk to `prior` by `weight` rows."""
    order = np.argsort(x, kind="stable")
    blocks: list[list[float]] = []
    for v, t in zip(x[order], y[order]):
        if blocks and blocks[-1][2] == v:
            blocks[-1][0] += t
            blocks[-1][1] += 1
        else:
            blocks.append([t, 1.0, v])
        while len(blocks) > 1 and blocks[-2][0] / blocks[-2][1] >= blocks[-1][0] / blocks[-1][1]:
            t1, n1, v1 = blocks.pop()
            blocks[-1][0] += t1
            blocks[-1][1] += n1
            blocks[-1][2] = v1
    levels = np.array([(t + weight * prior) / (n + weight) for t, n, _ in blocks])
    return np.array([b[2] for b in blocks]), np.maximum.accumulate(levels)
