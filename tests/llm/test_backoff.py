import math
import random
from collections import Counter

import numpy as np
import pytest

from xorvault.llm.backoff_lm import Backoff, backoff_scores, cut_runs, pack_sorted, packed, unpack_sorted, unpacked
from xorvault.llm.common import words_of


def brute(texts, spec):
    docs = [words_of(t or "") for t in texts]
    counts = Counter()
    for d in docs:
        counts[()] += len(d)
        for k in range(1, spec.order + 1):
            counts.update(tuple(d[i : i + k]) for i in range(len(d) - k + 1))

    def score(history, word):
        gram = (*history, word)
        if not history:
            return counts[gram] / counts[()]
        if counts[gram] >= spec.least:
            return counts[gram] / counts[history]
        return spec.backoff * score(history[1:], word)

    return [math.fsum(math.log(score(tuple(d[max(0, i - spec.order + 1) : i]), d[i])) for i in range(len(d))) for d in docs]


TEXTS = ["a b c a b", "a b", None, "", "   ", "a", "b c a b c a", "x y z", "x y z", "é è é", "a " * 400]


@pytest.mark.parametrize("order", [1, 2, 3, 4])
@pytest.mark.parametrize("chunk", [1, 1 << 30])
def test_as_brute_force(spark, order, chunk):
    spec = Backoff(order=order, chunk_bytes=chunk if chunk > 1 else 40)
    docs = spark.createDataFrame([(k, t, "n") for k, t in enumerate(TEXTS)], "doc_id long, text string, n_words string").repartition(3)
    got = {r.doc_id: (r.n_words, r.log_score, r.mean_log_score) for r in backoff_scores(docs, spec=spec).collect()}
    for k, want in enumerate(brute(TEXTS, spec)):
        n = len(words_of(TEXTS[k] or ""))
        assert got[k][0] == n
        assert got[k][1] == pytest.approx(want, abs=1e-9)
        assert got[k][2] is None if not n else got[k][2] == pytest.approx(want / n, abs=1e-9)


@pytest.mark.parametrize("fan", [2, 3])
def test_levels(spark, fan):
    """Many chunks over a small fan take several levels, which give the same scores; the runs a chunk sends stay within the fan."""
    rng = random.Random(fan)
    texts = [" ".join(rng.choices("abcdefgh", k=rng.randint(0, 12))) for _ in range(30)] + TEXTS
    spec = Backoff(chunk_bytes=1, fan=fan, runs_per_task=4)
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(2)
    chunks = sum(len(t or "") for t in texts)
    assert chunks > fan**5
    spec = Backoff(chunk_bytes=math.ceil(chunks / fan**3), fan=fan, runs_per_task=4)
    got = {r.doc_id: r.log_score for r in backoff_scores(docs, spec=spec).collect()}
    assert [got[k] for k in range(len(texts))] == pytest.approx(brute(texts, spec), abs=1e-9)


def test_runs_cover_the_hashes():
    values = np.unique(np.random.default_rng(3).integers(0, 1 << 56, 5000).astype(np.uint64))
    for depth in (1, 2, 3):
        runs = list(cut_runs(values, 4, depth))
        assert [a for _, a, _ in runs] == [0] + [b for _, _, b in runs][:-1] and runs[-1][2] == len(values)
        assert len(runs) <= 4**depth and [b for b, _, _ in runs] == sorted({b for b, _, _ in runs})
    coarse, fine = (np.repeat([b for b, _, _ in r], [e - a for _, a, e in r]) for r in (list(cut_runs(values, 4, 1)), list(cut_runs(values, 4, 2))))
    assert (fine // 4 == coarse).all()


def test_edges(spark):
    docs = spark.createDataFrame([(None, "a b"), (1, "a b"), (1, "a b")], "doc_id long, text string")
    assert len({r.log_score for r in backoff_scores(docs).collect()}) == 1
    assert backoff_scores(docs.limit(0)).count() == 0


def test_packing():
    rng = np.random.default_rng(1)
    for n in (0, 1, 1000):
        v = np.sort(rng.integers(0, 2**63, n).astype(np.uint64))
        assert (unpack_sorted(pack_sorted(v), n) == v).all()
        assert (unpacked(packed(v % 300), n) == v % 300).all()
