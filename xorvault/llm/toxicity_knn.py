"""Toxicity by the nearest labelled examples under exact TF-IDF cosine, found in a block-max inverted index.

Terms are lower-case letter runs and their prefixes (stems) at which labelled examples of the two classes differ; a
chi-square test on a bounded sample picks them, since in prose most words say nothing about the label and would drown
those that do. All other words of a text count as one term, so that a cosine also compares how dense the chosen terms
are. Document frequencies come from the whole corpus. Examples are indexed by term; postings are cut in blocks of
examples, and each term keeps its greatest weight per block. A query adds these up to bounds of all blocks, opens blocks
from the highest bound down and stops when no closed block can reach the k-th best cosine, so the neighbours are exact.
Equal cosines go to the lower example. Votes are weighted by cosine; the vote share is calibrated by an isotonic fit on
the examples, each scored by terms chosen, and among examples indexed, without its fifth of the sample. The ids of all
voting neighbours and the shared terms are the evidence.

The index holds at most `train_rows` examples, which bounds its broadcast; scoring covers every whole text. A text with
no chosen term (also an empty or null one) gets the calibrated rate of such examples and no evidence. Repeated rows get
equal results; a repeated label row counts once, as the greatest of its labels; an empty table of documents gives an empty
result, and one of labels the score 0.5 for every row. Columns other than those named aren't read, whatever their names.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_arrow, slices, stored, text_function, words_of
from .linear import fold, isotonic, labelled_sample

LETTERS = re.compile(r"[^\W\d_]+")


#: Lengths of the prefixes that are terms.
STEMS = range(4, 9)


def terms_of_word(word: bytes) -> tuple[bytes, ...]:
    """A blank-separated word's letter runs, and with a mark their proper prefixes."""
    out = []
    for run in LETTERS.findall(word.decode("utf-8", "replace").lower()):
        out.append(run.encode())
        out += [f"{run[:n]}-".encode() for n in STEMS if n < len(run)]
    return tuple(out)


class Terms(dict):
    """Chosen terms' numbers within a word."""

    def __init__(self, vocabulary: dict[bytes, int]):
        super().__init__()
        self.vocabulary = vocabulary

    def __missing__(self, word: bytes) -> tuple[int, ...]:
        if len(self) > 400_000:
            self.clear()
        self[word] = found = tuple(self.vocabulary[t] for t in terms_of_word(word) if t in self.vocabulary)
        return found

    def counts(self, text: str) -> dict[int, int]:
        """Counts by term; the last number stands for all words without a chosen term. Empty if none has one."""
        out: dict[int, int] = {}
        words, some = words_of(text), 0
        for found in filter(None, map(self.__getitem__, words)):
            some += 1
            for t in found:
                out[t] = out.get(t, 0) + 1
        if out and some < len(words):
            out[len(self.vocabulary)] = len(words) - some
        return out


@dataclass
class BlockMaxIndex:
    """Unit vectors of examples by term; the last term stands for all words without a chosen one."""

    n_terms: int
    ids: list
    label: np.ndarray
    idf: np.ndarray
    block: int = 64
    postings: dict[int, tuple[np.ndarray, np.ndarray, list[int]]] = field(default_factory=dict)
    tops: dict[int, np.ndarray] = field(default_factory=dict)

    def vector(self, counts: dict[int, int]) -> tuple[np.ndarray, np.ndarray]:
        t = np.array(sorted(counts), np.int64)
        v = (1 + np.log([counts[k] for k in t])) * self.idf[t] if len(t) else np.zeros(0)
        norm = np.sqrt(v @ v)
        return t, v / norm if norm else v

    def add(self, vectors: list[tuple[np.ndarray, np.ndarray]]) -> None:
        gathered: dict[int, tuple[list, list]] = {}
        for d, (terms, weights) in enumerate(vectors):
            for t, w in zip(terms.tolist(), weights.tolist()):
                at, of = gathered.setdefault(t, ([], []))
                at.append(d)
                of.append(w)
        blocks = -(-max(1, len(vectors)) // self.block)
        for t, (at, of) in gathered.items():
            at, of = np.array(at), np.array(of)
            top = np.zeros(blocks)
            np.maximum.at(top, at // self.block, of)
            starts = np.searchsorted(at, np.arange(blocks + 1) * self.block).tolist()
            self.postings[t], self.tops[t] = (at, of, starts), top

    def nearest(self, terms: np.ndarray, weights: np.ndarray, k: int, without: int = -1) -> tuple[np.ndarray, np.ndarray]:
        """The k examples of highest cosine above 0, ties to the lower number; `without` is left out."""
        parts = [(self.postings[t], self.tops[t], w) for t, w in zip(terms.tolist(), weights.tolist()) if t in self.postings]
        found, cosine = np.zeros(0, np.int64), np.zeros(0)
        if not parts:
            return found, cosine
        bound = np.zeros(len(parts[0][1]))
        for _, top, w in parts:
            bound += top * w
        order = np.argsort(-bound, kind="stable")
        bound = bound[order]
        at, step, size = 0, 2, self.block
        while at < len(order) and bound[at] > 0:
            if len(found) == k:  # a closed block can only matter above the k-th cosine, or with it and lower numbers
                worst = cosine[-1]
                if bound[at] < worst - 1e-9:
                    break
                if bound[at] < worst + 1e-9 and (order[at : np.searchsorted(-bound, -(worst - 1e-9), "right")] * size > found[-1]).all():
                    break
            opened = np.sort(order[at : at + step])
            scores = np.zeros(len(opened) * size)
            for (docs, of, starts), _, w in parts:
                for j, b in enumerate(opened.tolist()):
                    lo, hi = starts[b], starts[b + 1]
                    if hi > lo:
                        scores[docs[lo:hi] + (j - b) * size] += of[lo:hi] * w
            hit = np.flatnonzero(scores > 0)
            ids = opened[hit // size] * size + hit % size
            if without >= 0:
                hit, ids = hit[ids != without], ids[ids != without]
            found, cosine = np.append(found, ids), np.append(cosine, np.round(scores[hit], 12))
            best = np.lexsort((found, -cosine))[:k]
            found, cosine = found[best], cosine[best]
            at, step = at + step, min(2 * step, 16)
        return found, cosine


@dataclass
class ToxicityModel:
    terms: list[bytes]
    index: BlockMaxIndex
    k: int
    knots: np.ndarray
    levels: np.ndarray
    bare: float

    def share(self, found: np.ndarray, cosine: np.ndarray) -> float:
        return float((self.index.label[found] * cosine).sum() / (cosine.sum() + 0.25))

    def calibrated(self, share: float) -> float:
        return float(np.interp(share, self.knots, self.levels))


#: Parts of the sample that calibration leaves out in turn.
PARTS = 5


def contrast(featured: DataFrame, least_chi2: float, least_df: int) -> list[list[bytes]]:
    """Terms of rows (label, part, terms) that are more frequent in the positive class than chance allows, strongest first:
    by all rows, then by those outside each part.

    Counts are one Spark aggregate; only terms that pass come to the driver, a part of those of the bounded sample. Of terms
    of which one is another's stem only the stronger stays.
    """
    negative = 1 - F.col("label")
    sizes = {r["part"]: (r["p"], r["n"]) for r in featured.groupBy("part").agg(F.sum("label").alias("p"), F.sum(negative).alias("n")).collect()}
    counts = featured.select("label", "part", F.explode("terms").alias("t")).groupBy("t")
    of = lambda v, k: F.sum(F.when(F.col("part") == k, v).otherwise(0))
    counts = counts.agg(F.sum("label").alias("a"), F.sum(negative).alias("b"), *[x for k in range(PARTS) for x in (of(F.col("label"), k).alias(f"a{k}"), of(negative, k).alias(f"b{k}"))])
    total = [sum(x[i] for x in sizes.values()) for i in (0, 1)]

    def chi2(a, b, p: int, n: int):
        strong = (a + b >= least_df) & (a * n > b * p)
        return F.when(strong, (p + n) * F.pow(a * n - b * p, 2.0) / ((a + b) * (p + n - a - b) * p * n)).otherwise(0.0) if p and n else F.lit(0.0)

    a, b = F.col("a").cast("double"), F.col("b").cast("double")
    each = [chi2(a, b, *total)] + [chi2(a - F.col(f"a{k}"), b - F.col(f"b{k}"), *(total[i] - sizes.get(k, (0, 0))[i] for i in (0, 1))) for k in range(PARTS)]
    rows = counts.select("t", F.array(*each).alias("chi2")).where(F.array_max("chi2") >= least_chi2).collect()
    out = []
    for k in range(1 + PARTS):
        kept: list[bytes] = []
        for r in sorted((r for r in rows if r["chi2"][k] >= least_chi2), key=lambda r: (-r["chi2"][k], bytes(r["t"]))):
            stem = bytes(r["t"]).rstrip(b"-")
            if not any(stem.startswith(x.rstrip(b"-")) or x.startswith(stem) for x in kept):
                kept.append(bytes(r["t"]))
        out.append(sorted(kept))
    return out


def built_index(terms: list[bytes], examples: list[tuple], idf: np.ndarray) -> tuple[BlockMaxIndex, list]:
    """The index of examples (id, label, counts by term), and the examples in its order."""
    index = BlockMaxIndex(len(terms) + 1, [], np.zeros(0, np.int64), np.append(idf, 1.0))
    vectors = [index.vector(c) for _, _, c in examples]
    # Examples that are alike lie together, so that block maxima are tight: by their heaviest chosen term, then by its share.
    heavy = [max(((w, t) for t, w in zip(v[0].tolist(), v[1].tolist()) if t < len(terms)), default=(0.0, -1)) for v in vectors]
    order = sorted(range(len(examples)), key=lambda j: (heavy[j][1], round(heavy[j][0], 1), len(examples[j][0] or ""), examples[j][0] or ""))
    plain = index.vector({len(terms): 1})
    index.ids, index.label = [examples[j][0] for j in order], np.array([examples[j][1] for j in order], np.int64)
    index.add([vectors[j] if len(vectors[j][0]) else plain for j in order])
    return index, [examples[j] for j in order]


def fit_toxicity(docs: DataFrame, labels: DataFrame, *, label: str = "toxic", folds: int = 5, held_out: int = 0, train_rows: int = 8000, k: int = 15, least_chi2: float = 30.0, least_df: int = 4, id_col: str = "doc_id", text_col: str = "text") -> ToxicityModel:
    sample = labelled_sample(docs, labels, label, folds=folds, held_out=held_out, rows=train_rows, id_col=id_col, text_col=text_col)
    sample = stored(sample.withColumn("_part", F.pmod(F.xxhash64(id_col), F.lit(PARTS)).cast("int")), "toxicity-sample")

    def featured(batches):
        memo: dict[bytes, tuple] = {}
        for batch in slices(batches):
            sets = []
            for x in batch.column("_text").to_pylist():
                found: set[bytes] = set()
                for w in set(words_of(x or "")):
                    if w not in memo:
                        if len(memo) > 200_000:
                            memo.clear()
                        memo[w] = terms_of_word(w)
                    found.update(memo[w])
                sets.append(list(found))
            yield {"label": batch.column("_label"), "part": batch.column("_part"), "terms": sets}

    chosen = contrast(map_arrow(sample, featured, "label int, part int, terms array<binary>"), least_chi2, least_df)
    numbers = [{t: j for j, t in enumerate(terms)} for terms in chosen]

    def counted(batches):
        known = [Terms(x) for x in numbers]
        for batch in slices(batches):
            rows = [[x.counts(t or "") for x in known] for t in batch.column("_text").to_pylist()]
            yield {"id": batch.column(id_col).cast(pa.string()), "label": batch.column("_label"), "part": batch.column("_part"), "terms": [[list(c) for c in r] for r in rows], "counts": [[list(c.values()) for c in r] for r in rows]}

    got = map_arrow(sample, counted, "id string, label int, part int, terms array<array<int>>, counts array<array<int>>").toArrow().to_pylist()
    got.sort(key=lambda r: (len(r["id"] or ""), r["id"] or ""))
    every = sorted({t for terms in chosen for t in terms})
    n_docs, df = _document_frequencies(docs, {t: j for j, t in enumerate(every)}, text_col)
    idf = {t: float(x) for t, x in zip(every, np.log((1 + n_docs) / (1 + df)) + 1)}
    rows = lambda v, without: [(r["id"], r["label"], dict(zip(r["terms"][v], r["counts"][v]))) for r in got if r["part"] != without]
    weights = lambda v: np.array([idf[t] for t in chosen[v]])
    index, _ = built_index(chosen[0], rows(0, None), weights(0))
    model = ToxicityModel(chosen[0], index, k, np.zeros(1), np.full(1, 0.5), 0.5)
    # Calibration: each example is scored by terms that were chosen, and examples that are indexed, without its part.
    shares, truth, bare = [], [], []
    for part in range(PARTS):
        other = ToxicityModel(chosen[1 + part], built_index(chosen[1 + part], rows(1 + part, part), weights(1 + part))[0], k, model.knots, model.levels, 0.5)
        for r in got:
            if r["part"] == part:
                counts = dict(zip(r["terms"][1 + part], r["counts"][1 + part]))
                if counts:
                    shares.append(other.share(*other.index.nearest(*other.index.vector(counts), k)))
                    truth.append(r["label"])
                else:
                    bare.append(r["label"])
    model.bare = float((sum(bare) + 0.5) / (len(bare) + 2)) if got else 0.5
    if shares:
        model.knots, model.levels = isotonic(np.array(shares), np.array(truth, float), prior=float(np.mean(truth)))
    return model


def _document_frequencies(docs: DataFrame, number: dict[bytes, int], text_col: str) -> tuple[int, np.ndarray]:
    """Rows of docs, and how many have each chosen term; each task sends one row of counts, the rows' count last."""

    def count(batches):
        terms, df = Terms(number), np.zeros(len(number) + 1, np.int64)
        for batch in slices(batches):
            for x in batch.column(0).to_pylist():
                df[-1] += 1
                found = set(map(terms.__getitem__, words_of(x or "")))
                found.discard(())
                if found:
                    df[list({t for f in found for t in f})] += 1
        yield {"df": [df.tolist()]}

    each = map_arrow(docs.select(text_col), count, "df array<bigint>")
    total = np.zeros(len(number) + 1)
    for r in each.select(F.posexplode("df").alias("t", "c")).groupBy("t").agg(F.sum("c").alias("c")).collect():
        total[r["t"]] = r["c"]
    return int(total[-1]), total[:-1]


def score_toxicity(docs: DataFrame, labels: DataFrame, *, threshold: float = 0.5, folds: int = 5, held_out: int = 0, train_rows: int = 8000, k: int = 15, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, held_out, score, predicted, and the evidence (ids of neighbours, shared terms)."""
    model = fit_toxicity(docs, labels, folds=folds, held_out=held_out, train_rows=train_rows, k=k, id_col=id_col, text_col=text_col)
    number = {t: j for j, t in enumerate(model.terms)}

    def make():
        terms = Terms(number)
        known: dict[tuple, dict] = {}

        def one(text: str) -> dict:
            counts = terms.counts(text)
            at = tuple(sorted(counts.items()))
            if at not in known:
                if len(known) > 50_000:
                    known.clear()
                found, cosine = model.index.nearest(*model.index.vector(counts), model.k) if counts else (np.zeros(0, np.int64), np.zeros(0))
                score = model.calibrated(model.share(found, cosine)) if len(found) else model.bare
                known[at] = {"score": score, "neighbours": [model.index.ids[j] for j in found], "shared_terms": [model.terms[t].decode() for t in sorted(counts) if t < len(model.terms)]}
            return known[at]

        return lambda texts: [one(x) for x in texts]

    scored = text_function(make, "score double, neighbours array<string>, shared_terms array<string>")(F.col(text_col))
    made = docs.select(F.col(id_col), (fold(id_col, folds) == held_out).alias("held_out"), scored.alias("_r"))
    return made.select(id_col, "held_out", F.col("_r.score").alias("score"), (F.col("_r.score") >= threshold).cast("int").alias("predicted"), F.array_join("_r.neighbours", ",").alias("neighbours"), F.array_join("_r.shared_terms", ",").alias("shared_terms"))
