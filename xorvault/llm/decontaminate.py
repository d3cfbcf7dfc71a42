"""Benchmark decontamination: training passages are queries on a BM25 inverted index of test items.

Items are indexed in pieces of at most one and a half half-passages, so that a piece lies in some query whole or for the
most part, however long its item. Texts are cut in half-passages of a fixed count of words; a query is two neighbouring
halves. A term's weight in a piece is BM25's, taken as a share of the score at which that piece is retrieved, so that one
threshold, 1, holds for short and long pieces. Pieces lie in blocks, and each term keeps its greatest weight per block and
overall. Per query, the sum of its terms' bounds is looked at first: where it doesn't reach the threshold at any term
(no pivot), nothing can be a result. Else the block maxima are added up along the terms' lists of blocks, and blocks that
stay below the threshold are skipped: block-max WAND's two tests, taken for all queries of a text at once in place of
moving cursors. Opened blocks are scored exactly, and the items of all pieces at or above a set share of their own
self-score are retrieved, without a cap. Verification then asks that the item's question and its answer both occur: of the
question's word n-grams a given share within one window of the text, and of the answer's words (answers are often too
short for n-grams) a given share in that window or next to it.

A test item's question is its text up to its last sentence, its answer that last sentence; where there is only one
sentence it is both. The item table is read in shards of at most about `shard_items` items; a scan of the documents takes
at most `shards_per_scan` of their indexes along, which bounds what is on the driver and what is sent to executors. More
items mean more scans. Null or empty texts and items match nothing; each input row, repeated ones too, has its own pairs;
repeated items count once; an empty table on either side gives no pair. Columns other than those named aren't read.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import bounded_rows, fresh, map_arrow, slices, stored, text_function

WORD = re.compile(r"\w+")
#: Sums of block maxima that are worked out at once.
SUMS_HELD = 1 << 20
SENTENCE = re.compile(r"(?<=[.!?])\s+")


@dataclass(frozen=True)
class Match:
    k1: float = 1.2
    b: float = 0.75
    least_share: float = 0.5
    half: int = 32
    block: int = 4
    gram: int = 3
    question_overlap: float = 0.6
    answer_overlap: float = 0.7
    shard_items: int = 1000
    shards_per_scan: int = 16


class Words(dict):
    """Term numbers of blank-separated words: a term, -1 for one that no item has, or below that a place in `several`."""

    def __init__(self, number: dict[str, int]):
        super().__init__()
        self.number = number
        self.several: list[list[int]] = []

    def __missing__(self, word: bytes) -> int:
        core = word.strip(b".,;:!?()[]\"'")
        if core.isalnum():  # one run of ASCII letters and digits
            term = self.number.get(core.decode().lower(), -1)
        else:
            found = [self.number.get(x, -1) for x in WORD.findall(word.decode("utf-8", "replace").lower())]
            if len(found) == 1:
                term = found[0]
            else:
                self.several.append(found)
                term = -1 - len(self.several)
        self[word] = term
        return term

    def terms(self, text: str) -> np.ndarray:
        """The text's terms in order."""
        if len(self) > 400_000:
            self.clear()
            self.several = []
        words = text.encode("utf-8", "surrogatepass").split()
        out = np.fromiter(map(self.__getitem__, words), np.int64, len(words))
        if len(out) and out.min() < -1:
            out = np.array([t for x in out.tolist() for t in ((x,) if x >= -1 else self.several[-2 - x])], np.int64)
        return out


def _grams(terms, n: int) -> set[tuple]:
    n = min(n, len(terms))
    return set(zip(*[terms[k:] for k in range(n)])) if n else set()


class ItemIndex:
    """Block-max inverted index of test items. A posting's weight is its share of what its piece needs to be retrieved."""

    def __init__(self, items: list[tuple[object, str]], match: Match = Match()):
        self.match = match
        kept = [(i, t, WORD.findall(t.lower())) for i, t in items if t]
        kept = [x for x in kept if x[2]]
        self.ids = [i for i, _, _ in kept]
        self.number: dict[str, int] = {}
        for _, _, words in kept:
            for x in words:
                self.number.setdefault(x, len(self.number))
        numbers = lambda s: [self.number[x] for x in WORD.findall(s.lower())]
        self.parts, pieces = [], []
        for j, (_, text, words) in enumerate(kept):
            sentences = [s for s in SENTENCE.split(text.strip()) if WORD.search(s)]
            self.parts.append((numbers(" ".join(sentences[:-1]) if len(sentences) > 1 else text), numbers(sentences[-1])))
            count = -(-len(words) // (match.half * 3 // 2))
            size = -(-len(words) // count)
            pieces += [(j, [self.number[x] for x in words[k : k + size]]) for k in range(0, len(words), size)]
        n = len(pieces)
        mean = sum(len(p) for _, p in pieces) / max(1, n)
        df = np.zeros(len(self.number))
        for _, p in pieces:
            df[list(set(p))] += 1
        idf = np.log(1 + (n - df + 0.5) / (df + 0.5))
        # Pieces whose common words are alike go to the same block, so that block maxima stay tight.
        pieces.sort(key=lambda p: sorted(set(p[1]), key=lambda t: (-df[t], t))[:3])
        self.item = [j for j, _ in pieces]
        self.blocks = -(-n // match.block)
        self.postings: list[dict[int, list[tuple[int, float]]]] = [{} for _ in range(self.blocks)]
        self.self_score = np.zeros(n)
        tops: dict[int, float] = {}
        for k, (_, p) in enumerate(pieces):
            b, weight = k // match.block, {}
            for t in set(p):
                c = p.count(t)
                weight[t] = float(idf[t] * c * (match.k1 + 1) / (c + match.k1 * (1 - match.b + match.b * len(p) / mean)))
                self.postings[b].setdefault(t, []).append((k, weight[t]))
            self.self_score[k] = sum(weight.values())
            for t, v in weight.items():
                at = t * self.blocks + b
                tops[at] = max(tops.get(at, 0.0), v / (match.least_share * self.self_score[k]))
        # Block maxima by term and block, and each term's list of blocks and bound over all of them.
        self.top_at = np.array(sorted(tops), np.int64)
        self.top = np.array([tops[x] for x in self.top_at.tolist()])
        self.block_at = self.top_at % max(1, self.blocks)
        self.starts = np.searchsorted(self.top_at, np.arange(len(self.number) + 1) * max(1, self.blocks))
        self.lists = np.diff(self.starts)
        bound = np.maximum.reduceat(self.top, self.starts[:-1]) if len(self.top) else np.zeros(0)
        self.term = np.argsort(bound, kind="stable")  # terms by ascending bound
        self.rank, self.bound = np.argsort(self.term), bound[self.term]

    def queries(self, terms: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(query, rank of the term's bound), distinct and in order, of all neighbouring halves of a text that have terms."""
        size = len(self.number)
        at = np.flatnonzero(terms >= 0)
        pair = at // self.match.half * np.int64(size) + self.rank[terms[at]]
        pair.sort()
        pair = pair[np.append(True, pair[1:] != pair[:-1])] if len(pair) else pair
        pair = np.concatenate([pair, pair[np.searchsorted(pair, size) :] - size])  # a half is also the second one of the query before
        pair.sort(kind="stable")
        pair = pair[np.append(True, pair[1:] != pair[:-1])] if len(pair) else pair
        query = pair // max(1, size)
        return query, pair - query * size

    def reachable(self, query: np.ndarray, rank: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(query, block) whose block maxima can reach a piece's threshold.

        Only queries with a pivot go on: those whose terms' bounds over all blocks add up to the threshold at some term. For
        these the block maxima are added up along the terms' lists of blocks; what no list names is never touched.
        """
        begins = np.flatnonzero(np.append(True, query[1:] != query[:-1]))
        ends = np.append(begins[1:], len(query))
        some = np.flatnonzero(np.add.reduceat(self.bound[rank], begins) >= 1 - 1e-9)
        step = max(1, SUMS_HELD // self.blocks)
        parts = [self._sums(query, rank, begins, ends, some[k : k + step]) for k in range(0, len(some), step)]
        none = np.zeros(0, np.int64)
        return np.concatenate([none, *(q for q, _ in parts)]), np.concatenate([none, *(b for _, b in parts)])

    def _sums(self, query: np.ndarray, rank: np.ndarray, begins: np.ndarray, ends: np.ndarray, some: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        sizes = (ends - begins)[some]
        entry = np.arange(sizes.sum()) + np.repeat(begins[some] - np.cumsum(sizes) + sizes, sizes)
        t = self.term[rank[entry]]
        count = self.lists[t]
        place = np.arange(count.sum()) + np.repeat(self.starts[t] - np.cumsum(count) + count, count)
        at = np.repeat(np.repeat(np.arange(len(some)) * self.blocks, sizes), count) + self.block_at[place]
        sums = np.bincount(at, self.top[place], len(some) * self.blocks)
        found = np.flatnonzero(sums >= 1 - 1e-9)
        row = found // self.blocks
        return query[begins[some[row]]], found - row * self.blocks

    def candidates(self, terms: np.ndarray) -> list[tuple[int, float]]:
        """All items of which a piece reaches its threshold for some query of this text, with the best such score; -1 is no term."""
        if not self.ids:
            return []
        query, rank = self.queries(terms)
        if not len(query):
            return []
        best: dict[int, float] = {}
        held, words = -1, set()
        for h, b in zip(*(x.tolist() for x in self.reachable(query, rank))):
            if h != held:
                held, words = h, set(self.term[rank[np.searchsorted(query, h) : np.searchsorted(query, h, "right")]].tolist())
            got: dict[int, float] = {}
            postings = self.postings[b]
            for t in postings.keys() & words:
                for k, v in postings[t]:
                    got[k] = got.get(k, 0.0) + v
            for k, s in got.items():
                if s >= self.match.least_share * self.self_score[k] - 1e-12 and s > best.get(self.item[k], 0.0):
                    best[self.item[k]] = s
        return sorted(best.items())

    def matches(self, terms: np.ndarray) -> list[dict]:
        """The retrieved items whose question stands in the text, with their answer at it."""
        found = self.candidates(terms)
        if not found:
            return []
        terms = terms.tolist()
        places: dict[int, dict[tuple, list[int]]] = {}
        out = []
        for j, score in found:
            question, answer = self.parts[j]
            n = min(self.match.gram, len(question))
            if n not in places:
                places[n] = {}
                for i, g in enumerate(zip(*[terms[k:] for k in range(n)])):
                    places[n].setdefault(g, []).append(i)
            own = _grams(question, n)
            width = 3 * (len(question) + len(answer)) // 2 + self.match.half
            start, held = densest([(i, g) for g in own for i in places[n].get(g, ())], width)
            q = held / len(own)
            if q < self.match.question_overlap:
                continue
            reach = len(answer) + self.match.half
            near = set(terms[max(0, start - reach) : start + width + reach])
            a = sum(t in near for t in answer) / len(answer)
            if a >= self.match.answer_overlap:
                out.append({"item_id": self.ids[j], "score": score, "question_overlap": q, "answer_overlap": a})
        return out


def densest(hits: list[tuple[int, object]], width: int) -> tuple[int, int]:
    """(start, count) of the window of `width` places with the most different things; hits are (place, thing)."""
    hits = sorted(hits, key=lambda x: x[0])
    seen: dict[object, int] = {}
    best, lo = (0, 0), 0
    for place, thing in hits:
        seen[thing] = seen.get(thing, 0) + 1
        while hits[lo][0] <= place - width:
            old = hits[lo][1]
            seen[old] -= 1
            if not seen[old]:
                del seen[old]
            lo += 1
        if len(seen) > best[1]:
            best = (hits[lo][0], len(seen))
    return best


def scans(items: DataFrame, match: Match, id_col: str, text_col: str) -> Iterator[list[ItemIndex]]:
    """The indexes that one scan of the documents takes along, scan by scan: no more than these are on the driver at a time.

    Distinct items are dealt by a hash to shards of at most about shard_items.
    """
    items = items.select(F.col(id_col).alias("i"), F.col(text_col).alias("t")).distinct()
    parts = max(1, math.ceil(1.25 * items.count() / match.shard_items))
    dealt = items.withColumn("shard", F.pmod(F.xxhash64("i", "t"), F.lit(parts)))
    for k in range(0, parts, match.shards_per_scan):
        here = range(k, min(parts, k + match.shards_per_scan))
        rows = bounded_rows(dealt.where(F.col("shard").between(here[0], here[-1])), 2 * match.shard_items * len(here), "a scan's test items")
        shards = {j: [(r["i"], r["t"]) for r in rows if r["shard"] == j and r["t"]] for j in here}
        yield [ItemIndex(sorted(x, key=lambda x: (str(x[0]), x[1])), match) for x in shards.values()]


def find_contamination(docs: DataFrame, items: DataFrame, *, match: Match = Match(), id_col: str = "doc_id", text_col: str = "text", item_id: str = "item_id", item_text: str = "text") -> DataFrame:
    """A row per document row and item that it contains: id, item_id, score (of its best piece) and both overlaps."""
    kind = items.schema[item_id].dataType.simpleString()
    columns = f"item_id {kind}, score double, question_overlap double, answer_overlap double"
    id_kind = docs.schema[id_col].dataType.simpleString()
    found = None
    for taken in scans(items, match, item_id, item_text):

        def search(batches, taken=taken):
            words = [Words(x.number) for x in taken]
            for batch in slices(batches):
                rows, hits = [], []
                for j, text in enumerate(batch.column(1).to_pylist()):
                    for index, known in zip(taken, words):
                        for m in index.matches(known.terms(text or "")):
                            rows.append(j)
                            hits.append(m)
                yield {"_id": batch.column(0).take(pa.array(rows, pa.int64())), **{c: [h[c] for h in hits] for c in ("item_id", "score", "question_overlap", "answer_overlap")}}

        one = map_arrow(docs.select(id_col, text_col), search, f"_id {id_kind}, {columns}")
        # Beyond the first scan, what is found is written before the next scan's indexes are made.
        found = one if found is None else stored(found, "leaks").unionAll(stored(one, "leaks"))
    return found.withColumnRenamed("_id", id_col)


def without_contaminated(docs: DataFrame, items: DataFrame, *, match: Match = Match(), text_col: str = "text", item_id: str = "item_id", item_text: str = "text") -> DataFrame:
    """The rows of docs, with all their columns, that contain no test item; each scan's result is written before the next one's."""
    mark, scanned = fresh(docs, "_items"), 0
    for taken in scans(items, match, item_id, item_text):

        def make(taken=taken):
            each = [(x, Words(x.number)) for x in taken]
            return lambda texts: [{"n_items": sum(len(x.matches(w.terms(t))) for x, w in each)} for t in texts]

        docs = stored(docs, "clean") if scanned else docs
        docs = docs.withColumn(mark, text_function(make, "n_items bigint")(F.col(text_col))["n_items"]).where(F.col(mark) == 0).drop(mark)
        scanned += 1
    return docs
