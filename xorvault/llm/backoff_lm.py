"""Stupid-backoff language-model scores, computed as a join of n-gram counts over hash partitions.

Score of a word after its history: count(history word) / count(history) where the n-gram is counted at least `least`
times in the corpus, else `backoff` times the score after the history's shorter suffix; alone, count(word) / total.
A document's score is the sum of logarithms over its words, with histories inside the document.

Counts and join are relational: n-grams of all orders (the total is the count of the empty one) are exploded, keyed by
a 56-bit hash, partitioned by ranges of that hash, summed, and joined back to the documents. What moves is packed, since a
row for each n-gram would be some fifteen times the input: rows are gathered in chunks by a hash of document id and text;
a chunk sends each of its distinct n-grams once, as sorted, delta-coded runs of hashes with counts, one run for each of
`fan` ranges of hashes. A range's node sums its runs and returns the corpus counts run by run. Above `fan` chunks, nodes
merge their runs and send finer ranges to a next level, and hand on what comes back: runs a chunk stay constant in number
and size, and only levels grow, with the logarithm of the input. A frequent n-gram is one entry per run, so it makes no
hot node, and no table of n-grams is ever broadcast or held whole. Each chunk then scores its documents from its returned
counts. The number of shuffle partitions follows the input at every step.

Null and empty texts have no words: log_score 0 and no mean. Repeated rows each get the same score; they meet in one
chunk. An empty table gives an empty result; columns other than the two named aren't read, whatever their names.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

from .common import WordHashes, mixed, rolled, words_of

#: Bits of an n-gram's hash: of n distinct n-grams about n * n / 2 ** 57 pairs share one.
BITS = 56
EMPTY = np.uint64(0x34_5678_9ABC_DEF1)


@dataclass(frozen=True)
class Backoff:
    order: int = 3
    backoff: float = 0.4
    least: int = 2
    chunk_bytes: int = 2 << 20
    fan: int = 256
    runs_per_task: int = 256


def packed(values: np.ndarray) -> bytes:
    """Unsigned integers as compressed byte planes."""
    planes = np.ascontiguousarray(values.astype("<u8").view(np.uint8).reshape(-1, 8).T)
    used = max([k + 1 for k in range(8) if planes[k].any()], default=0)
    return bytes([used]) + zstandard.ZstdCompressor(level=1).compress(planes[:used].tobytes())


def unpacked(data: bytes, n: int) -> np.ndarray:
    used = data[0]
    out = np.zeros((8, n), np.uint8)
    out[:used] = np.frombuffer(zstandard.ZstdDecompressor().decompress(data[1:], max_output_size=max(1, used * n)), np.uint8).reshape(used, n)
    return np.ascontiguousarray(out.T).view("<u8").ravel()


def pack_sorted(values: np.ndarray) -> bytes:
    return packed(np.diff(values, prepend=np.uint64(0)))


def unpack_sorted(data: bytes, n: int) -> np.ndarray:
    return np.cumsum(unpacked(data, n), dtype=np.uint64)


class Chunk:
    """A chunk's n-grams: for each order, the hash at every position that has one, and the position's document."""

    def __init__(self, texts: list[str | None], order: int):
        hashes = WordHashes()
        per_doc = [hashes.array(words_of(t or "")) for t in texts]
        self.lengths = np.array([len(h) for h in per_doc], np.int64)
        h = np.concatenate([*per_doc, np.zeros(0, np.uint64)])
        self.n = len(h)
        self.first = np.repeat(np.cumsum(self.lengths) - self.lengths, self.lengths)  # where each position's document starts
        self.grams = []
        for k in range(1, order + 1):
            salted = mixed(rolled(h, k) + np.uint64(k)) >> np.uint64(64 - BITS)
            at = np.arange(len(salted))
            self.grams.append((salted, at + k - 1 - self.first[at + k - 1] >= k - 1))  # by start; whether it lies in one document

    def distinct(self) -> tuple[np.ndarray, np.ndarray]:
        """Sorted distinct hashes with the chunk's counts, and the empty n-gram with the chunk's words."""
        each = np.concatenate([g[ok] for g, ok in self.grams])
        each.sort()
        starts = np.flatnonzero(np.append(True, each[1:] != each[:-1])) if len(each) else np.zeros(0, np.int64)
        values, counts = each[starts], np.diff(np.append(starts, len(each)))
        at = int(np.searchsorted(values, EMPTY))
        return np.insert(values, at, EMPTY), np.insert(counts, at, self.n)

    def scores(self, counts: np.ndarray, spec: Backoff) -> np.ndarray:
        """Each document's sum of log scores, from the corpus counts of distinct()'s hashes in their order."""
        if not self.n:
            return np.zeros(len(self.lengths))
        where = [np.flatnonzero(ok) for _, ok in self.grams]
        each = np.concatenate([g[w] for (g, _), w in zip(self.grams, where)])
        order = np.argsort(each)
        each = each[order]
        rank = np.cumsum(np.append(False, each[1:] != each[:-1]))
        at = int(np.searchsorted(each, EMPTY))
        skip = int(rank[at]) if at < len(each) else int(rank[-1]) + 1  # where the empty n-gram stands among the distinct ones
        total = float(counts[skip])
        counts = np.delete(counts, skip)
        per = np.empty(len(each))
        per[order] = counts[rank]
        del each, order, rank
        count, done = [], 0
        for (g, _), w in zip(self.grams, where):
            c = np.zeros(len(g))
            c[w] = per[done : done + len(w)]
            done += len(w)
            count.append(c)
        log = np.log(count[0]) - math.log(total)
        for k in range(2, len(self.grams) + 1):
            c = count[k - 1]
            seen = np.zeros(self.n, bool)
            seen[k - 1 :] = c >= spec.least
            ends = np.flatnonzero(seen)
            # Unseen: a shorter history's score, discounted, wherever this document has a history of this length.
            deep = np.arange(self.n) - self.first >= k - 1
            log = np.where(deep & ~seen, log + math.log(spec.backoff), log)
            log[ends] = np.log(c[ends - k + 1]) - np.log(count[k - 2][ends - k + 1])
        ends = np.cumsum(self.lengths)
        return np.array([math.fsum(log[e - n : e].tolist()) for e, n in zip(ends, self.lengths)])


def bytes_of(docs: DataFrame, text_col: str) -> int:
    """The optimiser's estimate of the bytes of docs, from the sizes of its files; where it has none, the texts' bytes."""
    known = int(str(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    if known < 1 << 60:
        return known
    return docs.agg(F.sum(F.octet_length(text_col)).alias("n")).first()["n"] or 0


RUN = "node bigint, source bigint, bucket bigint, n bigint, hashes binary, counts binary"
BACK = "node bigint, source bigint, bucket bigint, n bigint, counts binary"


def cut_runs(values: np.ndarray, fan: int, depth: int) -> Iterator[tuple[int, int, int]]:
    """(bucket, start, end) of the runs of sorted hashes by the range of their leading digits: `depth` digits of base `fan`."""
    ranges = fan**depth
    bucket = ((values >> np.uint64(BITS - 32)) * np.uint64(ranges) >> np.uint64(32)).astype(np.int64) if len(values) else np.zeros(0, np.int64)
    cuts = np.flatnonzero(np.diff(bucket, prepend=-1, append=-1)) if len(bucket) else np.zeros(0, np.int64)
    return ((int(bucket[a]), a, b) for a, b in zip(cuts, cuts[1:]))


def gathered(table: pa.Table) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """A node's runs, one behind the other: their lengths; then the distinct hashes in order, their counts, and each entry's place among them."""
    n = table["n"].to_numpy()
    hashes = np.concatenate([unpack_sorted(x, k) for x, k in zip(table["hashes"].to_pylist(), n)])
    counts = np.concatenate([unpacked(x, k) for x, k in zip(table["counts"].to_pylist(), n)])
    order = np.argsort(hashes, kind="stable")
    ordered = hashes[order]
    first = np.append(True, ordered[1:] != ordered[:-1])
    place = np.empty(len(order), np.int64)
    place[order] = np.cumsum(first) - 1
    return n, ordered[first], np.add.reduceat(counts[order], np.flatnonzero(first)), place


def counted(runs: DataFrame, spec: Backoff, sources: int, depth: int) -> DataFrame:
    """The corpus counts of each run's hashes, run by run, as (node, source, bucket, n, counts).

    A node takes the runs of one range of hashes from up to `fan` sources. Where there are more sources than that, it
    merges its runs into one list and is itself a source of the next level, which cuts the range into `fan` finer ones;
    what comes back for its list it hands on to its runs. So a source sends at most `fan` runs, whatever the input's
    size, a node takes in at most `fan` runs, and levels grow with the logarithm of the number of sources.
    """
    run_schema, back_schema = arrow_schema(RUN), arrow_schema(BACK)
    groups = math.ceil(sources / spec.fan)
    dealt = runs.withColumn("node", F.col("bucket") * groups + F.floor(F.col("source") / spec.fan))
    most_runs = spec.fan**depth * sources
    dealt = dealt.repartition(min(spec.fan**depth * groups, math.ceil(most_runs / spec.runs_per_task)), "node")

    def total(key, table):
        n, _, sums, place = gathered(table)
        ends = np.cumsum(n)
        counts = sums[place]
        return pa.table([*(table[c].combine_chunks() for c in ("node", "source", "bucket", "n")), pa.array([packed(counts[e - k : e]) for e, k in zip(ends, n)], pa.binary())], schema=back_schema)

    if groups == 1:
        return dealt.groupBy("node").applyInArrow(total, BACK)

    def merge(key, table):
        _, values, sums, _ = gathered(table)
        node = key[0].as_py()
        rows = [(node, node % groups, bucket, b - a, pack_sorted(values[a:b]), packed(sums[a:b])) for bucket, a, b in cut_runs(values, spec.fan, depth + 1)]
        return table_of(rows, run_schema)

    # Sources of the next level: one for each group of this one's, in each range. Ranges are apart, so they number groups alone.
    finer = counted(dealt.groupBy("node").applyInArrow(merge, RUN), spec, groups, depth + 1)
    home = finer.withColumn("node", F.floor(F.col("bucket") / spec.fan) * groups + F.col("source"))
    def hand_on(runs, back):
        if not runs.num_rows:
            return back_schema.empty_table()
        n, _, _, place = gathered(runs)
        back = back.sort_by("bucket")
        sums = np.concatenate([unpacked(x, k) for x, k in zip(back["counts"].to_pylist(), back["n"].to_pylist())])
        ends, counts = np.cumsum(n), sums[place]
        return pa.table([*(runs[c].combine_chunks() for c in ("node", "source", "bucket", "n")), pa.array([packed(counts[e - k : e]) for e, k in zip(ends, n)], pa.binary())], schema=back_schema)

    return dealt.groupBy("node").cogroup(home.groupBy("node")).applyInArrow(hand_on, BACK)


def arrow_schema(ddl: str) -> pa.Schema:
    return to_arrow_schema(T._parse_datatype_string(ddl))


def table_of(rows: list[tuple], schema: pa.Schema) -> pa.Table:
    return pa.table([pa.array([r[k] for r in rows], f.type) for k, f in enumerate(schema)], schema=schema)


def backoff_scores(docs: DataFrame, *, spec: Backoff = Backoff(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, n_words, log_score, mean_log_score."""
    chunks = max(1, math.ceil(bytes_of(docs.select(id_col, text_col), text_col) / spec.chunk_bytes))
    kind = docs.schema[id_col].dataType
    rows = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"), F.pmod(F.xxhash64(id_col, text_col), F.lit(chunks)).alias("chunk"))
    rows = rows.repartition(chunks, "chunk")
    schema = arrow_schema(RUN)

    def send(key, table):
        values, counts = Chunk(table["text"].to_pylist(), spec.order).distinct()
        chunk = key[0].as_py()
        return table_of([(0, chunk, bucket, b - a, pack_sorted(values[a:b]), packed(counts[a:b])) for bucket, a, b in cut_runs(values, spec.fan, 1)], schema)

    out_kind = T.StructType([T.StructField("id", kind), T.StructField("n_words", T.LongType()), T.StructField("log_score", T.DoubleType())])
    out_schema = to_arrow_schema(out_kind)

    def score(left, right):
        if not left.num_rows:
            return out_schema.empty_table()
        chunk = Chunk(left["text"].to_pylist(), spec.order)
        right = right.sort_by("bucket")
        counts = np.concatenate([unpacked(x, k) for x, k in zip(right["counts"].to_pylist(), right["n"].to_pylist())])
        return pa.table({"id": left["id"].combine_chunks(), "n_words": pa.array(chunk.lengths), "log_score": pa.array(chunk.scores(counts, spec))}, schema=out_schema)

    counts = counted(rows.groupBy("chunk").applyInArrow(send, RUN), spec, chunks, 1)
    counts = counts.withColumnRenamed("source", "chunk").repartition(chunks, "chunk")
    scored = rows.groupBy("chunk").cogroup(counts.groupBy("chunk")).applyInArrow(score, out_kind)
    return scored.select(F.col("id").alias(id_col), "n_words", "log_score", F.when(F.col("n_words") > 0, F.col("log_score") / F.col("n_words")).alias("mean_log_score"))


def oracle_sql(spec: Backoff = Backoff()) -> str:
    """Trigram scores in DuckDB SQL, from words rather than hashes; sums rounded to four places."""
    if spec.order != 3:
        raise ValueError("the SQL is for trigrams")
    d = f"ln(CAST({spec.backoff} AS DOUBLE))"
    return f"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, list_filter(regexp_split_to_array(coalesce(text, ''), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS w FROM documents),
i AS (SELECT r, w, unnest(range(1, len(w) + 1)) AS i FROM d),
p AS (SELECT r, w[i] AS a, CASE WHEN i > 1 THEN w[i - 1] END AS b, CASE WHEN i > 2 THEN w[i - 2] END AS c FROM i),
n AS (SELECT CAST(count(*) AS DOUBLE) AS n FROM p), c1 AS (SELECT a, CAST(count(*) AS DOUBLE) AS n FROM p GROUP BY 1),
c2 AS (SELECT b, a, CAST(count(*) AS DOUBLE) AS n FROM p WHERE b IS NOT NULL GROUP BY 1, 2), c3 AS (SELECT c, b, a, CAST(count(*) AS DOUBLE) AS n FROM p WHERE c IS NOT NULL GROUP BY 1, 2, 3),
s AS (SELECT p.r, CASE WHEN c3.n >= {spec.least} THEN ln(c3.n) - ln(h2.n) ELSE CASE WHEN p.c IS NOT NULL THEN {d} ELSE 0 END
 + CASE WHEN c2.n >= {spec.least} THEN ln(c2.n) - ln(h1.n) ELSE CASE WHEN p.b IS NOT NULL THEN {d} ELSE 0 END + ln(c1.n) - ln(n.n) END END AS s
 FROM p JOIN c1 ON c1.a = p.a CROSS JOIN n LEFT JOIN c2 ON c2.a = p.a AND c2.b = p.b LEFT JOIN c3 ON c3.a = p.a AND c3.b = p.b AND c3.c = p.c LEFT JOIN c1 h1 ON h1.a = p.b LEFT JOIN c2 h2 ON h2.a = p.b AND h2.b = p.c),
t AS (SELECT r, sum(s) AS s FROM s GROUP BY 1)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, round(coalesce(s, 0), 4) AS log_score, round(s / len(w), 4) AS mean_log_score FROM d LEFT JOIN t USING (r)"""
