"""Chunk deduplication: content-defined chunking with a gear hash, fixed chunks, attribution, and compress-then-chunk orders.

A position's gear hash depends on the last 64 bytes only, so it is computed for a whole buffer by six shift-and-add
doublings; cut points are then chosen over the few candidate positions. Unlike a streaming chunker the window does not
start anew at a cut, which makes candidates independent of earlier cuts.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from xorvault.operators.codecs import on_rows

#: 256 constants from the md5 digests of the byte values.
GEAR = np.array([int.from_bytes(hashlib.md5(bytes([b])).digest()[:8], "little") for b in range(256)], np.uint64)


@dataclass(frozen=True)
class ChunkSizes:
    least: int = 16 << 10
    target: int = 64 << 10
    most: int = 256 << 10
    normalization: int = 2


SMALL = ChunkSizes(64, 256, 1024)


def gear_hashes(data: bytes) -> np.ndarray:
    h = GEAR[np.frombuffer(data, np.uint8)]
    for k in (1, 2, 4, 8, 16, 32):
        moved = np.zeros_like(h)
        moved[k:] = h[:-k] << np.uint64(k)
        h = h + moved
    return h


def cut_points(data: bytes, sizes: ChunkSizes) -> list[int]:
    """Ends of the chunks: none before `least`, a strict mask up to the target, a loose one after it, forced at `most`."""
    n = len(data)
    if not n:
        return []
    bits = sizes.target.bit_length() - 1
    top = lambda b: np.uint64(((1 << b) - 1) << (64 - b))
    h = gear_hashes(data)
    strict = np.flatnonzero((h & top(bits + sizes.normalization)) == 0) + 1
    loose = np.flatnonzero((h & top(max(1, bits - sizes.normalization))) == 0) + 1
    ends, at = [], 0
    while n - at > sizes.least:
        k = np.searchsorted(strict, at + sizes.least)
        end = int(strict[k]) if k < len(strict) and strict[k] <= at + sizes.target else 0
        if not end:
            k = np.searchsorted(loose, at + max(sizes.target, sizes.least) + 1)
            end = int(loose[k]) if k < len(loose) and loose[k] <= at + sizes.most else min(n, at + sizes.most)
        ends.append(end)
        at = end
    if at < n:
        ends.append(n)
    return ends


def chunks_of(data: bytes, sizes: ChunkSizes) -> list[dict]:
    out, at = [], 0
    for no, end in enumerate(cut_points(data, sizes)):
        out.append({"chunk_no": no, "begin": at, "n_bytes": end - at, "unit_hash": hashlib.sha256(data[at:end]).hexdigest()})
        at = end
    return out


CHUNK = "chunks array<struct<chunk_no: int, begin: bigint, n_bytes: bigint, unit_hash: string>>"


def chunk(files: DataFrame, keep: list[str], *, sizes: ChunkSizes = ChunkSizes(), content: str = "content") -> DataFrame:
    """(keep..., chunk_no, begin, n_bytes, unit_hash) of every file; bytes stay in the task that reads them."""
    each = on_rows(files, keep, [content], lambda data: {"chunks": chunks_of(bytes(data or b""), sizes)}, CHUNK)
    return each.select(*keep, F.inline("chunks"))


def chunk_blocks(blocks: DataFrame, keep: list[str], order: str, *, sizes: ChunkSizes = ChunkSizes(), content: str = "content") -> DataFrame:
    """The same chunks of files that come as rows of ordered blocks: (keep..., chunk_no, begin, n_bytes, unit_hash).

    A file's blocks are sorted into one task and cut as they come: what is held is one block and the chunk that is still
    open, never a file. A cut depends on at most `least` + 64 bytes before it and on the chunk's start, so a chunk is closed
    as soon as `most` bytes behind its start are there.
    """
    if sizes.least < 64:
        raise ValueError("chunks of fewer bytes than the hash's window depend on what was cut before")
    from pyspark.sql.pandas.types import to_arrow_schema

    names = [*keep, "chunk_no", "begin", "n_bytes", "unit_hash"]
    ordered = blocks.select(*keep, order, content).repartition(*keep).sortWithinPartitions(*keep, order)
    kinds = {f.name: f.type for f in to_arrow_schema(blocks.select(*keep).schema)} | {"chunk_no": pa.int32(), "begin": pa.int64(), "n_bytes": pa.int64(), "unit_hash": pa.string()}

    def run(batches):
        key, held, at, no = None, bytearray(), 0, 0

        def cut(last: bool) -> list[tuple]:
            nonlocal at, no
            out, done, data = [], 0, bytes(held)
            for end in cut_points(data, sizes):
                if not last and len(data) - done <= sizes.most:
                    break
                out.append((*key, no, at, end - done, hashlib.sha256(data[done:end]).hexdigest()))
                at, no, done = at + end - done, no + 1, end
            del held[:done]
            return out

        for batch in batches:
            rows = []
            for values in zip(*[batch.column(c).to_pylist() for c in (*keep, content)]):
                if values[:-1] != key:
                    rows += cut(True) if key is not None else []
                    key, at, no = values[:-1], 0, 0
                    held.clear()
                held += values[-1] or b""
                if len(held) > 4 * sizes.most:
                    rows += cut(False)
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], kinds[n]) for k, n in enumerate(names)], names=names)
        if key is not None:
            rows = cut(True)
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], kinds[n]) for k, n in enumerate(names)], names=names)

    schema = ", ".join([f"{c} {blocks.schema[c].dataType.simpleString()}" for c in keep] + ["chunk_no int, begin bigint, n_bytes bigint, unit_hash string"])
    return ordered.mapInArrow(run, schema)


def fixed_chunks(files: DataFrame, keep: list[str], *, size: int, content: str = "content") -> DataFrame:
    """Chunks of one fixed size, in Catalyst expressions."""
    n = F.octet_length(content)
    starts = F.when(n > 0, F.sequence(F.lit(0), n - 1, F.lit(size))).otherwise(F.array().cast("array<int>"))
    each = files.select(*keep, content, F.posexplode(starts).alias("chunk_no", "begin"))
    part = F.substring(F.col(content).cast("binary"), F.col("begin") + 1, F.lit(size))
    return each.select(*keep, "chunk_no", F.col("begin").cast("bigint").alias("begin"), F.octet_length(part).cast("bigint").alias("n_bytes"), F.sha2(part, 256).alias("unit_hash"))


def attribute(chunks: DataFrame, units: DataFrame, *, bin_bytes: int = 1 << 16) -> DataFrame:
    """(file_id, chunk_no, unit, overlap): a range join on byte intervals, cut to an equi-join on bins of the file."""
    bins = lambda lo, n: F.explode(F.sequence(F.floor(lo / bin_bytes), F.floor((lo + n - 1) / bin_bytes)))
    c = chunks.where("n_bytes > 0").select("file_id", "chunk_no", F.col("begin").alias("cb"), F.col("n_bytes").alias("cn"), bins(F.col("begin"), F.col("n_bytes")).alias("bin"))
    u = units.where("n_bytes > 0").select("file_id", "unit", F.col("begin").alias("ub"), F.col("n_bytes").alias("un"), bins(F.col("begin"), F.col("n_bytes")).alias("bin"))
    lo, hi = F.greatest("cb", "ub"), F.least(F.col("cb") + F.col("cn"), F.col("ub") + F.col("un"))
    met = c.join(u, ["file_id", "bin"]).where(lo < hi).where(F.floor(lo / bin_bytes) == F.col("bin"))
    return met.select("file_id", "chunk_no", "unit", (hi - lo).alias("overlap"))


def compressed_chunks(payloads: DataFrame, keep: list[str], *, codec: str, sizes: ChunkSizes = SMALL) -> DataFrame:
    """Chunks of coded payloads: the compress-then-deduplicate order. codec is zstd, grouping or xor (needs payload_b)."""
    from xorvault.operators import codecs

    def make(payload, base, dtype):
        if codec == "xor" and base is not None:
            data = codecs.delta_encode(payload, base, dtype)
        else:
            data = codecs.encode(payload, dtype, "grouping_huffman" if codec == "grouping" else "zstd")
        return {"n_raw": len(payload), "chunks": chunks_of(data, sizes)}

    each = on_rows(payloads, keep, ["payload", "payload_b", "dtype"], make, f"n_raw bigint, {CHUNK}")
    return each.select(*keep, "n_raw", F.inline_outer("chunks"))
