"""Lossless coders over tensor payloads: general compressors, component grouping, XOR delta and its variants.

A coded payload is `codec name, flags, raw length` and the body. A body that would not be smaller is kept raw. All coders
work on one block at a time, inside Arrow batches; XOR and compression happen in the same function, so that the XOR
stream is never a column.
"""

from __future__ import annotations

import heapq
import struct
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from xorvault.functions import words as W

GENERAL = ("zstd", "lz4", "gzip", "brotli", "snappy")
NAMES = (*GENERAL, "raw", "grouping_huffman", "grouping_zstd", "xor", "xor_planes", "wrap", "zigzag", "recipe")
HEAD = struct.Struct("<2sBBQ")
MAGIC = b"XV"


def _compress(data: bytes, codec: str, level: int | None) -> bytes:
    name = "lz4" if codec == "lz4" else codec
    c = pa.Codec(name, compression_level=level) if level is not None and pa.Codec.supports_compression_level(name) else pa.Codec(name)
    return c.compress(data, asbytes=True)


def _decompress(data: bytes, codec: str, size: int) -> bytes:
    return pa.Codec(codec).decompress(data, decompressed_size=size, asbytes=True) if size else b""


def pack(body: bytes, name: str, raw: bytes, general: str = "zstd") -> bytes:
    if len(body) >= len(raw):
        body, name = raw, "raw"
    return HEAD.pack(MAGIC, NAMES.index(name), GENERAL.index(general), len(raw)) + body


def codec_of(data: bytes) -> str:
    return NAMES[HEAD.unpack_from(data)[1]]


# --- Huffman over bytes -------------------------------------------------------------------------------------------

LONGEST = 16
#: Symbols per lane: long streams are decoded in lanes whose first bits are stored, all lanes one symbol at a time.
LANE = 1024
LANES_FROM = 16 * LANE


def code_lengths(counts: np.ndarray) -> np.ndarray:
    """Huffman code lengths of 256 symbols (0: absent), no longer than LONGEST: counts are flattened until they fit."""
    counts = counts.astype(np.int64)
    while True:
        heap = [(int(c), k, (k,)) for k, c in enumerate(counts) if c]
        lengths = np.zeros(256, np.int64)
        if len(heap) == 1:
            lengths[heap[0][1]] = 1
            return lengths
        heapq.heapify(heap)
        tie = 256
        while len(heap) > 1:
            a, b = heapq.heappop(heap), heapq.heappop(heap)
            both = a[2] + b[2]
            lengths[list(both)] += 1
            heapq.heappush(heap, (a[0] + b[0], tie, both))
            tie += 1
        if lengths.max(initial=0) <= LONGEST:
            return lengths
        counts = np.where(counts > 0, counts // 2 + 1, 0)


def canonical(lengths: np.ndarray) -> np.ndarray:
    """Canonical codes from code lengths: by length, then by symbol."""
    codes = np.zeros(256, np.int64)
    code = previous = 0
    for k in sorted(np.flatnonzero(lengths), key=lambda s: (lengths[s], s)):
        code <<= int(lengths[k]) - previous
        codes[k], previous = code, int(lengths[k])
        code += 1
    return codes


def huffman_encode(data: np.ndarray) -> bytes:
    """Counts, code lengths (compressed) and the code bits, highest bit first."""
    lengths = code_lengths(np.bincount(data, minlength=256))
    codes = canonical(lengths).astype(np.uint64)
    n = lengths[data]
    ends = np.cumsum(n)
    total = int(ends[-1]) if len(ends) else 0
    out = np.zeros(total // 64 + 2, np.uint64)
    if total:
        # Each code is put in the 64-bit word where it starts, and what sticks out in the next; a word gets one such rest at most.
        start, code = ends - n, codes[data]
        word, room = start >> 6, 64 - (start & 63) - n
        fits = np.maximum(room, 0).astype(np.uint64)
        out_by = np.maximum(-room, 0).astype(np.uint64)
        first = np.flatnonzero(np.append(True, word[1:] != word[:-1]))
        out[word[first]] = np.bitwise_or.reduceat((code << fits) >> out_by, first)
        over = np.flatnonzero(room < 0)
        out[word[over] + 1] |= code[over] << (np.uint64(64) - out_by[over])
    table = _compress(lengths.astype(np.uint8).tobytes(), "zstd", 3)
    lanes = np.diff(np.append((ends - n)[::LANE], total)).astype("<u2").tobytes() if len(data) >= LANES_FROM else b""
    return struct.pack("<QQH", len(data), total, len(table)) + table + lanes + out.astype(">u8").tobytes()[: -(-total // 8)]


def huffman_decode(body: bytes) -> np.ndarray:
    n, total, size = struct.unpack_from("<QQH", body)
    lengths = np.frombuffer(_decompress(body[18 : 18 + size], "zstd", 256), np.uint8).astype(np.int64)
    if not n:
        return np.zeros(0, np.uint8)
    codes = canonical(lengths)
    width = int(lengths.max())
    table_symbol, table_length = np.zeros(1 << width, np.uint8), np.ones(1 << width, np.int64)
    for s in np.flatnonzero(lengths):
        lo = int(codes[s]) << (width - int(lengths[s]))
        hi = lo + (1 << (width - int(lengths[s])))
        table_symbol[lo:hi], table_length[lo:hi] = s, lengths[s]
    if n >= LANES_FROM:
        return _decode_lanes(body[18 + size :], n, total, width, table_symbol, table_length)
    bits = np.unpackbits(np.frombuffer(body, np.uint8, offset=18 + size), count=total)
    padded = np.concatenate([bits, np.zeros(width, np.uint8)]).astype(np.int64)
    window = np.zeros(total, np.int64)
    for k in range(width):
        window = (window << 1) | padded[k : k + total]
    # Follow the jumps from code to code: doubling over the jump table finds all starts without a loop over symbols.
    jump = np.minimum(np.arange(total) + table_length[window], total)
    reached = np.zeros(total + 1, bool)
    reached[0] = True
    step = np.append(jump, total)
    frontier = np.array([0])
    while len(frontier) < n:
        nxt = step[frontier]
        frontier = np.unique(np.concatenate([frontier, nxt[nxt < total]]))
        step = step[step]
    return table_symbol[window[np.sort(frontier)[:n]]]


def _decode_lanes(body: bytes, n: int, total: int, width: int, symbol: np.ndarray, length: np.ndarray) -> np.ndarray:
    lanes = -(-n // LANE)
    spans = np.frombuffer(body, "<u2", lanes).astype(np.int64)
    at = np.cumsum(spans) - spans
    bits = body[2 * lanes :]
    words = np.frombuffer(bits + bytes(24 - len(bits) % 8), ">u8").astype(np.uint64)
    out = np.empty((LANE, lanes), np.uint8)
    one, top, drop = np.uint64(1), np.uint64(63), np.uint64(64 - width)
    for k in range(LANE):
        w, off = at >> 6, (at & 63).astype(np.uint64)
        code = ((words[w] << off) | ((words[w + 1] >> one) >> (top - off))) >> drop
        out[k] = symbol[code]
        at = np.minimum(at + length[code], total)  # the last lane may end early
    return out.T.ravel()[:n]


def huffman_bits(data: np.ndarray) -> int:
    counts = np.bincount(data, minlength=256)
    return int((counts * code_lengths(counts)).sum())


# --- Component grouping -------------------------------------------------------------------------------------------


def components(payload: bytes, dtype: str) -> list[np.ndarray]:
    """Byte streams of a float payload: the exponents, and the sign with the mantissa from its high byte down."""
    w = W.words(payload, dtype)
    if dtype == "BF16":
        return [((w >> 7) & 0xFF).astype(np.uint8), (((w >> 8) & 0x80) | (w & 0x7F)).astype(np.uint8)]
    if dtype == "F32":
        rest = ((w >> np.uint32(8)) & np.uint32(0x800000)) | (w & np.uint32(0x7FFFFF))
        return [((w >> np.uint32(23)) & np.uint32(0xFF)).astype(np.uint8), *[((rest >> np.uint32(s)) & np.uint32(0xFF)).astype(np.uint8) for s in (16, 8, 0)]]
    size = w.dtype.itemsize
    planes = np.frombuffer(payload, np.uint8).reshape(-1, size)
    return [np.ascontiguousarray(planes[:, k]) for k in range(size - 1, -1, -1)]


def joined(streams: list[np.ndarray], dtype: str) -> bytes:
    if dtype == "BF16":
        e, m = (s.astype(np.uint16) for s in streams)
        return (((m & 0x80) << 8) | (e << 7) | (m & 0x7F)).astype("<u2").tobytes()
    if dtype == "F32":
        e, a, b, c = (s.astype(np.uint32) for s in streams)
        rest = (a << np.uint32(16)) | (b << np.uint32(8)) | c
        return (((rest & np.uint32(0x800000)) << np.uint32(8)) | (e << np.uint32(23)) | (rest & np.uint32(0x7FFFFF))).astype("<u4").tobytes()
    return np.ascontiguousarray(np.stack(streams[::-1], axis=1)).tobytes()


def grouping_encode(payload: bytes, dtype: str, entropy: str = "huffman") -> bytes:
    parts = []
    for s in components(payload, dtype):
        body = huffman_encode(s) if entropy == "huffman" else _compress(s.tobytes(), "zstd", 3)
        flag = len(body) < len(s)
        body = body if flag else s.tobytes()
        parts.append(struct.pack("<BQQ", flag, len(s), len(body)) + body)
    return pack(b"".join(parts), f"grouping_{entropy}", payload)


def _grouping_decode(body: bytes, dtype: str, entropy: str) -> bytes:
    streams, at = [], 0
    while at < len(body):
        flag, n, size = struct.unpack_from("<BQQ", body, at)
        at += 17
        part = body[at : at + size]
        at += size
        streams.append(np.frombuffer(part, np.uint8) if not flag else huffman_decode(part) if entropy == "huffman" else np.frombuffer(_decompress(part, "zstd", n), np.uint8))
    return joined(streams, dtype)


# --- Delta coders -------------------------------------------------------------------------------------------------


def _planes(data: bytes, size: int) -> bytes:
    return np.ascontiguousarray(np.frombuffer(data, np.uint8).reshape(-1, size).T).tobytes()


def _unplanes(data: bytes, size: int) -> bytes:
    return np.ascontiguousarray(np.frombuffer(data, np.uint8).reshape(size, -1).T).tobytes()


def delta_words(payload: bytes, base: bytes, dtype: str, transform: str) -> bytes:
    """The difference of two equally long payloads: XOR, wrap-around difference of the words, or its zig-zag."""
    if transform == "xor":
        return W.xor(payload, base)
    w = W.words(payload, dtype) - W.words(base, dtype)
    if transform == "zigzag":
        signed = w.view(w.dtype.str.replace("u", "i"))
        w = ((signed << 1) ^ (signed >> (W.DTYPES[dtype][1] - 1))).view(w.dtype)
    return w.tobytes()


def apply_delta(delta: bytes, base: bytes, dtype: str, transform: str) -> bytes:
    if transform == "xor":
        return W.xor(delta, base)
    w, b = W.words(delta, dtype), W.words(base, dtype)
    if transform == "zigzag":
        w = (w >> w.dtype.type(1)) ^ (~(w & w.dtype.type(1)) + w.dtype.type(1))
    return (w + b).tobytes()


def delta_encode(payload: bytes, base: bytes, dtype: str, *, transform: str = "xor", codec: str = "zstd", level: int | None = 3, plane_split: bool = False) -> bytes:
    if len(payload) != len(base):
        raise ValueError("a delta needs payloads of one length")
    d = delta_words(payload, base, dtype, transform)
    name = transform
    if plane_split:
        if transform != "xor":
            raise ValueError("only XOR streams are split in planes")
        d, name = _planes(d, W.DTYPES[dtype][1] // 8), "xor_planes"
    return pack(_compress(d, codec, level), name, payload, codec)


def encode(payload: bytes, dtype: str, codec: str, level: int | None = 3) -> bytes:
    """Standalone coding by name: a general compressor, grouping_huffman, grouping_zstd or raw."""
    if codec.startswith("grouping_"):
        return grouping_encode(payload, dtype, codec.split("_")[1])
    return pack(payload if codec == "raw" else _compress(payload, codec, level), codec, payload, codec if codec in GENERAL else "zstd")


def recipe_encode(payload: bytes, base: bytes, base_dtype: str) -> bytes | None:
    """A quantized payload as the recipe that makes it from its base's tensor; None where it doesn't make it exactly."""
    from xorvault.operators.quantize import quantize

    if base_dtype not in W.DTYPES or quantize(base, base_dtype) != payload:
        return None
    return pack(base_dtype.encode(), "recipe", payload)


def smallest(payload: bytes, dtype: str, codecs: tuple[str, ...] = ("zstd", "grouping_huffman")) -> bytes:
    return min((encode(payload, dtype, c) for c in codecs), key=len)


def decode(data: bytes, dtype: str, base: bytes | None = None) -> bytes:
    magic, name, general, n = HEAD.unpack_from(data)
    if magic != MAGIC:
        raise ValueError("not a coded payload")
    name, general, body = NAMES[name], GENERAL[general], data[HEAD.size :]
    if name == "raw":
        return body
    if name in GENERAL:
        return _decompress(body, name, n)
    if name.startswith("grouping_"):
        return _grouping_decode(body, dtype, name.split("_")[1])
    if base is None:
        raise ValueError(f"a {name} payload needs its base")
    if name == "recipe":
        from xorvault.operators.quantize import quantize

        return quantize(base, body.decode())
    d = _decompress(body, general, n)
    if name == "xor_planes":
        return W.xor(_unplanes(d, W.DTYPES[dtype][1] // 8), base)
    return apply_delta(d, base, dtype, name)


# --- Entropy and sparsity -----------------------------------------------------------------------------------------


def entropy_bits(counts: np.ndarray) -> float:
    p = counts[counts > 0] / max(1, counts.sum())
    return float(-(p * np.log2(p)).sum())


def on_rows(df: DataFrame, keep: list[str], inputs: list[str], make: Callable[..., dict], extra: str) -> DataFrame:
    """(keep..., extra...) with `make` called on the inputs of every row, in one Arrow map."""
    kept = list(keep)
    schema = ", ".join([f"{c} {df.schema[c].dataType.simpleString()}" for c in kept] + [extra])
    from pyspark.sql import types as T
    from pyspark.sql.pandas.types import to_arrow_schema

    kinds = to_arrow_schema(T._parse_datatype_string(extra))
    names = kinds.names

    def run(batches):
        for batch in batches:
            made = [make(*row) for row in zip(*[batch.column(c).to_pylist() for c in inputs])]
            yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in kept], *[pa.array([m[n] for m in made], kinds.field(n).type) for n in names]], names=[*kept, *names])

    return df.select(*dict.fromkeys([*kept, *inputs])).mapInArrow(run, schema)


def xor_encode(pairs: DataFrame, keep: list[str], *, codec: str = "zstd", level: int | None = 3, transform: str = "xor", plane_split: bool = False) -> DataFrame:
    """(keep..., payload, n_raw, n_stored, codec) of aligned pairs with columns payload_a (target), payload_b (base), dtype."""

    def make(a, b, dtype):
        data = delta_encode(a, b, dtype, transform=transform, codec=codec, level=level, plane_split=plane_split)
        return {"payload": data, "n_raw": len(a), "n_stored": len(data), "codec": codec_of(data)}

    return on_rows(pairs, keep, ["payload_a", "payload_b", "dtype"], make, "payload binary, n_raw bigint, n_stored bigint, codec string")


def standalone_encode(tensors: DataFrame, keep: list[str], *, codecs: tuple[str, ...] = ("zstd", "grouping_huffman")) -> DataFrame:
    def make(payload, dtype):
        data = smallest(payload, dtype, codecs)
        return {"coded": data, "n_raw": len(payload), "n_stored": len(data), "codec": codec_of(data)}

    return on_rows(tensors, keep, ["payload", "dtype"], make, "coded binary, n_raw bigint, n_stored bigint, codec string")


def whole_files(tensors: DataFrame) -> DataFrame:
    """(repo_id, dtype, payload) of each file's tensors of one dtype, one behind the other: what a coder with file scope sees.

    A file must fit a row, which is why the pipeline codes by tensor or block; this serves the file-scope baselines.
    """

    def join(key, table):
        import pyarrow as pa

        table = table.sort_by("ordinal")
        return pa.table({"repo_id": pa.array([key[0].as_py()], pa.string()), "dtype": pa.array([key[1].as_py()], pa.string()), "payload": pa.array([b"".join(table["payload"].to_pylist())], pa.binary())})

    return tensors.select("repo_id", "dtype", "ordinal", "payload").groupBy("repo_id", "dtype").applyInArrow(join, "repo_id string, dtype string, payload binary")


def sparsity(pairs: DataFrame, keep: list[str]) -> DataFrame:
    """Words, zero words, zero bytes and one-bits of the XOR of aligned pairs, summed by keep."""

    def make(a, b, dtype):
        d = W.xor(a, b)
        w, u = W.words(d, dtype), np.frombuffer(d, np.uint8)
        return {"n_words": len(w), "zero_words": int((w == 0).sum()), "zero_bytes": int((u == 0).sum()), "one_bits": int(np.bitwise_count(u).sum())}

    each = on_rows(pairs, keep, ["payload_a", "payload_b", "dtype"], make, "n_words bigint, zero_words bigint, zero_bytes bigint, one_bits bigint")
    return each.groupBy(*keep).agg(*[F.sum(c).alias(c) for c in ("n_words", "zero_words", "zero_bytes", "one_bits")])


def numeric_density(pairs: DataFrame, keep: list[str]) -> DataFrame:
    """One-bits of the XOR, of the float difference in the same dtype, and of the zig-zag integer difference."""

    def make(a, b, dtype):
        x, y = W.words(a, dtype), W.words(b, dtype)
        diff = W.floats(x, dtype) - W.floats(y, dtype)
        d = W.bf16_words(diff.astype(np.float32)) if dtype == "BF16" else diff.astype({"F32": "<f4", "F64": "<f8"}[dtype]).view(x.dtype)
        ones = lambda w: int(np.bitwise_count(w).sum())
        return {"n_words": len(x), "xor_ones": ones(x ^ y), "diff_ones": ones(d), "zigzag_ones": ones(W.words(delta_words(a, b, dtype, "zigzag"), dtype))}

    each = on_rows(pairs, keep, ["payload_a", "payload_b", "dtype"], make, "n_words bigint, xor_ones bigint, diff_ones bigint, zigzag_ones bigint")
    return each.groupBy(*keep).agg(*[F.sum(c).alias(c) for c in ("n_words", "xor_ones", "diff_ones", "zigzag_ones")])


def truncate_mantissa(payload: bytes, dtype: str, bits: int) -> bytes:
    """A lossy coder for contrast: the lowest mantissa bits are cleared, so restoring is not exact."""
    w = W.words(payload, dtype)
    return (w & ~w.dtype.type((1 << bits) - 1)).tobytes()
