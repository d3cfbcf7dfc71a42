"""Float bit patterns: dtypes, packing, XOR and popcount, as numpy kernels and as Arrow column functions."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: dtype -> (numpy word, bits, exponent bits, mantissa bits)
DTYPES = {"BF16": ("<u2", 16, 8, 7), "F16": ("<u2", 16, 5, 10), "F32": ("<u4", 32, 8, 23), "F64": ("<u8", 64, 11, 52), "I8": ("u1", 8, 0, 7)}


def words(payload: bytes, dtype: str) -> np.ndarray:
    return np.frombuffer(payload, DTYPES[dtype][0])


def bf16_words(x: np.ndarray, rounding: str = "nearest") -> np.ndarray:
    """BF16 words of float32 values; NaN keeps a set mantissa bit, and rounding is to nearest even or by truncation."""
    b = np.ascontiguousarray(x, "<f4").view("<u4")
    if rounding == "truncate":
        up = b >> np.uint32(16)
    else:
        up = ((b.astype(np.uint64) + 0x7FFF + ((b >> np.uint32(16)) & np.uint32(1))) >> np.uint64(16)).astype(np.uint32)
    nan = (b & np.uint32(0x7FFFFFFF)) > 0x7F800000
    return np.where(nan, (b >> np.uint32(16)) | np.uint32(0x40), up).astype("<u2")


def floats(w: np.ndarray, dtype: str) -> np.ndarray:
    """Values of words, as float64."""
    if dtype == "BF16":
        return (w.astype("<u4") << np.uint32(16)).view("<f4").astype(np.float64)
    return w.view({"F16": "<f2", "F32": "<f4", "F64": "<f8"}[dtype]).astype(np.float64)


def is_zero(w: np.ndarray, dtype: str) -> np.ndarray:
    """Positive and negative zero: no bit set below the sign."""
    return (w & w.dtype.type((1 << (DTYPES[dtype][1] - 1)) - 1)) == 0


def counted(a: np.ndarray, b: np.ndarray, dtype: str, zero_policy: str) -> np.ndarray | None:
    """Mask of the positions that count under a zero policy; None means all."""
    if zero_policy == "keep":
        return None
    za, zb = is_zero(a, dtype), is_zero(b, dtype)
    if zero_policy == "drop_both_zero":
        return ~(za & zb)
    if zero_policy == "drop_either_zero":
        return ~(za | zb)
    raise ValueError(f"unknown zero policy {zero_policy!r}")


def differing_bits(a: bytes, b: bytes, dtype: str, zero_policy: str = "drop_both_zero") -> tuple[int, int]:
    """(counted positions, differing bits) of two payloads of one dtype and length."""
    x, y = words(a, dtype), words(b, dtype)
    if len(x) != len(y):
        raise ValueError("payloads differ in length")
    mask = counted(x, y, dtype, zero_policy)
    d = x ^ y
    if mask is not None:
        d = d[mask]
    return len(d), int(np.bitwise_count(d).sum())


def bit_ones(a: bytes, b: bytes, dtype: str) -> list[int]:
    """How many positions differ at each bit, lowest bit first."""
    d = words(a, dtype) ^ words(b, dtype)
    return [int(((d >> d.dtype.type(k)) & d.dtype.type(1)).sum()) for k in range(DTYPES[dtype][1])]


def xor(a: bytes, b: bytes) -> bytes:
    return (np.frombuffer(a, np.uint8) ^ np.frombuffer(b, np.uint8)).tobytes()


def differing(x: Column, y: Column) -> Column:
    """Differing bits of two INT words; bit_count alone would widen a negative INT to 64 bits."""
    return F.bit_count(x.bitwiseXOR(y).cast("bigint").bitwiseAND(F.lit(0xFFFFFFFF).cast("bigint")))


@F.arrow_udf(T.IntegerType())
def float_bits(x: pa.Array) -> pa.Array:
    """Raw bits of a FLOAT as INT; null for null."""
    v = x.cast(pa.float32())
    return pa.Array.from_buffers(pa.int32(), len(v), v.buffers(), offset=v.offset)


@F.arrow_udf(T.LongType())
def double_bits(x: pa.Array) -> pa.Array:
    v = x.cast(pa.float64())
    return pa.Array.from_buffers(pa.int64(), len(v), v.buffers(), offset=v.offset)


@F.arrow_udf(T.IntegerType())
def bf16_bits(x: pa.Array) -> pa.Array:
    """BF16 bits (0..65535) of a FLOAT, rounded to nearest even; null for null."""
    v = x.cast(pa.float32())
    return pa.array(bf16_words(v.fill_null(0).to_numpy()).astype(np.int32), mask=v.is_null().to_numpy(zero_copy_only=False))


@F.arrow_udf(T.BinaryType())
def xor_bytes(a: pa.Array, b: pa.Array) -> pa.Array:
    """XOR of two BINARY values of equal length; null if either is null or the lengths differ."""
    return pa.array([xor(x, y) if x is not None and y is not None and len(x) == len(y) else None for x, y in zip(a.to_pylist(), b.to_pylist())], pa.binary())


@F.arrow_udf(T.LongType())
def popcount_bytes(b: pa.Array) -> pa.Array:
    return pa.array([None if x is None else int(np.bitwise_count(np.frombuffer(x, np.uint8)).sum()) for x in b.to_pylist()], pa.int64())


@F.udtf(returnType="chunk_no int, begin bigint, n_bytes bigint, unit_hash string")
class CdcChunks:
    """SQL table function over one file's bytes: its content-defined chunks at small sizes."""

    def eval(self, content: bytes):
        from xorvault.operators.chunking import SMALL, chunks_of

        for c in chunks_of(bytes(content or b""), SMALL):
            yield c["chunk_no"], c["begin"], c["n_bytes"], c["unit_hash"]


def register(spark: SparkSession) -> None:
    """SQL names of the functions above, and of those that are plain expressions."""
    for name, f in {"float_bits": float_bits, "double_bits": double_bits, "bf16_bits": bf16_bits, "xor_bytes": xor_bytes, "popcount_bytes": popcount_bytes}.items():
        spark.udf.register(name, f)
    spark.udtf.register("cdc_chunks", CdcChunks)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION reduction(original BIGINT, stored BIGINT) RETURNS DOUBLE RETURN round(1 - stored / original, 6)")
