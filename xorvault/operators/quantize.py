"""Block quantization to int8, and quantized files that are kept as a recipe over their base."""

from __future__ import annotations

import hashlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from xorvault.functions import words as W
from xorvault.operators.codecs import on_rows

BLOCK = 32


def quantize(payload: bytes, dtype: str, block: int = BLOCK) -> bytes:
    """Per block of values: an FP16 scale of the greatest magnitude over 127, then int8 values rounded half to even."""
    x = W.floats(W.words(payload, dtype), dtype)
    pad = -len(x) % block
    x = np.concatenate([x, np.zeros(pad)]).reshape(-1, block)
    scale = (np.abs(x).max(axis=1, initial=0) / 127).astype("<f2")
    s = scale.astype(np.float64)[:, None]
    q = np.where(s > 0, np.rint(x / np.where(s > 0, s, 1)), 0).clip(-127, 127).astype(np.int8)
    return b"".join(a.tobytes() + b.tobytes() for a, b in zip(scale, q))


def dequantize(data: bytes, block: int = BLOCK) -> np.ndarray:
    rows = np.frombuffer(data, np.uint8).reshape(-1, block + 2)
    scale = np.ascontiguousarray(rows[:, :2]).view("<f2").astype(np.float64)
    return (np.ascontiguousarray(rows[:, 2:]).view(np.int8) * scale).ravel()


def plan(quantized: DataFrame, bases: DataFrame) -> DataFrame:
    """(repo_id, ordinal, recipe): a stored quantized tensor becomes (base hash, recipe) only if it regenerates exactly."""
    b = bases.select("family", "ordinal", F.col("payload").alias("base_payload"), F.col("dtype").alias("base_dtype"), F.col("tensor_hash").alias("base_hash"))
    both = quantized.select("repo_id", "family", "ordinal", "tensor_hash", "n_bytes").join(b, ["family", "ordinal"], "left")

    def make(payload, dtype, want):
        ok = payload is not None and hashlib.sha256(quantize(payload, dtype)).hexdigest() == want
        return {"recipe": f"int8 blocks of {BLOCK}" if ok else None}

    done = on_rows(both, ["repo_id", "ordinal", "tensor_hash", "base_hash", "n_bytes"], ["base_payload", "base_dtype", "tensor_hash"], make, "recipe string")
    return done


def regenerate(planned: DataFrame, pool: DataFrame) -> DataFrame:
    """(repo_id, ordinal, payload, lossless): the quantized bytes made again from the base tensors."""
    b = pool.select(F.col("tensor_hash").alias("base_hash"), "payload", "dtype").dropDuplicates(["base_hash"])

    def make(payload, dtype, want):
        data = quantize(payload, dtype)
        return {"restored": data, "lossless": hashlib.sha256(data).hexdigest() == want}

    return on_rows(planned.where("recipe IS NOT NULL").join(b, "base_hash"), ["repo_id", "ordinal", "n_bytes"], ["payload", "dtype", "tensor_hash"], make, "restored binary, lossless boolean")
