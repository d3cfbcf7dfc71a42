import hashlib
import struct

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from xorvault.functions import words as W
from xorvault.operators import chunking as C
from xorvault.operators import codecs as K
from xorvault.operators import quantize as Q

SPECIAL = np.array([0x0000, 0x8000, 0x7F80, 0xFF80, 0x7FC1, 0xFFFF, 0x0001, 0x8001, 0x3F80], "<u2").tobytes()


def payloads(dtype):
    size = np.dtype(W.DTYPES[dtype][0]).itemsize
    return st.binary(max_size=400).map(lambda b: b[: len(b) // size * size])


def weights(n=4000, sigma=0.0, seed=0):
    rng = np.random.default_rng(seed)
    w = rng.normal(0, 0.03, n).astype(np.float32)
    return W.bf16_words(w).tobytes(), W.bf16_words(w + rng.normal(0, sigma, n).astype(np.float32)).tobytes()


def test_worked_example():
    """1.000 -> 1.001 flips five bits of FP32; in BF16 both are the same word."""
    a, b = np.float32(1.0).tobytes(), np.float32(1.001).tobytes()
    assert W.differing_bits(a, b, "F32") == (1, 5)
    assert struct.unpack("<I", b)[0] == 1065361605
    x = W.bf16_words(np.array([1.0, 1.001], "<f4"))
    assert x[0] == x[1]


def test_bf16_rounding():
    x = np.array([1.0, 1.00390625, 1.01171875, np.nan, np.inf, -0.0, 1e-45], "<f4")
    assert W.bf16_words(x).tolist() == [0x3F80, 0x3F80, 0x3F82, 0x7FC0, 0x7F80, 0x8000, 0x0000]
    assert W.bf16_words(np.array([1.01171875], "<f4"), "truncate").tolist() == [0x3F81]


@given(payloads("BF16"), payloads("BF16"), payloads("BF16"))
@settings(max_examples=60, deadline=None)
def test_distance_is_a_metric(a, b, c):
    n = min(map(len, (a, b, c)))
    a, b, c = a[:n], b[:n], c[:n]
    d = lambda x, y: W.differing_bits(x, y, "BF16", "keep")[1]
    assert d(a, a) == 0 and d(a, b) == d(b, a) and d(a, c) <= d(a, b) + d(b, c) <= 2 * 16 * (n // 2)
    assert sum(W.bit_ones(a, b, "BF16")) == d(a, b)


def test_zero_policies():
    a, b = np.array([0x0000, 0x8000, 0x3F80, 0x0000], "<u2").tobytes(), np.array([0x8000, 0x0000, 0x3F81, 0x3F80], "<u2").tobytes()
    assert [W.differing_bits(a, b, "BF16", p)[0] for p in ("keep", "drop_both_zero", "drop_either_zero")] == [4, 2, 1]


@pytest.mark.parametrize("codec", [*K.GENERAL, "grouping_huffman", "grouping_zstd", "raw"])
@pytest.mark.parametrize("dtype", ["BF16", "F16", "F32", "F64"])
@given(data=st.data())
@settings(max_examples=15, deadline=None)
def test_standalone_roundtrip(codec, dtype, data):
    p = data.draw(payloads(dtype))
    assert K.decode(K.encode(p, dtype, codec, None), dtype) == p


@pytest.mark.parametrize("options", [{}, {"plane_split": True}, {"transform": "wrap"}, {"transform": "zigzag"}, {"codec": "lz4", "level": None}, {"codec": "brotli", "level": 5}])
@pytest.mark.parametrize("dtype", ["BF16", "F32", "F64"])
@given(data=st.data())
@settings(max_examples=15, deadline=None)
def test_delta_roundtrip(options, dtype, data):
    a, b = data.draw(payloads(dtype)), data.draw(payloads(dtype))
    n = min(len(a), len(b))
    coded = K.delta_encode(a[:n], b[:n], dtype, **options)
    assert K.decode(coded, dtype, b[:n]) == a[:n]
    assert len(coded) <= n + K.HEAD.size


def test_special_values_survive():
    base = bytes(len(SPECIAL))
    for coded in (K.delta_encode(SPECIAL * 50, base * 50, "BF16"), K.encode(SPECIAL * 50, "BF16", "grouping_huffman")):
        assert K.decode(coded, "BF16", base * 50) == SPECIAL * 50


@given(st.binary(min_size=1, max_size=3000))
@settings(max_examples=60, deadline=None)
def test_huffman(data):
    x = np.frombuffer(data, np.uint8)
    assert (K.huffman_decode(K.huffman_encode(x)) == x).all()
    counts = np.bincount(x, minlength=256)
    h, bits = K.entropy_bits(counts), K.huffman_bits(x) / len(x)
    assert h - 1e-9 <= bits < h + 1 or (counts > 0).sum() == 1
    lengths = K.code_lengths(counts)
    assert sum(2.0 ** -int(n) for n in lengths if n) <= 1


@pytest.mark.parametrize("n", [16 * 1024 - 1, 16 * 1024, 16 * 1024 + 1, 50_000])
def test_huffman_in_lanes(n):
    rng = np.random.default_rng(n)
    for x in (rng.geometric(0.3, n).clip(0, 255), rng.integers(0, 256, n), np.zeros(n, int)):
        x = x.astype(np.uint8)
        assert (K.huffman_decode(K.huffman_encode(x)) == x).all()


def test_long_codes_are_limited():
    fib = [1, 1]
    while len(fib) < 40:
        fib.append(fib[-1] + fib[-2])
    lengths = K.code_lengths(np.array(fib + [0] * 216))
    assert 0 < lengths.max() <= K.LONGEST and sum(2.0 ** -int(n) for n in lengths if n) <= 1


def test_codecs_rank_as_reported():
    """Within a family XOR beats grouping beats zstd; across families XOR gains nothing."""
    for sigma in (0.0005, 0.002):
        base, tuned = weights(20_000, sigma)
        xor, zstd, grouping = (len(x) for x in (K.delta_encode(tuned, base, "BF16"), K.encode(tuned, "BF16", "zstd"), K.encode(tuned, "BF16", "grouping_huffman")))
        assert xor < grouping < zstd
    other = weights(20_000, seed=9)[0]
    assert len(K.delta_encode(other, weights(20_000)[0], "BF16")) > 0.97 * len(K.encode(other, "BF16", "zstd"))
    assert not any(W.words(W.xor(base, base), "BF16"))


def test_xor_is_sparser_than_float_difference():
    for sigma in (0.0005, 0.002, 0.005):
        base, tuned = (W.words(x, "BF16") for x in weights(20_000, sigma))
        diff = W.bf16_words((W.floats(tuned, "BF16") - W.floats(base, "BF16")).astype(np.float32))
        assert np.bitwise_count(base ^ tuned).sum() < np.bitwise_count(diff).sum()


# --- Chunks


def gear_sequential(data):
    h, out = 0, []
    for b in data:
        h = ((h << 1) + int(C.GEAR[b])) % 2**64
        out.append(h)
    return out


@given(st.binary(max_size=300))
@settings(max_examples=40, deadline=None)
def test_gear_by_doubling(data):
    assert C.gear_hashes(data).tolist() == gear_sequential(data)


@given(st.binary(max_size=20_000))
@settings(max_examples=30, deadline=None)
def test_chunks_cover(data):
    s = C.ChunkSizes(64, 256, 1024)
    chunks = C.chunks_of(data, s)
    assert sum(c["n_bytes"] for c in chunks) == len(data)
    assert all(s.least <= c["n_bytes"] <= s.most for c in chunks[:-1])
    assert all(c["unit_hash"] == hashlib.sha256(data[c["begin"] : c["begin"] + c["n_bytes"]]).hexdigest() for c in chunks)


def test_chunks_resist_shifts():
    data = np.random.default_rng(1).integers(0, 256, 200_000).astype(np.uint8).tobytes()
    s = C.ChunkSizes(64, 256, 1024)
    a = {c["unit_hash"] for c in C.chunks_of(data, s)}
    b = {c["unit_hash"] for c in C.chunks_of(data[:1000] + b"inserted" + data[1000:], s)}
    assert len(a - b) <= 5
    fixed = lambda d: {hashlib.sha256(d[k : k + 256]).hexdigest() for k in range(0, len(d), 256)}
    assert len(fixed(data) - fixed(data[:1000] + b"inserted" + data[1000:])) > 700


def test_quantizer():
    base, _ = weights(1000)
    q = Q.quantize(base, "BF16")
    assert Q.quantize(base, "BF16") == q and len(q) == -(-1000 // 32) * 34
    x = W.floats(W.words(base, "BF16"), "BF16")
    assert np.abs(Q.dequantize(q)[:1000] - x).max() <= np.abs(x).max() / 127 * 0.51 + 1e-4
    assert Q.quantize(b"", "BF16") == b""


def test_chunks_of_blocks_are_those_of_files(spark):
    """Files cut as their blocks come in, whatever the blocks, give the chunks of whole files."""
    from pyspark.sql import functions as F

    rng = np.random.default_rng(8)
    files = {"empty": b"", "short": b"abc", "a": rng.integers(0, 256, 60_000, np.uint8).tobytes(), "zeros": bytes(20_000), "b": (rng.integers(0, 256, 9000, np.uint8).tobytes() * 3)}
    sizes = C.ChunkSizes(64, 256, 1024)
    rows = []
    for name, data in files.items():
        at, k = 0, 0
        while at < len(data) or not k:
            n = int(rng.choice([1, 50, 700, 5000]))
            rows.append((name, k, bytearray(data[at : at + n])))
            at, k = at + n, k + 1
    blocks = spark.createDataFrame(rows, "file_id string, k int, content binary").repartition(3)
    got = sorted(tuple(r) for r in C.chunk_blocks(blocks, ["file_id"], "k", sizes=sizes).collect())
    whole = spark.createDataFrame([(n, bytearray(d)) for n, d in files.items()], "file_id string, content binary")
    assert got == sorted(tuple(r) for r in C.chunk(whole, ["file_id"], sizes=sizes).collect()) and len(got) > 200
    assert C.chunk_blocks(blocks.where(F.lit(False)), ["file_id"], "k", sizes=sizes).count() == 0
    with pytest.raises(ValueError):
        C.chunk_blocks(blocks, ["file_id"], "k", sizes=C.ChunkSizes(16, 64, 256))
