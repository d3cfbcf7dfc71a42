"""Bit distance: the mean count of differing bits over aligned floats, and what follows from it.

The bulk path sends pairs of payload blocks through one Arrow function and gets (n, bits) per block; only those rows are
shuffled. The element path is plain SQL on words and serves as its check.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from xorvault.functions import words as W

POLICIES = ("drop_both_zero", "drop_either_zero", "keep")


def _schema(df: DataFrame, keep: list[str], extra: str) -> str:
    return ", ".join([f"{c} {df.schema[c].dataType.simpleString()}" for c in keep] + [extra])


def block_bits(pairs: DataFrame, keep: list[str], *, zero_policy: str = "drop_both_zero") -> DataFrame:
    """(keep..., n, bits) per row of pairs, whose columns payload_a, payload_b, dtype hold aligned blocks."""
    names = list(keep)

    def run(batches):
        for batch in batches:
            got = [W.differing_bits(a, b, t, zero_policy) for a, b, t in zip(batch.column("payload_a").to_pylist(), batch.column("payload_b").to_pylist(), batch.column("dtype").to_pylist())]
            yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in names], pa.array([n for n, _ in got], pa.int64()), pa.array([b for _, b in got], pa.int64())], names=[*names, "n", "bits"])

    return pairs.select(*names, "payload_a", "payload_b", "dtype").mapInArrow(run, _schema(pairs, names, "n bigint, bits bigint"))


def bit_distance(pairs: DataFrame, *, by: tuple[str, ...] = ("a", "b"), zero_policy: str = "drop_both_zero") -> DataFrame:
    """(by..., n, bits, distance) over all blocks of each pair; the distance is null where nothing counts."""
    sums = block_bits(pairs, list(by), zero_policy=zero_policy).groupBy(*by).agg(F.sum("n").alias("n"), F.sum("bits").alias("bits"))
    return sums.withColumn("distance", F.when(F.col("n") > 0, F.round(F.col("bits") / F.col("n"), 6)))


def bit_distance_sql(elements: DataFrame, pairs: DataFrame, *, width: int = 16, zero_policy: str = "drop_both_zero") -> DataFrame:
    """The same from element rows (repo_id, ordinal, idx, bits), in Catalyst expressions only."""
    a = elements.select(F.col("repo_id").alias("a"), "ordinal", "idx", F.col("bits").alias("x"))
    b = elements.select(F.col("repo_id").alias("b"), "ordinal", "idx", F.col("bits").alias("y"))
    low = (1 << (width - 1)) - 1
    zx, zy = F.col("x").bitwiseAND(low) == 0, F.col("y").bitwiseAND(low) == 0
    counted = {"drop_both_zero": ~(zx & zy), "drop_either_zero": ~(zx | zy), "keep": F.lit(True)}[zero_policy]
    both = pairs.select("a", "b").join(a, "a").join(b, ["b", "ordinal", "idx"]).where(counted)
    sums = both.groupBy("a", "b").agg(F.count("*").alias("n"), F.sum(F.bit_count(F.col("x").bitwiseXOR(F.col("y")))).alias("bits"))
    return sums.withColumn("distance", F.round(F.col("bits") / F.col("n"), 6))


def bit_distance_sampled(pairs: DataFrame, *, rate: float, delta: float = 0.05, tau: float = 4.0, by: tuple[str, ...] = ("a", "b"), block: tuple[str, ...] = ("ordinal",), width: int = 16, seed: int = 11) -> DataFrame:
    """(by..., blocks, n, bits, distance, half_width, decided) from a hash sample of blocks; blocks left out are not read.

    A block is the unit of the sample, since the floats of one tensor change together or not at all: half_width is
    Hoeffding's bound at confidence 1 - delta over block means in [0, width], for blocks of about one size. `decided` tells whether
    tau lies outside the interval, so that only undecided pairs need a full pass.
    """
    kept = pairs.where(F.pmod(F.xxhash64(F.lit(seed), *by, *block), F.lit(10_000)) < int(rate * 10_000))
    d = block_bits(kept, list(by)).where("n > 0").groupBy(*by).agg(F.count("*").alias("blocks"), F.sum("n").alias("n"), F.sum("bits").alias("bits")).withColumn("distance", F.round(F.col("bits") / F.col("n"), 6))
    half = width * F.sqrt(F.log(F.lit(2 / delta)) / (2 * F.col("blocks")))
    return d.withColumn("half_width", half).withColumn("decided", F.abs(F.col("distance") - tau) > half)


def bit_distance_settled(pairs: DataFrame, *, rate: float, by: tuple[str, ...] = ("a", "b"), **options) -> DataFrame:
    """The rows of bit_distance_sampled that are decided; the exact ones, with half_width 0, of all other pairs."""
    done = bit_distance_sampled(pairs, rate=rate, by=by, **options).where("decided")
    rest = block_bits(pairs.join(done.select(*by), list(by), "left_anti"), list(by))
    exact = rest.groupBy(*by).agg(F.count_if(F.col("n") > 0).alias("blocks"), F.sum("n").alias("n"), F.sum("bits").alias("bits"))
    exact = exact.withColumn("distance", F.when(F.col("n") > 0, F.round(F.col("bits") / F.col("n"), 6))).withColumn("half_width", F.lit(0.0)).withColumn("decided", F.col("distance").isNotNull())
    return done.unionByName(exact)


def bit_breakdown(pairs: DataFrame, *, by: tuple[str, ...] = ("a", "b"), width: int = 16, exponent: int = 8) -> DataFrame:
    """(by..., bit_pos, field, ones, share): how the differing bits spread over bit positions."""
    names = list(by)

    def run(batches):
        for batch in batches:
            ones = [W.bit_ones(a, b, t) for a, b, t in zip(batch.column("payload_a").to_pylist(), batch.column("payload_b").to_pylist(), batch.column("dtype").to_pylist())]
            yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in names], pa.array(ones, pa.list_(pa.int64()))], names=[*names, "ones"])

    each = pairs.select(*names, "payload_a", "payload_b", "dtype").mapInArrow(run, _schema(pairs, names, "ones array<bigint>"))
    rows = each.select(*names, F.posexplode("ones").alias("bit_pos", "c")).groupBy(*names, "bit_pos").agg(F.sum("c").alias("ones"))
    return shares(rows, by, width, exponent)


def shares(rows: DataFrame, by: tuple[str, ...], width: int, exponent: int) -> DataFrame:
    total = rows.groupBy(*by).agg(F.sum("ones").alias("total")) if by else rows.agg(F.sum("ones").alias("total"))
    joined = rows.join(total, list(by)) if by else rows.crossJoin(total)
    field = F.when(F.col("bit_pos") == width - 1, "sign").when(F.col("bit_pos") >= width - 1 - exponent, "exponent").otherwise("mantissa")
    return joined.select(*by, F.col("bit_pos").cast("int").alias("bit_pos"), field.alias("field"), "ones", F.when(F.col("total") > 0, F.round(F.col("ones") / F.col("total"), 6)).alias("share"))


def breakdown_of_columns(df: DataFrame, x: str, y: str, *, width: int = 64, exponent: int = 11) -> DataFrame:
    """Breakdown between two integer columns of raw bits, in Catalyst expressions only."""
    d = F.col(x).bitwiseXOR(F.col(y))
    sums = df.agg(*[F.sum(F.shiftrightunsigned(d, k).bitwiseAND(F.lit(1).cast("bigint"))).alias(f"b{k}") for k in range(width)])
    rows = sums.select(F.posexplode(F.array(*[f"b{k}" for k in range(width)])).alias("bit_pos", "ones"))
    return shares(rows, (), width, exponent)


def element_delta(a: DataFrame, b: DataFrame) -> DataFrame:
    """(a, b, dw) per aligned float of rows (repo_id, ordinal, idx, value)."""
    left = a.select(F.col("repo_id").alias("a"), "ordinal", "idx", F.col("value").alias("x"))
    right = b.select(F.col("repo_id").alias("b"), "ordinal", "idx", F.col("value").alias("y"))
    return left.join(right, ["ordinal", "idx"]).select("a", "b", (F.col("x") - F.col("y")).alias("dw"))


def delta_profile(deltas: DataFrame, *, bin_width: float = 0.001) -> DataFrame:
    """Histogram of element deltas: (a, b, bin, cnt)."""
    return deltas.groupBy("a", "b", F.floor(F.col("dw") / bin_width).alias("bin")).agg(F.count("*").alias("cnt"))


def delta_moments(deltas: DataFrame) -> DataFrame:
    """n, mean, sd, greatest magnitude, skewness and kurtosis per pair."""
    return deltas.groupBy("a", "b").agg(F.count("*").alias("n"), F.avg("dw").alias("mean"), F.stddev_pop("dw").alias("sd"), F.max(F.abs("dw")).alias("max_abs"), F.skewness("dw").alias("skew"), F.kurtosis("dw").alias("kurt"), F.percentile_approx("dw", 0.5, 1000).alias("median"))


def value_of_bf16(bits: str = "bits"):
    """The value of a BF16 word, by IEEE arithmetic: (1 + m/128) * 2^(e-127), with subnormals."""
    b = F.col(bits)
    e, m = F.shiftright(b, 7).bitwiseAND(255), b.bitwiseAND(127)
    sign = F.when(b.bitwiseAND(32768) != 0, -1.0).otherwise(1.0)
    return sign * F.when(e == 0, m / 128.0 * F.pow(F.lit(2.0), F.lit(-126.0))).otherwise((1 + m / 128.0) * F.pow(F.lit(2.0), e - 127.0))


def popcount(x: np.ndarray) -> int:
    return int(np.bitwise_count(x).sum())
