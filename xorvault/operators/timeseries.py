"""Extras: XOR of consecutive values, as time-series float coders do."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from xorvault.functions.words import double_bits


def consecutive_xor(series: DataFrame, *, by: str, order: str, value: str) -> DataFrame:
    """(by, n, zero_xors, one_bits): how much consecutive values of each series share bitwise."""
    bits = series.select(by, order, double_bits(value).alias("x"))
    d = bits.withColumn("d", F.expr(f"x ^ lag(x) OVER (PARTITION BY {by} ORDER BY {order})"))
    return d.groupBy(by).agg(F.count("*").alias("n"), F.count_if(F.col("d") == 0).alias("zero_xors"), F.coalesce(F.sum(F.bit_count("d")), F.lit(0)).cast("bigint").alias("one_bits"))
