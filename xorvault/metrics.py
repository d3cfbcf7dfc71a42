"""Cost and accuracy measures."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Fixed values of the published study: index entry size, hub and sample sizes, memory of one machine, sizes of the cost example.
ENTRY_BYTES = 64
HUB_TB, SAMPLE_TB = 17_000.0, 43.19
VM_GB = 384
SAVED_PB = 8.5
PRICE_GB_MONTH = 0.0216


def drr(original: Column, stored: Column) -> Column:
    """Data reduction ratio: the share of bytes that is saved."""
    return F.round(1 - stored / original, 6)


def metadata_mib(entries: int, entry_bytes: int = ENTRY_BYTES) -> float:
    return entries * entry_bytes / 2**20


def projected_gb(entries: int, hub_tb: float = HUB_TB, sample_tb: float = SAMPLE_TB, entry_bytes: int = ENTRY_BYTES) -> float:
    """Index size of the whole hub in GB, from a sample's entries."""
    return metadata_mib(entries, entry_bytes) * hub_tb / sample_tb / 1000


def vms(gb: float, each: float = VM_GB) -> int:
    """Machines whose memory together holds an index of gb."""
    return math.ceil(gb / each)


def annual_saving(saved_bytes: Column, price_gb_month: float = PRICE_GB_MONTH) -> Column:
    return F.round(saved_bytes / 1e9 * price_gb_month * 12, 4)


def confusion(pairs: DataFrame, predicted: Column, actual: Column, by: list[str] | None = None) -> DataFrame:
    """tp, fp, tn, fn and the four measures; precision, recall and f1 are null where undefined."""
    c = {"tp": predicted & actual, "fp": predicted & ~actual, "tn": ~predicted & ~actual, "fn": ~predicted & actual}
    counts = pairs.groupBy(*(by or [])).agg(*[F.count_if(x).alias(k) for k, x in c.items()])
    return with_rates(counts)


def with_rates(counts: DataFrame) -> DataFrame:
    tp, fp, tn, fn = (F.col(c) for c in ("tp", "fp", "tn", "fn"))
    ratio = lambda a, b: F.when(b > 0, F.round(a / b, 6))
    return counts.withColumns({"accuracy": ratio(tp + tn, tp + fp + tn + fn), "precision": ratio(tp, tp + fp), "recall": ratio(tp, tp + fn), "f1": ratio(2 * tp, 2 * tp + fp + fn)})


def throughput(run: Callable[[], DataFrame], n_bytes: int) -> dict[str, float]:
    """Seconds and MB/s of evaluating a DataFrame in full without keeping it."""
    began = time.perf_counter()
    run().write.format("noop").mode("overwrite").save()
    s = time.perf_counter() - began
    return {"s": s, "mb_s": n_bytes / 1e6 / s}


def relative(a: float, b: float) -> float:
    return a / b
