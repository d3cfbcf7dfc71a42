"""Exact deduplication at four granularities, and its measures.

Every level works on rows (hash, n_bytes, order columns); payloads never move. The canonical copy of a hash is its first
row in upload order. It is found by a partial aggregate and a join back rather than by a window over the hash, so that a
hash with a third of all rows is combined before the shuffle and the join's skew is left to adaptive execution.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Bytes of one entry in a deduplication index.
ENTRY_BYTES = 64
UPLOAD_ORDER = ("uploaded_at", "repo_id", "path")
LAYER = r"(?:^|\.)(?:layers|h|blocks)\.(\d+)\."


def with_canonical(units: DataFrame, keys: Sequence[str], order: Sequence[str]) -> DataFrame:
    """units with `canonical` (the order columns of the first unit of equal keys) and `is_dup`."""
    at = F.struct(*order)
    first = units.groupBy(*keys).agg(F.min(at).alias("canonical"))
    return units.join(first, list(keys)).withColumn("is_dup", F.struct(*order) != F.col("canonical"))


def dedup_files(files: DataFrame, *, order_by: Sequence[str] = UPLOAD_ORDER, content: str = "content", hash_col: str = "file_hash") -> DataFrame:
    """Files with file_hash (sha256 of the content, unless the column is there already), canonical and is_dup."""
    if hash_col not in files.columns:
        files = files.withColumn(hash_col, F.sha2(F.col(content).cast("binary"), 256))
    return with_canonical(files, [hash_col], order_by)


def split_unique(files: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Of deduplicated files: (unique files, links of the others to their canonical copy)."""
    return files.where(~F.col("is_dup")), files.where("is_dup")


def dedup_against(files: DataFrame, pool: DataFrame, hash_col: str = "file_hash") -> tuple[DataFrame, DataFrame]:
    """(files whose hash the pool lacks, links of the others); the pool is probed by its hashes alone."""
    known = pool.select(hash_col)
    return files.join(known, hash_col, "left_anti"), files.join(known, hash_col, "left_semi")


@dataclass
class TensorDedup:
    pool: DataFrame
    refs: DataFrame


def tensor_identity(identity: str = "typed") -> Column:
    """What makes two tensors equal: their bytes, or their bytes with dtype and shape."""
    if identity == "bytes":
        return F.col("tensor_hash")
    if identity == "typed":
        return F.sha2(F.concat_ws("|", "tensor_hash", "dtype", F.array_join(F.col("shape").cast("array<string>"), "x")), 256)
    raise ValueError(f"unknown identity {identity!r}")


def dedup_tensors(tensors: DataFrame, *, scope: str = "hub", identity: str = "typed", order_by: Sequence[str] = ("repo_id", "path", "ordinal")) -> TensorDedup:
    """The pool (one row per distinct tensor within its scope, with refcount) and the references of all tensors to it."""
    keys = {"hub": [], "repo": ["repo_id"], "file": ["repo_id", "path"]}[scope] + ["unit_hash"]
    meta = tensors.drop("payload").withColumn("unit_hash", tensor_identity(identity))
    refs = with_canonical(meta, keys, order_by)
    pool = meta.groupBy(*keys).agg(F.min_by("dtype", F.struct(*order_by)).alias("dtype"), F.first("n_bytes").alias("n_bytes"), F.count("*").alias("refcount"), F.min(F.struct(*order_by)).alias("first_at"), F.first("tensor_hash").alias("tensor_hash"))
    return TensorDedup(pool, refs)


def layer_id(name: str = "name", pattern: str = LAYER) -> Column:
    """The layer's number in a tensor name; a tensor without one is a layer of its own."""
    number = F.regexp_extract(name, pattern, 1)
    return F.when(number != "", F.concat(F.lit("layer "), number)).otherwise(F.col(name))


def layers(tensors: DataFrame, *, pattern: str = LAYER) -> DataFrame:
    """(repo_id, path, layer, unit_hash, n_bytes): the hash covers the layer's tensors in order."""
    meta = tensors.drop("payload").withColumn("layer", layer_id("name", pattern))
    member = F.struct("ordinal", F.concat_ws("|", "tensor_hash", "dtype", F.array_join(F.col("shape").cast("array<string>"), "x")).alias("h"))
    in_order = F.array_join(F.transform(F.array_sort(F.collect_list(member)), lambda m: m["h"]), ";")
    return meta.groupBy("repo_id", "path", "layer").agg(F.sha2(in_order, 256).alias("unit_hash"), F.sum("n_bytes").alias("n_bytes"), F.min("ordinal").alias("ordinal"))


def dedup_layers(tensors: DataFrame, *, layer_of: str = LAYER) -> DataFrame:
    return with_canonical(layers(tensors, pattern=layer_of), ["unit_hash"], ("repo_id", "path", "ordinal"))


def files_of(tensors: DataFrame) -> DataFrame:
    """(repo_id, path, unit_hash, n_bytes) of archives known by their tensors alone."""
    member = F.struct("ordinal", F.concat_ws("|", "name", "tensor_hash", "dtype", F.array_join(F.col("shape").cast("array<string>"), "x")).alias("h"))
    in_order = F.array_join(F.transform(F.array_sort(F.collect_list(member)), lambda m: m["h"]), ";")
    return tensors.drop("payload").groupBy("repo_id", "path").agg(F.sha2(in_order, 256).alias("unit_hash"), F.sum("n_bytes").alias("n_bytes"))


def dedup_stats(units: DataFrame, level: str, *, entry_bytes: int = ENTRY_BYTES) -> DataFrame:
    """One row: counts and bytes of all and of unique units, reduction ratio, unit sizes and index bytes."""
    unique = units.groupBy("unit_hash").agg(F.count("*").alias("n"), F.first("n_bytes").alias("one"), F.sum("n_bytes").alias("every"))
    total, kept = F.sum("every"), F.sum("one")
    return unique.agg(
        F.lit(level).alias("level"), F.coalesce(F.sum("n"), F.lit(0)).alias("total_units"), F.count("*").alias("unique_units"), total.alias("total_bytes"), kept.alias("unique_bytes"),
        F.round(1 - kept / total, 6).alias("drr"), F.max("one").alias("max_unit_bytes"), F.round(kept / F.count("*"), 3).alias("avg_unit_bytes"), (F.count("*") * entry_bytes).alias("metadata_bytes"),
    )


def duplicate_census(files: DataFrame, *, repo: str = "repo_id") -> DataFrame:
    """Files, duplicates, bytes, savings and repositories touched: holding a shared hash, or holding a non-first copy."""
    per_hash = files.groupBy("file_hash").agg(F.count("*").alias("n"), F.first("n_bytes").alias("one"), F.sum("n_bytes").alias("every"), F.min("order_key").alias("first_key"))
    sums = per_hash.agg(F.sum("n").alias("total_files"), (F.sum("n") - F.count("*")).alias("duplicate_files"), F.sum("every").alias("total_bytes"), (F.sum("every") - F.sum("one")).alias("saved_bytes"))
    touched = files.select(repo, "file_hash", "order_key").join(per_hash.where("n > 1").select("file_hash", "first_key"), "file_hash")
    shared = touched.agg(F.count_distinct(repo).alias("repos_shared"), F.count_distinct(F.when(F.col("order_key") != F.col("first_key"), F.col(repo))).alias("repos_with_redundant_copy"))
    repos = files.agg(F.count_distinct(repo).alias("repos_total"))
    return sums.crossJoin(repos).crossJoin(shared).select("total_files", "duplicate_files", "total_bytes", "saved_bytes", F.round(F.col("saved_bytes") / F.col("total_bytes"), 6).alias("saved_ratio"), "repos_total", "repos_shared", "repos_with_redundant_copy")


def missing_hashes(client: DataFrame, pool: DataFrame, hash_col: str = "tensor_hash") -> DataFrame:
    """The distinct hashes that a client offers and the server lacks: all that has to be uploaded."""
    return client.select(hash_col).distinct().join(pool.select(hash_col), hash_col, "left_anti")


def transfer_saved(client: DataFrame, pool: DataFrame, *, hash_col: str = "tensor_hash", by: Sequence[str] = ("repo_id",)) -> DataFrame:
    """Per client: units sent (first offer of a missing hash) and skipped, and the bytes not sent."""
    known = pool.select(hash_col).distinct().withColumn("known", F.lit(True))
    first = client.groupBy(hash_col).agg(F.min(F.struct(*by, "ordinal")).alias("first_at"))
    told = client.join(known, hash_col, "left").join(first, hash_col)
    sent = F.col("known").isNull() & (F.struct(*by, "ordinal") == F.col("first_at"))
    return told.groupBy(*by).agg(F.count_if(sent).alias("sent_units"), F.count_if(~sent).alias("skipped_units"), F.sum(F.when(sent, 0).otherwise(F.col("n_bytes"))).alias("bytes_saved"))


def prefix_curve(uploads: DataFrame, *, buckets: int = 64) -> DataFrame:
    """(seq, raw_bytes, stored_bytes, drr) after each upload, from rows (seq, raw, stored).

    Running sums in two levels: inside ranges of seq in parallel, and over the ranges' totals, of which there are
    `buckets` at most, in one small window.
    """
    per = uploads.groupBy("seq").agg(F.sum("raw").alias("raw"), F.sum("stored").alias("stored"))
    low, high = F.min("seq"), F.max("seq")
    limits = per.agg(low.alias("lo"), high.alias("hi"))
    ranged = per.crossJoin(F.broadcast(limits)).withColumn("part", F.floor((F.col("seq") - F.col("lo")) * buckets / (F.col("hi") - F.col("lo") + 1)))
    totals = ranged.groupBy("part").agg(F.sum("raw").alias("r"), F.sum("stored").alias("s"))
    before = "ORDER BY part ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING"
    offsets = totals.select("part", F.expr(f"coalesce(sum(r) OVER ({before}), 0)").alias("r0"), F.expr(f"coalesce(sum(s) OVER ({before}), 0)").alias("s0"))
    run = ranged.select("part", "seq", *[F.expr(f"sum({c}) OVER (PARTITION BY part ORDER BY seq)").alias(c) for c in ("raw", "stored")])
    total = run.join(F.broadcast(offsets), "part").select("seq", (F.col("raw") + F.col("r0")).alias("raw_bytes"), (F.col("stored") + F.col("s0")).alias("stored_bytes"))
    return total.withColumn("drr", F.round(1 - F.col("stored_bytes") / F.col("raw_bytes"), 6))


def dedup_map(units: DataFrame, repo: str) -> DataFrame:
    """Where one repository's units lie and which of them occur elsewhere: (level, unit_no, begin, n_bytes, is_dup)."""
    shared = units.groupBy("level", "unit_hash").agg((F.count_distinct("repo_id") > 1).alias("elsewhere"))
    own = units.where(F.col("repo_id") == repo).join(shared, ["level", "unit_hash"])
    return own.select("level", "unit_no", "begin", "n_bytes", F.col("elsewhere").alias("is_dup"))
