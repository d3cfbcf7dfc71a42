"""Blocks: element-aligned slices of tensors, so that no row, hash or task depends on a tensor's size.

A block row has the columns of a tensor row and may take its place everywhere: hashing, distance, alignment by order,
coding and the pipeline. A tensor's identity over blocks is a hash of its blocks' digests in order; a tensor of one block
keeps the plain hash of its bytes.
"""

from __future__ import annotations

import hashlib

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BLOCK_BYTES = 4 << 20


def as_blocks(tensors: DataFrame, *, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """Tensor rows cut in blocks: ordinal is over all blocks of the file, name gets a block number where there are several."""
    if block_bytes % 8:
        raise ValueError("block_bytes must be a multiple of 8, or floats would be cut")
    n = F.greatest(F.ceil(F.col("n_bytes") / block_bytes), F.lit(1)).cast("int")
    before = "coalesce(sum(_n) OVER (PARTITION BY repo_id, path ORDER BY ordinal ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)"
    meta = tensors.select("repo_id", "path", "ordinal", n.alias("_n")).withColumn("_first", F.expr(before).cast("int"))
    schema = tensors.schema

    def run(batches):
        for batch in batches:
            rows = []
            for r in batch.to_pylist():
                n, first = r.pop("_n"), r.pop("_first")
                size = r["n_bytes"] // r["n_elems"] if r["n_elems"] else 1
                for k in range(n):
                    part = r["payload"][k * block_bytes : (k + 1) * block_bytes]
                    own = {} if n == 1 else {"name": f"{r['name']}#{k}", "shape": [len(part) // size], "n_elems": len(part) // size, "tensor_hash": hashlib.sha256(part).hexdigest()}
                    rows.append({**r, **own, "ordinal": first + k, "offset": r["offset"] + k * block_bytes, "n_bytes": len(part), "payload": part})
            yield pa.RecordBatch.from_pylist(rows, schema=out)

    from pyspark.sql.pandas.types import to_arrow_schema

    out = to_arrow_schema(schema)
    return tensors.join(meta, ["repo_id", "path", "ordinal"]).select(*schema.names, "_n", "_first").mapInArrow(run, schema)


def tensor_hashes(blocks: DataFrame, *, keys: tuple[str, ...] = ("repo_id", "path", "tensor"), block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """(keys..., tensor_hash, n_bytes) from block rows (keys..., block_no, block_hash, n_bytes): only digests are shuffled."""
    in_order = F.transform(F.array_sort(F.collect_list(F.struct("block_no", "block_hash"))), lambda b: b["block_hash"])
    merged = blocks.groupBy(*keys).agg(in_order.alias("h"), F.sum("n_bytes").alias("n_bytes"))
    many = F.sha2(F.concat(F.lit(f"merkle-v1|{block_bytes}|"), F.array_join("h", "")), 256)
    return merged.select(*keys, F.when(F.size("h") == 1, F.col("h")[0]).otherwise(many).alias("tensor_hash"), "n_bytes")
