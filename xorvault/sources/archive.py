"""Tensor archives: parsing and writing, header-first extraction, and a Python data source over folders of archives.

Two containers: a JSON-header archive (little-endian u64 header length, JSON of name -> dtype, shape, data_offsets, then
buffers), and a quantized container with a typed tensor table. Bytes between or behind tensors are kept as filler units,
so that restoring is byte-exact for odd files too.
"""

from __future__ import annotations

import json
import os
import struct
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceStreamWriter, DataSourceWriter, EqualTo, Filter, InputPartition, WriterCommitMessage

TENSOR = "name string, dtype string, shape array<bigint>, begin bigint, end bigint"
QMAGIC = b"XVQ1"


@dataclass
class Header:
    """Tensors (name, dtype, shape, begin, end in the data part), the header's bytes as they are, and its metadata."""

    tensors: list[dict]
    raw: bytes
    metadata: dict

    @property
    def data_at(self) -> int:
        return len(self.raw)


def write_archive(tensors: list[tuple[str, str, list[int], bytes]], metadata: dict | None = None) -> bytes:
    table: dict = {"__metadata__": metadata} if metadata else {}
    at = 0
    for name, dtype, shape, data in tensors:
        table[name] = {"dtype": dtype, "shape": shape, "data_offsets": [at, at + len(data)]}
        at += len(data)
    head = json.dumps(table, separators=(",", ":")).encode()
    return struct.pack("<Q", len(head)) + head + b"".join(t[3] for t in tensors)


def read_header(head: bytes) -> Header:
    """The header of an archive, from its first bytes; the data part isn't needed."""
    (n,) = struct.unpack_from("<Q", head)
    if n > len(head) - 8:
        raise ValueError("the header is longer than what was given")
    table = json.loads(head[8 : 8 + n])
    meta = table.pop("__metadata__", {})
    tensors = [{"name": k, "dtype": v["dtype"], "shape": v["shape"], "begin": v["data_offsets"][0], "end": v["data_offsets"][1]} for k, v in table.items()]
    return Header(sorted(tensors, key=lambda t: (t["begin"], t["end"])), head[: 8 + n], meta)


def with_filler(tensors: list[dict], size: int) -> list[dict]:
    """Tensors and filler units, which together cover `size` bytes of data without a gap."""
    out, at = [], 0
    for t in [*tensors, {"begin": size, "end": size, "name": None}]:
        if t["begin"] > at:
            out.append({"name": f"__filler_{at}", "dtype": "U8", "shape": [t["begin"] - at], "begin": at, "end": t["begin"]})
        if t["name"] is not None:
            out.append(t)
        at = max(at, t["end"])
    return out


def written(key, table):
    """A group of tensor rows (repo_id, path, ordinal, name, dtype, shape, payload) as one archive, for applyInArrow."""
    rows = sorted(table.to_pylist(), key=lambda r: r["ordinal"])
    data = write_archive([(r["name"], r["dtype"], r["shape"], r["payload"]) for r in rows])
    return pa.table({"repo_id": pa.array([key[0].as_py()], pa.string()), "path": pa.array([key[1].as_py()], pa.string()), "content": pa.array([data], pa.binary())})


def write_quantized(tensors: list[tuple[str, list[int], bytes]], metadata: dict) -> bytes:
    """A container with key-value metadata and a typed table of quantized tensors."""
    meta = json.dumps(metadata, sort_keys=True).encode()
    out, at = [QMAGIC, struct.pack("<II", len(meta), len(tensors)), meta], 0
    for name, shape, data in tensors:
        n = name.encode()
        out.append(struct.pack("<HB", len(n), len(shape)) + n + struct.pack(f"<{len(shape)}Q", *shape) + struct.pack("<QQ", at, len(data)))
        at += len(data)
    return b"".join([*out, *[t[2] for t in tensors]])


def read_quantized(data: bytes) -> Header:
    if data[:4] != QMAGIC:
        raise ValueError("not a quantized container")
    n_meta, count = struct.unpack_from("<II", data, 4)
    at = 12 + n_meta
    meta, tensors = json.loads(data[12:at]), []
    for _ in range(count):
        n, rank = struct.unpack_from("<HB", data, at)
        at += 3
        name = data[at : at + n].decode()
        at += n
        shape = list(struct.unpack_from(f"<{rank}Q", data, at))
        at += 8 * rank
        begin, size = struct.unpack_from("<QQ", data, at)
        at += 16
        tensors.append({"name": name, "dtype": "I8", "shape": shape, "begin": begin, "end": begin + size})
    return Header(tensors, data[:at], meta)


def parse(data: bytes) -> Header:
    return read_quantized(data) if data[:4] == QMAGIC else read_header(data)


def extract_tensors(files: DataFrame, *, content: str = "content") -> DataFrame:
    """(repo_id, path, ordinal, name, dtype, shape, offset, n_elems, n_bytes, tensor_hash, header, payload) of binary files."""
    import hashlib

    from xorvault.functions.words import DTYPES

    kind = "ordinal int, name string, dtype string, shape array<bigint>, offset bigint, n_elems bigint, n_bytes bigint, tensor_hash string, header binary, payload binary"
    from pyspark.sql import types as T
    from pyspark.sql.pandas.types import to_arrow_schema

    schema = to_arrow_schema(T._parse_datatype_string("repo_id string, path string, " + kind))

    def run(batches):
        for batch in batches:
            for r in batch.to_pylist():
                h = parse(r["content"])
                data = memoryview(r["content"])[h.data_at :]
                rows = []
                for k, t in enumerate(with_filler(h.tensors, len(data))):
                    part = bytes(data[t["begin"] : t["end"]])
                    size = DTYPES.get(t["dtype"], ("", 8))[1] // 8
                    rows.append({"repo_id": r["repo_id"], "path": r["path"], "ordinal": k, "name": t["name"], "dtype": t["dtype"], "shape": t["shape"], "offset": t["begin"], "n_elems": len(part) // size, "n_bytes": len(part), "tensor_hash": hashlib.sha256(part).hexdigest(), "header": h.raw, "payload": part})
                yield pa.RecordBatch.from_pylist(rows, schema=schema)

    return files.select("repo_id", "path", F.col(content).alias("content")).mapInArrow(run, "repo_id string, path string, " + kind)


def read_files(spark: SparkSession, folder: str, *, glob: str = "*") -> DataFrame:
    """(repo_id, path, n_bytes, modified, content) of the files under folder/<repo>/..., from any store Spark can list.

    Columns are read lazily: a query that does not use content lists files only.
    """
    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").option("pathGlobFilter", glob).load(folder)
    rel = F.regexp_extract("path", r"([^/]+/[^/]+)$", 1)
    return files.select(F.split(rel, "/")[0].alias("repo_id"), F.split(rel, "/")[1].alias("path"), F.col("length").alias("n_bytes"), F.col("modificationTime").alias("modified"), "content")


def read_cards(spark: SparkSession, folder: str) -> DataFrame:
    """(repo_id, card, config) from README.md and config.json of folder/<repo>."""
    text = lambda glob, name: read_files(spark, folder, glob=glob).select("repo_id", F.decode("content", "UTF-8").alias(name))
    return text("README.md", "card").join(text("config.json", "config"), "repo_id", "full_outer")


# --- Data source --------------------------------------------------------------------------------------------------


@dataclass
class Range(InputPartition):
    file: str
    tensors: list[dict]
    data_at: int
    first: int

    def __init__(self, file, tensors, data_at, first):
        self.file, self.tensors, self.data_at, self.first = file, tensors, data_at, first


class ArchiveReader(DataSourceReader):
    """Plans from headers alone: a partition is a run of one file's tensors of about `split_bytes`."""

    def __init__(self, folder: str, split_bytes: int):
        self.folder, self.split_bytes, self.equal = folder, split_bytes, {}

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute[0] in ("file", "name", "dtype"):
                self.equal[f.attribute[0]] = f.value
            else:
                yield f

    def partitions(self) -> list[Range]:
        out = []
        for top, _, names in sorted(os.walk(self.folder)):
            for name in sorted(names):
                file = os.path.join(top, name)
                rel = os.path.relpath(file, self.folder)
                if not name.endswith(".tensors") or self.equal.get("file", rel) != rel:
                    continue
                with open(file, "rb") as f:
                    (n,) = struct.unpack("<Q", f.read(8))
                    f.seek(0)
                    header = read_header(f.read(8 + n))
                held, size, first = [], 0, 0
                for k, t in enumerate(header.tensors):
                    held.append(t)
                    size += t["end"] - t["begin"]
                    if size >= self.split_bytes:
                        out.append(Range(file, held, header.data_at, first))
                        held, size, first = [], 0, k + 1
                if held:
                    out.append(Range(file, held, header.data_at, first))
        return out or [Range("", [], 0, 0)]

    def read(self, partition: Range):
        if not partition.tensors:
            return
        rel = os.path.relpath(partition.file, self.folder)
        with open(partition.file, "rb") as f:
            for k, t in enumerate(partition.tensors):
                if all(self.equal.get(c, t[c]) == t[c] for c in ("name", "dtype")):
                    f.seek(partition.data_at + t["begin"])
                    yield (rel, partition.first + k, t["name"], t["dtype"], t["shape"], t["begin"], t["end"] - t["begin"], f.read(t["end"] - t["begin"]))


class ArchiveWriter(DataSourceWriter):
    """Writes each `file` of the rows (which must come with all rows of a file in one task, in order) as an archive."""

    def __init__(self, folder: str):
        self.folder = folder

    def write(self, rows: Iterator) -> WriterCommitMessage:
        files: dict[str, list] = {}
        for r in rows:
            files.setdefault(r["file"], []).append((r["ordinal"], r["name"], r["dtype"], list(r["shape"]), bytes(r["payload"])))
        for file, tensors in files.items():
            path = os.path.join(self.folder, file)
            os.makedirs(os.path.dirname(path), exist_ok=True)
            with open(f"{path}.part", "wb") as f:
                f.write(write_archive([t[1:] for t in sorted(tensors)]))
            os.replace(f"{path}.part", path)
        return WriterCommitMessage()


class TensorArchive(DataSource):
    """format("tensor_archive"): folders of .tensors files on storage that all executors mount. Options: split_bytes."""

    @classmethod
    def name(cls) -> str:
        return "tensor_archive"

    def schema(self) -> str:
        return "file string, ordinal int, name string, dtype string, shape array<bigint>, offset bigint, n_bytes bigint, payload binary"

    def reader(self, schema) -> DataSourceReader:
        return ArchiveReader(self.options["path"], int(self.options.get("split_bytes", 64 << 20)))

    def writer(self, schema, overwrite: bool) -> DataSourceWriter:
        return ArchiveWriter(self.options["path"])

    def streamWriter(self, schema, overwrite: bool) -> DataSourceStreamWriter:
        raise NotImplementedError("write streams of archives with foreachBatch")


def register(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(TensorArchive)


def read_headers(spark: SparkSession, folder: str) -> DataFrame:
    """(file, ordinal, name, dtype, shape, offset, n_bytes) of all archives in a folder."""
    register(spark)
    return spark.read.format("tensor_archive").load(folder).drop("payload")
