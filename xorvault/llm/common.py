"""Helpers that the corpus operators share: Arrow column functions, word splitting and the shared folder."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

#: Rows, and bytes of text, that one call of a per-document function handles (one row at least), which bounds what a
#: Python worker holds at once.
ROWS_PER_CALL = 512
BYTES_PER_CALL = 8 << 20
#: Distinct words whose hashes a Python worker remembers.
WORDS_REMEMBERED = 300_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_function(make: Callable[[], Callable[[list[str]], list[dict]]], ddl: str) -> Callable[..., Column]:
    """A column function over text whose result is a struct of type `ddl`.

    `make` is called once for each Python worker and batch stream; what it returns maps a list of texts (nulls come
    as empty texts) to a list of dicts. Text crosses to Python as Arrow batches and is handled in bounded slices.
    """
    kind = T._parse_datatype_string(ddl)
    arrow = pa.struct(list(to_arrow_schema(kind)))

    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        work = make()
        for batch in batches:
            made = [_structs(work, batch.slice(at, n), arrow) for at, n in spans([batch], len(batch), ROWS_PER_CALL)]
            yield pa.concat_arrays(made) if made else pa.array([], arrow)
        if rest := getattr(work, "rest", None):
            rest()

    return F.arrow_udf(run, kind)


def _structs(work: Callable, part: pa.Array, arrow: pa.DataType) -> pa.Array:
    return pa.array(work([x or "" for x in part.to_pylist()]), arrow)


def map_arrow(df: DataFrame, work: Callable[[Iterator[pa.RecordBatch]], Iterator[dict]], ddl: str) -> DataFrame:
    """mapInArrow whose function yields dicts of columns (lists or Arrow arrays)."""
    kind = T._parse_datatype_string(ddl)
    schema = to_arrow_schema(kind)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for columns in work(batches):
            yield pa.RecordBatch.from_arrays([pa.array(columns[f.name], f.type) if not isinstance(columns[f.name], pa.Array) else columns[f.name] for f in schema], schema=schema)

    return df.mapInArrow(run, kind)


def spans(columns: list[pa.Array], n: int, rows: int) -> Iterator[tuple[int, int]]:
    """(start, count) of runs of n rows with at most `rows` rows, and BYTES_PER_CALL bytes of text unless a single row has more."""
    ends = np.zeros(n, np.int64)
    for c in columns:
        if pa.types.is_string(c.type) or pa.types.is_large_string(c.type) or pa.types.is_binary(c.type):
            ends += pc.fill_null(pc.binary_length(c), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    ends = np.cumsum(ends)
    at = 0
    while at < n:
        before = int(ends[at - 1]) if at else 0
        count = max(1, min(rows, int(np.searchsorted(ends, before + BYTES_PER_CALL, "right")) - at))
        yield at, min(count, n - at)
        at += count


def slices(batches: Iterator[pa.RecordBatch], rows: int = ROWS_PER_CALL) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for at, n in spans(batch.columns, batch.num_rows, rows):
            yield batch.slice(at, n)


def words_of(text: str) -> list[bytes]:
    """Maximal runs of characters other than space and U+0009..U+000D, as UTF-8 (bytes.split cuts at just those)."""
    return text.encode("utf-8", "surrogatepass").split()


class WordHashes(dict):
    """64-bit hashes of words (bytes), remembered up to a bound."""

    def __missing__(self, word: bytes) -> int:
        if len(self) >= WORDS_REMEMBERED:
            self.clear()
        self[word] = h = xxhash.xxh64_intdigest(word)
        return h

    def array(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))


def mixed(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit reaches every output bit."""
    x = x ^ (x >> np.uint64(31))
    x = x * np.uint64(0x9E3779B97F4A7C15)
    x ^= x >> np.uint64(29)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(32)
    return x


def rolled(h: np.ndarray, n: int) -> np.ndarray:
    """Hashes of all runs of n words from the words' hashes; empty if there are fewer than n."""
    if len(h) < n:
        return h[:0]
    out = h[: len(h) - n + 1].copy()
    for k in range(1, n):
        out = mixed(out) + h[k : len(h) - n + 1 + k]
    return mixed(out)


def fresh(df: DataFrame, name: str) -> str:
    """A column name that df doesn't have."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. Only a local session without one gets one here."""
    sc = spark.sparkContext
    if found := spark.conf.get("spark.checkpoint.dir", None):
        return found
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        if not sc.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        sc.setCheckpointDir("/tmp/checkpoints")
    return sc._jsc.sc().getCheckpointDir().get()


def cut(df: DataFrame) -> DataFrame:
    """df materialised in the shared folder: later steps start from files there, whatever executors are lost."""
    shared_dir(df.sparkSession)
    if df.sparkSession.sparkContext._jsc.sc().getCheckpointDir().isEmpty():
        df.sparkSession.sparkContext.setCheckpointDir(shared_dir(df.sparkSession))
    return df.checkpoint()


def stored(df: DataFrame, name: str) -> DataFrame:
    """df written to a table of its own in the shared folder, and reread."""
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def bounded_rows(df: DataFrame, most: int, what: str) -> list:
    """df's rows on the driver, refused beyond `most` rows: for tables whose size has a stated bound."""
    rows = df.limit(most + 1).collect()
    if len(rows) > most:
        raise ValueError(f"{what} has over {most} rows")
    return rows
