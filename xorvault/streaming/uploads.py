"""Continuous uploads: first-seen deduplication, pool probes per batch, per-hash state, windows, joins of streams.

All functions take a streaming (or, where it makes sense, a batch) DataFrame with an event time column of type TIMESTAMP.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def upload_stream(spark: SparkSession, folder: str, *, files_per_trigger: int = 1) -> DataFrame:
    """A stream of events from a folder of Parquet files; the zone-less time becomes a TIMESTAMP, as watermarks need one."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)
    return uploads(raw)


def uploads(events: DataFrame) -> DataFrame:
    """Events as uploads: content id, kind, size and time."""
    kind = F.when(F.col("event_type") == "signup", "base").when(F.col("event_type") == "purchase", "tuned").when(F.col("event_type").isin("view", "click"), "retrieval").otherwise("failed")
    return events.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", kind.alias("kind"), F.get_json_object("props", "$.k").cast("long").alias("content_id"), F.col("value").alias("n_bytes"))


def first_seen(stream: DataFrame, *, within: str | None = None) -> DataFrame:
    """One upload per content: over all time (state grows with contents), or within the watermark's delay (bounded state)."""
    if within is None:
        return stream.dropDuplicates(["content_id"])
    return stream.withWatermark("ts", within).dropDuplicatesWithinWatermark(["content_id"])


def dedup_into_pool(stream: DataFrame, pool_path: str, checkpoint: str):
    """Append unseen contents to a Parquet pool, batch by batch; a batch that is run again writes the same folder again."""

    def batch(df: DataFrame, batch_id: int) -> None:
        spark = df.sparkSession
        mine = f"{pool_path}/batch={batch_id}"
        seen = spark.read.schema("content_id bigint, ts timestamp, batch int").parquet(pool_path).where(F.col("batch") < batch_id) if _exists(spark, pool_path) else None
        new = df.groupBy("content_id").agg(F.min("ts").alias("ts"))
        if seen is not None:
            new = new.join(seen.select("content_id"), "content_id", "left_anti")
        new.write.mode("overwrite").parquet(mine)

    return stream.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def _exists(spark: SparkSession, path: str) -> bool:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(p)


class ContentState(StatefulProcessor):
    """First owner and reference count of each content; the owner is that of the least event id, in whatever order rows come."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("content", "first long, owner long, refs long")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timer_values) -> Iterator[pd.DataFrame]:
        first, owner, refs = self.state.get() if self.state.exists() else (None, None, 0)
        for part in rows:
            refs += len(part)
            owned = part[part["owned"]]
            if len(owned):
                k = int(owned["event_id"].to_numpy().argmin())
                at = int(owned["event_id"].iloc[k])
                if first is None or at < first:
                    first, owner = at, int(owned["user_id"].iloc[k])
        self.state.update((first, owner, refs))
        yield pd.DataFrame({"content_id": [key[0]], "owner": [owner], "refs": [refs]})

    def close(self) -> None:
        pass


def content_state(stream: DataFrame) -> DataFrame:
    """(content_id, owner, refs) after each batch; needs the RocksDB state store provider. Rows without a user or an id own nothing."""
    whole = lambda c: F.coalesce(c, F.lit(0)).alias(c)  # noqa: E731 -- with nulls, pandas would hold ids as floats
    owned = (F.col("event_id").isNotNull() & F.col("user_id").isNotNull()).alias("owned")
    return stream.select("content_id", whole("event_id"), whole("user_id"), owned).groupBy("content_id").transformWithStateInPandas(ContentState(), outputStructType="content_id bigint, owner bigint, refs bigint", outputMode="Update", timeMode="None")


def tumbling(df: DataFrame, width: str = "1 day", late: str = "1 day") -> DataFrame:
    return _windowed(df.withWatermark("ts", late), F.window("ts", width))


def sliding(df: DataFrame, width: str = "7 days", step: str = "1 day", late: str = "1 day") -> DataFrame:
    return _windowed(df.withWatermark("ts", late), F.window("ts", width, step))


def _windowed(df: DataFrame, window) -> DataFrame:
    return df.groupBy(window.alias("w")).agg(F.count("*").alias("uploads"), F.round(F.sum("n_bytes"), 2).alias("n_bytes")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "uploads", "n_bytes")


def sessions(df: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """Upload sessions by user: rows of one user that follow each other within the gap."""
    s = df.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("uploads"))
    return s.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "uploads")


def with_base(stream: DataFrame, bases: DataFrame) -> DataFrame:
    """Stream-static join: uploads tagged with the family of their content."""
    return stream.join(bases, "content_id", "left")


def first_downloads(uploaded: DataFrame, retrieved: DataFrame, *, within: str = "1 day", late: str = "1 day") -> DataFrame:
    """Stream-stream interval join: retrievals of a content within a time after its upload.

    The join's state is looked up by equal keys only, so time is cut into slots of four such lengths: an upload stands in each
    slot that its interval meets, a retrieval in its own. A pair meets once, and no row is held against a content's whole history.
    """
    width = f"greatest(4 * unix_micros(timestamp_seconds(0) + INTERVAL {within}), 1)"
    slot = lambda t: f"CAST(floor(unix_micros({t}) / {width}) AS BIGINT)"
    u = uploaded.withWatermark("ts", late).select(F.col("content_id").alias("u_content"), F.col("ts").alias("u_ts"), F.col("event_id").alias("upload"))
    u = u.select("*", F.explode(F.expr(f"sequence({slot('u_ts')}, {slot(f'u_ts + INTERVAL {within}')})")).alias("u_slot"))
    r = retrieved.withWatermark("ts", late).select(F.col("content_id").alias("r_content"), F.col("ts").alias("r_ts"), F.col("event_id").alias("retrieval"))
    r = r.withColumn("r_slot", F.expr(slot("r_ts")))
    met = F.expr(f"u_content = r_content AND u_slot = r_slot AND r_ts >= u_ts AND r_ts <= u_ts + INTERVAL {within}")
    return u.join(r, met).select(F.col("u_content").alias("content_id"), "upload", "retrieval", "u_ts", "r_ts")
