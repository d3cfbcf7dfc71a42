"""Streaming workloads: events as continuous uploads, run to the end of what is there and returned as tables."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from xorvault.operators.graph import shared_dir
from xorvault.streaming import uploads as U
from xorvault.workloads.registry import query, table


def _folder(spark, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def _ran(stream: DataFrame, mode: str = "append") -> DataFrame:
    """The stream's rows after one run over all input, by way of a Parquet sink; in complete mode the last batch has them all."""
    spark = stream.sparkSession
    out, check = _folder(spark, "stream"), _folder(spark, "stream-state")
    if mode == "append":
        stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", check).trigger(availableNow=True).start().awaitTermination()
    else:
        stream.writeStream.outputMode(mode).foreachBatch(lambda df, k: df.write.mode("overwrite").parquet(f"{out}/batch_no={0 if mode == 'complete' else k}")).option("checkpointLocation", check).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(out).select(*stream.columns)


def _source(spark, sf_dir) -> DataFrame:
    """The events table as a stream: a folder view of its file."""
    path = f"{sf_dir}/events.parquet"
    return U.uploads(spark.readStream.schema(U.EVENTS).parquet(path)) if _is_folder(spark, path) else U.uploads(spark.readStream.schema(U.EVENTS).option("pathGlobFilter", "events*").parquet(sf_dir))


def _is_folder(spark, path: str) -> bool:
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(p).isDirectory()


CONTENT = "CAST(json_extract(props, '$.k') AS BIGINT)"


@query("stream_upload_dedup", f"SELECT {CONTENT} AS content_id, min(event_id) AS first_event, count(*) AS uploads, count(*) - 1 AS duplicate_uploads FROM events GROUP BY 1")
def stream_upload_dedup(spark, sf_dir):
    """Contents with their first event and copies, kept up to date by the stream."""
    e = _source(spark, sf_dir).groupBy("content_id").agg(F.min("event_id").alias("first_event"), F.count("*").alias("uploads"), (F.count("*") - 1).alias("duplicate_uploads"))
    return _ran(e, "complete")


@query("stream_pool_probe", f"SELECT DISTINCT {CONTENT} AS content_id FROM events")
def stream_pool_probe(spark, sf_dir):
    """Contents that batches of uploads appended to a pool, each after a look at what is there."""
    pool = _folder(spark, "pool")
    U.dedup_into_pool(_source(spark, sf_dir), pool, _folder(spark, "pool-state")).awaitTermination()
    return spark.read.schema("content_id bigint, ts timestamp, batch int").parquet(pool).select("content_id")


@query("stream_content_state", f"SELECT {CONTENT} AS content_id, arg_min(user_id, event_id) AS owner, count(*) AS refs FROM events GROUP BY 1")
def stream_content_state(spark, sf_dir):
    """First owner and references of each content, in the stream's state; of several batches' updates, the last (with most references)."""
    key, rocks = "spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"
    was = spark.conf.get(key, None)
    spark.conf.set(key, rocks)
    try:
        states = _ran(U.content_state(_source(spark, sf_dir)), "update")
    finally:
        spark.conf.set(key, was) if was else spark.conf.unset(key)
    return states.groupBy("content_id").agg(F.max_by("owner", "refs").alias("owner"), F.max("refs").alias("refs"))


@query("stream_first_seen_watermark", f"SELECT DISTINCT {CONTENT} AS content_id FROM events")
def stream_first_seen_watermark(spark, sf_dir):
    """First-seen contents with state that a watermark bounds; its delay covers the whole input."""
    return _ran(U.first_seen(_source(spark, sf_dir), within="400 days")).select("content_id")


@query("stream_with_base", f"WITH e AS (SELECT event_id, event_type, {CONTENT} AS c FROM events), b AS (SELECT DISTINCT c, c % 10 AS family FROM e WHERE event_type = 'signup') SELECT event_id, e.c AS content_id, family FROM e LEFT JOIN b USING (c)")
def stream_with_base(spark, sf_dir):
    """Uploads tagged with the family of their content, by a join with a static table of bases."""
    bases = U.uploads(table(spark, sf_dir, "events")).where("kind = 'base'").select("content_id", (F.col("content_id") % 10).alias("family")).distinct()
    return _ran(U.with_base(_source(spark, sf_dir), bases).select("event_id", "content_id", "family"))


@query("stream_first_seen", f"SELECT DISTINCT {CONTENT} AS content_id FROM events")
def stream_first_seen(spark, sf_dir):
    """First-seen contents, by the stream itself."""
    return _ran(U.first_seen(_source(spark, sf_dir))).select("content_id")


@query("stream_windows_daily", "SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, count(*) AS uploads FROM events GROUP BY 1")
def stream_windows_daily(spark, sf_dir):
    """Tumbling day windows; complete mode gives all windows of a finite input."""
    w = _source(spark, sf_dir).groupBy(F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("uploads")).select(F.col("w.start").cast("date").cast("string").alias("day"), "uploads")
    return _ran(w, "complete")


@query("stream_sessions", """WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTES THEN 0 ELSE 1 END AS new FROM events), s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)
SELECT user_id, CAST(count(*) AS BIGINT) AS uploads, CAST(epoch_us(min(ts)) // 1000 AS BIGINT) AS start_ms FROM s GROUP BY user_id, k""")
def stream_sessions(spark, sf_dir):
    """Sessions of uploads by user."""
    return _ran(U.sessions(_source(spark, sf_dir)), "complete").select("user_id", "uploads", F.unix_millis("start").alias("start_ms"))


@query("stream_sliding_weeks", "WITH d AS (SELECT unnest(range(0, 7)) AS k), e AS (SELECT CAST(ts AS DATE) - CAST(k AS INTEGER) AS start FROM events, d) SELECT CAST(start AS VARCHAR) AS start_day, count(*) AS uploads FROM e GROUP BY 1")
def stream_sliding_weeks(spark, sf_dir):
    return _ran(U.sliding(_source(spark, sf_dir)), "complete").select(F.col("start").cast("date").cast("string").alias("start_day"), "uploads")


@query("stream_first_downloads", f"""WITH e AS (SELECT event_id, ts, event_type, {CONTENT} AS c FROM events) SELECT u.c AS content_id, u.event_id AS upload, r.event_id AS retrieval FROM e u JOIN e r ON u.c = r.c AND r.ts >= u.ts AND r.ts <= u.ts + INTERVAL 1 HOUR WHERE u.event_type IN ('signup', 'purchase') AND r.event_type IN ('view', 'click')""")
def stream_first_downloads(spark, sf_dir):
    """Retrievals within an hour of an upload of the content, by the stream-stream join."""
    s = _source(spark, sf_dir)
    return _ran(U.first_downloads(s.where("kind IN ('base', 'tuned')"), s.where("kind = 'retrieval'"), within="1 hour")).select("content_id", "upload", "retrieval")
