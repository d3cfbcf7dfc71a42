import re

import duckdb
import pytest
from pyspark.sql import functions as F

from tests.oracle import differences
from xorvault.streaming import uploads as U
from xorvault.workloads import ORACLES, QUERIES


@pytest.fixture
def folder(spark, sf_dir, tmp_path):
    """The events in four files, in time order."""
    e = spark.read.parquet(f"{sf_dir}/events.parquet")
    n = e.count()
    for k in range(4):
        e.where(F.col("event_id").between(k * n // 4, (k + 1) * n // 4 - 1)).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    return str(tmp_path / "in")


def run(stream, tmp_path, mode="append", name="q"):
    out = str(tmp_path / name)
    q = stream.writeStream.outputMode(mode).foreachBatch(lambda df, k: df.write.mode("overwrite").parquet(f"{out}/k={k}")).option("checkpointLocation", f"{out}-state").trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(out), q


def test_first_seen_over_batches(spark, folder, tmp_path, sf_dir):
    want = U.uploads(spark.read.parquet(f"{sf_dir}/events.parquet")).select("content_id").distinct().count()
    got, q = run(U.first_seen(U.upload_stream(spark, folder)), tmp_path)
    assert got.count() == want and len(q.recentProgress) >= 4
    bounded, _ = run(U.first_seen(U.upload_stream(spark, folder), within="1 hour"), tmp_path, name="b")
    assert bounded.count() >= want  # state that was let go may see a content again


def test_pool_is_idempotent(spark, folder, tmp_path, sf_dir):
    want = U.uploads(spark.read.parquet(f"{sf_dir}/events.parquet")).select("content_id").distinct().count()
    pool, state = str(tmp_path / "pool"), str(tmp_path / "state")
    U.dedup_into_pool(U.upload_stream(spark, folder), pool, state).awaitTermination()
    assert spark.read.parquet(pool).select("content_id").count() == want
    U.dedup_into_pool(U.upload_stream(spark, folder), pool, state).awaitTermination()  # nothing new after a restart
    assert spark.read.parquet(pool).select("content_id").count() == want


def test_state_per_content(spark, folder, tmp_path, sf_dir):
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        got, _ = run(U.content_state(U.upload_stream(spark, folder)), tmp_path, "update")
    finally:
        spark.conf.unset("spark.sql.streaming.stateStore.providerClass")
    last = got.groupBy("content_id").agg(F.max("refs").alias("refs"), F.count_distinct("owner").alias("owners"))
    want = {r.content_id: r["count"] for r in U.uploads(spark.read.parquet(f"{sf_dir}/events.parquet")).groupBy("content_id").count().collect()}
    assert {r.content_id: r.refs for r in last.collect()} == want and last.where("owners <> 1").count() == 0


def test_owner_whatever_the_order_of_rows(spark, tmp_path):
    """The least event id with a user owns a content, also where it comes in a later Arrow batch of its group, or there is none."""
    rows = spark.range(12_000).select((12_000 - F.col("id")).alias("event_id"), F.expr("timestamp_ntz'2024-01-01 00:00:00'").alias("ts"), F.expr("CASE WHEN id % 4 = 3 THEN NULL ELSE 9007199254740993 + 12000 - id END").alias("user_id"), F.lit("view").alias("event_type"), F.lit(1.0).alias("value"), F.expr("CASE id % 4 WHEN 0 THEN '{\"k\": 7}' WHEN 1 THEN '{\"k\": 7}' WHEN 2 THEN '{}' ELSE '{\"k\": 8}' END").alias("props"))
    rows.coalesce(1).write.parquet(f"{tmp_path}/sf/events.parquet")
    batch = "spark.sql.execution.arrow.maxRecordsPerBatch"
    was = spark.conf.get(batch)
    spark.conf.set(batch, 100)
    try:
        got = {r.content_id: (r.owner, r.refs) for r in QUERIES["stream_content_state"](spark, f"{tmp_path}/sf").collect()}
    finally:
        spark.conf.set(batch, was)
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{tmp_path}/sf/events.parquet/*.parquet'")
    assert got == {c: (o, n) for c, o, n in con.execute(ORACLES["stream_content_state"]).fetchall()}
    assert got == {7: (9007199254740993 + 3, 6000), None: (9007199254740993 + 2, 3000), 8: (None, 3000)}


def test_late_rows_are_dropped(spark, folder, tmp_path, sf_dir):
    late = spark.read.parquet(f"{sf_dir}/events.parquet").limit(5).withColumn("event_id", F.col("event_id") + 10_000_000)
    late.coalesce(1).write.mode("append").parquet(folder)
    got, q = run(U.tumbling(U.upload_stream(spark, folder), "1 day", "1 hour"), tmp_path)
    dropped = sum(o.numRowsDroppedByWatermark for p in q.recentProgress for o in p.stateOperators)
    assert got.count() > 0 and dropped >= 1
    assert got.count() == got.select("start").distinct().count()


def test_windows_and_sessions_batch(spark, sf_dir):
    e = U.uploads(spark.read.parquet(f"{sf_dir}/events.parquet"))
    assert U.tumbling(e).agg(F.sum("uploads")).first()[0] == e.count()
    assert U.sliding(e).agg(F.sum("uploads")).first()[0] == 7 * e.count()
    assert U.sessions(e).agg(F.sum("uploads")).first()[0] == e.count()


def test_joins(spark, folder, tmp_path, sf_dir):
    bases = spark.createDataFrame([(k, f"m{k % 10}") for k in range(100)], "content_id long, family string")
    got, _ = run(U.with_base(U.upload_stream(spark, folder), bases), tmp_path)
    e = U.uploads(spark.read.parquet(f"{sf_dir}/events.parquet"))
    assert got.count() == e.count() and got.where("family IS NULL").count() == 0
    s = U.upload_stream(spark, folder)
    met, _ = run(U.first_downloads(s.where("kind IN ('base', 'tuned')"), s.where("kind = 'retrieval'"), within="6 hours"), tmp_path, name="j")
    u, r = e.where("kind IN ('base', 'tuned')").alias("u"), e.where("kind = 'retrieval'").alias("r")
    want = u.join(r, F.expr("u.content_id = r.content_id AND r.ts >= u.ts AND r.ts <= u.ts + INTERVAL 6 HOURS")).count()
    assert met.count() == want


def test_downloads_are_looked_up_by_time_too(spark, tmp_path):
    """Rows on the edges of slots and intervals; the join's keys hold a slot beside the content."""
    at = [-14_400, -3_600, -1, 0, 3_599, 3_600, 7_200, 10_800, 14_399, 14_400, 18_000, 18_001]
    for k, kind in enumerate(("signup", "view")):
        rows = spark.createDataFrame([(i + 100 * k, t, "{\"k\": %d}" % c) for c in (1, 2) for i, t in enumerate(at)], "event_id long, t long, props string")
        rows.select("event_id", F.expr("CAST(timestamp_seconds(1704067200 + t) AS timestamp_ntz)").alias("ts"), F.lit(1).cast("long").alias("user_id"), F.lit(kind).alias("event_type"), F.lit(1.0).alias("value"), "props").coalesce(1).write.mode("append").parquet(f"{tmp_path}/sf/events.parquet")
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{tmp_path}/sf/events.parquet/*.parquet'")
    assert differences(QUERIES["stream_first_downloads"](spark, f"{tmp_path}/sf"), con, ORACLES["stream_first_downloads"]) == ""
    e = U.uploads(spark.read.parquet(f"{tmp_path}/sf/events.parquet"))
    plan = U.first_downloads(e.where("kind = 'base'"), e.where("kind = 'retrieval'"), within="1 hour")._jdf.queryExecution().sparkPlan().toString()
    keys = re.search(r"Join \[([^\]]*)\]", plan).group(1).split(",")
    assert len(keys) == 2, keys
