"""Catalogue analytics on the star schema, and the relational operators around the methods."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from xorvault.workloads.registry import query, table

MONEY = "decimal(18,4)"


def total(column: str):
    """An exact sum of a money column, as a double."""
    return F.sum(F.col(column).cast(MONEY)).cast("double")


def money(column: str) -> str:
    return f"CAST(sum(CAST({column} AS DECIMAL(18,4))) AS DOUBLE)"


def day(column: str, unit: str):
    return F.date_trunc(unit, F.col(column)).cast("date").cast("string")


# --- Growth, formats, dtypes, bases and tuned ---------------------------------------------------------------------


@query("growth_orders_monthly", f"""
WITH m AS (SELECT CAST(CAST(date_trunc('month', o_orderdate) AS DATE) AS VARCHAR) AS month, count(*) AS uploads, {money('o_totalprice')} AS bytes FROM orders GROUP BY 1)
SELECT month, uploads, bytes, CAST(sum(uploads) OVER w AS BIGINT) AS total_uploads, CAST(sum(CAST(bytes AS DECIMAL(18,4))) OVER w AS DOUBLE) AS total_bytes FROM m WINDOW w AS (ORDER BY month)""")
def growth_orders_monthly(spark, sf_dir):
    """Uploads and bytes by month and in total: orders are uploads, their price the bytes."""
    m = table(spark, sf_dir, "orders").groupBy(day("o_orderdate", "month").alias("month")).agg(F.count("*").alias("uploads"), total("o_totalprice").alias("bytes"))
    w = Window.orderBy("month")  # over one row a month
    return m.select("month", "uploads", "bytes", F.sum("uploads").over(w).alias("total_uploads"), F.sum(F.col("bytes").cast(MONEY)).over(w).cast("double").alias("total_bytes"))


@query("growth_events_daily", """
WITH d AS (SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, count(*) AS n, count(*) FILTER (event_type IN ('signup', 'purchase')) AS uploads FROM events GROUP BY 1)
SELECT day, n, uploads, CAST(sum(uploads) OVER (ORDER BY day) AS BIGINT) AS total_uploads FROM d""")
def growth_events_daily(spark, sf_dir):
    d = table(spark, sf_dir, "events").groupBy(F.col("ts").cast("date").cast("string").alias("day")).agg(F.count("*").alias("n"), F.count_if(F.col("event_type").isin("signup", "purchase")).alias("uploads"))
    return d.withColumn("total_uploads", F.sum("uploads").over(Window.orderBy("day")))


@query("format_cumulative", f"""
WITH m AS (SELECT p_type AS format, CAST(CAST(date_trunc('month', l_shipdate) AS DATE) AS VARCHAR) AS month, {money('l_extendedprice')} AS bytes FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1, 2)
SELECT format, month, bytes, CAST(sum(CAST(bytes AS DECIMAL(18,4))) OVER (PARTITION BY format ORDER BY month) AS DOUBLE) AS total_bytes FROM m""")
def format_cumulative(spark, sf_dir):
    """Storage by file format over time: the part's type is the format."""
    li = table(spark, sf_dir, "lineitem").select("l_partkey", "l_extendedprice", "l_shipdate")
    p = table(spark, sf_dir, "part").select("p_partkey", "p_type")
    m = li.join(p, F.col("l_partkey") == F.col("p_partkey")).groupBy(F.col("p_type").alias("format"), day("l_shipdate", "month").alias("month")).agg(total("l_extendedprice").alias("bytes"))
    w = Window.partitionBy("format").orderBy("month")
    return m.withColumn("total_bytes", F.sum(F.col("bytes").cast(MONEY)).over(w).cast("double"))


@query("format_top2_share", """
WITH f AS (SELECT p_type AS format, sum(CAST(l_extendedprice AS DECIMAL(18,4))) AS b FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1),
r AS (SELECT *, row_number() OVER (ORDER BY b DESC, format) AS r FROM f)
SELECT round(CAST(sum(b) FILTER (r <= 2) AS DOUBLE) / CAST(sum(b) AS DOUBLE), 6) AS top2_share, count(*) AS formats FROM r""")
def format_top2_share(spark, sf_dir):
    li, p = table(spark, sf_dir, "lineitem").select("l_partkey", "l_extendedprice"), table(spark, sf_dir, "part").select("p_partkey", "p_type")
    f = li.join(p, F.col("l_partkey") == F.col("p_partkey")).groupBy(F.col("p_type").alias("format")).agg(F.sum(F.col("l_extendedprice").cast(MONEY)).alias("b"))
    r = f.withColumn("r", F.row_number().over(Window.orderBy(F.desc("b"), "format")))
    return r.agg(F.round(F.sum(F.when(F.col("r") <= 2, F.col("b"))).cast("double") / F.sum("b").cast("double"), 6).alias("top2_share"), F.count("*").alias("formats"))


@query("flag_bytes_vs_orders", f"SELECT l_returnflag AS flag, count(DISTINCT l_orderkey) AS orders, {money('l_extendedprice')} AS bytes FROM lineitem GROUP BY 1")
def flag_bytes_vs_orders(spark, sf_dir):
    """Classes by bytes and by the containers that hold them; a container of several classes counts in each."""
    return table(spark, sf_dir, "lineitem").groupBy(F.col("l_returnflag").alias("flag")).agg(F.count_distinct("l_orderkey").alias("orders"), total("l_extendedprice").alias("bytes"))


@query("base_vs_tuned_daily", """
SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, count(*) FILTER (event_type = 'signup') AS bases, count(*) FILTER (event_type = 'purchase') AS tuned FROM events GROUP BY 1""")
def base_vs_tuned_daily(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy(F.col("ts").cast("date").cast("string").alias("day")).agg(F.count_if(F.col("event_type") == "signup").alias("bases"), F.count_if(F.col("event_type") == "purchase").alias("tuned"))


# --- Scans, filters, joins ----------------------------------------------------------------------------------------


@query("scan_prune_lineitem", "SELECT l_orderkey, l_linenumber, l_quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '1997-01-01' AND l_shipdate < TIMESTAMP '1997-02-01' AND l_discount > 0.05")
def scan_prune_lineitem(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem")
    return li.where("l_shipdate >= TIMESTAMP_NTZ '1997-01-01' AND l_shipdate < TIMESTAMP_NTZ '1997-02-01' AND l_discount > 0.05D").select("l_orderkey", "l_linenumber", "l_quantity")


@query("filter_files", "SELECT doc_id, source, n_chars FROM documents WHERE lang IN ('en', 'de') AND n_chars BETWEEN 500 AND 5000 AND NOT regexp_matches(source, '1$')")
def filter_files(spark, sf_dir):
    d = table(spark, sf_dir, "documents")
    return d.where(F.col("lang").isin("en", "de") & F.col("n_chars").between(500, 5000) & ~F.col("source").rlike("1$")).select("doc_id", "source", "n_chars")


@query("project_sizes", "SELECT doc_id, CAST(strlen(text) AS BIGINT) AS n_bytes, CAST(length(text) AS BIGINT) AS n_code_points, CASE WHEN strlen(text) < 1000 THEN 'small' WHEN strlen(text) < 10000 THEN 'middle' ELSE 'large' END AS size_class FROM documents")
def project_sizes(spark, sf_dir):
    n = F.octet_length("text")
    return table(spark, sf_dir, "documents").select("doc_id", n.cast("bigint").alias("n_bytes"), F.length("text").cast("bigint").alias("n_code_points"), F.when(n < 1000, "small").when(n < 10000, "middle").otherwise("large").alias("size_class"))


@query("join_inner_broadcast", "SELECT n_name, count(*) AS uploads FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
def join_inner_broadcast(spark, sf_dir):
    """Uploads by nation; nation's side is a table of fixed size."""
    o, c = table(spark, sf_dir, "orders").select("o_custkey"), table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    n = table(spark, sf_dir, "nation").select("n_nationkey", "n_name")
    return o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("uploads"))


HALVES = "WITH h AS (SELECT doc_id, sha256(text) AS file_hash FROM documents), old AS (SELECT DISTINCT file_hash FROM h WHERE doc_id % 2 = 0)"


def _halves(spark, sf_dir):
    """Earlier and later uploads: even and odd documents."""
    h = table(spark, sf_dir, "documents").select("doc_id", F.sha2("text", 256).alias("file_hash"))
    return h.where("doc_id % 2 = 0").select("file_hash").distinct(), h.where("doc_id % 2 = 1")


@query("join_semi_known", f"{HALVES} SELECT doc_id FROM h SEMI JOIN old USING (file_hash) WHERE doc_id % 2 = 1")
def join_semi_known(spark, sf_dir):
    old, new = _halves(spark, sf_dir)
    return new.join(old, "file_hash", "left_semi").select("doc_id")


@query("join_anti_missing", f"{HALVES} SELECT doc_id FROM h ANTI JOIN old USING (file_hash) WHERE doc_id % 2 = 1")
def join_anti_missing(spark, sf_dir):
    old, new = _halves(spark, sf_dir)
    return new.join(old, "file_hash", "left_anti").select("doc_id")


@query("join_asof_base", """
SELECT t.event_id, b.event_id AS base_event FROM (SELECT * FROM events WHERE event_type = 'purchase') t ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'signup') b
ON t.user_id = b.user_id AND t.ts >= b.ts""")
def join_asof_base(spark, sf_dir):
    """For each tuned upload the uploader's latest base before it: an as-of join as one window over the union of both."""
    e = table(spark, sf_dir, "events").where(F.col("event_type").isin("signup", "purchase")).select("event_id", "ts", "user_id", "event_type")
    base = F.when(F.col("event_type") == "signup", F.col("event_id"))
    w = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "signup", 0).otherwise(1)).rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("base_event", F.last(base, ignorenulls=True).over(w)).where("event_type = 'purchase'").select("event_id", "base_event")


@query("join_theta_tau", "SELECT t.k AS tau, count(*) AS n FROM lineitem, (SELECT unnest([10, 20, 30, 40]) AS k) t WHERE l_quantity < t.k GROUP BY 1")
def join_theta_tau(spark, sf_dir):
    """A theta join against four thresholds: rows are counted by interval first, so that the join meets a few rows."""
    taus = [10, 20, 30, 40]
    at = F.size(F.filter(F.array(*[F.lit(float(t)) for t in taus]), lambda t: t <= F.col("l_quantity")))
    counts = table(spark, sf_dir, "lineitem").groupBy(at.alias("at")).agg(F.count("*").alias("c"))
    grid = spark.createDataFrame([(t, k) for k, t in enumerate(taus)], "tau int, k int")
    return grid.join(F.broadcast(counts), F.col("at") <= F.col("k")).groupBy("tau").agg(F.sum("c").alias("n"))


@query("join_lateral_topbase", "SELECT n_name, s_suppkey, s_acctbal FROM (SELECT n_name, s_suppkey, s_acctbal, row_number() OVER (PARTITION BY n_nationkey ORDER BY s_acctbal DESC, s_suppkey) AS r FROM nation JOIN supplier ON s_nationkey = n_nationkey) WHERE r <= 2")
def join_lateral_topbase(spark, sf_dir):
    for name in ("nation", "supplier"):
        table(spark, sf_dir, name).createOrReplaceTempView(name)
    return spark.sql("SELECT n_name, s_suppkey, s_acctbal FROM nation, LATERAL (SELECT s_suppkey, s_acctbal FROM supplier WHERE s_nationkey = n_nationkey ORDER BY s_acctbal DESC, s_suppkey LIMIT 2)")


@query("join_range_chunk_unit", """
WITH u AS (SELECT doc_id, generate_subscripts(string_split(text, chr(10)), 1) - 1 AS unit, unnest(string_split(text, chr(10))) AS line FROM documents),
p AS (SELECT doc_id, unit, CAST(coalesce(sum(strlen(line) + 1) OVER (PARTITION BY doc_id ORDER BY unit ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS b, strlen(line) AS n FROM u),
c AS (SELECT doc_id, unnest(range(0, strlen(text), 512)) AS cb, strlen(text) AS size FROM documents)
SELECT p.doc_id, CAST(c.cb // 512 AS INTEGER) AS chunk_no, CAST(p.unit AS BIGINT) AS unit, CAST(least(cb + 512, size, b + n) - greatest(cb, b) AS BIGINT) AS overlap FROM p JOIN c ON p.doc_id = c.doc_id AND greatest(cb, b) < least(cb + 512, size, b + n)""")
def join_range_chunk_unit(spark, sf_dir):
    """Which lines lie in which fixed chunk: a range join cut to an equi-join by bins."""
    from xorvault.operators import chunking
    from xorvault.workloads.dedup import lines

    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("file_id"), "text")
    chunks = chunking.fixed_chunks(docs, ["file_id"], size=512, content="text")
    units = lines(docs).select("file_id", F.col("unit_no").alias("unit"), "begin", "n_bytes")
    return chunking.attribute(chunks, units, bin_bytes=4096).select(F.col("file_id").alias("doc_id"), "chunk_no", F.col("unit").cast("bigint").alias("unit"), "overlap")


# --- Aggregates ---------------------------------------------------------------------------------------------------


@query("agg_by_family", f"SELECT p_brand AS family, count(*) AS n, {money('p_retailprice')} AS bytes, min(p_size) AS smallest, max(p_size) AS largest, count(DISTINCT p_type) AS formats, min_by(p_partkey, (p_size, p_partkey)) AS first_part, bool_and(p_size > 0) AS all_sized FROM part GROUP BY 1")
def agg_by_family(spark, sf_dir):
    return table(spark, sf_dir, "part").groupBy(F.col("p_brand").alias("family")).agg(F.count("*").alias("n"), total("p_retailprice").alias("bytes"), F.min("p_size").alias("smallest"), F.max("p_size").alias("largest"), F.count_distinct("p_type").alias("formats"), F.min_by("p_partkey", F.struct("p_size", "p_partkey")).alias("first_part"), F.bool_and(F.col("p_size") > 0).alias("all_sized"))


REGIONS = "customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _regions(spark, sf_dir):
    c, n, r = table(spark, sf_dir, "customer").select("c_nationkey", "c_acctbal", "c_mktsegment"), table(spark, sf_dir, "nation"), table(spark, sf_dir, "region")
    return c.join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))


@query("rollup_region_nation", f"SELECT r_name AS region, n_name AS nation, count(*) AS uploaders, {money('c_acctbal')} AS bytes FROM {REGIONS} GROUP BY ROLLUP (r_name, n_name)")
def rollup_region_nation(spark, sf_dir):
    return _regions(spark, sf_dir).rollup(F.col("r_name").alias("region"), F.col("n_name").alias("nation")).agg(F.count("*").alias("uploaders"), total("c_acctbal").alias("bytes"))


@query("cube_format_dtype", "SELECT p_type AS format, p_size % 4 AS dtype, CAST(grouping(p_type, p_size % 4) AS BIGINT) AS level, count(*) AS n FROM part GROUP BY CUBE (p_type, p_size % 4)")
def cube_format_dtype(spark, sf_dir):
    p = table(spark, sf_dir, "part").select(F.col("p_type").alias("format"), (F.col("p_size") % 4).alias("dtype"))
    return p.cube("format", "dtype").agg(F.grouping_id().cast("bigint").alias("level"), F.count("*").alias("n"))


@query("gsets_format_status", "SELECT l_returnflag AS flag, l_linestatus AS status, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def gsets_format_status(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem").select(F.col("l_returnflag").alias("flag"), F.col("l_linestatus").alias("status"))
    return li.groupingSets([["flag"], ["status"], []], "flag", "status").agg(F.count("*").alias("n"))


@query("pivot_dtype", "SELECT source, count(*) FILTER (lang = 'en') AS en, count(*) FILTER (lang = 'de') AS de, count(*) FILTER (lang = 'fr') AS fr, count(*) FILTER (lang = 'es') AS es FROM documents GROUP BY 1")
def pivot_dtype(spark, sf_dir):
    return table(spark, sf_dir, "documents").groupBy("source").pivot("lang", ["en", "de", "fr", "es"]).agg(F.count("doc_id")).fillna(0)


@query("agg_filter_clause", f"SELECT event_type, count(*) FILTER (value > 50) AS large, count(*) FILTER (value <= 50) AS small, {money('value')} AS bytes FROM events GROUP BY 1")
def agg_filter_clause(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.count_if(F.col("value") > 50).alias("large"), F.count_if(F.col("value") <= 50).alias("small"), total("value").alias("bytes"))


@query("approx_unique_hashes")
def approx_unique_hashes(spark, sf_dir):
    """Distinct contents by a HyperLogLog sketch beside the exact count."""
    h = F.sha2("text", 256)
    return table(spark, sf_dir, "documents").agg(F.approx_count_distinct(h, 0.02).alias("about"), F.hll_sketch_estimate(F.hll_sketch_agg(h, F.lit(12))).alias("sketch"), F.count_distinct(h).alias("exact"))


@query("xor_agg_checksum", "SELECT l_suppkey AS k, bit_xor(l_orderkey) AS x, bit_or(l_orderkey) AS o, count(*) AS n FROM lineitem GROUP BY 1")
def xor_agg_checksum(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").groupBy(F.col("l_suppkey").alias("k")).agg(F.bit_xor("l_orderkey").alias("x"), F.bit_or("l_orderkey").alias("o"), F.count("*").alias("n"))


# --- Windows, sorting, sets ---------------------------------------------------------------------------------------


@query("win_canonical_copy", "SELECT doc_id, first_value(doc_id) OVER w AS canonical_id, row_number() OVER w > 1 AS is_dup FROM documents WINDOW w AS (PARTITION BY sha256(text) ORDER BY doc_id)")
def win_canonical_copy(spark, sf_dir):
    """Canonical copies; the library finds them by an aggregate and a join, which a hot hash does not slow."""
    from xorvault.operators import dedup

    d = table(spark, sf_dir, "documents").select("doc_id", F.sha2("text", 256).alias("file_hash"))
    return dedup.dedup_files(d, order_by=("doc_id",)).select("doc_id", F.col("canonical.doc_id").alias("canonical_id"), "is_dup")


@query("win_growth_rate", """
WITH m AS (SELECT CAST(CAST(date_trunc('month', o_orderdate) AS DATE) AS VARCHAR) AS month, count(*) AS n FROM orders GROUP BY 1)
SELECT month, n, lag(n) OVER (ORDER BY month) AS before, round(CAST(n AS DOUBLE) / lag(n) OVER (ORDER BY month) - 1, 6) AS rate FROM m""")
def win_growth_rate(spark, sf_dir):
    m = table(spark, sf_dir, "orders").groupBy(day("o_orderdate", "month").alias("month")).agg(F.count("*").alias("n"))
    before = F.lag("n").over(Window.orderBy("month"))
    return m.select("month", "n", before.alias("before"), F.round(F.col("n").cast("double") / before - 1, 6).alias("rate"))


@query("win_prefix_sum", """
WITH f AS (SELECT doc_id, strlen(text) AS n, row_number() OVER (PARTITION BY sha256(text) ORDER BY doc_id) AS r FROM documents)
SELECT doc_id AS seq, CAST(sum(n) OVER w AS BIGINT) AS raw_bytes, CAST(sum(CASE WHEN r = 1 THEN n ELSE 0 END) OVER w AS BIGINT) AS stored_bytes, round(1 - CAST(sum(CASE WHEN r = 1 THEN n ELSE 0 END) OVER w AS DOUBLE) / sum(n) OVER w, 6) AS drr FROM f WINDOW w AS (ORDER BY doc_id)""")
def win_prefix_sum(spark, sf_dir):
    """The reduction curve of file deduplication over documents in order, by two-level running sums."""
    from xorvault.operators import dedup

    d = table(spark, sf_dir, "documents").select("doc_id", F.octet_length("text").cast("bigint").alias("n"), F.sha2("text", 256).alias("file_hash"))
    marked = dedup.dedup_files(d, order_by=("doc_id",))
    return dedup.prefix_curve(marked.select(F.col("doc_id").alias("seq"), F.col("n").alias("raw"), F.when(F.col("is_dup"), 0).otherwise(F.col("n")).alias("stored")))


@query("win_range_7d", """
WITH d AS (SELECT CAST(ts AS DATE) AS day, count(*) AS n FROM events GROUP BY 1)
SELECT CAST(day AS VARCHAR) AS day, n, CAST(sum(n) OVER (ORDER BY day RANGE BETWEEN INTERVAL 6 DAYS PRECEDING AND CURRENT ROW) AS BIGINT) AS week FROM d""")
def win_range_7d(spark, sf_dir):
    d = table(spark, sf_dir, "events").groupBy(F.col("ts").cast("date").alias("day")).agg(F.count("*").alias("n"))
    w = Window.orderBy(F.unix_date("day")).rangeBetween(-6, 0)
    return d.select(F.col("day").cast("string").alias("day"), "n", F.sum("n").over(w).alias("week"))


@query("win_ntile_drr", """
SELECT p_brand, n, rank() OVER w AS rk, dense_rank() OVER w AS drk, ntile(4) OVER (ORDER BY n, p_brand) AS quartile, round(percent_rank() OVER w, 6) AS prk, round(cume_dist() OVER w, 6) AS cd FROM (SELECT p_brand, count(*) AS n FROM part GROUP BY 1) WINDOW w AS (ORDER BY n)""")
def win_ntile_drr(spark, sf_dir):
    b = table(spark, sf_dir, "part").groupBy("p_brand").agg(F.count("*").alias("n"))
    w = Window.orderBy("n")
    return b.select("p_brand", "n", F.rank().over(w).cast("bigint").alias("rk"), F.dense_rank().over(w).cast("bigint").alias("drk"), F.ntile(4).over(Window.orderBy("n", "p_brand")).cast("bigint").alias("quartile"), F.round(F.percent_rank().over(w), 6).alias("prk"), F.round(F.cume_dist().over(w), 6).alias("cd"))


@query("topk_largest_units", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 20")
def topk_largest_units(spark, sf_dir):
    return table(spark, sf_dir, "documents").select("doc_id", "n_chars").orderBy(F.desc("n_chars"), "doc_id").limit(20)


@query("topk_per_family", "SELECT source, doc_id, n_chars, r FROM (SELECT source, doc_id, n_chars, row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) AS r FROM documents) WHERE r <= 3")
def topk_per_family(spark, sf_dir):
    """Per-group top-k by a filtered rank, which Spark limits per partition before the shuffle."""
    w = Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id")
    return table(spark, sf_dir, "documents").select("source", "doc_id", "n_chars", F.row_number().over(w).cast("bigint").alias("r")).where("r <= 3")


@query("set_shared_units", f"{HALVES} SELECT file_hash FROM old INTERSECT SELECT file_hash FROM h WHERE doc_id % 2 = 1")
def set_shared_units(spark, sf_dir):
    old, new = _halves(spark, sf_dir)
    return old.intersect(new.select("file_hash"))


@query("set_new_units", f"{HALVES} SELECT file_hash FROM h WHERE doc_id % 2 = 1 EXCEPT ALL SELECT file_hash FROM old")
def set_new_units(spark, sf_dir):
    old, new = _halves(spark, sf_dir)
    return new.select("file_hash").exceptAll(old)


@query("set_union_distinct", f"{HALVES} SELECT file_hash FROM old UNION SELECT file_hash FROM h WHERE doc_id % 2 = 1")
def set_union_distinct(spark, sf_dir):
    old, new = _halves(spark, sf_dir)
    return old.union(new.select("file_hash")).distinct()


# --- Functions ----------------------------------------------------------------------------------------------------


@query("fn_string_card", """
SELECT doc_id, len(regexp_extract_all(text, '[A-Z][a-z]+')) AS capitals, len(string_split(text, ' ')) AS pieces, lower(substr(trim(text), 1, 10)) AS head, levenshtein(source, 'base1') AS far FROM documents""")
def fn_string_card(spark, sf_dir):
    return table(spark, sf_dir, "documents").select("doc_id", F.size(F.regexp_extract_all("text", F.lit("[A-Z][a-z]+"), F.lit(0))).cast("bigint").alias("capitals"), F.size(F.split("text", " ")).cast("bigint").alias("pieces"), F.lower(F.substring(F.trim("text"), 1, 10)).alias("head"), F.levenshtein("source", F.lit("base1")).cast("bigint").alias("far"))


@query("fn_hashes", "SELECT doc_id, sha256(text) AS sha256, md5(text) AS md5, sha1(text) AS sha1, CAST(octet_length(encode(text)) AS BIGINT) AS n_bytes, hex(encode(substr(text, 1, 4))) AS head_hex, base64(encode(substr(text, 1, 4))) AS head_64 FROM documents")
def fn_hashes(spark, sf_dir):
    head = F.encode(F.substring("text", 1, 4), "UTF-8")
    return table(spark, sf_dir, "documents").select("doc_id", F.sha2("text", 256).alias("sha256"), F.md5("text").alias("md5"), F.sha1("text").alias("sha1"), F.octet_length("text").cast("bigint").alias("n_bytes"), F.hex(head).alias("head_hex"), F.base64(head).alias("head_64"))


@query("fn_date_growth", """
SELECT o_orderkey, CAST(CAST(date_trunc('quarter', o_orderdate) AS DATE) AS VARCHAR) AS quarter, date_diff('day', TIMESTAMP '1995-01-01', o_orderdate) AS days, CAST(year(o_orderdate) AS INTEGER) AS y, CAST(weekofyear(o_orderdate) AS INTEGER) AS week, CAST(CAST(last_day(o_orderdate) AS DATE) AS VARCHAR) AS month_end FROM orders""")
def fn_date_growth(spark, sf_dir):
    d = F.col("o_orderdate")
    return table(spark, sf_dir, "orders").select("o_orderkey", day("o_orderdate", "quarter").alias("quarter"), F.datediff(d, F.lit("1995-01-01").cast("date")).cast("bigint").alias("days"), F.year(d).alias("y"), F.weekofyear(d).alias("week"), F.last_day(d).cast("string").alias("month_end"))


@query("fn_bits", "SELECT DISTINCT l_orderkey AS k, l_orderkey & 255 AS a, l_orderkey | 255 AS o, xor(l_orderkey, 12345) AS x, ~l_orderkey AS n, l_orderkey << 3 AS sl, l_orderkey >> 3 AS sr, CAST(bit_count(l_orderkey) AS INTEGER) AS pc, l_orderkey % 7 AS m, CAST(ceil(log2(l_orderkey + 1)) AS BIGINT) AS width FROM lineitem")
def fn_bits(spark, sf_dir):
    k = F.col("l_orderkey")
    return table(spark, sf_dir, "lineitem").select(k.alias("k")).distinct().select("k", *[c.alias(n) for n, c in {"a": F.col("k").bitwiseAND(F.lit(255).cast("bigint")), "o": F.col("k").bitwiseOR(F.lit(255).cast("bigint")), "x": F.col("k").bitwiseXOR(F.lit(12345).cast("bigint")), "n": F.bitwise_not("k"), "sl": F.shiftleft("k", 3), "sr": F.shiftright("k", 3), "pc": F.bit_count("k"), "m": F.pmod("k", F.lit(7).cast("bigint")), "width": F.ceil(F.log2(F.col("k") + 1))}.items()])


@query("fn_entropy", """
WITH c AS (SELECT event_type, count(*) AS n FROM events GROUP BY 1), p AS (SELECT CAST(n AS DOUBLE) / sum(n) OVER () AS p FROM c)
SELECT round(-sum(p * log2(p)), 6) AS entropy_bits FROM p""")
def fn_entropy(spark, sf_dir):
    c = table(spark, sf_dir, "events").groupBy("event_type").agg(F.count("*").alias("n"))
    p = c.crossJoin(c.agg(F.sum("n").alias("t"))).select((F.col("n").cast("double") / F.col("t")).alias("p"))
    return p.agg(F.round(-F.sum(F.col("p") * F.log2("p")), 6).alias("entropy_bits"))


@query("fn_json_props", "SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k, json_valid(props) AS ok FROM events")
def fn_json_props(spark, sf_dir):
    parsed = F.from_json("props", "k bigint")
    return table(spark, sf_dir, "events").select("event_id", parsed["k"].alias("k"), F.try_parse_json("props").isNotNull().alias("ok"))


@query("fn_map_units", "SELECT lang, CAST(sum(n) AS BIGINT) AS n, list_sort(list(source || '=' || n)) AS units FROM (SELECT lang, source, count(*) AS n FROM documents GROUP BY 1, 2) GROUP BY 1")
def fn_map_units(spark, sf_dir):
    c = table(spark, sf_dir, "documents").groupBy("lang", "source").agg(F.count("*").alias("n"))
    m = c.groupBy("lang").agg(F.sum("n").alias("n"), F.map_from_entries(F.collect_list(F.struct("source", "n"))).alias("m"))
    shown = F.array_sort(F.transform(F.map_entries(F.transform_values("m", lambda k, v: v.cast("string"))), lambda e: F.concat(e["key"], F.lit("="), e["value"])))
    return m.select("lang", "n", shown.alias("units"))


@query("fn_array_bitdist", """
WITH b AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(CAST(CAST(x / 4 AS FLOAT) AS BIT) AS INTEGER)) AS w FROM embeddings)
SELECT a.vec_id, CAST(list_sum(list_transform(range(1, 65), lambda i: bit_count(xor(a.w[i], c.w[i])))) AS BIGINT) AS bits FROM b a JOIN b c ON c.vec_id = a.vec_id + 1""")
def fn_array_bitdist(spark, sf_dir):
    """Differing bits of neighbouring vectors, with array functions over words."""
    from xorvault.functions.words import differing, float_bits

    e = table(spark, sf_dir, "embeddings").select("vec_id", F.posexplode("embedding").alias("i", "x"))
    w = e.select("vec_id", "i", float_bits((F.col("x") / 4).cast("float")).alias("w")).groupBy("vec_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "w"))), lambda s: s["w"]).alias("w"))
    b = w.select((F.col("vec_id") - 1).alias("vec_id"), F.col("w").alias("v"))
    bits = F.aggregate(F.zip_with("w", "v", differing), F.lit(0).cast("bigint"), lambda s, x: s + x)
    return w.join(b, "vec_id").select("vec_id", bits.alias("bits"))
