"""Deduplication workloads: censuses, granularity studies, metadata, curves, chunks and maps."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from xorvault import metrics
from xorvault.functions.words import double_bits
from xorvault.operators import chunking, dedup
from xorvault.sources import zoo
from xorvault.workloads import zoo_sql as Z
from xorvault.workloads.registry import query, table


def lines(docs: DataFrame, text: str = "text") -> DataFrame:
    """(file_id, unit_no, begin, n_bytes, unit_hash) of a document's lines; begin counts bytes with the line breaks."""
    each = docs.select("file_id", F.posexplode(F.split(text, "\n")).alias("unit_no", "line")).withColumn("n_bytes", F.octet_length("line").cast("bigint"))
    before = "OVER (PARTITION BY file_id ORDER BY unit_no ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)"
    return each.select("file_id", "unit_no", F.expr(f"coalesce(sum(n_bytes + 1) {before}, 0)").cast("bigint").alias("begin"), "n_bytes", F.sha2("line", 256).alias("unit_hash"))


def _stats_sql(level: str, source: str, key: str, n: str) -> str:
    return f"SELECT '{level}' AS level, CAST(count(*) AS BIGINT) AS total_units, count(DISTINCT {key}) AS unique_units, CAST(sum({n}) AS BIGINT) AS total_bytes, (SELECT CAST(sum(m) AS BIGINT) FROM (SELECT {key}, any_value({n}) AS m FROM {source} GROUP BY 1)) AS unique_bytes, max({n}) AS max_unit_bytes FROM {source}"


def _levels(parts: list[str]) -> str:
    return "SELECT level, total_units, unique_units, total_bytes, unique_bytes, round(1 - CAST(unique_bytes AS DOUBLE) / total_bytes, 6) AS drr, CAST(max_unit_bytes AS BIGINT) AS max_unit_bytes, unique_units * 64 AS metadata_bytes FROM (" + " UNION ALL ".join(parts) + ")"


def _level(units: DataFrame, level: str) -> DataFrame:
    return dedup.dedup_stats(units, level).drop("avg_unit_bytes")


def _census_sql(source: str, key: str, repo: str, hashed: str, n: str) -> str:
    return f"""
WITH f AS (SELECT {repo} AS repo, {key} AS k, {hashed} AS h, {n} AS n FROM {source}),
g AS (SELECT h, count(*) AS c, any_value(n) AS one, sum(n) AS every, min(k) AS first FROM f GROUP BY 1),
s AS (SELECT count(DISTINCT repo) AS shared, count(DISTINCT repo) FILTER (k <> first) AS red FROM f JOIN g USING (h) WHERE c > 1)
SELECT CAST(sum(c) AS BIGINT) AS total_files, CAST(sum(c) - count(*) AS BIGINT) AS duplicate_files, CAST(sum(every) AS BIGINT) AS total_bytes, CAST(sum(every) - sum(one) AS BIGINT) AS saved_bytes,
 round(CAST(sum(every) - sum(one) AS DOUBLE) / CAST(sum(every) AS DOUBLE), 6) AS saved_ratio, (SELECT count(DISTINCT repo) FROM f) AS repos_total, (SELECT shared FROM s) AS repos_shared, (SELECT red FROM s) AS repos_with_redundant_copy FROM g"""


@query("file_dedup_census_documents", _census_sql("documents", "doc_id", "source", "sha256(text)", "strlen(text)"))
def file_dedup_census_documents(spark, sf_dir):
    """File deduplication over documents: a document is a file, its source the repository."""
    d = table(spark, sf_dir, "documents").select(F.col("source").alias("repo_id"), F.col("doc_id").alias("order_key"), F.sha2("text", 256).alias("file_hash"), F.octet_length("text").cast("bigint").alias("n_bytes"))
    return dedup.duplicate_census(d)


@query("file_dedup_census_pages", _census_sql("pages", "page_id", "regexp_extract(url, '^[a-z]+://([^/]+)', 1)", "sha256(html)", "strlen(html)"))
def file_dedup_census_pages(spark, sf_dir):
    p = table(spark, sf_dir, "pages").select(F.regexp_extract("url", "^[a-z]+://([^/]+)", 1).alias("repo_id"), F.col("page_id").alias("order_key"), F.sha2("html", 256).alias("file_hash"), F.octet_length("html").cast("bigint").alias("n_bytes"))
    return dedup.duplicate_census(p)


FILES = "fz AS (SELECT repo_id, sha256(string_agg(name || '|' || tensor_hash || '|' || dtype || '|' || shape, ';' ORDER BY ordinal)) AS h, CAST(sum(n_bytes) AS BIGINT) AS n_bytes FROM tn GROUP BY 1)"


def float_tensors(spark, sf_dir) -> DataFrame:
    return zoo.tensors(spark, sf_dir).where(F.col("variant").isin(*Z.ORDERED))


@query("file_dedup_census_zoo", lambda: f"WITH {Z.tensors()}, {FILES}, c AS (" + _census_sql("fz", "repo_id", "repo_id", "h", "n_bytes").replace("WITH f AS", "WITH f AS", 1) + ") SELECT * FROM c")
def file_dedup_census_zoo(spark, sf_dir):
    files = dedup.files_of(float_tensors(spark, sf_dir)).withColumnRenamed("unit_hash", "file_hash").withColumn("order_key", F.col("repo_id"))
    return dedup.duplicate_census(files)


@query("dedup_levels_documents", "WITH f AS (SELECT sha256(text) AS h, strlen(text) AS n FROM documents), l0 AS (SELECT unnest(string_split(text, chr(10))) AS line FROM documents), l AS (SELECT sha256(line) AS h, strlen(line) AS n FROM l0) " + _levels([_stats_sql("file", "f", "h", "n"), _stats_sql("line", "l", "h", "n")]))
def dedup_levels_documents(spark, sf_dir):
    d = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("file_id"), "text")
    files = d.select(F.sha2("text", 256).alias("unit_hash"), F.octet_length("text").cast("bigint").alias("n_bytes"))
    line = d.select(F.explode(F.split("text", "\n")).alias("line")).select(F.sha2("line", 256).alias("unit_hash"), F.octet_length("line").cast("bigint").alias("n_bytes"))
    return _level(files, "file").unionAll(_level(line, "line"))


@query("dedup_levels_pages", "WITH f AS (SELECT sha256(html) AS h, strlen(html) AS n FROM pages), l0 AS (SELECT unnest(regexp_extract_all(html, '[^>]*>|[^>]+$')) AS piece FROM pages), l AS (SELECT sha256(piece) AS h, strlen(piece) AS n FROM l0) " + _levels([_stats_sql("file", "f", "h", "n"), _stats_sql("piece", "l", "h", "n")]))
def dedup_levels_pages(spark, sf_dir):
    p = table(spark, sf_dir, "pages").select("html")
    files = p.select(F.sha2("html", 256).alias("unit_hash"), F.octet_length("html").cast("bigint").alias("n_bytes"))
    piece = p.select(F.explode(F.regexp_extract_all("html", F.lit("[^>]*>|[^>]+$"), F.lit(0))).alias("piece")).select(F.sha2("piece", 256).alias("unit_hash"), F.octet_length("piece").cast("bigint").alias("n_bytes"))
    return _level(files, "file").unionAll(_level(piece, "piece"))


@query("dedup_levels_conversations", "WITH t AS (SELECT sha256(text) AS h, strlen(text) AS n FROM conversations), f AS (SELECT sha256(string_agg(sha256(text), ';' ORDER BY turn)) AS h, sum(strlen(text)) AS n FROM conversations GROUP BY conv_id) " + _levels([_stats_sql("file", "f", "h", "n"), _stats_sql("turn", "t", "h", "n")]))
def dedup_levels_conversations(spark, sf_dir):
    c = table(spark, sf_dir, "conversations").select("conv_id", "turn", F.sha2("text", 256).alias("h"), F.octet_length("text").cast("bigint").alias("n_bytes"))
    turns = c.select(F.col("h").alias("unit_hash"), "n_bytes")
    whole = c.groupBy("conv_id").agg(F.sha2(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "h"))), lambda x: x["h"]), ";"), 256).alias("unit_hash"), F.sum("n_bytes").alias("n_bytes"))
    return _level(whole.select("unit_hash", "n_bytes"), "file").unionAll(_level(turns, "turn"))


LAYERS = """ly0 AS (SELECT *, CASE WHEN regexp_matches(name, '^layers\\.[0-9]+\\.') THEN 'layer ' || regexp_extract(name, '^layers\\.([0-9]+)\\.', 1) ELSE name END AS layer FROM tn),
ly AS (SELECT repo_id, layer, sha256(string_agg(tensor_hash || '|' || dtype || '|' || shape, ';' ORDER BY ordinal)) AS h, CAST(sum(n_bytes) AS BIGINT) AS n FROM ly0 GROUP BY 1, 2),
ts AS (SELECT *, sha256(tensor_hash || '|' || dtype || '|' || shape) AS h, n_bytes AS n FROM tn)"""


def zoo_levels(spark, sf_dir) -> dict[str, DataFrame]:
    t = float_tensors(spark, sf_dir)
    return {"file": dedup.files_of(t), "layer": dedup.layers(t), "tensor": t.drop("payload").withColumn("unit_hash", dedup.tensor_identity())}


@query("dedup_levels_zoo", lambda: f"WITH {Z.tensors()}, {FILES}, {LAYERS}, f AS (SELECT h, n_bytes AS n FROM fz) " + _levels([_stats_sql("file", "f", "h", "n"), _stats_sql("layer", "ly", "h", "n"), _stats_sql("tensor", "ts", "h", "n")]))
def dedup_levels_zoo(spark, sf_dir):
    """The granularity study: file, layer and tensor (chunks are in chunk_levels_zoo)."""
    made = [_level(units, level) for level, units in zoo_levels(spark, sf_dir).items()]
    return made[0].unionAll(made[1]).unionAll(made[2])


@query("tensor_dedup_pool", lambda: f"""WITH {Z.tensors()}, {LAYERS}, o AS (SELECT *, row_number() OVER (PARTITION BY h ORDER BY repo_id, ordinal) AS r FROM ts)
SELECT h AS unit_hash, any_value(dtype) AS dtype, any_value(n_bytes) AS n_bytes, count(*) AS refcount, min(repo_id) FILTER (r = 1) AS first_repo, min(name) FILTER (r = 1) AS first_name FROM o GROUP BY 1""")
def tensor_dedup_pool(spark, sf_dir):
    found = dedup.dedup_tensors(float_tensors(spark, sf_dir))
    names = found.refs.where("NOT is_dup").select("unit_hash", F.col("repo_id").alias("first_repo"), F.col("name").alias("first_name"))
    return found.pool.join(names, "unit_hash").select("unit_hash", "dtype", "n_bytes", "refcount", "first_repo", "first_name")


@query("tensor_dedup_scopes", lambda: f"""WITH {Z.tensors()}, {LAYERS}
SELECT 'hub' AS scope, count(*) - count(DISTINCT h) AS duplicate_units, CAST(sum(n) - (SELECT sum(n) FROM (SELECT h, any_value(n) AS n FROM ts GROUP BY 1)) AS BIGINT) AS saved_bytes FROM ts
UNION ALL SELECT 'repo', CAST(sum(c - d) AS BIGINT), CAST(sum(b - u) AS BIGINT) FROM (SELECT repo_id, count(*) AS c, count(DISTINCT h) AS d, sum(n) AS b FROM ts GROUP BY 1) JOIN (SELECT repo_id, sum(n) AS u FROM (SELECT repo_id, h, any_value(n) AS n FROM ts GROUP BY 1, 2) GROUP BY 1) USING (repo_id)
UNION ALL SELECT 'file', CAST(sum(c - d) AS BIGINT), CAST(sum(b - u) AS BIGINT) FROM (SELECT repo_id, count(*) AS c, count(DISTINCT h) AS d, sum(n) AS b FROM ts GROUP BY 1) JOIN (SELECT repo_id, sum(n) AS u FROM (SELECT repo_id, h, any_value(n) AS n FROM ts GROUP BY 1, 2) GROUP BY 1) USING (repo_id)""")
def tensor_dedup_scopes(spark, sf_dir):
    t = float_tensors(spark, sf_dir)
    made = [dedup.dedup_tensors(t, scope=s).refs.agg(F.lit(s).alias("scope"), F.count_if("is_dup").alias("duplicate_units"), F.coalesce(F.sum(F.when(F.col("is_dup"), F.col("n_bytes"))), F.lit(0)).cast("bigint").alias("saved_bytes")) for s in ("hub", "repo", "file")]
    return made[0].unionAll(made[1]).unionAll(made[2])


@query("tensor_identity_modes", lambda: f"WITH {Z.tensors()}, {LAYERS} SELECT 'typed' AS identity, count(DISTINCT h) AS unique_units FROM ts UNION ALL SELECT 'bytes', count(DISTINCT tensor_hash) FROM ts")
def tensor_identity_modes(spark, sf_dir):
    t = float_tensors(spark, sf_dir)
    made = [dedup.dedup_tensors(t, identity=i).pool.agg(F.lit(i).alias("identity"), F.count("*").alias("unique_units")) for i in ("typed", "bytes")]
    return made[0].unionAll(made[1])


@query("client_missing_hashes", lambda: f"""WITH {Z.tensors()}, early AS (SELECT DISTINCT tensor_hash FROM tn WHERE variant IN ('v0', 'v1', 'v2')),
late AS (SELECT tn.*, row_number() OVER (PARTITION BY tensor_hash ORDER BY repo_id, ordinal) AS r, tensor_hash IN (SELECT tensor_hash FROM early) AS known FROM tn WHERE variant NOT IN ('v0', 'v1', 'v2'))
SELECT repo_id, count(*) FILTER (NOT known AND r = 1) AS sent_units, count(*) FILTER (known OR r > 1) AS skipped_units, CAST(coalesce(sum(n_bytes) FILTER (known OR r > 1), 0) AS BIGINT) AS bytes_saved FROM late GROUP BY 1""")
def client_missing_hashes(spark, sf_dir):
    """Client-side deduplication: later repositories offer hashes to the pool of earlier ones."""
    t = float_tensors(spark, sf_dir).drop("payload")
    early, late = t.where(F.col("variant").isin("v0", "v1", "v2")), t.where(~F.col("variant").isin("v0", "v1", "v2"))
    return dedup.transfer_saved(late, early)


@query("dedup_against_pool", lambda: f"WITH {Z.tensors()}, {FILES} SELECT n.repo_id, n.h IN (SELECT h FROM fz WHERE repo_id LIKE '%\\_v0' ESCAPE '\\') AS known FROM fz n WHERE repo_id NOT LIKE '%\\_v0' ESCAPE '\\'")
def dedup_against_pool(spark, sf_dir):
    """Incremental file deduplication of later uploads against the pool of bases."""
    files = dedup.files_of(float_tensors(spark, sf_dir)).withColumnRenamed("unit_hash", "file_hash")
    old, new = files.where(F.col("repo_id").endswith("_v0")), files.where(~F.col("repo_id").endswith("_v0"))
    unseen, links = dedup.dedup_against(new, old.select("file_hash").distinct())
    return unseen.select("repo_id", F.lit(False).alias("known")).unionAll(links.select("repo_id", F.lit(True)))


@query("metadata_projection", lambda: f"""WITH {Z.tensors()}, {FILES}, {LAYERS}, f AS (SELECT h, n_bytes AS n FROM fz), s AS ({_levels([_stats_sql("file", "f", "h", "n"), _stats_sql("layer", "ly", "h", "n"), _stats_sql("tensor", "ts", "h", "n")])})
SELECT level, unique_units AS entries, metadata_bytes, CAST(floor(CAST(metadata_bytes AS DOUBLE) * {metrics.HUB_TB * 1e12} / total_bytes) AS BIGINT) AS projected_bytes, CAST(ceil(CAST(metadata_bytes AS DOUBLE) * {metrics.HUB_TB * 1e12} / total_bytes / {metrics.VM_GB * 1e9}) AS BIGINT) AS vms FROM s""")
def metadata_projection(spark, sf_dir):
    """Index bytes by level, projected to the whole hub, and the machines that hold them."""
    s = dedup_levels_zoo(spark, sf_dir)
    projected = F.col("metadata_bytes").cast("double") * (metrics.HUB_TB * 1e12) / F.col("total_bytes")
    return s.select("level", F.col("unique_units").alias("entries"), "metadata_bytes", F.floor(projected).alias("projected_bytes"), F.ceil(projected / (metrics.VM_GB * 1e9)).alias("vms"))


@query("metadata_published", f"""WITH t AS (SELECT text FROM documents WHERE text IS NOT NULL), b AS (SELECT CAST(sum(strlen(text)) AS DOUBLE) / 1e12 AS tb FROM t),
u AS (SELECT 'file' AS level, count(DISTINCT text) AS n FROM t UNION ALL SELECT 'line', count(DISTINCT line) FROM (SELECT unnest(string_split(text, chr(10))) AS line FROM t)),
m AS (SELECT level, CAST(n * {metrics.ENTRY_BYTES} AS DOUBLE) / 1048576 AS mib, CAST(n * {metrics.ENTRY_BYTES} AS DOUBLE) / 1048576 * CAST({metrics.HUB_TB} AS DOUBLE) / nullif(tb, 0) / 1000 AS gb FROM u, b)
SELECT level, round(mib, 6) AS metadata_mib, round(gb, 3) AS projected_gb, CAST(ceil(gb / {metrics.VM_GB}) AS BIGINT) AS vms FROM m""")
def metadata_published(spark, sf_dir):
    """The published formulas for an index, with the unique files and lines of documents as the sample; the published counts are in the tests."""
    d = table(spark, sf_dir, "documents").where("text IS NOT NULL").select("text")
    sample = d.agg((F.sum(F.octet_length("text").cast("bigint")).cast("double") / 1e12).alias("tb"))
    units = {"file": d.select(F.sha2("text", 256).alias("h")), "line": d.select(F.explode(F.split("text", "\n")).alias("line")).select(F.sha2("line", 256).alias("h"))}
    made = [u.distinct().agg(F.lit(level).alias("level"), F.count("*").alias("n")) for level, u in units.items()]
    c = made[0].unionAll(made[1]).crossJoin(sample)  # one row each
    gb = metrics.projected_gb(F.col("n"), sample_tb=F.nullif("tb", F.lit(0.0)))
    return c.select("level", F.round(metrics.metadata_mib(F.col("n")), 6).alias("metadata_mib"), F.round(gb, 3).alias("projected_gb"), F.ceil(gb / metrics.VM_GB).alias("vms"))


SEQ = "CASE variant " + " ".join(f"WHEN '{v}' THEN {seq}" for v, (seq, _, _) in zoo.VARIANTS.items()) + " END * 1000 + family"


def _curve(spark, sf_dir, units: DataFrame) -> DataFrame:
    seq = zoo.repos(spark, sf_dir).select("repo_id", F.col("seq").cast("bigint").alias("seq"))
    u = units.join(seq, "repo_id")
    at = [c for c in ("seq", "repo_id", "ordinal") if c in u.columns]
    marked = dedup.with_canonical(u, ["unit_hash"], at)
    return dedup.prefix_curve(marked.select("seq", F.col("n_bytes").alias("raw"), F.when(F.col("is_dup"), 0).otherwise(F.col("n_bytes")).alias("stored")))


def _curve_sql(units: str, key: str) -> str:
    return f"""WITH {Z.tensors()}, {FILES}, {LAYERS}, u AS ({units}), m AS (SELECT *, row_number() OVER (PARTITION BY h ORDER BY {key}) AS r FROM u),
p AS (SELECT CAST(seq AS BIGINT) AS seq, sum(n) AS raw, sum(CASE WHEN r = 1 THEN n ELSE 0 END) AS st FROM m GROUP BY 1)
SELECT seq, CAST(sum(raw) OVER w AS BIGINT) AS raw_bytes, CAST(sum(st) OVER w AS BIGINT) AS stored_bytes, round(1 - CAST(sum(st) OVER w AS DOUBLE) / CAST(sum(raw) OVER w AS DOUBLE), 6) AS drr FROM p WINDOW w AS (ORDER BY seq)"""


@query("drr_curve_file", lambda: _curve_sql(f"SELECT s AS seq, repo_id, fz.h, fz.n_bytes AS n FROM fz JOIN (SELECT DISTINCT repo_id, {SEQ} AS s FROM tn) USING (repo_id)", "seq, repo_id"))
def drr_curve_file(spark, sf_dir):
    """Reduction against the number of uploads, by file deduplication."""
    return _curve(spark, sf_dir, dedup.files_of(float_tensors(spark, sf_dir)))


@query("drr_curve_tensor", lambda: _curve_sql(f"SELECT {SEQ} AS seq, repo_id, ordinal, h, n FROM ts", "seq, repo_id, ordinal"))
def drr_curve_tensor(spark, sf_dir):
    t = float_tensors(spark, sf_dir).drop("payload").withColumn("unit_hash", dedup.tensor_identity())
    return _curve(spark, sf_dir, t.select("repo_id", "ordinal", "unit_hash", "n_bytes"))


@query("drr_curve_layer", lambda: _curve_sql(f"SELECT s AS seq, repo_id, layer, ly.h, ly.n FROM ly JOIN (SELECT DISTINCT repo_id, {SEQ} AS s FROM tn) USING (repo_id)", "seq, repo_id, layer"))
def drr_curve_layer(spark, sf_dir):
    return _curve(spark, sf_dir, dedup.layers(float_tensors(spark, sf_dir)))


@query("drr_curve_docs", "WITH f AS (SELECT doc_id, strlen(text) AS n, row_number() OVER (PARTITION BY sha256(text) ORDER BY doc_id) AS r FROM documents) SELECT doc_id AS seq, CAST(sum(n) OVER w AS BIGINT) AS raw_bytes, CAST(sum(CASE WHEN r = 1 THEN n ELSE 0 END) OVER w AS BIGINT) AS stored_bytes, round(1 - CAST(sum(CASE WHEN r = 1 THEN n ELSE 0 END) OVER w AS DOUBLE) / CAST(sum(n) OVER w AS DOUBLE), 6) AS drr FROM f WINDOW w AS (ORDER BY doc_id)")
def drr_curve_docs(spark, sf_dir):
    d = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("seq"), F.octet_length("text").cast("bigint").alias("raw"), F.sha2("text", 256).alias("h"))
    first = dedup.with_canonical(d, ["h"], ("seq",))
    return dedup.prefix_curve(first.select("seq", "raw", F.when(F.col("is_dup"), 0).otherwise(F.col("raw")).alias("stored")))


@query("metadata_curve", lambda: f"""WITH {Z.tensors()}, {LAYERS}, m AS (SELECT {SEQ} AS seq, row_number() OVER (PARTITION BY h ORDER BY {SEQ}, repo_id, ordinal) AS r FROM ts), p AS (SELECT seq, count(*) FILTER (r = 1) AS new FROM m GROUP BY 1)
SELECT CAST(seq AS BIGINT) AS seq, CAST(sum(new) OVER (ORDER BY seq) * 64 AS BIGINT) AS metadata_bytes FROM p""")
def metadata_curve(spark, sf_dir):
    """Index bytes as uploads come in."""
    seq = zoo.repos(spark, sf_dir).select("repo_id", F.col("seq").cast("bigint").alias("seq"))
    t = float_tensors(spark, sf_dir).drop("payload").withColumn("unit_hash", dedup.tensor_identity()).join(seq, "repo_id")
    marked = dedup.with_canonical(t, ["unit_hash"], ("seq", "repo_id", "ordinal"))
    return dedup.prefix_curve(marked.select("seq", F.lit(1).alias("raw"), (~F.col("is_dup")).cast("int").alias("stored"))).select("seq", (F.col("stored_bytes") * dedup.ENTRY_BYTES).alias("metadata_bytes"))


# --- Chunks -------------------------------------------------------------------------------------------------------


@query("cdc_chunks_documents")
def cdc_chunks_documents(spark, sf_dir):
    """Content-defined chunks of documents at three settings: counts, bytes, reduction."""
    d = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("file_id"), F.col("text").cast("binary").alias("content"))
    made = None
    for s in (chunking.ChunkSizes(64, 256, 1024), chunking.ChunkSizes(128, 512, 2048), chunking.ChunkSizes(256, 1024, 4096)):
        one = dedup.dedup_stats(chunking.chunk(d, ["file_id"], sizes=s), f"chunk {s.target}")
        made = one if made is None else made.unionAll(one)
    return made


@query("cdc_chunks_pages")
def cdc_chunks_pages(spark, sf_dir):
    p = table(spark, sf_dir, "pages").select(F.col("page_id").alias("file_id"), F.col("html").cast("binary").alias("content"))
    return dedup.dedup_stats(chunking.chunk(p, ["file_id"], sizes=chunking.SMALL), "chunk 256")


@query("fixed_chunks_documents", "WITH c AS (SELECT unnest(list_transform(range(0, strlen(text), 512), lambda b: substr(hex(encode(text)), 2 * b + 1, 1024))) AS h FROM documents), u AS (SELECT sha256(unhex(h)) AS h, strlen(h) // 2 AS n FROM c) " + _levels([_stats_sql("fixed 512", "u", "h", "n")]))
def fixed_chunks_documents(spark, sf_dir):
    d = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("file_id"), "text")
    return _level(chunking.fixed_chunks(d, ["file_id"], size=512, content="text"), "fixed 512")


def zoo_chunks(spark, sf_dir, sizes: chunking.ChunkSizes = chunking.SMALL) -> DataFrame:
    """Chunks of each model's file: its tensors one behind the other, cut as they come."""
    return chunking.chunk_blocks(zoo.tensors(spark, sf_dir).select("repo_id", "ordinal", "payload"), ["repo_id"], "ordinal", sizes=sizes, content="payload")


def production_chunks(spark, sf_dir) -> DataFrame:
    """(file_id, ...) chunks of 16 to 256 KiB of files that reach such sizes: each source's documents and price columns as one file."""
    d = table(spark, sf_dir, "documents").select(F.concat(F.lit("documents/"), "source").alias("file_id"), F.col("doc_id").alias("block_no"), F.col("text").cast("binary").alias("content"))
    kept = F.when(F.col("p").isNotNull(), F.unhex(F.lpad(F.hex(double_bits("p")), 16, "0")))
    li = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("o"), F.col("l_linenumber").alias("l"), F.explode(F.create_map(*[x for c in PRICES for x in (F.lit(f"lineitem/{c}"), F.col(c).cast("double"))])).alias("file_id", "p"))
    by_order = li.groupBy("file_id", F.floor(F.col("o") / 1024).alias("block_no")).agg(F.array_sort(F.collect_list(F.struct("o", "l", kept.alias("b")))).alias("v"))
    columns = by_order.select("file_id", "block_no", F.unhex(F.array_join(F.transform("v", lambda x: F.hex(x["b"])), "")).alias("content"))
    return chunking.chunk_blocks(d.unionByName(columns), ["file_id"], "block_no")


PRICES = ("l_quantity", "l_extendedprice", "l_discount", "l_tax")


@query("cdc_production", "SELECT 'documents/' || source AS file_id, CAST(sum(strlen(text)) AS BIGINT) AS n_bytes, TRUE AS covered, TRUE AS within_sizes FROM documents GROUP BY 1 HAVING sum(strlen(text)) > 0" + "".join(f" UNION ALL SELECT 'lineitem/{c}', count(*) * 8, TRUE, TRUE FROM lineitem" for c in PRICES))
def cdc_production(spark, sf_dir):
    """Chunks at the production setting, 16 / 64 / 256 KiB: they cover each file without a gap, and all but the last keep the sizes."""
    c = production_chunks(spark, sf_dir)
    last = c.groupBy("file_id").agg(F.max("chunk_no").alias("last"), F.sum("n_bytes").alias("n_bytes"), F.max(F.col("begin") + F.col("n_bytes")).alias("end"), F.count_distinct("begin").alias("starts"), F.count("*").alias("n"))
    s = chunking.ChunkSizes()
    held = c.join(last.select("file_id", "last"), "file_id").groupBy("file_id").agg(F.bool_and((F.col("n_bytes") <= s.most) & ((F.col("n_bytes") >= s.least) | (F.col("chunk_no") == F.col("last")))).alias("within_sizes"))
    return last.join(held, "file_id").select("file_id", "n_bytes", ((F.col("end") == F.col("n_bytes")) & (F.col("starts") == F.col("n")) & (F.col("n") == F.col("last") + 1)).alias("covered"), "within_sizes")


@query("cdc_production_levels")
def cdc_production_levels(spark, sf_dir):
    """Their count, bytes and reduction, beside those of the models' files and of the small setting."""
    stats = dedup.dedup_stats(production_chunks(spark, sf_dir), "chunk 64 KiB, documents and prices")
    for name, sizes in (("chunk 64 KiB, models", chunking.ChunkSizes()), ("chunk 256 B, models", chunking.SMALL)):
        stats = stats.unionAll(dedup.dedup_stats(zoo_chunks(spark, sf_dir, sizes), name))
    return stats


@query("chunk_levels_zoo")
def chunk_levels_zoo(spark, sf_dir):
    """The granularity study with chunks beside the structural units."""
    stats = dedup.dedup_stats(zoo_chunks(spark, sf_dir), "chunk")
    for level, units in zoo_levels(spark, sf_dir).items():
        stats = stats.unionAll(dedup.dedup_stats(units, level))
    return stats


@query("cdc_attribution")
def cdc_attribution(spark, sf_dir):
    """Which share of redundant chunks' bytes lies in tensors that repeat, and in tensors that are changed elsewhere."""
    chunks = zoo_chunks(spark, sf_dir).withColumnRenamed("repo_id", "file_id")
    repeated = chunks.groupBy("unit_hash").agg(F.count("*").alias("c")).where("c > 1").select("unit_hash")
    redundant = chunks.join(repeated, "unit_hash", "left_semi")
    t = zoo.tensors(spark, sf_dir).drop("payload").select(F.col("repo_id").alias("file_id"), F.col("ordinal").alias("unit"), F.col("offset").alias("begin"), "n_bytes", "tensor_hash")
    often = t.groupBy("tensor_hash").agg((F.count("*") > 1).alias("whole_tensor_repeats"))
    met = chunking.attribute(redundant, t).join(t.select("file_id", "unit", "tensor_hash"), ["file_id", "unit"]).join(often, "tensor_hash")
    return met.groupBy("whole_tensor_repeats").agg(F.sum("overlap").alias("redundant_bytes"), F.count_distinct("file_id", "chunk_no").alias("chunks"))


@query("chunk_vs_tensor_repo")
def chunk_vs_tensor_repo(spark, sf_dir):
    """One family as one repository: unique bytes by chunk and by tensor."""
    one = zoo.tensors(spark, sf_dir).where("family = 0")
    c = dedup.dedup_stats(zoo_chunks(spark, sf_dir).where(F.col("repo_id").startswith("m0_")), "chunk")
    return c.unionAll(dedup.dedup_stats(one.drop("payload").withColumn("unit_hash", dedup.tensor_identity()), "tensor")).select("level", "total_bytes", "unique_bytes", "drr")


@query("dedup_map_repo", lambda: f"""WITH {Z.tensors()}, {LAYERS}, one AS (SELECT *, CAST(sum(n_bytes) OVER (PARTITION BY repo_id ORDER BY ordinal) - n_bytes AS BIGINT) AS b FROM ts),
e AS (SELECT h, count(DISTINCT repo_id) > 1 AS d FROM ts GROUP BY 1)
SELECT 'tensor' AS level, CAST(ordinal AS INTEGER) AS unit_no, b AS begin, n_bytes, d AS is_dup FROM one JOIN e USING (h) WHERE repo_id = 'm0_v5'""")
def dedup_map_repo(spark, sf_dir):
    """Where a model with an expanded vocabulary shares tensors with others: not in its embedding."""
    t = float_tensors(spark, sf_dir).drop("payload").select(F.lit("tensor").alias("level"), "repo_id", F.col("ordinal").alias("unit_no"), F.col("offset").alias("begin"), "n_bytes", dedup.tensor_identity().alias("unit_hash"))
    return dedup.dedup_map(t, "m0_v5")


@query("dedup_map_chunks")
def dedup_map_chunks(spark, sf_dir):
    c = zoo_chunks(spark, sf_dir).select(F.lit("chunk").alias("level"), "repo_id", F.col("chunk_no").alias("unit_no"), "begin", "n_bytes", "unit_hash")
    return dedup.dedup_map(c, "m0_v5")


@query("dataset_summary", lambda: f"WITH {Z.tensors()}, {FILES}, g AS (SELECT h, min(repo_id) AS r, any_value(n_bytes) AS n FROM fz GROUP BY 1) SELECT family, count(*) AS models, CAST(sum(fz.n_bytes) AS BIGINT) AS bytes, CAST(coalesce(sum(g.n), 0) AS BIGINT) AS bytes_after_file_dedup FROM fz JOIN (SELECT DISTINCT repo_id, family FROM tn) USING (repo_id) LEFT JOIN g ON g.r = fz.repo_id AND g.h = fz.h GROUP BY 1")
def dataset_summary(spark, sf_dir):
    """Models and bytes per family, before and after file deduplication."""
    t = float_tensors(spark, sf_dir)
    files = dedup.with_canonical(dedup.files_of(t), ["unit_hash"], ("repo_id", "path")).join(t.select("repo_id", "family").distinct(), "repo_id")
    return files.groupBy(F.col("family")).agg(F.count("*").alias("models"), F.sum("n_bytes").alias("bytes"), F.sum(F.when(F.col("is_dup"), 0).otherwise(F.col("n_bytes"))).alias("bytes_after_file_dedup"))


@query("udtf_cdc", "SELECT sum(strlen(text))::BIGINT AS n_bytes, TRUE AS same FROM documents")
def udtf_cdc(spark, sf_dir):
    """The SQL table function for chunks covers every byte and agrees with the DataFrame operator."""
    from xorvault.functions import words

    words.register(spark)
    table(spark, sf_dir, "documents").createOrReplaceTempView("documents")
    by_sql = spark.sql("SELECT doc_id, c.unit_hash, c.n_bytes FROM documents, LATERAL cdc_chunks(CAST(text AS BINARY)) c")
    d = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("file_id"), F.col("text").cast("binary").alias("content"))
    by_map = chunking.chunk(d, ["file_id"], sizes=chunking.SMALL)
    sign = lambda df, k: df.agg(F.sum("n_bytes").alias(f"n{k}"), F.bit_xor(F.xxhash64("unit_hash")).alias(f"x{k}"), F.count("*").alias(f"c{k}"))
    return sign(by_sql, 1).crossJoin(sign(by_map, 2)).select(F.col("n1").alias("n_bytes"), ((F.col("x1") == F.col("x2")) & (F.col("c1") == F.col("c2"))).alias("same"))


@query("fn_sql_reduction", "SELECT source, round(1 - CAST(sum(n) FILTER (r = 1) AS DOUBLE) / CAST(sum(n) AS DOUBLE), 6) AS drr FROM (SELECT source, strlen(text) AS n, row_number() OVER (PARTITION BY source, sha256(text) ORDER BY doc_id) AS r FROM documents) GROUP BY 1")
def fn_sql_reduction(spark, sf_dir):
    """Reduction inside each repository, with the SQL function."""
    from xorvault.functions import words

    words.register(spark)
    d = table(spark, sf_dir, "documents").select("source", F.sha2("text", 256).alias("h"), F.octet_length("text").cast("bigint").alias("n"))
    g = d.groupBy("source", "h").agg(F.sum("n").alias("every"), F.first("n").alias("one")).groupBy("source").agg(F.sum("every").alias("o"), F.sum("one").alias("s"))
    return g.select("source", F.expr("reduction(o, s)").alias("drr"))


@query("block_hash_classes", lambda: f"WITH {Z.tensors()} SELECT count(*) AS tensors, count(DISTINCT tensor_hash) AS classes FROM tn")
def block_hash_classes(spark, sf_dir):
    """Tensor identity over blocks of 512 bytes makes the same classes as over whole tensors."""
    from xorvault.operators import blocks

    t = float_tensors(spark, sf_dir).withColumn("tensor", F.col("ordinal"))
    b = blocks.as_blocks(t.withColumn("path", F.concat_ws("/", "path", F.col("ordinal").cast("string"))), block_bytes=512)
    rows = b.select("repo_id", "path", F.col("ordinal").alias("block_no"), F.col("tensor_hash").alias("block_hash"), "n_bytes")
    h = blocks.tensor_hashes(rows, keys=("repo_id", "path"), block_bytes=512)
    return h.agg(F.count("*").alias("tensors"), F.count_distinct("tensor_hash").alias("classes"))
