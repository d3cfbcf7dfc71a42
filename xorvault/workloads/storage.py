"""Workloads on coding and storing: sparsity, codecs, the pipeline, orders of dedup and compression, restore, fallbacks."""

from __future__ import annotations

from functools import partial

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from xorvault import metrics
from xorvault.functions import words as W
from xorvault.operators import bitdist, chunking, codecs, dedup, family, graph, quantize
from xorvault.plans import hub
from xorvault.operators.graph import shared_dir
from xorvault.sources import zoo
from xorvault.workloads import zoo_sql as Z
from xorvault.workloads.dedup import float_tensors, zoo_chunks
from xorvault.workloads.models import DIST, NOT_BOTH_ZERO, TAUS, TUNED, _sweep_sql, all_pairs, blocks, cross_pairs, family_pairs
from xorvault.workloads.registry import query, table

#: Aligned blocks name the target payload_b's partner first: the base is `a`, the tuned model `b`.


def coded_pairs(spark, sf_dir, others: tuple[str, ...] = TUNED) -> DataFrame:
    """(model, base, ordinal, dtype, payload_a = tuned, payload_b = base)."""
    b = blocks(spark, sf_dir, family_pairs(spark, sf_dir, others))
    return b.select(F.col("b").alias("model"), F.col("a").alias("base"), "ordinal", "dtype", F.col("payload_b").alias("payload_a"), F.col("payload_a").alias("payload_b"))


@query("xor_sparsity", lambda: f"""WITH {Z.elements(('v0', *TUNED))}, {Z.pairs()}
SELECT b AS model, count(*) AS n_words, count(*) FILTER (x = y) AS zero_words, CAST(sum(CASE WHEN xor(x, y) & 255 = 0 THEN 1 ELSE 0 END + CASE WHEN xor(x, y) >> 8 = 0 THEN 1 ELSE 0 END) AS BIGINT) AS zero_bytes, CAST(sum(bit_count(CAST(xor(x, y) AS BIGINT))) AS BIGINT) AS one_bits FROM pe GROUP BY 1""")
def xor_sparsity(spark, sf_dir):
    """Zero words, zero bytes and one-bits of XOR deltas."""
    return codecs.sparsity(coded_pairs(spark, sf_dir), ["model"])


DIFF = zoo.bf16_sql("duckdb", zoo.bits32_sql("duckdb", f"({Z.VALUE.format(b='y')}) - ({Z.VALUE.format(b='x')})"))


@query("xor_vs_numeric", lambda: f"""WITH {Z.elements(('v0', *TUNED))}, {Z.pairs()}, o AS (SELECT b AS model, xor(x, y) AS d, {DIFF} AS f FROM pe)
SELECT model, CAST(count(*) * 16 - sum(bit_count(CAST(d AS BIGINT))) AS BIGINT) AS xor_zero_bits, CAST(count(*) * 16 - sum(bit_count(CAST(f AS BIGINT))) AS BIGINT) AS diff_zero_bits, sum(bit_count(CAST(d AS BIGINT))) < sum(bit_count(CAST(f AS BIGINT))) AS xor_sparser FROM o GROUP BY 1""")
def xor_vs_numeric(spark, sf_dir):
    """Zero bits of the XOR against those of the float difference."""
    d = codecs.numeric_density(coded_pairs(spark, sf_dir), ["model"])
    return d.select("model", (F.col("n_words") * 16 - F.col("xor_ones")).alias("xor_zero_bits"), (F.col("n_words") * 16 - F.col("diff_ones")).alias("diff_zero_bits"), (F.col("xor_ones") < F.col("diff_ones")).alias("xor_sparser"))


@query("delta_transforms")
def delta_transforms(spark, sf_dir):
    """Stored bytes of the XOR, the planes of the XOR, the wrap-around difference and its zig-zag."""
    p = coded_pairs(spark, sf_dir)
    made = None
    for name, options in {"xor": {}, "xor_planes": {"plane_split": True}, "wrap": {"transform": "wrap"}, "zigzag": {"transform": "zigzag"}}.items():
        one = codecs.xor_encode(p, ["model"], **options).groupBy("model").agg(F.lit(name).alias("transform"), F.sum("n_raw").alias("n_raw"), F.sum("n_stored").alias("n_stored"))
        made = one if made is None else made.unionAll(one)
    return made


@query("general_compressors")
def general_compressors(spark, sf_dir):
    """The XOR stream under each general compressor."""
    p = coded_pairs(spark, sf_dir)
    made = None
    for name in codecs.GENERAL:
        one = codecs.xor_encode(p, ["model"], codec=name, level=None).agg(F.lit(name).alias("compressor"), F.sum("n_raw").alias("n_raw"), F.sum("n_stored").alias("n_stored"))
        made = one if made is None else made.unionAll(one)
    return made


@query("xor_roundtrip", lambda: f"WITH {Z.tensors(('v0', *TUNED))} SELECT repo_id AS model, CAST(ordinal AS INTEGER) AS ordinal, n_bytes, tensor_hash AS restored_sha256, TRUE AS lossless FROM tn WHERE variant <> 'v0'")
def xor_roundtrip(spark, sf_dir):
    """Tensors coded against their base and decoded again."""
    p = coded_pairs(spark, sf_dir)
    coded = codecs.xor_encode(p, ["model", "base", "ordinal", "dtype", "payload_b"])

    def back(data, base, dtype):
        return {"restored": codecs.decode(data, dtype, base)}

    got = codecs.on_rows(coded, ["model", "ordinal"], ["payload", "payload_b", "dtype"], back, "restored binary")
    want = zoo.tensors(spark, sf_dir).select(F.col("repo_id").alias("model"), "ordinal", "tensor_hash")
    h = F.sha2("restored", 256)
    return got.join(want, ["model", "ordinal"]).select("model", "ordinal", F.length("restored").cast("bigint").alias("n_bytes"), h.alias("restored_sha256"), (h == F.col("tensor_hash")).alias("lossless"))


STANDALONE = (*codecs.GENERAL, "grouping_huffman", "grouping_zstd")


@query("codec_roundtrip", lambda: f"WITH {Z.tensors(('v0', 'v2', 'v9'))}, c AS (SELECT unnest([{Z.listed(STANDALONE)}]) AS codec) SELECT codec, CAST(sum(CASE WHEN variant = 'v0' THEN 2 ELSE 1 END) AS BIGINT) AS tensors, TRUE AS lossless FROM tn, c GROUP BY 1")
def codec_roundtrip(spark, sf_dir):
    """Every standalone codec over every tensor of four variants, the quantized one among them, decodes exactly."""
    return _coded_alone(spark, sf_dir).groupBy("codec").agg(F.count("*").alias("tensors"), F.bool_and("ok").alias("lossless"))


@query("codec_bytes")
def codec_bytes(spark, sf_dir):
    """Their bytes."""
    return _coded_alone(spark, sf_dir).groupBy("codec").agg(F.sum("n_raw").alias("n_raw"), F.sum("n_stored").alias("n_stored"))


def _coded_alone(spark, sf_dir) -> DataFrame:

    def make(payload, dtype):
        out = []
        for c in STANDALONE:
            data = codecs.encode(payload, dtype, c, None)
            out.append({"codec": c, "n_stored": len(data), "ok": codecs.decode(data, dtype) == payload})
        return {"coded": out, "n_raw": len(payload)}

    t = zoo.tensors(spark, sf_dir).where("variant IN ('v0', 'v2', 'v9', 'v10')")
    rows = codecs.on_rows(t, ["repo_id", "ordinal"], ["payload", "dtype"], make, "coded array<struct<codec: string, n_stored: bigint, ok: boolean>>, n_raw bigint")
    return rows.select("n_raw", F.inline("coded"))


@query("codec_drr")
def codec_drr(spark, sf_dir):
    """Per-model reduction by zstd, component grouping and XOR delta."""
    p = coded_pairs(spark, sf_dir, ("v2", "v3", "v4", "v7", "v13"))
    alone = codecs.whole_files(p.select(F.col("model").alias("repo_id"), "dtype", "ordinal", F.col("payload_a").alias("payload"))).withColumnRenamed("repo_id", "model")
    made = [codecs.standalone_encode(alone, ["model"], codecs=(c,)).select("model", F.lit(c).alias("method"), "n_raw", "n_stored") for c in ("zstd", "grouping_huffman")]
    made.append(codecs.xor_encode(p, ["model"]).select("model", F.lit("xor_delta").alias("method"), "n_raw", "n_stored"))
    every = made[0].unionAll(made[1]).unionAll(made[2])
    return every.groupBy("model", "method").agg(F.sum("n_raw").alias("n_raw"), F.sum("n_stored").alias("n_stored")).withColumn("drr", F.round(1 - F.col("n_stored") / F.col("n_raw"), 6))


@query("codec_drr_distribution")
def codec_drr_distribution(spark, sf_dir):
    """Quartiles of the per-model reductions by codec, and a histogram."""
    return codec_drr(spark, sf_dir).groupBy("method").agg(F.count("*").alias("models"), *[F.percentile("drr", q).alias(n) for n, q in (("q1", 0.25), ("median", 0.5), ("q3", 0.75))], F.to_json(F.histogram_numeric("drr", F.lit(8))).alias("histogram"))


@query("codec_drr_lineitem")
def codec_drr_lineitem(spark, sf_dir):
    """FP64 columns: each codec on price slices by supplier, and the XOR against the discounted price."""
    li = table(spark, sf_dir, "lineitem").select("l_suppkey", "l_orderkey", "l_linenumber", F.col("l_extendedprice").alias("p"), (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("q"))
    s = li.groupBy("l_suppkey").agg(F.array_sort(F.collect_list(F.struct("l_orderkey", "l_linenumber", "p", "q"))).alias("v"))
    cols = s.select("l_suppkey", F.transform("v", lambda x: x["p"]).alias("p"), F.transform("v", lambda x: x["q"]).alias("q"))

    def make(p, q):
        import numpy as np

        a, b = np.array(p, "<f8").tobytes(), np.array(q, "<f8").tobytes()
        return {"n_raw": len(a), "zstd": len(codecs.encode(a, "F64", "zstd")), "grouping": len(codecs.encode(a, "F64", "grouping_zstd")), "xor": len(codecs.delta_encode(a, b, "F64"))}

    each = codecs.on_rows(cols, ["l_suppkey"], ["p", "q"], make, "n_raw bigint, zstd bigint, grouping bigint, xor bigint")
    return each.agg(*[F.sum(c).alias(c) for c in ("n_raw", "zstd", "grouping", "xor")])


@query("plane_entropy", lambda: f"""WITH {Z.elements(('v0',))}, s AS (SELECT 'exponent' AS stream, (bits >> 7) & 255 AS v FROM el UNION ALL SELECT 'sign_mantissa', ((bits >> 8) & 128) | (bits & 127) FROM el),
c AS (SELECT stream, v, count(*) AS c FROM s GROUP BY 1, 2), p AS (SELECT stream, c, CAST(c AS DOUBLE) / sum(c) OVER (PARTITION BY stream) AS p FROM c) SELECT stream, CAST(sum(c) AS BIGINT) AS n, round(-sum(p * log2(p)), 6) AS entropy_bits FROM p GROUP BY 1""")
def plane_entropy(spark, sf_dir):
    """Order-0 entropy of the component streams of base weights."""
    b = F.col("bits").cast("bigint")
    streams = F.array(F.struct(F.lit("exponent").alias("stream"), F.shiftright(b, 7).bitwiseAND(255).alias("v")), F.struct(F.lit("sign_mantissa").alias("stream"), F.shiftright(b, 8).bitwiseAND(128).bitwiseOR(b.bitwiseAND(127)).alias("v")))
    c = zoo.elements(spark, sf_dir).where("variant = 'v0'").select(F.inline(streams)).groupBy("stream", "v").agg(F.count("*").alias("c"))
    total = c.groupBy("stream").agg(F.sum("c").alias("n"))
    p = F.col("c") / F.col("n")
    return c.join(total, "stream").groupBy("stream", "n").agg(F.round(-F.sum(p * F.log2(p)), 6).alias("entropy_bits"))


# --- Pipeline -----------------------------------------------------------------------------------------------------

_stores: dict[tuple[str, str], hub.HubStore] = {}


def plain_repos(spark, sf_dir) -> tuple[DataFrame, DataFrame]:
    """The models that the study of methods compares: without adapters and quantized ones, which no delta or chunk helps."""
    t = zoo.tensors(spark, sf_dir).where("variant NOT IN ('v10', 'v11')")
    return t, zoo.repos(spark, sf_dir).where("variant NOT IN ('v10', 'v11')")


def built(spark, sf_dir) -> hub.HubStore:
    """The store of every model, written once per session and input: adapters by the standalone coder, quantized ones as recipes."""
    import uuid

    key = (spark.sparkContext.applicationId, sf_dir)
    if key not in _stores:
        base = shared_dir(spark)
        _stores[key] = hub.reduce_hub(zoo.tensors(spark, sf_dir), zoo.repos(spark, sf_dir)).written(f"{base.rstrip('/')}/store-{uuid.uuid4().hex}")
    return _stores[key]


@query("pipeline_report")
def pipeline_report(spark, sf_dir):
    """Stored bytes by model under the whole pipeline."""
    return built(spark, sf_dir).report()


@query("pipeline_codecs")
def pipeline_codecs(spark, sf_dir):
    """Which coder the pool's tensors ended up with."""
    return built(spark, sf_dir).pool.groupBy("codec").agg(F.count("*").alias("tensors"), F.sum("n_bytes").alias("n_raw"), F.sum("n_stored").alias("n_stored"))


@query("drr_per_family")
def drr_per_family(spark, sf_dir):
    """Reduction of each family, ascending, with its rank."""
    r = built(spark, sf_dir).report().withColumn("family", F.regexp_extract("repo_id", r"^m(\d+)_", 1).cast("int"))
    f = r.groupBy("family").agg(F.sum("n_raw").alias("n_raw"), F.sum("n_stored").alias("n_stored"), F.median("drr").alias("median_model_drr"))
    return f.withColumn("drr", F.round(1 - F.col("n_stored") / F.col("n_raw"), 6)).withColumn("pct", F.expr("percent_rank() OVER (ORDER BY drr)"))


@query("drr_curve_engine")
def drr_curve_engine(spark, sf_dir):
    """Reduction against the number of uploads, under the pipeline."""
    seq = zoo.repos(spark, sf_dir).select("repo_id", F.col("seq").cast("bigint").alias("seq"))
    return dedup.prefix_curve(built(spark, sf_dir).report().join(seq, "repo_id").select("seq", F.col("n_raw").alias("raw"), F.col("n_stored").alias("stored")))


def _order_rows(spark, sf_dir) -> DataFrame:
    """(repo_id, ordinal, payload, payload_b, dtype) of models that are not file copies, each with its base's tensor."""
    t, r = plain_repos(spark, sf_dir)
    files = dedup.with_canonical(dedup.files_of(t), ["unit_hash"], ("repo_id", "path")).where("NOT is_dup").select("repo_id")
    live = t.join(files, "repo_id")
    base = r.where("true_base IS NOT NULL").select("repo_id", F.col("true_base").alias("base_repo"))
    b = t.select(F.col("repo_id").alias("base_repo"), "ordinal", "dtype", "shape", F.col("payload").alias("payload_b"))
    return live.join(base, "repo_id", "left").join(b, ["base_repo", "ordinal", "dtype", "shape"], "left").select("repo_id", "ordinal", "payload", "payload_b", "dtype")


@query("order_ablation")
def order_ablation(spark, sf_dir):
    """Dedup-then-compress against compress-then-chunk-dedup with three coders, dedup alone and compression alone.

    zstd and component grouping code whole files, as they are used; XOR deltas and the engine work by tensor.
    """
    t, _ = plain_repos(spark, sf_dir)
    total = t.agg(F.sum("n_bytes").alias("n_raw"))
    rows = _order_rows(spark, sf_dir)
    stored = lambda df, name: df.select(F.lit(name).alias("method"), F.col("s").cast("bigint").alias("n_stored"))
    pool = built(spark, sf_dir).pool.join(t.select(F.col("repo_id").alias("first_repo")).distinct(), "first_repo", "left_semi")
    made = [stored(pool.agg(F.sum("n_stored").alias("s")), "engine")]
    whole = codecs.whole_files(rows).withColumn("payload_b", F.lit(None).cast("binary"))
    for c in ("xor", "grouping", "zstd"):
        unique = chunking.compressed_chunks(rows if c == "xor" else whole, ["repo_id"], codec=c).where("unit_hash IS NOT NULL").groupBy("unit_hash").agg(F.first("n_bytes").alias("n"))
        made.append(stored(unique.agg(F.sum("n").alias("s")), f"{c} then chunks"))
    chunks = zoo_chunks(spark, sf_dir).join(t.select("repo_id").distinct(), "repo_id", "left_semi")
    made.append(stored(chunks.groupBy("unit_hash").agg(F.first("n_bytes").alias("n")).agg(F.sum("n").alias("s")), "chunks"))
    made.append(stored(dedup.dedup_tensors(t).pool.agg(F.sum("n_bytes").alias("s")), "tensors"))
    made.append(stored(dedup.files_of(t).groupBy("unit_hash").agg(F.first("n_bytes").alias("n")).agg(F.sum("n").alias("s")), "files"))
    alone = whole.select("repo_id", "payload", "dtype")
    made.append(stored(codecs.standalone_encode(alone, ["repo_id"], codecs=("grouping_huffman",)).agg(F.sum("n_stored").alias("s")), "grouping with files"))
    made.append(stored(codecs.standalone_encode(alone, ["repo_id"], codecs=("zstd",)).agg(F.sum("n_stored").alias("s")), "zstd with files"))
    every = made[0]
    for m in made[1:]:
        every = every.unionAll(m)
    return every.crossJoin(total).withColumn("drr", F.round(1 - F.col("n_stored") / F.col("n_raw"), 6))


@query("capabilities", "SELECT * FROM (VALUES ('chunk dedup', TRUE, FALSE, FALSE, TRUE), ('component grouping', FALSE, TRUE, FALSE, TRUE), ('engine', TRUE, TRUE, TRUE, TRUE), ('file dedup', TRUE, FALSE, FALSE, TRUE), ('mantissa truncation', FALSE, TRUE, FALSE, FALSE), ('numeric delta', FALSE, TRUE, TRUE, TRUE), ('tensor dedup', TRUE, FALSE, FALSE, TRUE), ('xor delta', FALSE, TRUE, TRUE, TRUE), ('zstd', FALSE, TRUE, FALSE, TRUE)) t(technique, dedup, compression, cross_model, lossless)")
def capabilities(spark, sf_dir):
    """What each technique does with tuned models beside their bases: deduplicate, compress, use other models, restore exactly.

    Every tensor (for file deduplication: every file) that differs from its base's is stored alone, once more, and beside its
    base, and restored; the flags are of the sums of bytes.
    """
    pairs = coded_pairs(spark, sf_dir)
    side = lambda c: codecs.whole_files(pairs.select(F.col("model").alias("repo_id"), "ordinal", "dtype", F.col(c).alias("payload"))).withColumnRenamed("payload", c)
    files = side("payload_a").join(side("payload_b"), ["repo_id", "dtype"])
    made = "m array<struct<technique: string, n_raw: bigint, alone: bigint, again: bigint, beside: bigint, exact: boolean>>"
    each = [codecs.on_rows(rows.where("payload_a <> payload_b"), [], ["payload_a", "payload_b", "dtype"], partial(_measured, {n: TECHNIQUES[n] for n in names}), made) for rows, names in ((pairs, [n for n in TECHNIQUES if n != "file dedup"]), (files, ["file dedup"]))]
    sums = each[0].unionAll(each[1]).select(F.inline("m")).groupBy("technique").agg(*[F.sum(c).alias(c) for c in ("n_raw", "alone", "again", "beside")], F.bool_and("exact").alias("lossless"))
    return sums.select("technique", (F.col("again") == 0).alias("dedup"), (F.least("alone", "beside") < F.col("n_raw")).alias("compression"), (F.col("beside") < F.col("alone")).alias("cross_model"), "lossless")


def _delta(transform):
    return lambda p, base, dtype: codecs.encode(p, dtype, "raw") if base is None else codecs.delta_encode(p, base, dtype, transform=transform)


def _engine(p, base, dtype):
    found = codecs.smallest(p, dtype)
    return found if base is None else min(found, codecs.delta_encode(p, base, dtype), key=len)


def _whole(p):
    return [p]


def _chunked(p):
    return [p[c["begin"] : c["begin"] + c["n_bytes"]] for c in chunking.chunks_of(p, chunking.SMALL)]


def _kept(p, base, dtype):
    return codecs.encode(p, dtype, "raw")


#: technique -> (how a pool of known units splits a payload, or None without one; the coder of a payload, with or without a base)
TECHNIQUES = {
    "file dedup": (_whole, _kept), "tensor dedup": (_whole, _kept), "chunk dedup": (_chunked, _kept), "engine": (_whole, _engine),
    "zstd": (None, lambda p, base, dtype: codecs.encode(p, dtype, "zstd")), "component grouping": (None, lambda p, base, dtype: codecs.encode(p, dtype, "grouping_huffman")),
    "mantissa truncation": (None, lambda p, base, dtype: codecs.encode(codecs.truncate_mantissa(p, dtype, 3), dtype, "zstd")), "xor delta": (None, _delta("xor")), "numeric delta": (None, _delta("wrap")),
}


def _measured(techniques, payload, base, dtype):
    rows = []
    for name, (split, code) in techniques.items():
        pool, r = set(split(base)) if split else set(), {"technique": name, "n_raw": 0, "alone": 0, "again": 0, "beside": 0}
        restored = b""
        for unit in (split or _whole)(payload):
            if unit not in pool:
                beside = code(unit, base if len(unit) == len(base) else None, dtype)
                back = codecs.decode(beside, dtype, base)
                head = codecs.HEAD.size  # a container's frame isn't content
                r = r | {"n_raw": r["n_raw"] + len(unit), "alone": r["alone"] + len(code(unit, None, dtype)) - head, "beside": r["beside"] + len(beside) - head}
                pool |= {unit} if split else set()
            else:
                back = unit
            restored += back
            r["again"] += 0 if unit in pool else len(code(unit, base if len(unit) == len(base) else None, dtype))
        rows.append({**r, "exact": restored == payload})
    return {"m": rows}


@query("lossy_contrast")
def lossy_contrast(spark, sf_dir):
    """Clearing mantissa bits: bytes, the greatest error, and that restoring is not exact."""

    def make(payload, dtype):
        import numpy as np

        cut = codecs.truncate_mantissa(payload, dtype, 3)
        a, b = W.floats(W.words(payload, dtype), dtype), W.floats(W.words(cut, dtype), dtype)
        return {"n_raw": len(payload), "n_stored": len(codecs.encode(cut, dtype, "zstd")), "max_error": float(np.abs(a - b).max(initial=0)), "exact": cut == payload}

    t = zoo.tensors(spark, sf_dir).where("variant = 'v0'")
    return codecs.on_rows(t, ["repo_id"], ["payload", "dtype"], make, "n_raw bigint, n_stored bigint, max_error double, exact boolean").groupBy("repo_id").agg(F.sum("n_raw").alias("n_raw"), F.sum("n_stored").alias("n_stored"), F.max("max_error").alias("max_error"), F.bool_and("exact").alias("exact"))


@query("annual_saving", "SELECT CAST(sum(strlen(text)) - (SELECT sum(n) FROM (SELECT any_value(strlen(text)) AS n FROM documents GROUP BY text)) AS BIGINT) AS saved_bytes, CAST(0.0216 AS DOUBLE) AS price_gb_month, round(CAST(sum(strlen(text)) - (SELECT sum(n) FROM (SELECT any_value(strlen(text)) AS n FROM documents GROUP BY text)) AS DOUBLE) / 1e9 * 0.0216 * 12, 4) AS usd_per_year FROM documents")
def annual_saving(spark, sf_dir):
    d = table(spark, sf_dir, "documents").select(F.sha2("text", 256).alias("unit_hash"), F.octet_length("text").cast("bigint").alias("n_bytes"))
    saved = dedup.dedup_stats(d, "file").select((F.col("total_bytes") - F.col("unique_bytes")).alias("saved_bytes"))
    return saved.select("saved_bytes", F.lit(metrics.PRICE_GB_MONTH).alias("price_gb_month"), metrics.annual_saving(F.col("saved_bytes").cast("double")).alias("usd_per_year"))


# --- Restore, fallback, upkeep ------------------------------------------------------------------------------------

RESTORED = ("v0", "v1", "v2", "v3", "v4", "v5", "v7", "v8", "v9", "v12", "v12c", "v13")


@query("restore_verify", lambda: f"WITH {Z.tensors(RESTORED)} SELECT repo_id, 'model.tensors' AS path, CAST(sum(n_bytes) AS BIGINT) AS n_bytes, sha256(string_agg(tensor_hash, '' ORDER BY ordinal)) AS sha256, TRUE AS ok FROM tn GROUP BY 1")
def restore_verify(spark, sf_dir):
    """All models out of the store, links followed, against their originals."""
    t = zoo.tensors(spark, sf_dir).where(F.col("variant").isin(*RESTORED))
    return hub.verify(hub.restore(built(spark, sf_dir)), t)


@query("restore_one", lambda: f"WITH {Z.tensors(('v1', 'v3'))} SELECT repo_id, CAST(ordinal AS INTEGER) AS ordinal, tensor_hash FROM tn WHERE repo_id IN ('m1_v1', 'm1_v3')")
def restore_one(spark, sf_dir):
    """Two models only: a copy and a delta-coded one."""
    got = hub.restore(built(spark, sf_dir), ["m1_v1", "m1_v3"])
    return got.select("repo_id", "ordinal", F.sha2("payload", 256).alias("tensor_hash"))


@query("manifest_contents", lambda: f"WITH {Z.tensors(('v0', 'v2'))} SELECT repo_id, CAST(ordinal AS INTEGER) AS ordinal, name, CAST(sum(n_bytes) OVER (PARTITION BY repo_id ORDER BY ordinal) - n_bytes AS BIGINT) AS \"offset\", n_bytes, tensor_hash FROM tn")
def manifest_contents(spark, sf_dir):
    return built(spark, sf_dir).manifests.where(F.col("repo_id").rlike("_v[02]$")).select("repo_id", "ordinal", "name", "offset", "n_bytes", "tensor_hash")


@query("store_chain_depth")
def store_chain_depth(spark, sf_dir):
    return hub.chain(built(spark, sf_dir).pool).groupBy("depth").agg(F.count("*").alias("tensors"))


@query("pool_integrity", "SELECT TRUE AS ok")
def pool_integrity(spark, sf_dir):
    return hub.integrity(built(spark, sf_dir)).agg(F.bool_and("ok").alias("ok"))


@query("gc_unreferenced")
def gc_unreferenced(spark, sf_dir):
    """Fates of pooled tensors once the second family's tuned models are removed."""
    removed = [f"m1_{v}" for v in ("v2", "v3", "v4", "v12c")]
    return hub.collect_garbage(built(spark, sf_dir), removed)[1].groupBy("fate").agg(F.count("*").alias("tensors"))


@query("pool_refcounts")
def pool_refcounts(spark, sf_dir):
    return hub.refcounts(built(spark, sf_dir)).groupBy("n_manifest").agg(F.count("*").alias("tensors"), F.sum("n_delta").alias("deltas_on_them"))


@query("fallback_copy", "SELECT 'm0_v0' AS lost, 'm0_v1' AS substitute")
def fallback_copy(spark, sf_dir):
    """A lost base with an identical copy."""
    return hub.substitute_copy("m0_v0", dedup.files_of(float_tensors(spark, sf_dir)))


def _surrogate(spark, sf_dir) -> DataFrame:
    t = zoo.tensors(spark, sf_dir).where("family = 0")
    children = [f"m0_{v}" for v in ("v2", "v3", "v4", "v13")]
    stand_in = hub.surrogate(t, "m0_v0", children).first()["surrogate"]
    return hub.surrogate_plan(t, "m0_v0", stand_in, children)


@query("fallback_surrogate", "SELECT * FROM (VALUES ('mask', TRUE), ('rebase', TRUE), ('standalone', TRUE)) t(mode, ok)")
def fallback_surrogate(spark, sf_dir):
    """Base and copies gone: a sibling stands in, exactly, in each of three ways."""
    return _surrogate(spark, sf_dir).groupBy("mode").agg(F.bool_and("ok").alias("ok"))


@query("fallback_choice")
def fallback_choice(spark, sf_dir):
    return hub.choose_smaller(_surrogate(spark, sf_dir))


@query("surrogate_distance", lambda: f"WITH {Z.elements(('v0', 'v2', 'v3', 'v4', 'v13'), 'label = 0')}, {Z.pairs('v0', ('v2', 'v3', 'v4', 'v13'))}, d AS (SELECT b, count(*) AS n, round(CAST(sum(bit_count(CAST(xor(x, y) AS BIGINT))) AS DOUBLE) / count(*), 6) AS distance FROM pe WHERE NOT ((x & 32767) = 0 AND (y & 32767) = 0) GROUP BY 1) SELECT b AS surrogate, distance FROM d ORDER BY distance, b LIMIT 1")
def surrogate_distance(spark, sf_dir):
    return hub.surrogate(zoo.tensors(spark, sf_dir).where("family = 0"), "m0_v0", [f"m0_{v}" for v in ("v2", "v3", "v4", "v13")])


@query("quant_regenerate", lambda: f"WITH {Z.tensors(('v0',))} SELECT replace(repo_id, '_v0', '_v10') AS repo_id, count(*) AS tensors, TRUE AS lossless, CAST(sum((n_elems + {quantize.BLOCK - 1}) // {quantize.BLOCK} * {quantize.BLOCK + 2}) AS BIGINT) AS bytes_not_stored FROM tn GROUP BY 1")
def quant_regenerate(spark, sf_dir):
    """Quantized variants made again from base and recipe."""
    t = zoo.tensors(spark, sf_dir)
    bases = t.where("variant = 'v0'")
    plan = quantize.plan(t.where("variant = 'v10'"), bases)
    done = quantize.regenerate(plan, bases)
    return done.groupBy("repo_id").agg(F.count("*").alias("tensors"), F.bool_and("lossless").alias("lossless"), F.sum("n_bytes").alias("bytes_not_stored"))


@query("xor_unrelated_control")
def xor_unrelated_control(spark, sf_dir):
    """XOR against another family's base gains nothing over standalone coding."""
    b = blocks(spark, sf_dir, cross_pairs(spark, sf_dir))
    x = codecs.xor_encode(b, ["a"]).agg(F.sum("n_raw").alias("n_raw"), F.sum("n_stored").alias("xor_stored"))
    alone = codecs.standalone_encode(b.select("a", "dtype", F.col("payload_a").alias("payload")), ["a"], codecs=("zstd",)).agg(F.sum("n_stored").alias("zstd_stored"))
    return x.crossJoin(alone)


@query("threshold_pick", lambda: f"""WITH {all_pairs()}, d AS (SELECT a, b, same AS actual, {DIST} FROM pe WHERE {NOT_BOTH_ZERO} GROUP BY 1, 2, 3), nr AS (SELECT min(distance) AS m FROM d WHERE split_part(a, '_', 1) = split_part(b, '_', 1) AND split_part(a, '_', 2) = 'v0' AND split_part(b, '_', 2) = 'v12'),
sw AS (WITH {_sweep_sql('distance', TAUS)}),
pk AS (SELECT 'max_accuracy' AS policy, (SELECT tau FROM sw ORDER BY accuracy DESC NULLS LAST, tau LIMIT 1) AS tau UNION ALL SELECT 'max_f1', (SELECT tau FROM sw ORDER BY f1 DESC NULLS LAST, tau LIMIT 1) UNION ALL SELECT 'guarded', (SELECT max(tau) FROM sw WHERE tau < (SELECT m FROM nr))) SELECT policy, sw.* FROM pk JOIN sw USING (tau)""")
def threshold_pick(spark, sf_dir):
    """Thresholds that each policy picks, with their measures."""
    from xorvault.workloads.models import threshold_sweep_zoo

    swept = graph.checkpointed(threshold_sweep_zoo(spark, sf_dir))
    near = bitdist.bit_distance(graph.aligned_blocks(family_pairs(spark, sf_dir, ("v12",)), zoo.tensors(spark, sf_dir))).agg(F.min("distance")).first()[0]
    rows = [(p, family.pick(swept, p, near)) for p in ("max_accuracy", "max_f1", "guarded")]
    return spark.createDataFrame(rows, "policy string, tau double").join(swept, "tau")


@query("udf_xor_bytes", lambda: f"WITH {Z.elements(('v0', 'v2'))}, {Z.pairs('v0', ('v2',))} SELECT a, b, CAST(ordinal AS INTEGER) AS ordinal, CAST(sum(bit_count(CAST(xor(x, y) AS BIGINT))) AS BIGINT) AS bits FROM pe GROUP BY ALL")
def udf_xor_bytes(spark, sf_dir):
    """The registered SQL functions on payloads."""
    W.register(spark)
    blocks(spark, sf_dir, family_pairs(spark, sf_dir, ("v2",))).createOrReplaceTempView("aligned")
    return spark.sql("SELECT a, b, ordinal, popcount_bytes(xor_bytes(payload_a, payload_b)) AS bits FROM aligned")


@query("sql_tensor_dedup", lambda: f"WITH {Z.tensors()} SELECT tensor_hash, count(*) AS refcount, min(repo_id) AS first_repo FROM tn GROUP BY 1 HAVING count(*) > 1")
def sql_tensor_dedup(spark, sf_dir):
    """Tensor deduplication as plain SQL over views."""
    float_tensors(spark, sf_dir).drop("payload").createOrReplaceTempView("tensors")
    return spark.sql("SELECT tensor_hash, count(*) AS refcount, min(repo_id) AS first_repo FROM tensors GROUP BY tensor_hash HAVING count(*) > 1")


@query("fn_header_inline", lambda: f"WITH {Z.tensors(('v0',))} SELECT repo_id, name, dtype, CAST(sum(n_bytes) OVER (PARTITION BY repo_id ORDER BY ordinal) - n_bytes AS BIGINT) AS begin FROM tn")
def fn_header_inline(spark, sf_dir):
    """Headers as arrays of structs, taken apart again."""
    t = zoo.tensors(spark, sf_dir).where("variant = 'v0'").drop("payload")
    h = t.groupBy("repo_id").agg(F.array_sort(F.collect_list(F.struct(F.col("offset").alias("begin"), "name", "dtype"))).alias("header"))
    return h.select("repo_id", F.inline("header")).select("repo_id", "name", "dtype", "begin")


@query("join_full_header_diff", lambda: f"WITH {Z.tensors(('v0', 'v5'))} SELECT coalesce(x.family, y.family) AS family, coalesce(x.name, y.name) AS name, CASE WHEN x.tensor_hash = y.tensor_hash THEN 'same' WHEN x.n_bytes = y.n_bytes THEN 'changed' ELSE 'reshaped' END AS state FROM (SELECT * FROM tn WHERE variant = 'v0') x FULL JOIN (SELECT * FROM tn WHERE variant = 'v5') y ON x.family = y.family AND x.name = y.name")
def join_full_header_diff(spark, sf_dir):
    """The difference of two headers."""
    t = zoo.tensors(spark, sf_dir).select("family", "variant", "name", "tensor_hash", "n_bytes")
    x = t.where("variant = 'v0'").select("family", "name", F.col("tensor_hash").alias("hx"), F.col("n_bytes").alias("nx"))
    y = t.where("variant = 'v5'").select("family", "name", F.col("tensor_hash").alias("hy"), F.col("n_bytes").alias("ny"))
    state = F.when(F.col("hx") == F.col("hy"), "same").when(F.col("nx") == F.col("ny"), "changed").otherwise("reshaped")
    return x.join(y, ["family", "name"], "full_outer").select("family", "name", state.alias("state"))


@query("archive_extract", lambda: f"WITH {Z.tensors(('v0', 'v2', 'v9'))} SELECT repo_id, CAST(ordinal AS INTEGER) AS ordinal, name, dtype, CAST(sum(n_bytes) OVER (PARTITION BY repo_id ORDER BY ordinal) - n_bytes AS BIGINT) AS \"offset\", n_elems, n_bytes, tensor_hash FROM tn")
def archive_extract(spark, sf_dir):
    """Models written as archives, and their tensors found again from the headers."""
    from xorvault.sources import archive

    t = zoo.tensors(spark, sf_dir).where("variant IN ('v0', 'v2', 'v9')")
    files = t.select("repo_id", "path", "ordinal", "name", "dtype", "shape", "payload").groupBy("repo_id", "path").applyInArrow(archive.written, "repo_id string, path string, content binary")
    return archive.extract_tensors(files).select("repo_id", "ordinal", "name", "dtype", "offset", "n_elems", "n_bytes", "tensor_hash")


@query("route_formats", "SELECT CASE WHEN p_type IN (SELECT min(p_type) FROM part) THEN 'tensors' ELSE 'opaque' END AS route, count(*) AS files FROM part GROUP BY 1")
def route_formats(spark, sf_dir):
    """Files by route: parsed archives against opaque legacy formats, whose extension decides."""
    p = table(spark, sf_dir, "part").select("p_partkey", "p_type")
    first = p.agg(F.min("p_type").alias("first"))
    files = p.crossJoin(F.broadcast(first)).select(F.concat(F.lit("model-"), F.col("p_partkey").cast("string"), F.when(F.col("p_type") == F.col("first"), ".safetensors").otherwise(".bin")).alias("path"))
    return hub.route(files).groupBy("route").agg(F.count("*").alias("files"))


@query("drr_curves_coded")
def drr_curves_coded(spark, sf_dir):
    """Reduction against the number of uploads: chunks alone, component grouping behind file deduplication, and zstd and grouping
    by file and XOR by tensor, each with chunks behind it."""
    rows = _order_rows(spark, sf_dir)
    seq = zoo.repos(spark, sf_dir).select("repo_id", F.col("seq").cast("bigint").alias("seq"))
    raw = plain_repos(spark, sf_dir)[0].groupBy("repo_id").agg(F.sum("n_bytes").alias("raw")).join(seq, "repo_id")
    whole = codecs.whole_files(rows).withColumn("payload_b", F.lit(None).cast("binary"))

    def first_of_each(chunks: DataFrame) -> DataFrame:
        marked = dedup.with_canonical(chunks.join(seq, "repo_id"), ["unit_hash"], ("seq", "chunk_no", "begin"))
        return marked.groupBy("repo_id").agg(F.sum(F.when(F.col("is_dup"), 0).otherwise(F.col("n_bytes"))).alias("stored"))

    stored = {f"{c} then chunks": first_of_each(chunking.compressed_chunks(rows if c == "xor" else whole, ["repo_id"], codec=c).where("unit_hash IS NOT NULL")) for c in ("zstd", "grouping", "xor")}
    stored["chunks"] = first_of_each(zoo_chunks(spark, sf_dir).join(raw.select("repo_id"), "repo_id", "left_semi"))
    stored["grouping with files"] = codecs.standalone_encode(whole.select("repo_id", "payload", "dtype"), ["repo_id"], codecs=("grouping_huffman",)).groupBy("repo_id").agg(F.sum("n_stored").alias("stored"))
    made = None
    for name, each in stored.items():
        one = dedup.prefix_curve(raw.join(each, "repo_id", "left").select("seq", "raw", F.coalesce("stored", F.lit(0)).alias("stored"))).withColumn("method", F.lit(name))
        made = one if made is None else made.unionAll(one)
    return made


@query("relative_factors")
def relative_factors(spark, sf_dir):
    """How many times, and by how many points, one method reduces more than another."""
    pairs = [("chunks", "files"), ("chunks", "tensors"), ("engine", "chunks"), ("engine", "zstd then chunks"), ("engine", "grouping then chunks"), ("engine", "grouping with files"), ("engine", "xor then chunks")]
    drr = graph.checkpointed(order_ablation(spark, sf_dir).select("method", "drr"))
    of = lambda c: drr.select(F.col("method").alias(c), F.col("drr").alias(f"{c}_drr"))
    both = spark.createDataFrame(pairs, "method string, against string").join(of("method"), "method").join(of("against"), "against")
    return both.select("method", "against", F.round(metrics.relative(F.col("method_drr"), F.col("against_drr")), 4).alias("times"), F.round(100 * (F.col("method_drr") - F.col("against_drr")), 2).alias("points"))


@query("quantized_container", lambda: f"WITH {Z.tensors(('v0',))} SELECT replace(repo_id, '_v0', '_v10') AS repo_id, CAST(ordinal AS INTEGER) AS ordinal, name, 'I8' AS dtype, (n_elems + {quantize.BLOCK - 1}) // {quantize.BLOCK} * {quantize.BLOCK + 2} AS n_bytes, TRUE AS same_bytes FROM tn")
def quantized_container(spark, sf_dir):
    """Quantized models written as containers, and their tensors found again from the typed table."""
    import pyarrow as pa

    from xorvault.sources import archive

    def packed(key, group):
        rows = sorted(group.to_pylist(), key=lambda r: r["ordinal"])
        data = archive.write_quantized([(r["name"], r["shape"], r["payload"]) for r in rows], {"block": quantize.BLOCK})
        return pa.table({"repo_id": pa.array([key[0].as_py()], pa.string()), "path": pa.array(["model.gguf"], pa.string()), "content": pa.array([data], pa.binary())})

    t = zoo.tensors(spark, sf_dir).where("variant = 'v10'")
    files = t.select("repo_id", "ordinal", "name", "shape", "payload").groupBy("repo_id").applyInArrow(packed, "repo_id string, path string, content binary")
    got = archive.extract_tensors(files).select("repo_id", "ordinal", "name", "dtype", "n_bytes", F.col("tensor_hash").alias("got"))
    return got.join(t.select("repo_id", "ordinal", "tensor_hash"), ["repo_id", "ordinal"]).select("repo_id", "ordinal", "name", "dtype", "n_bytes", (F.col("got") == F.col("tensor_hash")).alias("same_bytes"))


@query("bitdist_fp64", """WITH w AS (SELECT l_suppkey, CAST(CAST(l_extendedprice AS BIT) AS BIGINT) AS x, CAST(CAST(l_extendedprice * (1 - l_discount) AS BIT) AS BIGINT) AS y FROM lineitem)
SELECT l_suppkey, count(*) AS n, CAST(sum(bit_count(xor(x, y))) AS BIGINT) AS bits, round(CAST(sum(bit_count(xor(x, y))) AS DOUBLE) / count(*), 6) AS distance FROM w WHERE NOT ((x & 9223372036854775807) = 0 AND (y & 9223372036854775807) = 0) GROUP BY 1""")
def bitdist_fp64(spark, sf_dir):
    """FP64 distances of prices and discounted prices by supplier, in Catalyst expressions."""
    li = table(spark, sf_dir, "lineitem").select("l_suppkey", W.double_bits("l_extendedprice").alias("x"), W.double_bits(F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("y"))
    zero = lambda c: F.col(c).bitwiseAND(F.lit((1 << 63) - 1)) == 0
    d = li.where(~(zero("x") & zero("y"))).groupBy("l_suppkey").agg(F.count("*").alias("n"), F.sum(F.bit_count(F.col("x").bitwiseXOR(F.col("y")))).cast("bigint").alias("bits"))
    return d.withColumn("distance", F.round(F.col("bits") / F.col("n"), 6))


@query("bitdist_dtype_tensors")
def bitdist_dtype_tensors(spark, sf_dir):
    """The block path at each width: distances of tuned models from their base, rewritten as FP16, BF16, FP32 and FP64."""
    import numpy as np

    b = coded_pairs(spark, sf_dir).where("dtype = 'BF16'")

    def recast(a, base):
        out = []
        for t, kind in (("F16", "<f2"), ("F32", "<f4"), ("F64", "<f8")):
            x, y = (W.floats(W.words(p, "BF16"), "BF16").astype(kind).tobytes() for p in (a, base))
            out.append({"dtype": t, "payload_a": x, "payload_b": y})
        return {"made": [*out, {"dtype": "BF16", "payload_a": a, "payload_b": base}]}

    rows = codecs.on_rows(b, ["model", "ordinal"], ["payload_a", "payload_b"], recast, "made array<struct<dtype: string, payload_a: binary, payload_b: binary>>").select("model", "ordinal", F.inline("made"))
    return bitdist.bit_distance(rows.withColumn("width", F.col("dtype")), by=("model", "width"))


@query("throughput_kernels")
def throughput_kernels(spark, sf_dir):
    """MB/s of one task's kernels on this input: hashing, XOR coding and decoding, grouping, chunking (one figure per partition)."""
    import time

    def timed(batches):
        import hashlib

        import pyarrow as pa

        spent = {k: 0.0 for k in ("hash", "xor", "xor_decode", "grouping", "chunk")}
        n = 0
        for batch in batches:
            for r in batch.to_pylist():
                a, b, t = r["payload_a"], r["payload_b"], r["dtype"]
                n += len(a)
                kept = {}
                for k, f in {"hash": lambda: hashlib.sha256(a).digest(), "xor": lambda: codecs.delta_encode(a, b, t), "xor_decode": lambda: codecs.decode(kept["xor"], t, b), "grouping": lambda: codecs.grouping_encode(a, t), "chunk": lambda: chunking.cut_points(a, chunking.SMALL)}.items():
                    began = time.perf_counter()
                    kept[k] = f()
                    spent[k] += time.perf_counter() - began
        if n:
            yield pa.RecordBatch.from_pylist([{"kernel": k, "n_bytes": n, "mb_s": n / 1e6 / s} for k, s in spent.items() if s])

    return coded_pairs(spark, sf_dir).select("payload_a", "payload_b", "dtype").mapInArrow(timed, "kernel string, n_bytes bigint, mb_s double")
