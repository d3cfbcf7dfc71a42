"""A family of derived models in place of real weights: a pure function of the embeddings table.

A family is a label; its base's weights are the label's vectors over 4, eight vectors to a tensor. Variants follow by
IEEE sums and products with noise from md5 digests, so that Spark and the SQL twin (`elements_sql`) give equal bits.
The fixture is written once per session and input to the shared folder, and read from there.
"""

from __future__ import annotations

import json
import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: variant -> (order of upload, sigma, what it exercises)
VARIANTS = {
    "v0": (0, 0.0, "base"), "v1": (1, 0.0, "copy"), "v2": (2, 0.0005, "tuned"), "v3": (3, 0.002, "tuned"), "v4": (4, 0.005, "tuned"),
    "v5": (5, 0.002, "expanded"), "v6": (6, 0.0005, "renamed"), "v7": (7, 0.002, "pruned"), "v8": (8, 0.005, "pruned"), "v9": (9, 0.0005, "mixed"),
    "v10": (10, 0.0, "quantized"), "v11": (11, 0.0, "adapter"), "v12": (12, 0.004, "near"), "v12c": (13, 0.0005, "near child"), "v13": (14, 0.0005, "no card"),
}
ROWS_PER_TENSOR = 8
PRUNED_BELOW = 0.01
SEED = 42
#: Variants with plain float tensors of the base's shapes.
COMPARABLE = ("v0", "v1", "v2", "v3", "v4", "v7", "v8", "v12", "v12c", "v13")


def noise_sql(dialect: str, seed: str, index: str) -> str:
    """Near-normal noise: the first 12 bytes of an md5 digest, summed and centred."""
    text = f"concat_ws('|', '{SEED}', {seed}, {index})"
    byte = {"spark": "CAST(conv(substr(h, {k}, 2), 16, 10) AS INT)", "duckdb": "CAST(('0x' || substr(h, {k}, 2)) AS INTEGER)"}[dialect]
    total = " + ".join(byte.format(k=2 * j + 1) for j in range(12)).replace("h,", f"md5({text}),")
    return f"(({total}) - 1530) / {'256.0D' if dialect == 'spark' else 'CAST(256.0 AS DOUBLE)'}"


def bits32_sql(dialect: str, x: str) -> str:
    return f"float_bits({x})" if dialect == "spark" else f"CAST(CAST(CAST({x} AS FLOAT) AS BIT) AS INTEGER)"


def bf16_sql(dialect: str, bits: str) -> str:
    """BF16 word, rounded to nearest even, of FP32 bits given as a signed integer."""
    u = f"(CAST({bits} AS BIGINT) & 4294967295)"
    if dialect == "spark":
        return f"shiftright({u} + 32767 + (shiftright({u}, 16) & 1), 16) & 65535"
    return f"(({u} + 32767 + (({u} >> 16) & 1)) >> 16) & 65535"


def elements_sql(dialect: str, families: str = "label >= 0") -> str:
    """SQL of (family, variant, ordinal, idx, n_rows, dtype, bits) over view `embeddings`, for float tensors of base shapes and v5, v9."""
    spark = dialect == "spark"
    double = "DOUBLE"
    explode = "SELECT label, vec_id, pos AS dim, w FROM embeddings LATERAL VIEW posexplode(embedding) t AS pos, w" if spark else "SELECT label, vec_id, unnest(range(len(embedding))) AS dim, unnest(embedding) AS w FROM embeddings"
    hash4 = (lambda s: f"CAST(conv(substr(md5({s}), 1, 1), 16, 10) AS INT) % 4") if spark else (lambda s: f"CAST(('0x' || substr(md5({s}), 1, 1)) AS INTEGER) % 4")
    intdiv = (lambda a, b: f"CAST(floor(({a}) / {b}) AS BIGINT)") if spark else (lambda a, b: f"CAST(({a}) // {b} AS BIGINT)")
    f32 = lambda x: f"CAST({x} AS FLOAT)"
    sigma = lambda s: f"{s}D" if spark else f"CAST({s} AS DOUBLE)"
    tuned = lambda seed, s, base="w": f32(f"CAST({base} AS {double}) + {sigma(s)} * z_{seed}")
    seeds = {"v2": "v2", "v3": "v3", "v4": "v4", "v12": "v12", "v12c": "v12c", "v13": "v13"}
    noise = ", ".join(f"{noise_sql(dialect, repr(s), 'label, vec_id, dim')} AS z_{s}" for s in seeds)
    frozen = ", ".join(f"{hash4(f"concat_ws('|', CAST(label AS {'STRING' if spark else 'VARCHAR'}), '{s}', CAST(ordinal AS {'STRING' if spark else 'VARCHAR'}))")} = 0 AS frozen_{s}" for s in seeds)
    value = lambda s, sig: f"CASE WHEN frozen_{s} THEN w ELSE {tuned(s, sig)} END"
    near = tuned("v12", 0.004)
    rows = {
        "v0": "w", "v1": "w", "v2": value("v2", 0.0005), "v3": value("v3", 0.002), "v4": value("v4", 0.005),
        "v5": "CASE WHEN ordinal = 0 THEN w ELSE " + value("v3", 0.002) + " END", "v6": value("v2", 0.0005),
        "v7": f"CASE WHEN abs(w) < {sigma(PRUNED_BELOW)} THEN {f32('0')} ELSE {value('v3', 0.002)} END",
        "v8": f"CASE WHEN abs(w) < {sigma(PRUNED_BELOW)} THEN {f32('0')} ELSE {value('v4', 0.005)} END",
        "v9": value("v2", 0.0005), "v12": near, "v12c": f32(f"CAST({near} AS DOUBLE) + {sigma(0.0005)} * z_v12c"), "v13": value("v13", 0.0005),
    }
    union = " UNION ALL ".join(f"SELECT label AS family, '{v}' AS variant, ordinal, CAST(r % {ROWS_PER_TENSOR} * 64 + dim AS BIGINT) AS idx, {x} AS x FROM n" for v, x in rows.items())
    # The expanded vocabulary: two rows of noise behind the first tensor.
    more = f"SELECT label AS family, 'v5' AS variant, CAST(0 AS BIGINT) AS ordinal, CAST(512 + (r % 2) * 64 + dim AS BIGINT) AS idx, {f32(f'{sigma(0.03125)} * z_v3')} AS x FROM n WHERE r < 2"
    return f"""WITH e0 AS ({explode}),
e1 AS (SELECT label, vec_id, dim, CAST(w / 4 AS FLOAT) AS w FROM e0 WHERE {families}),
rk AS (SELECT label, vec_id, row_number() OVER (PARTITION BY label ORDER BY vec_id) - 1 AS r FROM (SELECT DISTINCT label, vec_id FROM e1) q),
e2 AS (SELECT e1.label, e1.vec_id, e1.dim, e1.w, rk.r, {intdiv('rk.r', ROWS_PER_TENSOR)} AS ordinal FROM e1 JOIN rk ON e1.label = rk.label AND e1.vec_id = rk.vec_id),
n AS (SELECT *, {noise}, {frozen} FROM e2),
a AS ({union} UNION ALL {more}),
b AS (SELECT *, {bits32_sql(dialect, 'x')} AS fb FROM a)
SELECT family, variant, ordinal, idx, CASE WHEN variant = 'v9' AND ordinal = 1 THEN 'F32' ELSE 'BF16' END AS dtype,
 CASE WHEN variant = 'v9' AND ordinal = 1 THEN CAST(fb AS BIGINT) & 4294967295 ELSE {bf16_sql(dialect, 'fb')} END AS bits FROM b"""


_made: dict[tuple[str, str], str] = {}


def _folder(spark: SparkSession, sf_dir: str) -> str:
    key = (spark.sparkContext.applicationId, sf_dir)
    if key not in _made:
        from xorvault.operators.graph import shared_dir

        path = f"{shared_dir(spark)}/zoo-{uuid.uuid4().hex}"
        _write(spark, sf_dir, path)
        _made[key] = path
    return _made[key]


def tensor_name() -> Column:
    """A tensor's name from its ordinal and its model's count n: embedding first, head last, pairs of layers between."""
    o = F.col("ordinal")
    layer = F.concat(F.lit("layers."), F.floor((o - 1) / 2).cast("string"), F.when(o % 2 == 1, ".attn.weight").otherwise(".mlp.weight"))
    return F.when(o == 0, "embed_tokens.weight").when(o == F.col("n") - 1, "lm_head.weight").otherwise(layer)


def _write(spark: SparkSession, sf_dir: str, path: str) -> None:
    from xorvault.functions import words

    words.register(spark)
    spark.read.parquet(f"{sf_dir}/embeddings.parquet").createOrReplaceTempView("embeddings")
    elements = spark.sql(elements_sql("spark"))
    elements.write.parquet(f"{path}/elements")
    elements = spark.read.parquet(f"{path}/elements")

    def pack(key, table):
        table = table.sort_by("idx")
        dtype = table["dtype"][0].as_py()
        bits = table["bits"].to_numpy()
        payload = bits.astype(words.DTYPES[dtype][0]).tobytes()
        return pa.table({"family": pa.array([key[0].as_py()], pa.int32()), "variant": [key[1].as_py()], "ordinal": pa.array([key[2].as_py()], pa.int32()), "dtype": [dtype], "shape": pa.array([[-(-len(bits) // 64), 64]], pa.list_(pa.int64())), "n_elems": pa.array([len(bits)], pa.int64()), "payload": pa.array([payload], pa.binary())})

    packed = elements.groupBy("family", "variant", "ordinal").applyInArrow(pack, "family int, variant string, ordinal int, dtype string, shape array<bigint>, n_elems bigint, payload binary")
    packed.write.parquet(f"{path}/packed")
    packed = spark.read.parquet(f"{path}/packed")

    # Quantized and adapter variants come from the base's tensors.
    def derived(batches):
        from xorvault.operators.quantize import quantize

        for batch in batches:
            rows = []
            for r in batch.to_pylist():
                data = quantize(r["payload"], "BF16")
                rows.append({**r, "variant": "v10", "dtype": "I8", "payload": data, "shape": [len(data)], "n_elems": len(data)})
                if r["ordinal"] < 2:
                    w = words.words(r["payload"], "BF16")[:32]
                    rows.append({**r, "variant": "v11", "payload": (w ^ np.uint16(r["ordinal"] + 1)).astype("<u2").tobytes(), "shape": [4, 8], "n_elems": len(w)})
            yield pa.RecordBatch.from_pylist(rows, schema=batch.schema)

    base = packed.where("variant = 'v0'")
    every = packed.unionByName(base.mapInArrow(derived, base.schema))
    count = base.groupBy("family").agg(F.count("*").alias("n"))
    named = every.join(F.broadcast(count), "family").withColumn("name", F.when(F.col("variant") == "v11", F.element_at(F.array(F.lit("lora_A.weight"), F.lit("lora_B.weight")), F.col("ordinal") + 1)).otherwise(tensor_name()))
    named = named.withColumn("name", F.when(F.col("variant") == "v6", F.concat(F.lit("model."), "name")).otherwise(F.col("name")))
    order = F.when(F.col("variant") == "v6", F.expr("row_number() OVER (PARTITION BY family, variant ORDER BY name) - 1")).otherwise(F.col("ordinal"))
    placed = named.withColumn("ordinal", order.cast("int")).withColumn("n_bytes", F.length("payload").cast("long"))
    offset = "coalesce(sum(n_bytes) OVER (PARTITION BY family, variant ORDER BY ordinal ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)"
    placed = placed.withColumn("offset", F.expr(offset).cast("long")).withColumn("tensor_hash", F.sha2("payload", 256)).withColumn("repo_id", repo_id("family", "variant")).withColumn("path", F.lit("model.tensors"))
    placed.select("repo_id", "family", "variant", "path", "ordinal", "name", "dtype", "shape", "offset", "n_elems", "n_bytes", "tensor_hash", "payload").write.parquet(f"{path}/tensors")


def repo_id(family: str, variant: str):
    return F.concat(F.lit("m"), F.col(family).cast("string"), F.lit("_"), F.col(variant))


def elements(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(family, variant, repo_id, ordinal, idx, dtype, bits)."""
    return spark.read.parquet(f"{_folder(spark, sf_dir)}/elements").withColumn("repo_id", repo_id("family", "variant"))


def tensors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The tensors of all repositories, with payloads."""
    return spark.read.parquet(f"{_folder(spark, sf_dir)}/tensors")


def card_of(family: int, variant: str) -> tuple[str | None, str, str | None]:
    """(card, config, true base) of a repository."""
    base = f"m{family}_v0"
    config = json.dumps({"architectures": ["DecoderOnly"], "family": f"m{family}", "vocab_size": 10 if variant == "v5" else 8}, sort_keys=True)
    if variant == "v0" or variant == "v12":
        return f"---\nlicense: open\n---\nA pretrained base of family m{family}.\n", config, None
    if variant == "v13":
        return (f"---\nbase_model_family: m{family}\n---\nTuned from a model of this family.\n" if family % 2 else None), config, base
    if variant == "v12c":
        base = f"m{family}_v12"
    if variant == "v3":
        return f"Tuned from [the base](https://hub.example/{base}) on dialogues.\n", config, base
    if variant == "v8":
        return "---\nbase_model: : [broken\n---\n", "{not json", base
    return f"---\nbase_model: {base}\nlicense: open\n---\nVariant {variant}.\n", config, base


def repos(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(repo_id, family, variant, kind, seq, uploaded_at, card, config, true_base), one row per repository."""
    families = tensors(spark, sf_dir).select("family").distinct()
    card = F.udf(lambda f, v: card_of(f, v), "card string, config string, true_base string")
    rows = spark.createDataFrame([(v, kind, seq) for v, (seq, _, kind) in VARIANTS.items()], "variant string, kind string, at int")
    all_rows = families.crossJoin(F.broadcast(rows)).withColumn("seq", (F.col("at") * 1000 + F.col("family")).cast("int"))
    stamped = all_rows.withColumn("uploaded_at", F.expr("timestamp_seconds(1704067200 + seq * 3600L)")).withColumn("c", card("family", "variant"))
    return stamped.select(repo_id("family", "variant").alias("repo_id"), "family", "variant", "kind", "seq", "uploaded_at", "c.card", "c.config", "c.true_base")
