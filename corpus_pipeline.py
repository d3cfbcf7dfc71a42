"""A corpus clean-up in stages; each stage's result is written as Parquet and reread as the next one's documents.

1. quality_rules: documents that the compression bands or the base rules reject go.
2. near_duplicates: of each class of the n-gram Jaccard join, one row whose id is the class id stays.
3. decontamination: documents that contain a test item (question and answer) go.
4. secret_scans: secrets are masked in the text, and n_chars follows the new text; no document goes.
5. bpe: documents are encoded and decoded; the result has their ids' count and digests.

Columns that the stages don't know pass through the first four; a null text fails stage 1. SQL cannot express the
stages' compression, signatures, retrieval or merges, so there is no ORACLE_SQL: the tests hold each stage and the
whole against brute force.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from xorvault.llm.common import fresh, shared_dir
from xorvault.llm.compression_rules import rules_column
from xorvault.llm.decontaminate import without_contaminated
from xorvault.llm.jaccard_forest import digest_column, marked_rows
from xorvault.llm.pair_index_bpe import encode_documents
from xorvault.llm.secret_guess import secrets_column

ORACLE_SQL = None


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    mark = fresh(docs, "_kept")
    return docs.withColumn(mark, rules_column()(F.col("text"))["kept"]).where(F.col(mark)).drop(mark)


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each class stays: of the least id, or of none where no row has one.

    Where an id is null or repeated, rows are told apart by their words' digest too. Texts without words have no class:
    those that repeat an id and a text count as copies.
    """
    found = marked_rows(docs)
    per_id = found.where("doc_id IS NOT NULL").groupBy("doc_id").agg(F.count("*").alias("n"), F.bool_and("kept").alias("kept"))
    named = docs.where("doc_id IS NOT NULL")
    alone = named.join(per_id.where("n > 1 OR NOT kept").select("doc_id"), "doc_id", "left_anti").select(*docs.columns)
    same = per_id.where("n > 1").select("doc_id")
    h = fresh(docs, "_h")
    repeated = named.join(same, "doc_id", "left_semi").select(*docs.columns).unionAll(docs.where("doc_id IS NULL"))
    repeated = repeated.withColumn(h, digest_column()(F.col("text"))["h"])
    marks = found.where("kept AND h IS NOT NULL").select(F.col("doc_id").alias("_id"), F.col("h").alias("_digest"))
    marks = marks.join(same.withColumnRenamed("doc_id", "_id"), "_id", "left_semi").select("_id", "_digest").unionAll(marks.where("_id IS NULL"))
    worded = repeated.join(marks, F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col(h) == F.col("_digest")), "left_semi").dropDuplicates(["doc_id", h])
    empty = repeated.where(F.col(h).isNull())
    copies = empty.where("doc_id IS NOT NULL").dropDuplicates(["doc_id", "text"])
    rest = [x.select(*docs.columns) for x in (worded, copies, empty.where("doc_id IS NULL"))]
    return alone.unionAll(rest[0]).unionAll(rest[1]).unionAll(rest[2])


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return without_contaminated(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def secret_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    mark = fresh(docs, "_masked")
    masked = docs.withColumn(mark, secrets_column(redact=True)(F.col("text")))
    text = {"text": F.when(F.col("text").isNotNull(), F.col(mark)["text"])}
    count = {"n_chars": F.when(F.col(mark)["n_spans"] > 0, F.length(F.col(mark)["text"])).otherwise(F.col("n_chars")).cast(docs.schema["n_chars"].dataType)} if "n_chars" in docs.columns else {}
    return masked.withColumns(text | count).select(*docs.columns)


def bpe_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return encode_documents(docs, keep_ids=False)


STAGES = [("quality_rules", quality_stage), ("near_duplicates", near_duplicate_stage), ("decontamination", decontamination_stage), ("secret_scans", secret_stage), ("bpe", bpe_stage)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages in order; every result but the last is written to the shared folder and reread."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    base = f"{shared_dir(spark).rstrip('/')}/pipeline-{uuid.uuid4().hex}"
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs.write.parquet(path := f"{base}/{k}-{name}")
            docs = spark.read.parquet(path)
    return docs
