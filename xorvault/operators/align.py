"""Tensor alignment for delta coding: by order, by name, or by normalised name."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

PREFIX = r"^(?:model|transformer|base_model)\."


def align(tuned: DataFrame, base: DataFrame, *, by: str = "order") -> DataFrame:
    """Tuned tensors with the base tensor each is delta-coded against; base columns are null where there is none.

    `tuned` has a column base_repo; the key is the serialization order, the name, or the name without usual prefixes.
    Tensors of another dtype or shape never pair. Both sides may come without payloads: the pairing is metadata, and
    base_path and base_ordinal tell where the base tensor's bytes are.
    """
    key = {"order": F.col("ordinal").cast("string"), "name": F.col("name"), "normalized_name": F.regexp_replace("name", PREFIX, "")}[by]
    bytes_ = [F.col("payload").alias("payload_b")] if "payload" in base.columns else []
    b = base.select(F.col("repo_id").alias("base_repo"), key.alias("k"), "dtype", "shape", F.col("tensor_hash").alias("base_hash"), F.col("path").alias("base_path"), F.col("ordinal").alias("base_ordinal"), *bytes_)
    return tuned.withColumn("k", key).join(b, ["base_repo", "k", "dtype", "shape"], "left").drop("k")


def align_recipes(paired: DataFrame, base: DataFrame) -> DataFrame:
    """paired, where quantized tensors (I8) of a model with a base get the base's tensor in their place as what they are made from."""
    b = base.where("dtype <> 'I8'").select(F.col("repo_id").alias("base_repo"), "ordinal", F.col("tensor_hash").alias("from_hash"), F.col("path").alias("from_path"), F.col("ordinal").alias("from_ordinal"))
    made = paired.join(b, ["base_repo", "ordinal"], "left")
    open_ = (F.col("dtype") == "I8") & F.col("base_hash").isNull()
    return made.withColumns({f"base_{c}": F.when(open_, F.col(f"from_{c}")).otherwise(F.col(f"base_{c}")) for c in ("hash", "path", "ordinal")}).drop("from_hash", "from_path", "from_ordinal")


def naming_audit(tensors: DataFrame, bases: DataFrame) -> DataFrame:
    """(repo_id, base, n_tensors, by_order, by_name, by_normalized, alphabetical, finding) of archives against their base.

    `tensors` has base_repo; the finding tells which alignment loses tensors that another would pair.
    """
    b = bases.select(F.col("repo_id").alias("base_repo"), F.col("ordinal").alias("bo"), F.col("name").alias("bn"), "dtype", "shape")
    t = tensors.select("repo_id", "base_repo", "ordinal", "name", "dtype", "shape", F.regexp_replace("name", PREFIX, "").alias("nn"))
    n = t.groupBy("repo_id", "base_repo").agg(F.count("*").alias("n_tensors"), F.array_sort(F.collect_list(F.struct("ordinal", "name"))).alias("o"))
    listed = n.withColumn("names", F.transform("o", lambda x: x["name"])).withColumn("alphabetical", F.col("names") == F.array_sort("names")).drop("o", "names")
    met = t.join(b, ["base_repo", "dtype", "shape"]).groupBy("repo_id", "base_repo").agg(F.count_if(F.col("ordinal") == F.col("bo")).alias("by_order"), F.count_if(F.col("name") == F.col("bn")).alias("by_name"), F.count_if(F.col("nn") == F.col("bn")).alias("by_normalized"))
    out = listed.join(met, ["repo_id", "base_repo"], "left").fillna(0, ["by_order", "by_name", "by_normalized"])
    finding = F.when(F.col("by_normalized") > F.col("by_name"), "renamed").when(F.col("by_name") > F.col("by_order"), "reordered").otherwise("aligned")
    return out.withColumn("finding", finding)
