"""Pairs within equal structure, the similarity graph, its components and their quality."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. Only a local session without one gets a folder here."""
    sc = spark.sparkContext
    if found := spark.conf.get("spark.checkpoint.dir", None):
        return found.rstrip("/")
    if sc._jsc.sc().getCheckpointDir().isDefined():
        return sc._jsc.sc().getCheckpointDir().get()
    if not sc.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    return f"{tempfile.gettempdir()}/xorvault-shared"


def checkpointed(df: DataFrame) -> DataFrame:
    """df kept in the shared folder."""
    sc = df.sparkSession.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        sc.setCheckpointDir(shared_dir(df.sparkSession))
    return df.checkpoint()


def signature(tensors: DataFrame) -> DataFrame:
    """(repo_id, signature): a hash of the ordered dtypes and shapes."""
    member = F.struct("ordinal", F.concat_ws(":", "dtype", F.array_join(F.col("shape").cast("array<string>"), "x")).alias("s"))
    text = F.array_join(F.transform(F.array_sort(F.collect_list(member)), lambda m: m["s"]), ";")
    return tensors.groupBy("repo_id").agg(F.sha2(text, 256).alias("signature"))


def pairs_of(signatures: DataFrame) -> DataFrame:
    """(a, b), a < b, of models with an equal signature; others are never compared."""
    a = signatures.select(F.col("repo_id").alias("a"), "signature")
    b = signatures.select(F.col("repo_id").alias("b"), "signature")
    return a.join(b, "signature").where("a < b").select("a", "b")


def aligned_blocks(pairs: DataFrame, tensors: DataFrame) -> DataFrame:
    """(a, b, ordinal, dtype, payload_a, payload_b) of pairs whose tensors agree in order, dtype and shape."""
    x = tensors.select(F.col("repo_id").alias("a"), "ordinal", "dtype", "shape", F.col("payload").alias("payload_a"))
    y = tensors.select(F.col("repo_id").alias("b"), "ordinal", "dtype", "shape", F.col("payload").alias("payload_b"))
    return pairs.select("a", "b").join(x, "a").join(y, ["b", "ordinal", "dtype", "shape"]).select("a", "b", "ordinal", "dtype", "payload_a", "payload_b")


def similarity_graph(edges: DataFrame, tau: float = 4.0) -> DataFrame:
    return edges.where(F.col("distance") < tau).select("a", "b", "distance")


def components(nodes: DataFrame, edges: DataFrame, *, max_rounds: int = 50) -> DataFrame:
    """(node, component): the least node of each connected part, by label propagation with pointer jumping.

    A round joins labels to edges and then follows the label's own label; lineage is cut in the shared folder each
    round, and the only thing on the driver is the count of changed labels.
    """
    links = checkpointed(edges.select(F.col("a").alias("u"), F.col("b").alias("v")).unionAll(edges.select("b", "a")).distinct())
    label = checkpointed(nodes.select(F.col("node"), F.col("node").alias("component")))
    for _ in range(max_rounds):
        offered = links.join(label, links["v"] == label["node"]).groupBy("u").agg(F.min("component").alias("low"))
        near = label.join(offered, label["node"] == offered["u"], "left").select("node", F.least("component", F.coalesce("low", "component")).alias("component"), F.col("component").alias("was"))
        jump = near.select(F.col("node").alias("n2"), F.col("component").alias("c2"))
        moved = checkpointed(near.join(jump, near["component"] == jump["n2"], "left").select("node", F.least("component", F.coalesce("c2", "component")).alias("component"), "was"))
        label = moved.select("node", "component")
        if not moved.where("component <> was").limit(1).count():
            return label
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")


def cluster_quality(components_: DataFrame, truth: DataFrame, edges: DataFrame) -> DataFrame:
    """One row: purity, and edge densities within and across true families; truth has (node, family)."""
    sized = components_.join(truth, "node").groupBy("component", "family").agg(F.count("*").alias("n"))
    purity = sized.groupBy("component").agg(F.max("n").alias("top"), F.sum("n").alias("all")).agg((F.sum("top") / F.sum("all")).alias("purity"))
    fam = truth.groupBy("family").agg(F.count("*").alias("n"))
    possible = fam.agg(F.sum(F.col("n") * (F.col("n") - 1) / 2).alias("inside"), (F.sum("n") * (F.sum("n") - 1) / 2).alias("every"))
    a, b = truth.select(F.col("node").alias("a"), F.col("family").alias("fa")), truth.select(F.col("node").alias("b"), F.col("family").alias("fb"))
    got = edges.join(a, "a").join(b, "b").agg(F.count_if(F.col("fa") == F.col("fb")).alias("e_in"), F.count_if(F.col("fa") != F.col("fb")).alias("e_out"))
    return purity.crossJoin(possible).crossJoin(got).select(F.round("purity", 6).alias("purity"), F.round(F.col("e_in") / F.col("inside"), 6).alias("within_density"), F.round(F.col("e_out") / (F.col("every") - F.col("inside")), 6).alias("cross_density"))


def provenance(distances: DataFrame, model: str, *, k: int = 5) -> DataFrame:
    """The k nearest models of one model: (model, candidate, distance, rank)."""
    other = F.when(F.col("a") == model, F.col("b")).otherwise(F.col("a"))
    near = distances.where((F.col("a") == model) | (F.col("b") == model)).select(F.lit(model).alias("model"), other.alias("candidate"), "distance")
    return near.orderBy("distance", "candidate").limit(k).withColumn("rank", F.expr("row_number() OVER (ORDER BY distance, candidate)"))
