"""Families: lineage from metadata, structure and candidates, nearest base, classification, thresholds, Monte Carlo."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from xorvault import metrics
from xorvault.operators import bitdist, graph

BASE_KEY = r"(?m)^base_model:[ \t]*([A-Za-z0-9_./-]+)[ \t]*$"
BASE_LINK = r"\]\(https?://[^)\s]*/([A-Za-z0-9_.-]+)\)"
FAMILY_KEY = r"(?m)^base_model_family:[ \t]*([A-Za-z0-9_./-]+)[ \t]*$"


def rule_parser(card: Column) -> Column:
    """The default card parser: a struct (base, family) from the front matter's keys, then from links."""
    found = lambda pattern: F.nullif(F.regexp_extract(F.coalesce(card, F.lit("")), pattern, 1), F.lit(""))
    return F.struct(F.coalesce(found(BASE_KEY), found(BASE_LINK)).alias("base"), found(FAMILY_KEY).alias("family"))


def from_metadata(repos: DataFrame, *, parser: Callable[[Column], Column] = rule_parser) -> DataFrame:
    """(repo_id, status, base, family, source): exact if the declared base exists, ambiguous if only a family is known.

    `parser` maps the card column to struct(base, family); a model-based parser may take the rules' place. The config's
    family is used where the card says none; malformed JSON counts as absent.
    """
    config = F.from_json("config", "family string, architectures array<string>, vocab_size int")
    parsed = repos.withColumn("p", parser(F.col("card"))).withColumn("c", config)
    known = repos.select(F.col("repo_id").alias("known_base"))
    joined = parsed.join(known, F.col("p.base") == F.col("known_base"), "left")
    family = F.coalesce("p.family", "c.family")
    status = F.when(F.col("known_base").isNotNull(), "exact").when(family.isNotNull(), "ambiguous").otherwise("missing")
    source = F.when(F.col("known_base").isNotNull(), "card").when(F.col("p.family").isNotNull(), "card family").when(family.isNotNull(), "config")
    return joined.select("repo_id", status.alias("status"), F.col("known_base").alias("base"), family.alias("family"), source.alias("source"))


def candidate_bases(models: DataFrame, bases: DataFrame) -> DataFrame:
    """(model, base): every base of equal signature for each model; hints cut nothing, as a card may be broken or absent."""
    m, b = models.select(F.col("repo_id").alias("model"), "signature"), bases.select(F.col("repo_id").alias("base"), "signature")
    return m.join(b, "signature").where("model <> base").select("model", "base")


def shared_share(models: DataFrame, bases: DataFrame) -> DataFrame:
    """(model, base, shared_share): the share of a model's tensors that have a twin in dtype, shape and order in the base."""
    m = models.select(F.col("repo_id").alias("model"), "ordinal", "dtype", "shape")
    b = bases.select(F.col("repo_id").alias("base"), "ordinal", "dtype", "shape")
    total = m.groupBy("model").agg(F.count("*").alias("total"))
    twins = m.join(b, ["ordinal", "dtype", "shape"]).where("model <> base").groupBy("model", "base").agg(F.count("*").alias("shared"))
    return twins.join(total, "model").select("model", "base", F.round(F.col("shared") / F.col("total"), 6).alias("shared_share"))


def nearest_base(distances: DataFrame, *, tau: float | None = None) -> DataFrame:
    """(model, base, distance, runner_up, margin, within) from rows (model, base, distance): the least distance, ties by base id.

    Bases beyond the least leave only a margin. With tau, a model whose least distance is not below it has no base.
    """
    near = distances.groupBy("model").agg(F.slice(F.array_sort(F.collect_list(F.struct("distance", "base"))), 1, 2).alias("best"))
    first, second = F.get("best", F.lit(0)), F.get("best", F.lit(1))
    within = F.lit(True) if tau is None else first["distance"] < tau
    return near.select("model", F.when(within, first["base"]).alias("base"), first["distance"].alias("distance"), second["distance"].alias("runner_up"), F.round(second["distance"] - first["distance"], 6).alias("margin"), within.alias("within"))


def classify_pairs(pairs: DataFrame, *, tau: float = 4.0) -> DataFrame:
    """pairs (signature_a, signature_b, distance) with `rule` (structure or distance) and `predicted` (within the family?)."""
    differ = F.col("signature_a") != F.col("signature_b")
    return pairs.withColumn("rule", F.when(differ, "structure").otherwise("distance")).withColumn("predicted", F.when(differ, False).otherwise(F.coalesce(F.col("distance") < tau, F.lit(False))))


def structure_pairs(models: DataFrame) -> DataFrame:
    """(rule, predicted, actual, pairs): how many pairs of models (signature, family) differ in structure, of one family and of two."""
    half = lambda c: (F.col(c) * (F.col(c) - 1) / 2).cast("bigint")
    each = models.groupBy("signature", "family").agg(F.count("*").alias("n"))
    total = lambda df, name: df.agg(F.coalesce(F.sum(half("n")), F.lit(0)).alias(name))
    summed = lambda *by: each.groupBy(*by).agg(F.sum("n").alias("n"))
    counts = total(summed(), "every").crossJoin(total(summed("signature"), "alike")).crossJoin(total(summed("family"), "kin")).crossJoin(total(each, "both"))  # one row each
    within = F.struct(F.lit(True).alias("actual"), (F.col("kin") - F.col("both")).alias("pairs"))
    across = F.struct(F.lit(False).alias("actual"), (F.col("every") - F.col("kin") - F.col("alike") + F.col("both")).alias("pairs"))
    return counts.select(F.inline(F.array(within, across))).where("pairs > 0").select(F.lit("structure").alias("rule"), F.lit(False).alias("predicted"), "actual", "pairs")


def sweep(scored: DataFrame, taus: list[float], *, score: str = "distance", actual: str = "actual") -> DataFrame:
    """Confusion and measures for each threshold: positive is a score below it.

    Scores are counted once per threshold interval, and the counts (a row per interval) are summed up cumulatively.
    """
    spark = scored.sparkSession
    sorted_taus = sorted(taus)
    step = F.size(F.filter(F.array(*[F.lit(float(t)) for t in sorted_taus]), lambda t: t <= F.col(score)))
    counts = scored.groupBy(step.alias("at")).agg(F.count_if(F.col(actual)).alias("p"), F.count_if(~F.col(actual)).alias("n"))
    grid = spark.createDataFrame([(float(t), k) for k, t in enumerate(sorted_taus)], "tau double, k int")
    below = F.col("at") <= F.col("k")
    c = grid.crossJoin(F.broadcast(counts)).groupBy("tau").agg(F.sum(F.when(below, F.col("p")).otherwise(0)).alias("tp"), F.sum(F.when(below, F.col("n")).otherwise(0)).alias("fp"), F.sum(F.when(below, 0).otherwise(F.col("n"))).alias("tn"), F.sum(F.when(below, 0).otherwise(F.col("p"))).alias("fn"))
    return metrics.with_rates(c)


def pick(swept: DataFrame, policy: str = "max_accuracy", near_cross: float | None = None) -> float:
    """A threshold from a sweep: max_accuracy, max_f1, or guarded (the largest below the least near-cross distance)."""
    if policy == "guarded":
        row = swept.where(F.col("tau") < near_cross).agg(F.max("tau").alias("tau")).first()
    else:
        row = swept.orderBy(F.col(policy.removeprefix("max_")).desc_nulls_last(), "tau").first()
    return row["tau"]


# --- Expected bit distance ----------------------------------------------------------------------------------------


def _byte_sum(text: Column) -> Column:
    h = F.md5(text)
    return sum((F.conv(F.substring(h, 2 * k + 1, 2), 16, 10).cast("int") for k in range(12)), F.lit(0))


def with_normals(draws: DataFrame, key: Column, names: tuple[str, ...] = ("w", "d"), *, generator: str = "md5", seed: int = 42) -> DataFrame:
    """draws and one column of unit normals per name, drawn by a key: md5 byte sums (equal in any engine), Box-Muller on hashes, or randn."""
    if generator == "md5":
        draw = lambda name, k: (_byte_sum(F.concat_ws("|", F.lit(str(seed)), F.lit(name), key)) - 1530) / 256.0
    elif generator == "box_muller":
        unit = lambda salt: (F.pmod(F.xxhash64(F.lit(seed), F.lit(salt), key), F.lit(1 << 40)) + 1) / float((1 << 40) + 1)
        draw = lambda name, k: F.sqrt(-2 * F.log(unit(name + "u"))) * F.cos(2 * F.pi() * unit(name + "v"))
    elif generator == "randn":
        draw = lambda name, k: F.randn(seed + k)
    else:
        raise ValueError(f"unknown generator {generator!r}")
    return draws.select("*", *[draw(name, k).alias(name) for k, name in enumerate(names)])


def normals(spark: SparkSession, n: int, names: tuple[str, ...] = ("w", "d"), **options) -> DataFrame:
    """(i, one column of unit normals per name) of n draws."""
    return with_normals(spark.range(n).withColumnRenamed("id", "i"), F.col("i"), names, **options)


def unit_weights(weights: DataFrame) -> DataFrame:
    """weights (w float, any other columns) over their standard deviation, which is rounded as any engine's would be; w must be finite."""
    held = weights.where("abs(w) < double('Infinity')").withColumn("w", F.col("w").cast("double"))
    scale = held.agg(F.nullif(F.round(F.stddev_pop("w"), 6), F.lit(0.0)).alias("scale"))
    return held.crossJoin(F.broadcast(scale)).withColumn("w", F.col("w") / F.col("scale")).drop("scale")


def expected_grid(spark: SparkSession, sigmas_w: list[float], sigmas_d: list[float], *, n: int = 100_000, dtype: str = "bf16", generator: str = "md5", seed: int = 42, weights: DataFrame | None = None) -> DataFrame:
    """(sigma_w, sigma_d, n, bits, expected): mean differing bits of w and w + d over the draws for each pair of sigmas.

    Draws are n pairs of unit normals, or each of `weights` (i, w) over their standard deviation with a normal d drawn by i.
    """
    from xorvault.functions.words import bf16_bits, differing, float_bits

    grid = spark.createDataFrame([(float(w), float(d)) for w in sigmas_w for d in sigmas_d], "sigma_w double, sigma_d double")
    word = {"bf16": bf16_bits, "f32": float_bits}[dtype]
    draws = normals(spark, n, generator=generator, seed=seed) if weights is None else with_normals(unit_weights(weights), F.col("i"), ("d",), generator=generator, seed=seed)
    drawn = draws.crossJoin(F.broadcast(grid))
    w = F.col("sigma_w") * F.col("w")
    pair = drawn.select("sigma_w", "sigma_d", word(w.cast("float")).alias("x"), word((w + F.col("sigma_d") * F.col("d")).cast("float")).alias("y"))
    sums = pair.groupBy("sigma_w", "sigma_d").agg(F.count("*").alias("n"), F.sum(differing(F.col("x"), F.col("y"))).cast("bigint").alias("bits"))
    return sums.withColumn("expected", F.round(F.col("bits") / F.col("n"), 6))


def expected_distance(spark: SparkSession, sigma_w: float, sigma_d: float, **options) -> DataFrame:
    return expected_grid(spark, [sigma_w], [sigma_d], **options)


def empirical_sigmas(elements: DataFrame, base: str = "v0", tuned: tuple[str, ...] = ("v2", "v3", "v4")) -> DataFrame:
    """(family, variant, sigma_w, sigma_d) of tuned models against their base."""
    v = elements.withColumn("value", bitdist.value_of_bf16())
    b = v.where(F.col("variant") == base).select("family", "ordinal", "idx", F.col("value").alias("w"))
    t = v.where(F.col("variant").isin(*tuned)).select("family", "variant", "ordinal", "idx", "value")
    return t.join(b, ["family", "ordinal", "idx"]).groupBy("family", "variant").agg(F.round(F.stddev_pop("w"), 6).alias("sigma_w"), F.round(F.stddev_pop(F.col("value") - F.col("w")), 6).alias("sigma_d"))


def match_distances(candidates: DataFrame, tensors: DataFrame, **options) -> DataFrame:
    """(model, base, n, bits, distance) of candidate pairs; payloads are read for candidates only."""
    pairs = candidates.select(F.col("model").alias("a"), F.col("base").alias("b"))
    return bitdist.bit_distance(graph.aligned_blocks(pairs, tensors), **options).withColumnsRenamed({"a": "model", "b": "base"})
