"""The corpus operators' queries: each applies one operator, with production parameters, to its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import backoff_lm, compression_rules, decontaminate, jaccard_forest, license_diagonals, pair_index_bpe, quality_svm, secret_guess, token_counts, toxicity_knn
from .common import table


def op1_trie_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.count_tokens(table(spark, sf_dir, "documents"))


def op2_nb_svm_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_svm.score_quality(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op3_knn_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity_knn.score_toxicity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op4_stupid_backoff(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scores rounded to four places, as sums in another order differ beyond."""
    scored = backoff_lm.backoff_scores(table(spark, sf_dir, "documents"))
    return scored.withColumns({c: F.round(c, 4) for c in ("log_score", "mean_log_score")})


def op5_jaccard_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_forest.ngram_jaccard_join(table(spark, sf_dir, "documents"))


def op6_compression_bands(spark: SparkSession, sf_dir: str) -> DataFrame:
    return compression_rules.quality_rules(table(spark, sf_dir, "documents"))


def op7_secret_guess_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_guess.scan_secrets(table(spark, sf_dir, "documents"))


def op8_license_diagonals(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_diagonals.scan_licenses(table(spark, sf_dir, "documents"))


def op9_pair_index_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pair_index_bpe.encode_documents(table(spark, sf_dir, "documents"), keep_ids=False)


def op10_bm25_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.find_contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


QUERIES = {
    f.__name__: f
    for f in (op1_trie_token_counts, op2_nb_svm_quality, op3_knn_toxicity, op4_stupid_backoff, op5_jaccard_forest, op6_compression_bands, op7_secret_guess_cost, op8_license_diagonals, op9_pair_index_bpe, op10_bm25_decontamination)
}


def oracle_sql() -> dict[str, str]:
    return {"op4_stupid_backoff": backoff_lm.oracle_sql(), "op5_jaccard_forest": jaccard_forest.oracle_sql(), "op8_license_diagonals": license_diagonals.oracle_sql()}
