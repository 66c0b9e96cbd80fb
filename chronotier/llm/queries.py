"""Queries of the training-data operators for the driver, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chronotier.llm import cover_tree, feistel_pii, license_scan, line_spread, mixing, prefix_free, secret_crf, simhash_bktree, spaced_seeds, toxicity_cnn


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op5_toxicity_cnn(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    model = toxicity_cnn.fit(docs, labels)
    found = toxicity_cnn.score(docs.select("doc_id", "text", "lang"), model)
    held_out = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0
    cut = toxicity_cnn.threshold(model)
    return found.select("doc_id", held_out.alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), (F.col("score") >= cut).alias("rejected"))


def op6_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """documents has no paths; a folder tree by source and id stands in for one, in
    which one file in 16 is a licence file."""
    docs = table(spark, sf_dir, "documents")
    n = F.col("doc_id")
    name = F.when(n % 16 == 0, F.lit("LICENSE")).otherwise(F.concat(F.lit("f"), n.cast("string"), F.lit(".txt")))
    path = F.concat_ws("/", "source", F.floor(n / 4096).cast("string"), F.floor(n / 256).cast("string"), name)
    return license_scan.scan(docs, path)


def op7_secret_crf(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return secret_crf.scan(docs, secret_crf.fit(docs))


def op8_feistel_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = feistel_pii.pseudonymise(table(spark, sf_dir, "documents"), key="key of the sample data")
    return found.select("doc_id", "n_found", "kinds", "text")


def op9_prefix_free(spark: SparkSession, sf_dir: str) -> DataFrame:
    return prefix_free.remove_repeats(table(spark, sf_dir, "documents"))


def op10_simhash_bktree(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = simhash_bktree.group_near_duplicates(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "fingerprint", "component_id")


def op1_cover_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cover_tree.near_duplicates(table(spark, sf_dir, "embeddings"))


def op2_line_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = line_spread.drop_boilerplate(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_lines", "n_removed", "text")


def op3_spaced_seeds(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spaced_seeds.overlaps(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op4_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = mixing.mix_plan(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "size", "source_size", "target", "taken")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_cover_tree": op1_cover_tree,
    "op2_line_spread": op2_line_spread,
    "op3_spaced_seeds": op3_spaced_seeds,
    "op4_mixing": op4_mixing,
    "op5_toxicity_cnn": op5_toxicity_cnn,
    "op6_license_scan": op6_license_scan,
    "op7_secret_crf": op7_secret_crf,
    "op8_feistel_pii": op8_feistel_pii,
    "op9_prefix_free": op9_prefix_free,
    "op10_simhash_bktree": op10_simhash_bktree,
}

SQL: dict[str, str] = {
    "op2_line_spread": line_spread.ORACLE,
    "op3_spaced_seeds": spaced_seeds.ORACLE,
    "op4_mixing": mixing.ORACLE,
    "op6_license_scan": license_scan.oracle("concat_ws('/', source, doc_id // 4096, doc_id // 256, CASE WHEN doc_id % 16 = 0 THEN 'LICENSE' ELSE 'f' || doc_id || '.txt' END)"),
}
