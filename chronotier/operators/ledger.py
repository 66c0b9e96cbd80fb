"""The ledger: the ordered keys of every document's last version."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def build(segments: DataFrame) -> DataFrame:
    """(doc_id, ordinal, content_key, revision) of each document's last revision."""
    last = segments.groupBy("doc_id").agg(F.max("revision").alias("revision"))
    return segments.join(last, ["doc_id", "revision"]).select("doc_id", "ordinal", "content_key", "revision")


def apply(ledger: DataFrame, segments: DataFrame, withdrawn: DataFrame | None = None) -> DataFrame:
    """The ledger after these new versions: their documents are replaced whole."""
    ids = segments.select("doc_id")
    ids = ids.union(withdrawn.select("doc_id")) if withdrawn is not None else ids
    return ledger.join(ids.distinct(), "doc_id", "left_anti").unionByName(build(segments))


def for_docs(ledger: DataFrame, docs: DataFrame) -> DataFrame:
    return ledger.join(docs.select("doc_id").distinct(), "doc_id", "left_semi")


def nested(ledger: DataFrame) -> DataFrame:
    """One row per document with its keys in order."""
    rows = F.array_sort(F.collect_list(F.struct("ordinal", "content_key")))
    return ledger.groupBy("doc_id", "revision").agg(F.transform(rows, lambda x: x["content_key"]).alias("keys"))


def to_json(ledger: DataFrame, path: str) -> None:
    nested(ledger).write.mode("overwrite").json(path)


def from_json(spark: SparkSession, path: str) -> DataFrame:
    rows = spark.read.schema("doc_id long, revision long, keys array<string>").json(path)
    return rows.select("doc_id", F.posexplode("keys").alias("ordinal", "content_key"), "revision").withColumn("ordinal", F.col("ordinal").cast("long"))


def from_history(history: DataFrame) -> DataFrame:
    """The same from the history alone, without a ledger."""
    from chronotier.operators.history import snapshot_at

    return snapshot_at(history, None).select("doc_id", "ordinal", "content_key", "revision")
