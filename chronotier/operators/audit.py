"""Audit: what changed where, lineage, timelines, reconstruction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from chronotier.operators import history as hist


def describe_changes(changes: DataFrame) -> DataFrame:
    """One sentence per change."""
    n = (F.col("ordinal") + 1).cast("string")
    said = F.when(F.col("op") == "moved", F.concat_ws("", F.lit("segment "), n, F.lit(" was moved from "), (F.col("moved_from") + 1).cast("string"))).otherwise(F.concat_ws("", F.lit("segment "), n, F.lit(" was "), "op"))
    return changes.where("op <> 'kept'").select("doc_id", "revision", "ordinal", "op", said.alias("sentence"))


def rebuild_documents(history: DataFrame, t: int, join: str = "\n") -> DataFrame:
    """The texts as of t, put together in order."""
    rows = F.array_sort(F.collect_list(F.struct("ordinal", "body")))
    return hist.snapshot_at(history, t).groupBy("doc_id").agg(F.array_join(F.transform(rows, lambda x: x["body"]), join).alias("text"))


def lineage(history: DataFrame) -> DataFrame:
    """Each event of each slot with its number in the slot and the key before it."""
    w = W.partitionBy("doc_id", "ordinal").orderBy("effective_at", "revision")
    return history.select("doc_id", "ordinal", "revision", "op", "content_key", F.row_number().over(w).cast("long").alias("step"), F.lag("content_key").over(w).alias("before"))


def ancestry(history: DataFrame, key: str, max_hops: int = 20) -> DataFrame:
    """The chain of keys that were edited into `key`: (hop, content_key)."""
    spark = history.sparkSession
    history.where("op = 'edited'").select("content_key", "prior_key").distinct().createOrReplaceTempView("chronotier_edits")
    return spark.sql(
        f"""WITH RECURSIVE chain(hop, content_key) AS (
          SELECT 0, :key UNION ALL
          SELECT hop + 1, e.prior_key FROM chain JOIN chronotier_edits e ON e.content_key = chain.content_key WHERE hop < {int(max_hops)})
        SELECT hop, content_key FROM chain""",
        args={"key": key},
    )


def timeline(history: DataFrame) -> DataFrame:
    """Per revision the events of each kind and the slots that live after it."""
    per = history.groupBy("effective_at", "revision").agg(*[F.count_if(F.col("op") == op).alias(op) for op in ("added", "edited", "moved", "dropped", "vacated")], F.sum(F.when(F.col("content_key").isNull(), -1).otherwise(0)).alias("less"))
    spans = hist.intervals(history)
    ends = spans.groupBy(F.col("retired_at").alias("effective_at")).agg(F.count("*").alias("ended"))
    starts = spans.groupBy("effective_at").agg(F.count("*").alias("begun"))
    met = per.join(starts, "effective_at", "left").join(ends, "effective_at", "left").na.fill(0, ["begun", "ended"])
    w = W.orderBy("effective_at").rowsBetween(W.unboundedPreceding, 0)  # one row per revision
    return met.select("revision", "effective_at", "added", "edited", "moved", "dropped", "vacated", F.sum(F.col("begun") - F.col("ended")).over(w).alias("live_slots"))


def near_copies(segments: DataFrame, least: int = 3, longer_than: int = 20) -> DataFrame:
    """(a, b, shared, keys_a, keys_b): pairs of documents, a < b, that share `least` keys
    of lines longer than so many characters, or more.

    Two documents that share that many keys share one that is not among the least - 1 most
    frequent of either; so these are left out of the join, and what is on every page makes
    no pairs unless a page has nothing else. Candidates are verified on their whole sets."""
    keys = segments.where(F.length("body") > longer_than).select("doc_id", "content_key").distinct()
    often = keys.groupBy("content_key").agg(F.count("*").alias("n"))
    ranked = keys.join(often, "content_key").where("n > 1")
    sets = ranked.groupBy("doc_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("n", "content_key"))), lambda x: x["content_key"]).alias("rare"))
    sets = sets.where(F.size("rare") >= least)
    probe = sets.select("doc_id", F.explode(F.slice("rare", F.lit(1), F.size("rare") - (least - 1))).alias("content_key"))
    pairs = probe.withColumnRenamed("doc_id", "a").join(probe.withColumnRenamed("doc_id", "b"), "content_key").where("a < b").select("a", "b").distinct()
    total = keys.groupBy("doc_id").agg(F.count("*").alias("n"))
    of = lambda c: sets.join(total, "doc_id").select(F.col("doc_id").alias(c), F.col("rare").alias(f"rare_{c}"), F.col("n").alias(f"keys_{c}"))
    met = pairs.join(of("a"), "a").join(of("b"), "b").withColumn("shared", F.size(F.array_intersect("rare_a", "rare_b")).cast("long"))
    return met.where(F.col("shared") >= least).select("a", "b", "shared", "keys_a", "keys_b")
