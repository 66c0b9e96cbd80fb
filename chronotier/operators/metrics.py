"""Cost and accuracy measures, each one aggregate over rows already made."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def reprocessed(encoded: DataFrame, segments: DataFrame, strategy: str, unit: str = "rows") -> DataFrame:
    """(strategy, revision, encoded, total, share) of what goes to the encoder. unit:
    rows, chars (encoded carries body) or keys (distinct keys)."""
    amount = {"rows": F.count("*"), "chars": F.sum(F.length("body")), "keys": F.count_distinct("content_key")}
    total = segments.groupBy("revision").agg((amount["chars"] if unit == "chars" else F.count("*")).alias("total"))
    sent = encoded.groupBy("revision").agg(amount[unit].alias("encoded"))
    met = total.join(sent, "revision", "left").na.fill(0, ["encoded"])
    return met.select(F.lit(strategy).alias("strategy"), "revision", "encoded", "total", F.round(F.col("encoded") / F.col("total"), 6).alias("share"))


def detection_quality(predicted: DataFrame, truth: DataFrame, on: list[str]) -> DataFrame:
    """tp, fp, fn, precision, recall and f1 of predicted places against true ones."""
    p, t = predicted.select(*on, F.lit(1).alias("p")), truth.select(*on, F.lit(1).alias("t"))
    m = p.join(t, on, "full_outer").agg(F.count_if(F.col("p").isNotNull() & F.col("t").isNotNull()).alias("tp"), F.count_if(F.col("t").isNull()).alias("fp"), F.count_if(F.col("p").isNull()).alias("fn"))
    share = lambda d: F.round(F.when(d > 0, F.col("tp") / d), 6)
    return m.select("tp", "fp", "fn", share(F.col("tp") + F.col("fp")).alias("precision"), share(F.col("tp") + F.col("fn")).alias("recall"), share(F.col("tp") + (F.col("fp") + F.col("fn")) / 2).alias("f1"))


def leakage(answers: DataFrame, asked: int, k: int, name: str) -> DataFrame:
    """answers(qid, rank, valid) of `asked` queries: rows, invalid rows, places left
    empty, and their shares."""
    got = answers.agg(F.count("*").alias("n_rows"), F.count_if(~F.col("valid")).alias("invalid"))
    return got.select(F.lit(name).alias("variant"), "n_rows", "invalid", (F.lit(asked * k) - F.col("n_rows")).alias("shortfall"))


def accuracy(answers: DataFrame, truth: DataFrame, place: list[str]) -> DataFrame:
    """Queries whose ranked places equal the truth's, of all queries with an answer."""
    order = lambda df, c: df.groupBy("qid").agg(F.array_sort(F.collect_list(F.struct("rank", *place))).alias(c))
    met = order(truth, "t").join(order(answers, "a"), "qid", "left")
    return met.agg(F.count("*").alias("queries"), F.count_if(F.col("a").eqNullSafe(F.col("t"))).alias("right"))


def recall_at_k(approximate: DataFrame, exact: DataFrame, item: str = "vec_id") -> DataFrame:
    """Shared items of each query's answers, of the exact ones."""
    met = exact.select("qid", item).join(approximate.select("qid", item, F.lit(1).alias("hit")), ["qid", item], "left")
    return met.agg(F.count("*").alias("wanted"), F.count("hit").alias("found"), F.round(F.count("hit") / F.count("*"), 6).alias("recall"))


def ndcg_at_k(answers: DataFrame, relevance: DataFrame, k: int = 10) -> DataFrame:
    """Mean NDCG and reciprocal rank; relevance(qid, item, rel), answers(qid, rank, item)."""
    w = relevance.withColumn("i", F.row_number().over(_by_rel())).where(F.col("i") <= k)
    ideal = w.groupBy("qid").agg(F.sum(F.col("rel") / F.log2(F.col("i") + 1.0)).alias("ideal"))
    met = answers.where(F.col("rank") <= k).join(relevance, ["qid", "item"])
    got = met.groupBy("qid").agg(F.sum(F.col("rel") / F.log2(F.col("rank") + 1.0)).alias("dcg"), F.min("rank").alias("first"))
    per = ideal.join(got, "qid", "left").select("qid", F.coalesce(F.col("dcg") / F.col("ideal"), F.lit(0.0)).alias("ndcg"), F.coalesce(1.0 / F.col("first"), F.lit(0.0)).alias("rr"))
    return per.agg(F.count("*").alias("queries"), F.round(F.avg("ndcg"), 6).alias("ndcg"), F.round(F.avg("rr"), 6).alias("mrr"))


def _by_rel():
    from pyspark.sql import Window as W

    return W.partitionBy("qid").orderBy(F.col("rel").desc(), "item")


def dedup_ratio(segments: DataFrame) -> DataFrame:
    return segments.agg(F.count("*").alias("slots"), F.count_distinct("content_key").alias("keys")).withColumn("ratio", F.round(F.col("slots") / F.col("keys"), 6))


def storage_rows(live: DataFrame, history: DataFrame, copies: DataFrame) -> DataFrame:
    """Rows by tier and form, and the live share of each form of history."""
    n = lambda df, name: df.agg(F.count("*").alias("n_rows")).select(F.lit(name).alias("form"), "n_rows")
    return n(live, "live").union(n(history, "event_log")).union(n(history.where("content_key is not null"), "intervals")).union(n(copies, "full_copies"))


def staleness(commits: DataFrame) -> DataFrame:
    """Longest and mean time between log and visibility of committed batches."""
    return commits.where("phase = 'COMMITTED'").agg(F.max(F.col("visible_at") - F.col("logged_at")).alias("longest"), F.avg(F.col("visible_at") - F.col("logged_at")).alias("mean"))


def tier_bytes(spark, paths: dict[str, str]) -> DataFrame:
    """(tier, bytes) of the files that lie under each path."""
    at = lambda p: spark._jvm.org.apache.hadoop.fs.Path(p)
    size = lambda p: at(p).getFileSystem(spark._jsc.hadoopConfiguration()).getContentSummary(at(p)).getLength()
    return spark.createDataFrame([(name, size(p)) for name, p in paths.items()], "tier string, bytes long")


def collision_bound(n: int) -> float:
    """log2 of the birthday bound n**2 / 2**257 for n keys."""
    return 2 * math.log2(n) - 257


def break_even(updates: float, touched: float, changed: float, encode_cost: float, queries: float, extra_latency: float) -> float:
    """What selective encoding saves less what the two tiers cost, per period."""
    return updates * (touched - changed) * encode_cost - queries * extra_latency


def work_model(rate: float, lengths: list[int]) -> dict[str, float]:
    """Expected shares that document upsert and chunk sync reprocess at an edit rate."""
    total = sum(lengths)
    upsert = sum(c * (1 - (1 - rate) ** c) for c in lengths) / total
    return {"upsert": upsert, "sync": rate, "speedup": upsert / rate}


def timed(fn: Callable, runs: int = 20) -> dict[str, float]:
    """Milliseconds of fn's runs: p50, p95, p99."""
    took = []
    for _ in range(runs):
        t = time.perf_counter()
        fn()
        took.append((time.perf_counter() - t) * 1000)
    took.sort()
    at = lambda p: took[min(len(took) - 1, math.ceil(p * len(took)) - 1)]
    return {"p50": at(0.5), "p95": at(0.95), "p99": at(0.99)}
