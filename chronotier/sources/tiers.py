"""The workload's tables as a deployment would hold them: written once per session and
input, read afterwards.

segments, changes, log (all events with their ends, by month), live_terms (live with hashed
terms in place of texts) and graphs (the index over live) are written; events, spans (events that hold a key) and live
(spans without an end) are selections from the log. The log is made in one pass over
`documents` that shuffles no texts.
Queries read these instead of deriving five revisions each time, so that a snapshot is
a filter on a scan, and months after the asked instant are not opened."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from chronotier.operators import baselines, diff, history as hist
from chronotier.operators.ann import live as live_index
from chronotier.sources import scratch, workload

VERSION = ("doc_id", "revision")
#: (application, input, name) to where it lies and its schema.
_WRITTEN: dict[tuple[str, str, str], tuple[str, object]] = {}


def _there(spark: SparkSession, sf_dir: str, name: str) -> bool:
    """Has this session written the named table, and is its folder still there?"""
    path, _ = _WRITTEN.get((spark.sparkContext.applicationId, sf_dir, name), ("", None))
    if not path:
        return False
    done = spark._jvm.org.apache.hadoop.fs.Path(f"{path}/_SUCCESS")
    return done.getFileSystem(spark._jsc.hadoopConfiguration()).exists(done)


def kept(spark: SparkSession, sf_dir: str, name: str, make: Callable[[], DataFrame], by_month: bool = False) -> DataFrame:
    """The named table, made and written if this session has not yet, or if the folder is gone."""
    at = (spark.sparkContext.applicationId, sf_dir, name)
    if not _there(spark, sf_dir, name):
        df = make()
        path = scratch.folder(spark, name.replace("/", "-"))
        if by_month:
            hist.write(df, path, dealt=True)
        else:
            df.write.parquet(path)
        schema = T.StructType([*df.schema.fields, T.StructField("month", T.StringType())]) if by_month else df.schema
        _WRITTEN[at] = path, schema
    path, schema = _WRITTEN[at]
    return spark.read.schema(schema).parquet(path)


def path_of(spark: SparkSession, sf_dir: str, name: str) -> str:
    """Where a kept table lies."""
    return _WRITTEN[spark.sparkContext.applicationId, sf_dir, name][0]


def segments(spark: SparkSession, sf_dir: str, profile: str = "structural") -> DataFrame:
    return kept(spark, sf_dir, f"segments/{profile}", lambda: workload.segments(spark, sf_dir, profile))


def diffed(segs: DataFrame, how=diff.combined) -> DataFrame:
    """Every revision against the one before; a document that is empty now is dropped."""
    old, new = baselines.pairs(segs)
    return how(old, new, VERSION, old.select(*VERSION).distinct())


def changes(spark: SparkSession, sf_dir: str, profile: str = "structural") -> DataFrame:
    return kept(spark, sf_dir, f"changes/{profile}", lambda: diffed(segments(spark, sf_dir, profile)))


def made_log(spark: SparkSession, sf_dir: str, profile: str = "structural") -> DataFrame:
    """The log with ends as one narrow pass over `documents`, not written: for what reads it
    once or twice."""
    return hist.folded(*workload.keyed(spark, sf_dir, profile))


def _of_log(log: DataFrame, name: str) -> DataFrame:
    month = [c for c in ("month",) if c in log.columns]
    if name == "events":
        return log.select("doc_id", "ordinal", "content_key", "effective_at", "revision", "op", "prior_key", "body", F.col("revision").alias("commit_seq"), *month)
    held = log.where("content_key is not null")
    if name == "spans":
        return held
    return held.where("retired_at is null").select("doc_id", "ordinal", "content_key", "body", "effective_at", "revision")


def log(spark: SparkSession, sf_dir: str, profile: str = "structural", once: bool = False) -> DataFrame:
    """The log with ends, written. once: for what reads it once or twice, which takes it as
    written if it is, and else makes it on the way and stores it nowhere: that costs about
    what writing and reading it back does, and no disk."""
    if once and not _there(spark, sf_dir, f"log/{profile}"):
        return made_log(spark, sf_dir, profile)
    return kept(spark, sf_dir, f"log/{profile}", lambda: made_log(spark, sf_dir, profile), True)


def events(spark: SparkSession, sf_dir: str, profile: str = "structural", once: bool = False) -> DataFrame:
    return _of_log(log(spark, sf_dir, profile, once), "events")


def spans(spark: SparkSession, sf_dir: str, profile: str = "structural", once: bool = False) -> DataFrame:
    return _of_log(log(spark, sf_dir, profile, once), "spans")


def live(spark: SparkSession, sf_dir: str, profile: str = "structural", once: bool = False) -> DataFrame:
    return _of_log(log(spark, sf_dir, profile, once), "live")


def live_terms(spark: SparkSession, sf_dir: str, profile: str = "structural") -> DataFrame:
    """The live tier with hashed terms in place of texts, written: what the graphs are made
    of and what their answers meet, without the log."""
    return kept(spark, sf_dir, f"live_terms/{profile}", lambda: live_index.narrow(live(spark, sf_dir, profile, once=True)))


def graphs(spark: SparkSession, sf_dir: str, profile: str = "structural") -> DataFrame:
    return kept(spark, sf_dir, f"graphs/{profile}", lambda: live_index.build(live_terms(spark, sf_dir, profile)))
