"""Streaming operators against their batch results, on files read as a stream."""

import datetime as dt

import pytest
from pyspark.sql import functions as F

from chronotier.streaming import stream

T0 = dt.datetime(2024, 1, 1)


def at(hours):
    return T0 + dt.timedelta(hours=hours)


def replay(spark, df_parts, schema, tmp_path, make, name, mode="append"):
    """Rows of a query over parts that arrive one file after another."""
    for part in df_parts:
        spark.createDataFrame(part, schema).coalesce(1).write.mode("append").parquet(f"{tmp_path}/{name}-in")
    source = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/{name}-in")
    q = make(source).writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", f"{tmp_path}/{name}-cp").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name).collect()


UPDATES = "doc_id long, revision long, ts timestamp"
ROWS = [(d, r, at(5 * r + d)) for d in (1, 2) for r in range(8)]
FLUSH = [(9, 0, at(500))]  # moves the watermark past all windows


def test_redelivered_versions_go_within_the_watermark(spark, tmp_path):
    schema = "doc_id long, revision long, arrived_at timestamp"
    rows = [(1, 1, at(0)), (1, 2, at(1)), (2, 1, at(1))]
    got = replay(spark, [rows, [(1, 1, at(1)), (1, 3, at(2))], rows], schema, tmp_path, stream.deduplicated, "dedup")
    assert sorted((r["doc_id"], r["revision"]) for r in got) == [(1, 1), (1, 2), (1, 3), (2, 1)]


def test_refresh_windows_equal_batch(spark, tmp_path):
    got = replay(spark, [ROWS[:8], ROWS[8:], FLUSH], UPDATES, tmp_path, stream.refresh_windows, "refresh")
    df = spark.createDataFrame(ROWS, UPDATES)
    want = df.groupBy("doc_id", F.window("ts", "12 hours").alias("w")).agg(F.max_by("revision", "ts").alias("revision"), F.count("*").alias("updates")).collect()
    key = lambda r: (r["doc_id"], r["w"]["start"], r["revision"], r["updates"])
    assert sorted(map(key, got)) == sorted(map(key, want))


def test_rates_and_bursts_equal_batch(spark, tmp_path):
    df = spark.createDataFrame(ROWS, UPDATES)
    got = replay(spark, [ROWS, FLUSH], UPDATES, tmp_path, stream.update_rate, "rate")
    want = df.groupBy(F.window("ts", "24 hours", "1 hour").alias("w")).agg(F.count("*").alias("updates")).collect()
    assert sorted((r["w"]["start"], r["updates"]) for r in got) == sorted((r["w"]["start"], r["updates"]) for r in want)
    got = replay(spark, [ROWS, FLUSH], UPDATES, tmp_path, lambda s: stream.edit_bursts(s, gap="4 hours"), "bursts")
    assert sorted((r["doc_id"], r["updates"]) for r in got) == sorted([(1, 1)] * 8 + [(2, 1)] * 8)


def test_late_rows_beyond_the_watermark_go(spark, tmp_path):
    # A batch is judged by the watermark of the one before the last; the fourth is 39 hours late.
    parts = [[(1, 1, at(0))], [(1, 2, at(40))], [(3, 1, at(40))], [(1, 3, at(1))], FLUSH]
    got = replay(spark, parts, UPDATES, tmp_path, stream.refresh_windows, "late")
    assert sorted((r["doc_id"], r["revision"]) for r in got) == [(1, 1), (1, 2), (3, 1)]


@pytest.mark.parametrize(("policy", "kept"), [("reject", [2]), ("quarantine", [1]), ("splice", [1, 2])])
def test_late_policy(spark, policy, kept):
    versions = spark.createDataFrame([(1, 1, 50), (1, 2, 150), (2, 2, 1)], "doc_id long, revision long, effective_at long").where("doc_id = 1")
    seen = spark.createDataFrame([(1, 100)], "doc_id long, effective_at long")
    assert sorted(r["revision"] for r in stream.late_policy(versions, seen, policy).collect()) == kept


def test_questions_meet_recent_updates(spark, tmp_path):
    asked = "qid long, doc_id long, asked_at timestamp"
    spark.createDataFrame([(1, 1, at(10)), (2, 1, at(30)), (3, 2, at(10))], asked).coalesce(1).write.parquet(f"{tmp_path}/q")
    spark.createDataFrame([(1, 1, at(9.5)), (1, 2, at(20)), (2, 1, at(10.5))], UPDATES).coalesce(1).write.parquet(f"{tmp_path}/u")
    met = stream.matched_queries(spark.readStream.schema(asked).parquet(f"{tmp_path}/q"), spark.readStream.schema(UPDATES).parquet(f"{tmp_path}/u"))
    met.writeStream.format("memory").queryName("matched").option("checkpointLocation", f"{tmp_path}/cp").trigger(availableNow=True).start().awaitTermination()
    assert [(r["qid"], r["revision"]) for r in spark.table("matched").collect()] == [(1, 1)]
