"""Commit protocol, recovery and streaming replay."""

import pytest

from chronotier.operators import history as hist
from chronotier.operators.commit import POINTS, Fault, Store
from chronotier.streaming import stream

EVENTS = "doc_id long, ordinal long, content_key string, effective_at long, revision long, op string, prior_key string, body string"


def batches(spark):
    one = spark.createDataFrame([(1, 0, "a", 100, 1, "added", None, "x"), (1, 1, "b", 100, 1, "added", None, "y")], EVENTS)
    two = spark.createDataFrame([(1, 0, "c", 200, 2, "edited", "a", "z"), (1, 1, None, 200, 2, "dropped", "b", None)], EVENTS)
    return one, two


def state(store):
    return sorted((r["doc_id"], r["ordinal"], r["content_key"]) for r in store.live().collect()), sorted((r["ordinal"], r["revision"]) for r in store.history().collect())


@pytest.mark.parametrize("point", POINTS)
def test_no_update_is_lost(spark, tmp_path, point):
    one, two = batches(spark)
    store = Store(spark, f"file://{tmp_path}/s")
    store.publish(one, "b1")
    store.fault = point
    with pytest.raises(Fault):
        store.publish(two, "b2")
    assert len(store.history().collect()) == 2  # readers see nothing of the open commit
    store.reconcile("forward")
    store.publish(two, "b2")
    assert state(store) == ([(1, 0, "c")], [(0, 1), (0, 2), (1, 1), (1, 2)])
    assert not store._names("tmp")
    assert all(c.phase == "COMMITTED" for c in store.commits())
    store.publish(two, "b2")
    assert len(store.commits()) == 2


@pytest.mark.parametrize("mode", ["forward", "back"])
def test_failing_live_tier_is_flagged(spark, tmp_path, mode):
    one, two = batches(spark)
    store = Store(spark, f"file://{tmp_path}/s")
    store.publish(one, "b1")
    before, store.failing = state(store), OSError("no space")
    with pytest.raises(OSError):
        store.publish(two, "b2")
    assert [(c.phase, c.error) for c in store.commits()] == [("COMMITTED", None), ("UNCOMMITTED", "no space")]
    assert state(store) == before and store.history(committed_only=False).count() == 4
    assert store.reconcile(mode) == 1
    store.publish(two, "b2")
    assert state(store)[0] == [(1, 0, "c")] and store.commits()[-1].phase == "COMMITTED"


def test_untouched_buckets_are_not_written(spark, tmp_path):
    rows = [(d, 0, f"k{d}", 100, 1, "added", None, "x") for d in range(200)]
    store = Store(spark, f"file://{tmp_path}/s", buckets=16)
    store.publish(spark.createDataFrame(rows, EVENTS), "b1")
    before = store._pointer()["folders"]
    store.publish(spark.createDataFrame([(7, 0, "new", 200, 2, "edited", "k7", "y")], EVENTS), "b2")
    after = store._pointer()["folders"]
    assert len(before) == 16 and sum(before[b] != after[b] for b in after) == 1
    assert store.live().count() == 200 and store.live().where("doc_id = 7").first()["content_key"] == "new"
    gone = [(d, 0, None, 300, 3, "dropped", f"k{d}", None) for d in range(200) if d != 7]
    store.publish(spark.createDataFrame(gone, EVENTS), "b3")
    assert [r["doc_id"] for r in store.live().collect()] == [7]


def test_roll_back_then_retry(spark, tmp_path):
    one, two = batches(spark)
    store = Store(spark, f"file://{tmp_path}/s", fault="after_log")
    with pytest.raises(Fault):
        store.publish(one, "b1")
    assert store.reconcile("back") == 1 and store.live().count() == 0
    store.publish(one, "b1")
    assert state(store)[0] == [(1, 0, "a"), (1, 1, "b")]


def test_stream_replay_equals_batch(spark, tmp_path):
    rows = [(1, 1, 100, "a\nb", False), (2, 1, 100, "c", False), (1, 2, 200, "a\nC", False), (2, 2, 200, None, True)]
    for i, r in enumerate(rows):
        spark.createDataFrame([r], stream.SCHEMA).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
    source = spark.readStream.schema(stream.SCHEMA).parquet(f"{tmp_path}/in")
    streamed = Store(spark, f"file://{tmp_path}/s")
    stream.run(streamed, source, f"{tmp_path}/cp").awaitTermination()
    batch = Store(spark, f"file://{tmp_path}/b")
    stream.ingest_batch(batch, spark.createDataFrame(rows, stream.SCHEMA), "all")
    assert state(streamed) == state(batch)
    now = sorted((r["doc_id"], r["body"]) for r in hist.snapshot_at(streamed.history(), None).collect())
    assert now == [(1, "C"), (1, "a")]


def test_streaming_ledger_equals_the_batch_diff(spark, tmp_path):
    from chronotier.functions import fingerprint, segment
    from chronotier.operators import diff

    texts = {1: ["a\nb\nc", "x\na\nb\nc", "x\nb\nB!\n\nb", None, "c"], 2: ["p\nq", "q\np", "q", "q\nq", ""]}
    rows = [(d, v + 1, 100 * v, t, t is None) for d, ts in texts.items() for v, t in enumerate(ts)]
    for part in (rows[:3] + rows[5:7], rows[3:5] + rows[6:], rows[:2]):  # with redelivered versions
        spark.createDataFrame(part, stream.SCHEMA).coalesce(1).write.mode("append").parquet(f"{tmp_path}/in")
        source = stream.keyed(spark.readStream.schema(stream.SCHEMA).parquet(f"{tmp_path}/in"))
        stream.changes_to(source, f"{tmp_path}/out", f"{tmp_path}/cp")
    cols = ["doc_id", "revision", "ordinal", "op", "content_key", "prior_key"]
    got = spark.read.parquet(f"{tmp_path}/out").select(*cols)
    segs = fingerprint.with_keys(segment.split_lines(spark.createDataFrame(rows, stream.SCHEMA)))
    old = segs.withColumn("revision", segs.revision + 1).where("revision <= 5")
    by = ("doc_id", "revision")
    want = diff.combined(old, segs, by, old.select(*by).distinct()).where("op <> 'kept' and not audit").select(*cols)
    assert sorted(map(repr, got.collect())) == sorted(map(repr, want.collect()))
