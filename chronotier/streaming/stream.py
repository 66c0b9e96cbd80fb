"""Document versions as a stream, through the diff into both tiers."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from chronotier.functions import fingerprint, segment
from chronotier.operators import diff, history as hist
from chronotier.operators.commit import Store

SCHEMA = "doc_id long, revision long, effective_at long, text string, gone boolean"


def ingest_batch(store: Store, versions: DataFrame, batch_id: str) -> None:
    """One batch of versions. Several versions of a document in one batch are taken in
    order of time, one commit each, so that every state enters the history."""
    order = W.partitionBy("doc_id").orderBy("effective_at", "revision")
    versions = versions.dropDuplicates(["doc_id", "revision"]).withColumn("turn", F.row_number().over(order)).persist()
    last = versions.agg(F.max("turn")).first()[0] or 0  # versions of one document, a small number
    for turn in range(1, last + 1):
        now = versions.where(F.col("turn") == turn)
        segs = fingerprint.with_keys(segment.split_lines(now.where("not coalesce(gone, false)")))
        ids = now.select("doc_id", "revision", "effective_at")
        known = store.live().join(ids.select("doc_id"), "doc_id", "left_semi").select("doc_id", "ordinal", "content_key")
        changes = diff.combined(known, segs, withdrawn=ids).where("op <> 'kept' and not audit").drop("audit", "needs_encoding", "moved_from")
        events = changes.join(ids, "doc_id").join(segs.select("doc_id", "ordinal", "body"), ["doc_id", "ordinal"], "left")
        cols = ["doc_id", "ordinal", "content_key", "effective_at", "revision", "op", "prior_key", "body"]
        store.publish(events.select(*cols), f"{batch_id}/{turn}")
    versions.unpersist()


def run(store: Store, source: DataFrame, checkpoint: str, **trigger):
    """Start the stream; availableNow=True replays what is there and stops. A batch
    that is delivered again is recognised by its id."""

    def each(batch: DataFrame, number: int) -> None:
        ingest_batch(store, batch, f"stream-{number}")

    return source.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


def deduplicated(source: DataFrame, ts: str = "arrived_at", late: str = "2 hours") -> DataFrame:
    """Redelivered versions go, within the watermark."""
    return source.withWatermark(ts, late).dropDuplicatesWithinWatermark(["doc_id", "revision"])


def refresh_windows(source: DataFrame, ts: str = "ts", every: str = "12 hours", late: str = "2 hours") -> DataFrame:
    """The batch baseline as a stream: the last version of a document per window."""
    w = F.window(ts, every)
    return source.withWatermark(ts, late).groupBy("doc_id", w.alias("w")).agg(F.max_by("revision", ts).alias("revision"), F.count("*").alias("updates"))


def update_rate(source: DataFrame, ts: str = "ts", span: str = "24 hours", step: str = "1 hour", late: str = "2 hours") -> DataFrame:
    return source.withWatermark(ts, late).groupBy(F.window(ts, span, step).alias("w")).agg(F.count("*").alias("updates"))


def edit_bursts(source: DataFrame, ts: str = "ts", gap: str = "6 hours", late: str = "2 hours") -> DataFrame:
    return source.withWatermark(ts, late).groupBy("doc_id", F.session_window(ts, gap).alias("s")).agg(F.count("*").alias("updates"))


def late_policy(versions: DataFrame, last_seen: DataFrame, policy: str = "splice") -> DataFrame:
    """Versions older than the document's last: reject drops them, quarantine keeps
    only them, splice lets all pass (their events enter the slot's past)."""
    met = versions.join(last_seen.select("doc_id", F.col("effective_at").alias("last_at")), "doc_id", "left")
    is_late = F.coalesce(F.col("effective_at") < F.col("last_at"), F.lit(False))
    kept = {"reject": ~is_late, "quarantine": is_late, "splice": F.lit(True)}[policy]
    return met.where(kept).drop("last_at")


def matched_queries(queries: DataFrame, updates: DataFrame, within: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """Queries with updates of the document they ask about shortly before: an interval
    join of two streams."""
    q = queries.withWatermark("asked_at", late).withColumnRenamed("doc_id", "q_doc")
    u = updates.withWatermark("ts", late)
    return q.join(u, F.expr(f"q_doc = doc_id AND ts <= asked_at AND ts >= asked_at - INTERVAL {within}"))


def replayed(history: DataFrame) -> DataFrame:
    return hist.snapshot_at(history, None)


def keyed(versions: DataFrame) -> DataFrame:
    """Versions with the ordered keys of their lines in place of the text: (doc_id,
    revision, effective_at, keys), keys null for a withdrawn document. Narrow, so it
    serves streams as well."""
    lines = F.filter(F.split("text", "\n"), lambda x: F.length(F.regexp_replace(x, segment.BLANK, "")) > 0)
    keys = F.transform(lines, lambda x: fingerprint.content_key(x))
    return versions.select("doc_id", "revision", "effective_at", F.when(~F.coalesce("gone", F.lit(False)), F.coalesce(keys, F.array().cast("array<string>"))).alias("keys"))


def slot_changes(was: list[str], now: list[str]) -> Iterator[tuple[int, str, str | None, str | None]]:
    """(ordinal, op, content_key, prior_key) of the slots that are not kept, as
    diff.combined has them, from two lists of keys."""
    old, new = set(was), set(now)
    for i in range(max(len(was), len(now))):
        a, b = was[i] if i < len(was) else None, now[i] if i < len(now) else None
        if b is not None and a != b:
            op = "moved" if b in old else "edited" if a is not None and a not in new else "added"
            yield i, op, b, a if op == "edited" else None
        elif b is None:
            yield i, "vacated" if a in new else "dropped", None, a


LEDGER_STATE = "revision long, effective_at long, keys array<string>"
LEDGER_CHANGES = "doc_id long, revision long, effective_at long, ordinal long, op string, content_key string, prior_key string"


def ledger_stream(versions: DataFrame) -> DataFrame:
    """A stream of versions (see keyed) turned into a stream of changes, with the ledger
    as keyed state: a document's last keys stay with the task that owns the document,
    so no batch reads the live tier. State holds 64 characters per live slot. Versions
    of one batch are taken in order of time; a version that is not later than the
    document's last is a redelivery or late, and gives nothing here (late_policy)."""

    def step(key, frames, state):
        import pandas as pd

        got = pd.concat(list(frames)).sort_values(["effective_at", "revision"], kind="stable")
        seen = state.get if state.exists else None
        last, was = (seen[1], seen[0]) if seen else (-(2**63), 0), list(seen[2]) if seen else []
        out = []
        for revision, at, keys in zip(got["revision"], got["effective_at"], got["keys"], strict=True):
            if (at, revision) <= last:
                continue
            now = [] if keys is None else list(keys)
            out += [(key[0], revision, at, *change) for change in slot_changes(was, now)]
            last, was = (at, revision), now
        state.update((int(last[1]), int(last[0]), was))
        yield pd.DataFrame(out, columns=["doc_id", "revision", "effective_at", "ordinal", "op", "content_key", "prior_key"])

    return versions.groupBy("doc_id").applyInPandasWithState(step, LEDGER_CHANGES, LEDGER_STATE, "append", "NoTimeout")


def changes_to(versions: DataFrame, path: str, checkpoint: str) -> None:
    """Run ledger_stream over what is there, appending the changes as Parquet."""
    ledger_stream(versions).writeStream.format("parquet").option("checkpointLocation", checkpoint).trigger(availableNow=True).start(path).awaitTermination()
