"""The append-only history: events, derived intervals, snapshots.

An event says what a slot (doc_id, ordinal) holds from effective_at on, or that it
holds nothing (content_key null). Ends and states are derived, so a late revision
spliced into the past moves its neighbours' ends by itself.
"""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

SLOT = ["doc_id", "ordinal"]


def stamp(changes: DataFrame, bodies: DataFrame, commit_seq: int | None = None) -> DataFrame:
    """Events of the state rows that change a slot. changes and bodies carry doc_id,
    revision and ordinal; bodies also effective_at (one per revision) and body."""
    state = changes.where("op <> 'kept' and not audit")
    when = bodies.select("revision", "effective_at").distinct()
    text = bodies.select("doc_id", "revision", "ordinal", "body")
    met = state.join(F.broadcast(when), "revision").join(text, ["doc_id", "revision", "ordinal"], "left")
    out = met.select("doc_id", "ordinal", "content_key", "effective_at", "revision", "op", "prior_key", F.when(F.col("content_key").isNotNull(), F.col("body")).alias("body"))
    return out.withColumn("commit_seq", F.lit(commit_seq).cast("long") if commit_seq is not None else F.col("revision"))


def intervals(history: DataFrame) -> DataFrame:
    """Events that hold a key, with retired_at (null while live) and state."""
    w = W.partitionBy(*SLOT).orderBy("effective_at", "revision")
    after = F.lead("op").over(w)
    state = F.when(after.isNull(), "live").when(after.isin("dropped", "vacated"), "removed").otherwise("replaced")
    return history.withColumn("retired_at", F.lead("effective_at").over(w)).withColumn("state", state).where("content_key is not null")


def _seen(history: DataFrame, t: int | None, as_known_at: int | None = None) -> DataFrame:
    """Rows not after t and known by commit as_known_at; of a log that lies by month,
    only the months up to t are opened."""
    seen = history if as_known_at is None else history.where(F.col("commit_seq") <= as_known_at)
    if t is None:
        return seen
    if "month" in history.columns:
        seen = seen.where(F.col("month") <= time.strftime("%Y-%m", time.gmtime(t)))
    return seen.where(F.col("effective_at") <= t)


def snapshot_at(history: DataFrame, t: int | None, as_known_at: int | None = None) -> DataFrame:
    """Slots as of t (None: now): the last event not after t, if it holds a key. The
    time filter is below the aggregation and reaches the scan; the aggregation works
    on fixed-width columns, and the texts meet it by the same key. Of a history with
    ends (see closed), a snapshot is a filter only."""
    if "retired_at" in history.columns and as_known_at is None:
        return valid_at(history, t)
    seen = _seen(history, t, as_known_at)
    last = seen.groupBy(*SLOT).agg(F.max(F.struct("effective_at", "revision")).alias("e"))
    last = last.select(*SLOT, "e.effective_at", "e.revision")
    held = seen.join(last, [*SLOT, "effective_at", "revision"]).where("content_key is not null")
    return held.select("doc_id", "ordinal", "content_key", "body", "effective_at", "revision")


def valid_at(spans: DataFrame, t: int | None) -> DataFrame:
    """The same from intervals: effective_at <= t < retired_at, or no end. Hashed terms
    (codes) come with them if they are stored."""
    open_ended = F.col("retired_at").isNull()
    held = _seen(spans, t).where(open_ended if t is None else open_ended | (F.col("retired_at") > t))
    return held.select("doc_id", "ordinal", "content_key", "body", "effective_at", "revision", *[c for c in ("codes",) if c in spans.columns])


def valid_between(spans: DataFrame, t1: int, t2: int) -> DataFrame:
    """Valid at any moment of [t1, t2)."""
    spans = _seen(spans, t2)
    return spans.where((F.col("effective_at") < t2) & (F.col("retired_at").isNull() | (F.col("retired_at") > t1)))


def closed(history: DataFrame) -> DataFrame:
    """The form with ends, to be written where snapshots and ranges are read often: a
    late version then means writing its slots anew."""
    return intervals(history).drop("commit_seq")


LOG = "doc_id long, ordinal long, content_key string, effective_at long, revision long, op string, prior_key string, body string, retired_at long, state string"
NAMES = [c.split()[0] for c in LOG.split(", ")]
#: Events to an Arrow batch that leaves the task, and documents that are unfolded at once.
EVENTS_AT_ONCE, DOCS_AT_ONCE = 20_000, 1_000


def _nested(batch) -> Iterator:
    """(doc_id, versions) of rows (doc_id, revs)."""
    for doc, revs in zip(*(c.to_pylist() for c in batch.columns), strict=True):
        yield doc, [(r["revision"], r["effective_at"], [x["content_key"] for x in r["rows"]], [x["body"] and x["body"].encode() for x in r["rows"]]) for r in revs]


def events_of(doc: int, versions: list) -> list[list]:
    """The rows of the log (LOG) of one document from its (revision, effective_at, keys,
    bodies) in the order of effect, keys and bodies by slot."""
    out, old, last = [], [], {}
    for revision, t, new, bodies in versions:
        if new != old or None in new:
            was, now = set(old) - {None}, set(new) - {None}
            for i in range(max(len(old), len(new))):
                had, has = i < len(old), i < len(new)
                if had and has and old[i] == new[i] and new[i] is not None:
                    continue
                op = "moved" if has and new[i] in was else "edited" if had and has and old[i] not in now else "added" if has else "vacated" if old[i] in now else "dropped"
                if i in last:
                    last[i][8:] = t, "replaced" if has else "removed"
                last[i] = [doc, i, new[i] if has else None, t, revision, op, old[i] if op in ("edited", "vacated", "dropped") else None, bodies[i] if has else None, None, "live"]
                out.append(last[i])
        old = new
    return out


def folded(rows: DataFrame, unfold: Callable = _nested) -> DataFrame:
    """The log with ends (LOG, events that empty a slot included) of documents whose
    versions come together. unfold(batch) gives (doc_id, versions) of each row, as
    events_of takes them; by default rows are (doc_id, revs), revs an array of (revision,
    effective_at, rows) in the order of effect, rows an array of (content_key, body) by
    slot. The same events as diff.combined, stamp and intervals give, but a document is
    compared within its row, so nothing is shuffled or stored, and the events of a row
    leave its task one after another."""

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        kinds = {"long": pa.int64(), "string": pa.string()}
        types = [kinds[c.split()[1]] for c in LOG.split(", ")]

        def table(out):
            cols = [pa.array(x, pa.binary()).view(pa.string()) if name == "body" else pa.array(x, kind) for name, kind, x in zip(NAMES, types, zip(*out, strict=True), strict=True)]
            return pa.RecordBatch.from_arrays(cols, names=NAMES)

        for batch in (b.slice(i, DOCS_AT_ONCE) for b in batches for i in range(0, len(b), DOCS_AT_ONCE)):
            out = []
            for doc, versions in unfold(batch):
                out += events_of(doc, versions)
                if len(out) >= EVENTS_AT_ONCE:
                    yield table(out)
                    out = []
            if out:
                yield table(out)

    return rows.mapInArrow(run, LOG)


def full_copies(segments: DataFrame) -> DataFrame:
    """Every revision with all its segments: the storage baseline."""
    return segments.select("doc_id", "ordinal", "content_key", "effective_at", "revision", "body")


def write(history: DataFrame, path: str, dealt: bool = False) -> None:
    """Append, by month of effect (a string, as readers should take it); rows within
    files by slot. dealt: each task already holds whole documents, and writes its own
    files of each month, so that nothing is shuffled."""
    rows = history.withColumn("month", F.date_format(F.timestamp_seconds("effective_at"), "yyyy-MM"))
    if not dealt:
        rows = rows.repartition("month", F.pmod("doc_id", F.lit(64))).sortWithinPartitions(*SLOT)
    rows.write.mode("append").option("compression", "zstd" if dealt else "snappy").partitionBy("month").parquet(path)
