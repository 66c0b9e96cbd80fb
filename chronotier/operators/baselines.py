"""Baselines to compare with, as what each sends to the encoder or returns."""

from __future__ import annotations

import math
from collections.abc import Iterator
from itertools import batched

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from chronotier.functions.fingerprint import canonical
from chronotier.operators import diff, encode, history as hist, search

VERSION = ("doc_id", "revision")
#: Terms of slots whose weights are added up at once, for up to search.AT_ONCE questions.
TERMS_AT_ONCE = 20_000


def previous(segments: DataFrame) -> DataFrame:
    """Each revision's predecessor, under the later revision's number."""
    return segments.withColumn("revision", F.col("revision") + 1)


def pairs(segments: DataFrame, last: int = 5) -> tuple[DataFrame, DataFrame]:
    return previous(segments.where(F.col("revision") < last)), segments


def full_reindex(segments: DataFrame) -> DataFrame:
    """Everything of every revision."""
    return segments


def document_upsert(segments: DataFrame, only_changed: bool = True) -> DataFrame:
    """All segments of the documents that changed, or of all delivered ones."""
    if not only_changed:
        return segments
    old, new = pairs(segments)
    return new.join(diff.touched_docs(old, new, VERSION), list(VERSION), "left_semi")


def chunk_sync(segments: DataFrame) -> DataFrame:
    """Only the changed segments: rows of the combined diff that need encoding."""
    old, new = pairs(segments)
    return diff.combined(old, new, VERSION).where("needs_encoding")


def windowed_refresh(updates: DataFrame, by: list[str], ts: str = "ts", every: str = "12 hours") -> DataFrame:
    """The last update of each key in each window, visible at the window's end, with
    the number of updates it stands for and the longest and mean wait in seconds."""
    w = F.window(ts, every)
    at = F.unix_timestamp(ts)
    grouped = updates.groupBy(*by, w.alias("w")).agg(F.max(ts).alias("last_ts"), F.count("*").alias("updates"), F.min(at).alias("first_s"), F.sum(at).alias("sum_s"))
    end = F.unix_timestamp("w.end")
    return grouped.select(*by, F.unix_timestamp("w.start").alias("window_start"), "last_ts", "updates", (end - F.col("first_s")).alias("longest_wait"), (end * F.col("updates") - F.col("sum_s")).alias("total_wait"))


def last_of_window(versions: DataFrame, hours: int) -> DataFrame:
    """versions(doc_id, revision, arrived), arrived in hours: those that a refresh every so
    many hours sees, the last of each document and window, numbered from 1, with the hours
    until the refresh. hours = 0: every version at once."""
    if hours == 0:
        seen = versions.withColumn("waits", F.lit(0).cast("long"))
    else:
        window = F.floor(F.col("arrived") / hours)
        last = F.max_by(F.struct("revision", "arrived"), "revision").alias("v")
        seen = versions.groupBy("doc_id", window.alias("window")).agg(last)
        seen = seen.select("doc_id", "v.revision", "v.arrived", ((F.col("window") + 1) * hours - F.col("v.arrived")).cast("long").alias("waits"))
    return seen.withColumn("run", F.row_number().over(W.partitionBy("doc_id").orderBy("revision")).cast("long"))


#: Indexes that ignore instants: today's slots, every slot that ever was, and today's with
#: the removed.
INDEXES = {"live": "state = 'live'", "all": "true", "stale": "state in ('live', 'removed')"}


def indexed(queries: DataFrame, spans: DataFrame, k: int = 5, indexes: tuple[str, ...] = ("live", "all", "stale")) -> DataFrame:
    """(qid, t, index, rank, score, PLACE, retired_at, valid): the top k of each of INDEXES
    for queries(qid, text, t), valid saying whether a slot is so at t; index `snapshot` is
    what is valid at t, masked before ranking. One pass over spans answers for all."""
    n = len(indexes)
    each = F.explode(F.array(*[F.struct(F.lit(i).alias("i"), F.lit(name).alias("index")) for i, name in enumerate(indexes)])).alias("x")
    asked = queries.select("*", each).select((F.col("qid") * n + F.col("x.i")).alias("qid"), "text", "t", "x.index")
    free = F.col("index") != "snapshot"
    asked = asked.select("qid", "text", F.when(free, F.lit(search.NEVER)).otherwise(F.col("t")).alias("t"), F.when(free, F.lit(search.ALWAYS)).alias("until"), F.when(free, F.concat(F.lit("in_"), "index")).alias("among"))
    slots = spans.select("*", *[F.expr(where).alias(f"in_{name}") for name, where in INDEXES.items()])
    found = search.best(asked, slots, k, ("retired_at",))
    i = F.pmod("qid", F.lit(n))
    found = found.withColumn("index", F.element_at(F.array(*map(F.lit, indexes)), (i + 1).cast("int"))).withColumn("qid", F.expr(f"(qid - pmod(qid, {n})) div {n}"))
    found = found.join(F.broadcast(queries.select("qid", "t")), "qid")
    valid = (F.col("effective_at") <= F.col("t")) & (F.col("retired_at").isNull() | (F.col("retired_at") > F.col("t")))
    return found.withColumn("valid", valid)


def validated(ranked: DataFrame, k: int = 5, oversample: int = 1) -> DataFrame:
    """Filter after ranking: of the first k * oversample of each question those valid, k at
    most, ranked anew."""
    again = search.W.partitionBy("qid").orderBy("rank")
    rows = ranked.where(F.col("rank") <= k * oversample).where("valid")
    return rows.withColumn("rank", F.row_number().over(again)).where(F.col("rank") <= k)


def postfilter(queries: DataFrame, spans: DataFrame, k: int = 5, index: str = "live", oversample: int = 1, validate: bool = True) -> DataFrame:
    """Rank first, filter later: the top k * oversample of an index that ignores the
    queries' instants t, then those valid at t, if validate. spans: history with ends."""
    found = indexed(queries, spans, k * oversample, (index,)).drop("index")
    return validated(found, k, oversample) if validate else found


def memory_index(spark, slots: DataFrame, queries: DataFrame, k: int = 5):
    """Cached live slots, to be searched repeatedly: (cached, answer function)."""
    cached = slots.persist()
    cached.count()
    return cached, lambda q: search.live(q, cached, k)


def single_tier(history: DataFrame) -> DataFrame:
    """All rows that ever held a key, as one index would hold them."""
    return history.where("content_key is not null")


def keyword(queries: DataFrame, slots: DataFrame, k: int = 5) -> DataFrame:
    """Term overlap weighted by inverse document frequency, over the different keys of
    slots. Only terms of questions count: a first pass finds how many keys hold each, where
    a row per key is shuffled with the numbers of its terms; a second scores slots against
    all questions within tasks, which keep the k best. No row per question and slot, or per
    slot and term, is made."""
    words = F.array_distinct(F.split(canonical(F.col("text")), encode.SEPARATOR))
    asked = [(r["qid"], [w for w in r["words"] or () if w]) for r in queries.select("qid", words.alias("words")).collect()]
    number = {w: i for i, w in enumerate(sorted({w for _, ws in asked for w in ws}))}
    if not number:
        asked, number = [], {"": 0}
    spark, rows = slots.sparkSession, slots.where("content_key is not null")
    known = spark.sparkContext.broadcast(number)

    def places(body: bytes | None, find, known=known) -> list[int]:
        got = known.value
        return sorted({got[w] for w in find(body.decode("utf-8", "replace").lower()) if w in got}) if body else []

    def terms(batches: Iterator) -> Iterator:
        import pyarrow as pa

        find = encode.Coder().words
        for b in batches:
            found = {}
            for key, body in zip(b.column(0).to_pylist(), b.column(1).cast(pa.binary()).to_pylist(), strict=True):
                if key not in found:
                    found[key] = places(body, find)
            yield pa.RecordBatch.from_arrays([pa.array(found, pa.string()), pa.array(found.values(), pa.list_(pa.int32()))], names=["content_key", "terms"])

    keys = rows.select("content_key", "body").mapInArrow(terms, "content_key string, terms array<int>")
    keys = keys.groupBy("content_key").agg(F.first("terms").alias("terms"))
    held = keys.select(F.explode(F.concat(F.array(F.lit(-1)), "terms")).alias("term")).groupBy("term").agg(F.count("*").alias("n"))  # -1: each key
    count = {r["term"]: r["n"] for r in held.collect()}  # a row per term of the questions
    shared = spark.sparkContext.broadcast((asked, {i: math.log((count.get(-1, 0) + 1.0) / (count.get(i, 0) + 1.0)) for i in number.values()}))
    keep = ["doc_id", "ordinal", "content_key", "effective_at", "revision"]

    def score(batches: Iterator) -> Iterator:
        import numpy as np
        import pyarrow as pa

        (asked, idf), find, kept, sets = shared.value, encode.Coder().words, search.Kept(k), []
        for part in batched(asked, search.AT_ONCE):
            has = np.zeros((len(known.value), len(part)), bool)
            for j, (_, ws) in enumerate(part):
                has[[known.value[w] for w in ws], j] = True
            weight = np.array([idf[i] for i in range(len(has))])
            sets.append((np.array([q for q, _ in part], np.int64), has, has * weight[:, None], np.full(len(part), -np.inf)))
        for batch in (b.slice(i, search.SLOTS_AT_ONCE) for b in batches for i in range(0, len(b), search.SLOTS_AT_ONCE)):
            different = batch.column(5).cast(pa.binary()).dictionary_encode("encode")
            found = [places(x, find) for x in different.dictionary.to_pylist()]
            full = np.array([i for i, x in enumerate(found) if x], np.int64)
            if not len(full):
                continue
            size = np.array([len(found[i]) for i in full])
            runs = np.split(full, np.flatnonzero(np.diff(np.cumsum(size) // TERMS_AT_ONCE)) + 1)
            table, which = pa.Table.from_batches([batch]).select(keep), different.indices.to_numpy()
            order = search._order(table)
            for ids, has, weight, least in sets:
                scores = np.full((len(ids), len(found)), -np.inf)
                for some in runs:
                    flat, start = np.concatenate([found[i] for i in some]), np.cumsum([0, *(len(found[i]) for i in some[:-1])])
                    met = np.logical_or.reduceat(has[flat], start)
                    scores[:, some] = np.where(met, np.round(np.add.reduceat(weight[flat], start), 6), -np.inf).T
                kept.add(table, order, scores[:, which], ids, least)
        yield from kept.batches()

    schema = "qid long, score double, doc_id long, ordinal long, content_key string, effective_at long, revision long"
    return search.rank(rows.select(*keep, "body").mapInArrow(score, schema), k).select("qid", "rank", "score", "doc_id", "ordinal")
