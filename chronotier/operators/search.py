"""Search by similarity: live, at an instant, over a range. The validity of a slot is
always decided below the ranking, so no answer holds anything from another time.

Rows of slots carry their hashed terms (codes), or tasks make them on the way. Questions
are few against them: they travel in broadcast blocks, each task multiplies its rows
with them as matrices and keeps the k best of each question, and only those meet.
So nothing is shuffled but k rows a question and task, however common a line is.
Ranks follow score descending, then doc_id and ordinal, then effective_at.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import cache
from itertools import batched

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from chronotier.operators import encode, history as hist

#: Questions to a broadcast, and to a matrix; slots to a matrix.
MAX_QUERIES, AT_ONCE, SLOTS_AT_ONCE = 100_000, 512, 4096
PLACE = ["doc_id", "ordinal", "content_key", "effective_at", "revision"]


def coded(df: DataFrame, text: str) -> DataFrame:
    """df with its hashed terms, as stored or made from text."""
    return df if "codes" in df.columns else df.withColumn("codes", encode.codes(F.col(text)))


#: What a question may say of the slots that it ranks: see best.
TERMS = {"t": "long", "until": "long", "ended": "boolean", "among": "string"}
NEVER, ALWAYS = -(2**63), 2**63 - 1


def _blocks(queries: DataFrame) -> list[list]:
    """All questions as lists of (qid, codes, *TERMS), MAX_QUERIES in each."""
    terms = [(F.col(c) if c in queries.columns else F.lit(None)).cast(kind).alias(c) for c, kind in TERMS.items()]
    return [[tuple(r) for r in b] for b in batched(coded(queries, "text").select("qid", "codes", *terms).toLocalIterator(), MAX_QUERIES)]


def _first(scores, order, k: int):
    """The places of the k greatest of scores, ties in the given order."""
    import numpy as np

    cut = np.partition(scores, len(scores) - k)[len(scores) - k] if len(scores) > k else -np.inf
    some = np.flatnonzero((scores >= cut) & (scores > -np.inf))
    return some[np.lexsort((order[some], -scores[some]))[:k]]


def _order(table):
    """The rank of each slot by place."""
    import numpy as np

    order = np.empty(len(table), np.int64)
    order[np.lexsort([table.column(c).to_numpy() for c in ("effective_at", "ordinal", "doc_id")])] = np.arange(len(table))
    return order


class Kept:
    """The k best slots of each question that a task has met, as tables with qid and score."""

    def __init__(self, k: int):
        self.k, self.held, self.n = k, [], 0

    def add(self, table, order, scores, ids, least) -> None:
        """scores by question and row of table, -inf where a row is no answer; least by
        question: k slots seen before are no worse, so what is below it is no answer."""
        import numpy as np
        import pyarrow as pa

        some, found = (scores >= least[:, None]) & (scores > -np.inf), []
        for i in np.flatnonzero(some.any(1)):
            place = np.flatnonzero(some[i])
            place = place[_first(scores[i, place], order[place], self.k)]
            if len(place) == self.k:
                least[i] = max(least[i], scores[i, place[-1]])
            found.append((i, place))
        if found:
            where = np.concatenate([p for _, p in found])
            which = np.repeat(np.array([i for i, _ in found], np.int64), [len(p) for _, p in found])
            self.held.append(table.take(where).add_column(0, "score", pa.array(scores[which, where])).add_column(0, "qid", pa.array(ids[which])))
            self.n += len(where)
        if self.n > 200_000 or len(self.held) > 2_000:
            self.held = [self._settled()]
            self.n = len(self.held[0])

    def _settled(self):
        import numpy as np
        import pyarrow as pa

        table = pa.concat_tables(self.held)
        cols = [table.column(c).to_numpy() for c in ("effective_at", "ordinal", "doc_id", "score", "qid")]
        order = np.lexsort((*cols[:3], -cols[3], cols[4]))
        ids = cols[4][order]
        return table.take(order[np.arange(len(ids)) - np.searchsorted(ids, ids) < self.k])

    def batches(self) -> list:
        return self._settled().to_batches() if self.held else []


def _product(q, x):
    """q @ x.T of whole numbers, exact; in single precision where that holds it."""
    import numpy as np

    small = np.abs(q).max(initial=0) * np.abs(x).sum(1).max(initial=0) < 1 << 24
    return (q.astype(np.float32) @ x.astype(np.float32).T).astype(np.float64) if small else q @ x.T


def _texts(column, coder: encode.Coder) -> tuple[list, object]:
    """Codes of the different texts of an Arrow array, and which of them each row has; or
    the codes that it holds."""
    import numpy as np
    import pyarrow as pa

    if pa.types.is_list(column.type):
        return [c or () for c in column.to_pylist()], np.arange(len(column))
    different = column.cast(pa.binary()).dictionary_encode("encode")
    return [coder.codes(c) for c in different.dictionary.to_pylist()], different.indices.to_numpy()


@cache
def _coder() -> encode.Coder:
    """The terms that this worker has met in closeness."""
    return encode.Coder()


def closeness(texts, questions):
    """For SQL, as an Arrow UDF: the cosine of the hashed terms of each text (or the codes
    that are stored for it) and the question beside it; null if they share none."""
    import numpy as np
    import pyarrow as pa

    out, coder = [pa.array([], pa.float64())], _coder()
    for i in range(0, len(texts), SLOTS_AT_ONCE):
        codes, which_text = _texts(texts.slice(i, SLOTS_AT_ONCE), coder)
        asked, which = _texts(questions.slice(i, SLOTS_AT_ONCE), coder)
        x, q, scores = encode.matrix(codes), encode.matrix(asked), np.zeros(len(which))
        norms, shared = (x * x).sum(1), np.zeros(len(which), bool)
        for j in range(len(q)):
            rows, terms = np.flatnonzero(which == j), np.flatnonzero(q[j])
            mine, own = np.unique(which_text[rows], return_inverse=True)
            part = x[np.ix_(mine, terms)]
            scale = np.sqrt(norms[mine] * (q[j] * q[j]).sum())
            scores[rows] = (part @ q[j, terms] / np.where(scale > 0, scale, 1))[own]
            shared[rows] = (part != 0).any(1)[own]
        out.append(pa.array(scores, mask=~shared))
    return pa.concat_arrays(out)


def best(queries: DataFrame, slots: DataFrame, k: int = 5, extra: tuple[str, ...] = ()) -> DataFrame:
    """(qid, rank, score, PLACE, extra) of the first k slots of each question that share
    a hashed term with it. queries(qid, text) may have further columns, a null saying
    nothing but in t: an instant t, at which a slot must be valid; with until, at any moment
    of [t, until); ended: the slot has an end; among: the name of a column of slots that must
    be true. For t, until and ended slots need retired_at. extra: further columns of slots
    to keep. Questions of all sorts are answered in one pass over slots; hashed terms that
    slots do not carry are made within it, once for equal texts of a batch."""
    blocks = _blocks(queries)
    by_instant, by_end = "t" in queries.columns, "ended" in queries.columns
    flags = sorted({r[-1] for b in blocks for r in b} - {None})
    shared = [queries.sparkSession.sparkContext.broadcast(b) for b in blocks]
    keep = [*PLACE, *extra, *(["retired_at"] if (by_instant or by_end) and "retired_at" not in extra else [])]
    text = "codes" if "codes" in slots.columns else "body"
    rows = slots.where("content_key is not null").select(*keep, *[F.col(c).alias(f"among_{c}") for c in flags], F.col(text).alias("asked_text"))
    schema = ", ".join(["qid long", "score double", *(f"{c} {rows.schema[c].dataType.simpleString()}" for c in keep)])

    def run(batches: Iterator) -> Iterator:
        import numpy as np
        import pyarrow as pa

        sets, coder = [], encode.Coder()
        for b in shared:
            for part in batched(b.value, AT_ONCE):
                ids, codes, t, until, ended, among = zip(*part, strict=True)
                q = encode.matrix([c or () for c in codes])
                first = np.array([NEVER if i is None else i for i in t])[:, None]
                last = np.array([NEVER if i is None else i if u is None else u - 1 for i, u in zip(t, until, strict=True)])[:, None]
                sets.append((np.array(ids, np.int64), q, (q != 0).astype(np.float32), (q * q).sum(1), first, last, np.array([bool(e) for e in ended]), among, np.full(len(ids), -np.inf)))
        kept = Kept(k)
        for batch in (b.slice(i, SLOTS_AT_ONCE) for b in batches for i in range(0, len(b), SLOTS_AT_ONCE)):
            table = pa.Table.from_batches([batch])
            codes, which_text = _texts(batch.column(batch.schema.names.index("asked_text")), coder)
            order, since = _order(table), table.column("effective_at").to_numpy()
            x = encode.matrix(codes)
            norms, has = (x * x).sum(1), (x != 0).astype(np.float32).T
            if by_instant or by_end:
                ends = table.column("retired_at").fill_null(ALWAYS).to_numpy()
            flag = {c: table.column(f"among_{c}").fill_null(False).to_numpy() for c in flags}
            table = table.select(keep)
            for ids, q, q_has, q_norms, first, last, ended, among, least in sets:
                scale = np.sqrt(np.outer(q_norms, norms))
                scores = np.where(q_has @ has > 0, np.round(_product(q, x) / np.where(scale > 0, scale, 1), 6), -np.inf)[:, which_text]
                if by_instant:
                    scores[(since[None] > last) | (ends[None] <= first)] = -np.inf
                if by_end:
                    scores[ended[:, None] & (ends[None] == ALWAYS)] = -np.inf
                for c in flags:
                    scores[np.array([a == c for a in among])[:, None] & ~flag[c][None]] = -np.inf
                kept.add(table, order, scores, ids, least)
        yield from kept.batches()

    return rank(rows.mapInArrow(run, schema), k).select("qid", "rank", "score", *keep)


def rank(scored: DataFrame, k: int = 5) -> DataFrame:
    """The first k slots of each query."""
    w = W.partitionBy("qid").orderBy(F.col("score").desc(), "doc_id", "ordinal", "effective_at")
    return scored.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def _answer(queries: DataFrame, slots: DataFrame, k: int, tier: str) -> DataFrame:
    return best(queries.drop("t"), slots, k).withColumn("tier", F.lit(tier))


def live(queries: DataFrame, slots: DataFrame, k: int = 5, where=None) -> DataFrame:
    """Top-k of the live slots; where: a predicate on them, applied before ranking."""
    return _answer(queries, slots if where is None else slots.where(where), k, "hot")


def at(queries: DataFrame, history: DataFrame, t: int, k: int = 5, as_known_at: int | None = None, where=None) -> DataFrame:
    """Top-k of what was valid at t (and known by commit as_known_at); history as
    events, or with ends."""
    slots = hist.snapshot_at(history, t, as_known_at)
    return _answer(queries, slots if where is None else slots.where(where), k, "cold")


def at_each(queries: DataFrame, spans: DataFrame, k: int = 5) -> DataFrame:
    """Each query (qid, text, t) at its own instant, which masks the scores of slots
    that were not valid then before any is chosen."""
    return best(queries, spans, k).join(F.broadcast(queries.select("qid", "t")), "qid").select("qid", "t", "rank", "score", *PLACE)


def between(queries: DataFrame, history: DataFrame, t1: int, t2: int, k: int = 5, mode: str = "side_by_side") -> DataFrame:
    """Over [t1, t2): side_by_side compares the answers at both ends (fate: stayed,
    reworded, entered, left), any_time ranks what was valid at any moment, delta ranks
    the events of the range."""
    if t1 > t2:
        raise ValueError("t1 is after t2")
    if mode == "side_by_side":
        cols = ["rank", "score", "content_key"]
        a, b = (at(queries, history, t, k).select("qid", "doc_id", "ordinal", *[F.col(c).alias(f"{c}_{s}") for c in cols]) for t, s in ((t1, "from"), (max(t1, t2 - 1), "to")))
        met = a.join(b, ["qid", "doc_id", "ordinal"], "full_outer")
        fate = F.when(F.col("rank_from").isNull(), "entered").when(F.col("rank_to").isNull(), "left").when(F.col("content_key_from") == F.col("content_key_to"), "stayed").otherwise("reworded")
        return met.select("qid", "doc_id", "ordinal", "rank_from", "rank_to", "score_from", "score_to", fate.alias("fate"))
    if mode == "any_time":
        spans = history if "retired_at" in history.columns else hist.intervals(history)
        return _answer(queries, hist.valid_between(spans, t1, t2), k, "both")
    events = history.where((F.col("effective_at") >= t1) & (F.col("effective_at") < t2))
    found = best(queries.drop("t"), events, k, ("op", "prior_key"))
    return found.select("qid", "rank", "score", "doc_id", "ordinal", "effective_at", "op", "prior_key")


def with_bodies(answers: DataFrame, slots: DataFrame) -> DataFrame:
    """Answers with their texts, and the end of their validity (null while they are
    valid) if slots know it, fetched for these rows only."""
    found = [c for c in ("body", "retired_at") if c in slots.columns]
    return answers.join(slots.select("doc_id", "ordinal", "effective_at", *found), ["doc_id", "ordinal", "effective_at"])
