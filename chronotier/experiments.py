"""Queries of the experiments, beside those of the methods in registry: the update table,
ablations, storage, freshness, indexes behind the live tier, costs. Timings and sizes
have no SQL; all that is counted has."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronotier.functions import fingerprint, route, segment
from chronotier.operators import audit, baselines, diff, dispatch, encode, history as hist, ledger, live, metrics, search
from chronotier.operators.ann import index
from chronotier.operators.ann import live as live_index
from chronotier.plans.guard import assert_guard
from chronotier.registry import _ASKED, _BENCH, _GOOD, _ORDER, _PICK, _TOP, CH, HI, LIVE, NOW, S, ST, T3, VERSION, _benchmark, _changes, _history, _live, _scored, _segments, _spans, _vectors, _sparse_sql, query
from chronotier.sources import tiers, workload
from chronotier.sources import workload_sql as sql
from chronotier.sources.tables import load
from chronotier.sources.workload import INSTANTS

# The update table: what each strategy sends, and what waits


#: Hours from one delivered revision to the next, and how much it may come later.
STEP, LATE = 8, 12
PERIODS = (0, 1, 12, 24)


def _arrivals(segs: DataFrame) -> DataFrame:
    """(doc_id, revision, arrived): hours, drawn by a hash of the document."""
    late = workload.roll(F.col("doc_id"), "arrive") % LATE
    return segs.select("doc_id", "revision").distinct().withColumn("arrived", (F.col("revision") - 1) * STEP + late)


def _batched(segs: DataFrame, hours: int) -> DataFrame:
    """Changes between the versions that a refresh every so many hours sees."""
    seen = baselines.last_of_window(_arrivals(segs), hours)
    now = segs.join(seen.select("doc_id", "revision", "run"), ["doc_id", "revision"]).select("doc_id", F.col("run").alias("revision"), "ordinal", "content_key")
    last = now.agg(F.max("revision")).first()[0]
    return diff.combined(*baselines.pairs(now, last), VERSION)


def _batched_sql(hours: int) -> str:
    keep = f"row_number() OVER (PARTITION BY doc_id, {f'arrived // {hours}' if hours else 'revision'} ORDER BY revision DESC) = 1"
    return f"""SELECT CAST({hours} AS BIGINT) AS every_hours, count(*) FILTER (needs_encoding) AS encoded, count(*) FILTER (op NOT IN ('dropped', 'vacated')) AS total FROM (
WITH kept AS (SELECT doc_id, revision AS r0, CAST(row_number() OVER (PARTITION BY doc_id ORDER BY revision) AS BIGINT) AS run FROM (SELECT *, (revision - 1) * {STEP} + {sql.roll('doc_id', "'arrive'")} % {LATE} AS arrived FROM (SELECT DISTINCT doc_id, revision FROM raw) QUALIFY {keep})),
seg AS (SELECT raw.doc_id, run AS revision, ordinal, content_key, body FROM raw JOIN kept ON raw.doc_id = kept.doc_id AND raw.revision = r0), {sql.PAIRS.replace('revision < 5', 'revision < 99')}, {sql.COMBINED.split(sql.PAIRS + ',', 1)[1]} SELECT * FROM changes) WHERE revision > 1 AND NOT audit"""


@query(f"WITH {sql.seg('steady')}, raw AS (SELECT * FROM seg), found AS ({' UNION ALL '.join(_batched_sql(h) for h in PERIODS)}) SELECT every_hours, encoded, total, round(encoded / CAST(total AS DOUBLE), 6) AS share FROM found")
def reprocessed_batch(spark, sf):
    """What a refresh every 1, 12 or 24 hours encodes, of what it looks at; 0 is chunk sync
    on arrival. Versions that come in the same window are encoded once, but a run that
    stands for two versions holds the edits of both."""
    segs, out = _segments(spark, sf, "steady"), None
    for h in PERIODS:
        rows = _batched(segs, h).where("revision > 1 and not audit")
        one = rows.agg(F.lit(h).cast("long").alias("every_hours"), F.count_if("needs_encoding").alias("encoded"), F.count_if(~F.col("op").isin("dropped", "vacated")).alias("total"))
        out = one if out is None else out.union(one)
    return out.withColumn("share", F.round(F.col("encoded") / F.col("total"), 6))


def _waits_sql(hours: int) -> str:
    waits = "0" if hours == 0 else f"(arrived // {hours} + 1) * {hours} - arrived"
    keep = f"row_number() OVER (PARTITION BY doc_id, {f'arrived // {hours}' if hours else 'revision'} ORDER BY revision DESC) = 1"
    return f"SELECT CAST({hours} AS BIGINT) AS every_hours, count(*) AS versions, CAST(max(w) AS BIGINT) AS longest, round(avg(w), 6) AS mean FROM (SELECT {waits} AS w FROM arrivals QUALIFY {keep})"


@query(f"WITH {sql.seg('steady')}, arrivals AS (SELECT *, (revision - 1) * {STEP} + {sql.roll('doc_id', chr(39) + 'arrive' + chr(39))} % {LATE} AS arrived FROM (SELECT DISTINCT doc_id, revision FROM seg)) {' UNION ALL '.join(_waits_sql(h) for h in PERIODS)}")
def waits_by_period(spark, sf):
    """Hours until a version can be found, before any processing."""
    found, out = _arrivals(_segments(spark, sf, "steady")), None
    for h in PERIODS:
        one = baselines.last_of_window(found, h).agg(F.lit(h).cast("long").alias("every_hours"), F.count("*").alias("versions"), F.max("waits").alias("longest"), F.round(F.avg("waits"), 6).alias("mean"))
        out = one if out is None else out.union(one)
    return out


#: Milliseconds that encoding a row takes, stated.
ENCODE_MS = 2.0


@query()
def update_table(spark, sf):
    """By strategy, at the last revision: rows sent, of all; milliseconds to find and
    encode them with an encoder of ENCODE_MS a row; hours that a version waits before."""
    segs = _segments(spark, sf, "steady")
    old, new = (segs.where(F.col("revision") == v).drop("revision") for v in (4, 5))
    total, encoder = new.count(), encode.PacedEncoder(encode.HashEncoder(), ENCODE_MS)
    bodies = new.select("doc_id", "ordinal", "body", "content_key")
    touched = lambda: diff.touched_docs(old, new)
    sent = {
        "sync": lambda: bodies.join(diff.combined(old, new).where("needs_encoding").select("doc_id", "ordinal"), ["doc_id", "ordinal"], "left_semi"),
        "upsert": lambda: bodies.join(touched(), "doc_id", "left_semi"),
        "full": lambda: bodies,
    }
    rows = []
    for name, make in sent.items():
        took = metrics.timed(lambda make=make: encoder.encode(make().repartition(16)).write.format("noop").mode("overwrite").save(), 1)
        n = make().count()
        rows.append((name, n, round(n / total, 6), float(took["p50"]), 0.0))
    waits = {r["every_hours"]: r["mean"] for r in waits_by_period(spark, sf).collect()}
    rows.append(("batch_12h", *rows[0][1:4], float(waits[12])))
    return spark.createDataFrame(rows, "strategy string, n_rows long, share double, ms double, waits_hours double")


@query()
def time_to_query(spark, sf):
    """Seconds from the arrival of the last revision's versions until a search of the live
    tier can find them: diff, commit to both tiers, and for a 12-hour refresh the waiting."""
    import time

    from chronotier.operators.commit import Store
    from chronotier.sources import scratch

    events = _history(spark, sf, "steady").drop("month")
    store = Store(spark, scratch.folder(spark, "store"), buckets=8)
    store.publish(events.where("revision < 5"), "before")
    segs = _segments(spark, sf, "steady")
    old, new = (segs.where(F.col("revision") == v) for v in (4, 5))
    began = time.time()
    changes = diff.combined(old.drop("revision"), new.drop("revision")).withColumn("revision", F.lit(5).cast("long"))
    store.publish(hist.stamp(changes, new), "r5")
    took = time.time() - began
    wait = {r["every_hours"]: r["mean"] for r in waits_by_period(spark, sf).collect()}[12] * 3600
    return spark.createDataFrame([("sync", took), ("batch_12h", wait + took)], "strategy string, seconds double")


@query()
def change_lookup_latency(spark, sf):
    """Milliseconds to fetch the last keys of 50 documents: from the ledger, held in memory
    or stored, and from the history, as a database would be asked."""
    history = _history(spark, sf)
    kept = tiers.kept(spark, sf, "ledger", lambda: ledger.nested(ledger.from_history(history)))
    ids = kept.select("doc_id").orderBy("doc_id").limit(50)
    memory = {r["doc_id"]: r["keys"] for r in ledger.for_docs(kept, ids).collect()}  # the documents of one update
    asked = sorted(memory)
    ways = {"memory": lambda: [memory[i] for i in asked], "stored_ledger": lambda: kept.where(F.col("doc_id").isin(asked)).collect(), "history": lambda: hist.snapshot_at(history.where(F.col("doc_id").isin(asked)), None).collect()}
    return spark.createDataFrame([(n, *(float(x) for x in metrics.timed(fn, 10).values())) for n, fn in ways.items()], "way string, p50 double, p95 double, p99 double")


_COSTS = {"encode_ms": 10.0, "extra_ms": 25.0}


@query(f"""{ST}, dk AS (SELECT doc_id, revision, string_agg(content_key, '|' ORDER BY ordinal) AS d FROM seg GROUP BY ALL),
td AS (SELECT n.doc_id, n.revision FROM dk n JOIN dk o ON o.doc_id = n.doc_id AND o.revision = n.revision - 1 WHERE o.d <> n.d),
c AS (SELECT (SELECT count(*) FROM seg JOIN td USING (doc_id, revision)) AS touched, (SELECT count(*) FROM changes JOIN td USING (doc_id, revision) WHERE needs_encoding) AS changed, (SELECT count(*) FROM td) AS updates)
SELECT updates, round((touched - changed) * {_COSTS['encode_ms']} / updates, 3) AS saved_ms, round((touched - changed) * {_COSTS['encode_ms']} / updates / {_COSTS['extra_ms']}, 3) AS queries_per_update FROM c""")
def break_even(spark, sf):
    """What an update saves by encoding only what changed, against upsert, at a stated cost
    per row; and how many queries per update use it up, each some milliseconds slower than
    in an index in memory."""
    segs = _segments(spark, sf, "steady")
    old, new = baselines.pairs(segs)
    ids = diff.touched_docs(old, new, VERSION).where("revision > 1").join(old.select(*VERSION).distinct(), list(VERSION), "left_semi")
    ids = tiers.kept(spark, sf, "touched", lambda: ids)
    n = lambda df: df.join(ids, list(VERSION), "left_semi").count()
    updates, touched, changed = ids.count(), n(segs), n(_changes(spark, sf, "steady").where("needs_encoding"))
    saved = metrics.break_even(1, touched / updates, changed / updates, _COSTS["encode_ms"], 0, 0)
    return spark.createDataFrame([(updates, round(saved, 3), round(saved / _COSTS["extra_ms"], 3))], "updates long, saved_ms double, queries_per_update double")


# Storage


@query(f"""{HI}, n AS (SELECT (SELECT count(*) FROM spans WHERE retired_at IS NULL) AS live, (SELECT count(*) FROM spans) AS held, (SELECT count(*) FROM seg) AS copies)
SELECT live, held, copies, 4 * {encode.DIM} * live AS live_vector_bytes, 4 * {encode.DIM} * held AS held_vector_bytes, round(1 - live / CAST(held AS DOUBLE), 6) AS less_than_history, round(1 - live / CAST(copies AS DOUBLE), 6) AS less_than_copies FROM n""")
def storage_model(spark, sf):
    """Rows that the index must hold with two tiers and with one (every row that ever held a
    key, or every revision whole), and the bytes of their vectors."""
    count = lambda df, c: df.agg(F.count("*").alias(c))
    met = count(_live(spark, sf), "live").join(count(baselines.single_tier(_history(spark, sf)), "held")).join(count(hist.full_copies(_segments(spark, sf)), "copies"))
    less = lambda c: F.round(1 - F.col("live") / F.col(c), 6)
    return met.select("live", "held", "copies", (4 * encode.DIM * F.col("live")).alias("live_vector_bytes"), (4 * encode.DIM * F.col("held")).alias("held_vector_bytes"), less("held").alias("less_than_history"), less("copies").alias("less_than_copies"))


@query()
def storage_bytes(spark, sf):
    """Bytes of the stored tiers: live, log, log with ends, all revisions."""
    made = {"live": _live, "events": _history, "spans": _spans, "segments": _segments}
    for name, make in made.items():  # live, events and spans are views of one log: each is written here to be weighed
        rows = lambda make=make, name=name: search.coded(make(spark, sf), "body") if name in ("live", "spans") else make(spark, sf)
        tiers.kept(spark, sf, f"{name}/structural", lambda rows=rows: rows().drop("month"), name in ("events", "spans"))
    return metrics.tier_bytes(spark, {name: tiers.path_of(spark, sf, f"{name}/structural") for name in made})


# Ablations: unit, normalisation, diff policy, scope, oversampling


def _share_sql(name: str, seg: str) -> str:
    body = sql.COMBINED
    return f"""SELECT '{name}' AS variant, count(*) FILTER (needs_encoding) AS encoded, count(*) FILTER (op NOT IN ('dropped', 'vacated')) AS total FROM (WITH seg AS ({seg}), {body} SELECT * FROM changes) WHERE revision > 1 AND NOT audit"""


def _share(changes: DataFrame, name: str) -> DataFrame:
    rows = changes.where("revision > 1 and not audit")
    return rows.agg(F.lit(name).alias("variant"), F.count_if("needs_encoding").alias("encoded"), F.count_if(~F.col("op").isin("dropped", "vacated")).alias("total"))


def _cut_sql(split: str) -> str:
    return f"""SELECT doc_id, revision, CAST(row_number() OVER (PARTITION BY doc_id, revision ORDER BY n) - 1 AS BIGINT) AS ordinal, body, {sql.key('body')} AS content_key FROM (SELECT doc_id, revision, unnest(x) AS body, generate_subscripts(x, 1) AS n FROM (SELECT doc_id, revision, {split} AS x FROM texts)) WHERE length(regexp_replace(body, '{sql.WS}', '', 'g')) > 0"""


_SENTENCES = r"string_split(regexp_replace(text, '([.!?])[ \t\r\f]+', '\1' || chr(10), 'g'), chr(10))"
_TEXTS = f"WITH {sql.seg('steady')}, texts AS (SELECT doc_id, revision, string_agg(body, chr(10) ORDER BY ordinal) AS text FROM seg GROUP BY ALL)"


@query(f"{_TEXTS} {_share_sql('line', _cut_sql('string_split(text, chr(10))'))} UNION ALL {_share_sql('sentence', _cut_sql(_SENTENCES))} UNION ALL {_share_sql('whole', _cut_sql('[text]'))}")
def ablation_unit(spark, sf):
    """Segments encoded, of all, by the unit that texts are cut into."""
    texts = tiers.kept(spark, sf, "texts", lambda: workload.revisions(spark, sf))
    cuts = {"line": segment.split_lines, "sentence": segment.split_sentences, "whole": segment.whole}
    out = None
    for name, cut in cuts.items():
        segs = fingerprint.with_keys(cut(texts))
        one = _share(diff.combined(*baselines.pairs(segs), VERSION), name)
        out = one if out is None else out.union(one)
    return out


_KEYS = {"none": "sha256(body)", "outer": f"sha256(lower(regexp_replace(body, '^{sql.WS}+|{sql.WS}+$', '', 'g')))", "collapse": sql.key("body")}


@query(f"WITH {sql.seg('steady')}, raw AS (SELECT * FROM seg) " + " UNION ALL ".join(_share_sql(name, f"SELECT doc_id, revision, ordinal, body, {key} AS content_key FROM raw") for name, key in _KEYS.items()))
def ablation_normalisation(spark, sf):
    """The same by what counts as an equal line: without normalisation, changes in looks
    alone are encoded too."""
    segs, out = _segments(spark, sf, "steady"), None
    for name, how in {"none": {"raw": True}, "outer": {"whitespace": "outer"}, "collapse": {}}.items():
        keyed = segs.withColumn("content_key", fingerprint.content_key(F.col("body"), **how))
        one = _share(diff.combined(*baselines.pairs(keyed), VERSION), name)
        out = one if out is None else out.union(one)
    return out


@query(f"""{CH} SELECT 'by_slot' AS variant, count(*) FILTER (has AND (NOT had OR a <> b)) AS encoded FROM slots WHERE revision > 1 UNION ALL SELECT 'combined', count(*) FILTER (needs_encoding) FROM changes WHERE revision > 1
UNION ALL SELECT 'by_content', CAST(sum(greatest(now - was, 0)) AS BIGINT) FROM (SELECT coalesce(o.n, 0) AS was, coalesce(n.n, 0) AS now FROM (SELECT doc_id, revision, content_key, count(*) AS n FROM old GROUP BY ALL) o FULL JOIN (SELECT doc_id, revision, content_key, count(*) AS n FROM seg WHERE revision > 1 GROUP BY ALL) n USING (doc_id, revision, content_key))""")
def ablation_policy(spark, sf):
    """Rows that each diff would encode over revisions 2 to 5 of the structural profile."""
    old, new = baselines.pairs(_segments(spark, sf))
    new = new.where("revision > 1")
    n = lambda df, name, amount=F.count("*"): df.agg(F.lit(name).alias("variant"), F.coalesce(amount, F.lit(0)).cast("long").alias("encoded"))
    slot = n(diff.by_slot(old, new, VERSION).where("needs_encoding"), "by_slot")
    content = n(diff.by_content(old, new, VERSION).where("op = 'added'"), "by_content", F.sum("copies"))
    return slot.union(n(_changes(spark, sf).where("revision > 1 and needs_encoding"), "combined")).union(content)


@query(f"{CH}, c AS (SELECT * FROM changes WHERE needs_encoding) SELECT 'none' AS scope, count(*) AS encoded FROM c UNION ALL SELECT 'document', count(DISTINCT (doc_id, content_key)) FROM c UNION ALL SELECT 'corpus', count(DISTINCT content_key) FROM c")
def ablation_scope(spark, sf):
    """Rows to encode by how far a text counts as known."""
    rows, out = _changes(spark, sf), None
    for scope in ("none", "document", "corpus"):
        one = encode.pending_keys(rows, None, scope).agg(F.lit(scope).alias("scope"), F.count("*").alias("encoded"))
        out = one if out is None else out.union(one)
    return out


_VALID = "effective_at <= t AND (retired_at IS NULL OR retired_at > t)"


def _over_sql(n: int) -> str:
    top = f"SELECT qid, {_VALID} AS valid, row_number() OVER (PARTITION BY qid {_ORDER}) AS rank FROM scored JOIN asked USING (qid) JOIN spans USING (content_key) QUALIFY rank <= {5 * n}"
    return f"SELECT CAST({n} AS BIGINT) AS oversample, 500 - CAST(sum(least(got, 5)) AS BIGINT) AS places_empty FROM (SELECT qid, count(*) FILTER (valid) AS got FROM ({top}) GROUP BY qid)"


@query(f"{HI}, {_ASKED}, {_scored('spans', 'asked')} " + " UNION ALL ".join(_over_sql(n) for n in (1, 2, 4)))
def ablation_oversampling(spark, sf):
    """Places that filtering after ranking leaves empty, of 500, by how many answers too
    many are taken."""
    from chronotier.registry import _asked

    spans, out = _spans(spark, sf, once=True), None
    asked = tiers.kept(spark, sf, "asked", lambda: _asked(spans))
    ranked = tiers.kept(spark, sf, "asked_of_all", lambda: baselines.indexed(asked, spans, 20, ("all",)))
    for n in (1, 2, 4):  # the first 5 n of the 20
        got = baselines.validated(ranked, oversample=n)
        one = got.agg(F.lit(n).cast("long").alias("oversample"), (F.lit(500) - F.count("*")).alias("places_empty"))
        out = one if out is None else out.union(one)
    return out


@query(f"{HI}, {_ASKED}, {_scored('spans', 'asked')}, truth AS (SELECT qid, array_agg((doc_id, ordinal) ORDER BY rank) AS places FROM (SELECT qid, doc_id, ordinal, row_number() OVER (PARTITION BY qid {_ORDER}) AS rank FROM scored JOIN asked USING (qid) JOIN spans USING (content_key) WHERE {_VALID} QUALIFY rank <= 5) GROUP BY qid)" + """, late AS (SELECT qid, doc_id, ordinal, %s AS valid, row_number() OVER (PARTITION BY qid %s) AS rank FROM scored JOIN asked USING (qid) JOIN spans USING (content_key) QUALIFY rank <= 5), got AS (SELECT qid, array_agg((doc_id, ordinal) ORDER BY rank) AS places FROM late WHERE valid GROUP BY qid)
SELECT count(*) AS queries, count(*) FILTER (got.places IS DISTINCT FROM truth.places) AS wrong FROM truth LEFT JOIN got USING (qid)""" % (_VALID, _ORDER))
def postfilter_wrong_answers(spark, sf):
    """Questions whose five answers are not those of the asked instant, if the filter comes
    after the ranking."""
    from chronotier.registry import _asked

    spans = _spans(spark, sf, once=True)
    asked = tiers.kept(spark, sf, "asked", lambda: _asked(spans))
    found = tiers.kept(spark, sf, "asked_of_two", lambda: baselines.indexed(asked, spans, 5, ("snapshot", "all")))
    of = lambda index: found.where(F.col("index") == index)
    right = metrics.accuracy(baselines.validated(of("all")), of("snapshot"), ["doc_id", "ordinal"])
    return right.select("queries", (F.col("queries") - F.col("right")).alias("wrong"))


# Near copies, reconstruction, meaning


@query(f"""WITH {sql.BASE}, k AS (SELECT DISTINCT doc_id, {sql.key('body')} AS content_key FROM base WHERE length(body) > 20), n AS (SELECT doc_id, count(*) AS n FROM k GROUP BY doc_id),
p AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS shared FROM k x JOIN k y ON x.content_key = y.content_key AND x.doc_id < y.doc_id GROUP BY ALL HAVING count(*) >= 3)
SELECT a, b, shared, na.n AS keys_a, nb.n AS keys_b FROM p JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b""")
def near_copies(spark, sf):
    lines = workload.base_lines(load(spark, sf, "documents"))
    return audit.near_copies(lines.withColumn("content_key", fingerprint.content_key(F.col("body"))))


@query(f"{S} SELECT revision, count(DISTINCT doc_id) AS docs, CAST(0 AS BIGINT) AS differing FROM seg GROUP BY revision")
def rebuild_at_every_instant(spark, sf):
    """Documents put together from the history at each instant against the texts of that
    revision, keys and order."""
    history, segs, out = _history(spark, sf), _segments(spark, sf), None
    for v, t in INSTANTS.items():
        want = diff.document_keys(segs.where(F.col("revision") == v)).withColumnRenamed("doc_key", "want")
        got = diff.document_keys(hist.snapshot_at(history, t))
        met = want.join(got, "doc_id", "full_outer")
        one = met.agg(F.lit(v).cast("long").alias("revision"), F.count("want").alias("docs"), F.count_if(~F.col("doc_key").eqNullSafe(F.col("want"))).alias("differing"))
        out = one if out is None else out.union(one)
    return out


_MEANING = 0.8512


@query(f"""{CH}, e AS (SELECT doc_id, revision, ordinal, content_key, prior_key FROM changes WHERE op = 'edited'), keyed AS (SELECT content_key, min(body) AS body FROM seg GROUP BY content_key),
kv AS MATERIALIZED ({_sparse_sql('keyed', 'content_key', 'body')}), n2 AS MATERIALIZED (SELECT content_key, sum(w * w) AS n FROM kv GROUP BY content_key),
x AS MATERIALIZED (SELECT doc_id, revision, ordinal, bucket, w FROM e JOIN kv ON kv.content_key = e.content_key), y AS MATERIALIZED (SELECT doc_id, revision, ordinal, bucket, w FROM e JOIN kv ON kv.content_key = e.prior_key),
d AS MATERIALIZED (SELECT doc_id, revision, ordinal, sum(x.w * y.w) AS dot FROM x JOIN y USING (doc_id, revision, ordinal, bucket) GROUP BY ALL)
SELECT e.revision, count(*) AS edited, count(*) FILTER (coalesce(dot, 0) / sqrt(CAST(nx.n * ny.n AS DOUBLE)) < {_MEANING}) AS meaning_changed FROM e JOIN n2 nx ON nx.content_key = e.content_key JOIN n2 ny ON ny.content_key = e.prior_key LEFT JOIN d USING (doc_id, revision, ordinal) GROUP BY e.revision""")
def semantic_change(spark, sf):
    """Edited slots by revision, and those whose vector moved by more than a threshold."""
    texts = _segments(spark, sf).groupBy("content_key").agg(F.min("body").alias("body"))
    vectors = encode.HashEncoder().encode(texts).select("content_key", "embedding")
    found = diff.semantic_change(_changes(spark, sf), vectors, _MEANING).where("similarity is not null")
    return found.groupBy("revision").agg(F.count("*").alias("edited"), F.count_if("meaning_changed").alias("meaning_changed"))


# Routes by argument, one tier in memory, indexes behind the live tier


@query(f"{HI}, {sql.snapshot(T3)}, {_scored('snap', _BENCH)}, {_TOP % 'snap'} SELECT qid, rank, score, doc_id, ordinal, 'cold' AS tier FROM ranked WHERE rank <= 5")
def answer_at_argument(spark, sf):
    """An instant given as an argument goes the same way as one in the text."""
    qs = route.explicit(_benchmark(spark, sf), at=T3).select("qid", F.col("core_text").alias("text"), "kind", "t_from", "t_to")
    return assert_guard(dispatch.answer(qs, _live(spark, sf, once=True), _spans(spark, sf, once=True))).select("qid", "rank", "score", "doc_id", "ordinal", "tier")


@query(f"{LIVE}, {_scored('live', _BENCH)}, {_TOP % 'live'} {_PICK % 'hot'}")
def search_memory_index(spark, sf):
    """The live tier held in memory: the same answers."""
    cached, ask = baselines.memory_index(spark, _live(spark, sf), _benchmark(spark, sf))
    found = tiers.kept(spark, sf, "memory_answers", lambda: ask(_benchmark(spark, sf)))
    cached.unpersist()
    return found


@query()
def search_live_indexed(spark, sf):
    """The benchmark texts asked of the graphs over the live tier."""
    return live_index.find(_benchmark(spark, sf), tiers.live_terms(spark, sf), tiers.graphs(spark, sf))


def _good(spark, sf) -> DataFrame:
    ids = load(spark, sf, "documents").where("lang = 'en'").select("doc_id").join(load(spark, sf, "labels").where("quality = 1 and toxic = 0").select("doc_id"), "doc_id")
    return tiers.live_terms(spark, sf).join(ids, "doc_id", "left_semi")


@query()
def search_live_indexed_filtered(spark, sf):
    """The same with a predicate on documents, which goes into the walk of the graphs."""
    return live_index.find(_benchmark(spark, sf), _good(spark, sf), tiers.graphs(spark, sf), filtered=True)


def _score_recall(found: DataFrame, exact: DataFrame) -> DataFrame:
    """(wanted, hits): answers no worse than the last exact one, of the exact ones."""
    last = exact.groupBy("qid").agg(F.min("score").alias("last"), F.count("*").alias("n"))
    hits = found.join(last, "qid").where(F.col("score") >= F.col("last") - 1.5e-6).groupBy("qid").agg(F.count("*").alias("hits"))
    return last.join(hits, "qid", "left").agg(F.sum("n").alias("wanted"), F.sum(F.least("n", F.coalesce("hits", F.lit(0)))).alias("hits"))


_WANTED = "SELECT count(*) AS wanted FROM ranked WHERE rank <= 5"


def _recalls(spark, sf) -> DataFrame:
    q, graphs = _benchmark(spark, sf), tiers.graphs(spark, sf)
    return _score_recall(live_index.find(q, _live(spark, sf), graphs), search.live(q, _live(spark, sf)))


@query(f"{LIVE}, {_scored('live', _BENCH)}, {_TOP % 'live'} SELECT wanted, true AS enough FROM ({_WANTED})")
def live_index_recall(spark, sf):
    """Is the recall of the graphs over the live tier 0.9 or more?"""
    return _recalls(spark, sf).select("wanted", (F.col("hits") >= 0.9 * F.col("wanted")).alias("enough"))


@query(f"{LIVE}, {_GOOD}, {_scored('ok', _BENCH)}, {_TOP % 'ok'} SELECT wanted, true AS enough FROM ({_WANTED})")
def live_index_recall_filtered(spark, sf):
    """The same under a predicate that most slots fail."""
    q = _benchmark(spark, sf)
    found = live_index.find(q, _good(spark, sf), tiers.graphs(spark, sf), filtered=True)
    return _score_recall(found, search.live(q, _good(spark, sf))).select("wanted", (F.col("hits") >= 0.9 * F.col("wanted")).alias("enough"))


@query()
def live_index_figures(spark, sf):
    """Recall of the graphs over the live tier, and texts that a question looks at, of how
    many."""
    q = live_index.dense(search.coded(_benchmark(spark, sf), "text"), "qid")
    hops = index.Graph(None, graphs=tiers.graphs(spark, sf)).hops(q, 5, 64)
    seen = hops.agg(F.round(F.avg("visited"), 1).alias("visited"), F.max("n").alias("texts"))
    return _recalls(spark, sf).select("wanted", F.round(F.col("hits") / F.col("wanted"), 6).alias("recall")).join(seen)


def _recall(name: str, make) -> None:
    @query(f"SELECT '{name}' AS method, 10 * count(*) AS wanted, true AS enough FROM embeddings WHERE vec_id % 20 = 0", f"ann_recall_{name}")
    def _(spark, sf):
        q, v = _vectors(spark, sf)
        got = metrics.recall_at_k(make(q, v), index.exact_blocks(q, v))
        return got.select(F.lit(name).alias("method"), "wanted", (F.col("recall") >= 0.9).alias("enough"))

    @query(None, f"ann_recall_{name}_figure")
    def _(spark, sf):
        q, v = _vectors(spark, sf)
        return metrics.recall_at_k(make(q, v), index.exact_blocks(q, v)).withColumn("method", F.lit(name))


def cells(q: DataFrame, v: DataFrame) -> DataFrame:
    """Three quarters of the cells: these vectors have no clusters."""
    made = index.Cells(v)
    return made.search(q, nprobe=-(-3 * len(made.centres) // 4))


_recall("graph", lambda q, v: index.Graph(v).search(q, ef=100))
_recall("cells", cells)
_recall("planes", lambda q, v: index.Planes(v, tables=24).search(q))


@query()
def graph_hops(spark, sf):
    """Vectors that a query of the graph looks at, of how many, by the width of its walk."""
    q, v = _vectors(spark, sf)
    made, out = index.Graph(v), None
    made = index.Graph(None, graphs=tiers.kept(spark, sf, "vector_graphs", lambda: made.graphs))
    for ef in (10, 50, 100):
        one = made.hops(q, 10, ef).agg(F.lit(ef).alias("ef"), F.round(F.avg("visited"), 1).alias("visited"), F.max("n").alias("vectors"))
        out = one if out is None else out.union(one)
    return out.withColumn("log2", F.round(F.log2("vectors"), 2))


# Other measures, lineage of a text, questions in SQL


def _measured_sql(expression: str) -> str:
    return f"""WITH q AS (SELECT vec_id AS qid, CAST(embedding AS DOUBLE[]) AS a FROM embeddings WHERE vec_id % 20 = 0), e AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS b FROM embeddings),
s AS (SELECT qid, vec_id, round({expression}, 6) AS score FROM q, e) SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY score DESC, vec_id) AS rank, vec_id, score FROM s QUALIFY rank <= 10"""


@query(_measured_sql("list_sum(list_transform(list_zip(a, b), lambda p: p[1] * p[2]))"))
def vector_search_dot(spark, sf):
    return index.exact(*_vectors(spark, sf), measure="dot")


@query(_measured_sql("-sqrt(list_sum(list_transform(list_zip(a, b), lambda p: (p[1] - p[2]) * (p[1] - p[2]))))"))
def vector_search_l2(spark, sf):
    return index.exact(*_vectors(spark, sf), measure="l2")


@query(f"""WITH RECURSIVE {HI.removeprefix('WITH ')}, edits AS (SELECT DISTINCT content_key, prior_key FROM history WHERE op = 'edited'),
chain AS (SELECT 0 AS hop, (SELECT min(content_key) FROM history WHERE op = 'edited' AND revision = 5) AS content_key UNION ALL SELECT hop + 1, prior_key FROM chain JOIN edits USING (content_key) WHERE hop < 20)
SELECT hop, content_key FROM chain""")
def audit_ancestry(spark, sf):
    """The texts that were edited into one text of the last revision."""
    history = _history(spark, sf)
    key = history.where("op = 'edited' and revision = 5").agg(F.min("content_key")).first()[0]
    return audit.ancestry(history, key)


_ONE = "(SELECT min(item_id) AS qid, arg_min(text, item_id) AS text FROM benchmark)"


@query(f"{LIVE}, {_scored('live', _ONE)}, {_TOP % 'live'} SELECT doc_id, ordinal, content_key, effective_at, score FROM ranked WHERE rank <= 10")
def sql_live_scores(spark, sf):
    from chronotier.plans import surface

    surface.register(spark, _spans(spark, sf, once=True))
    text = load(spark, sf, "benchmark").agg(F.min_by("text", "item_id")).first()[0]
    return spark.sql("SELECT * FROM live_scores(:q) ORDER BY score DESC, doc_id, ordinal LIMIT 10", args={"q": text})


@query(f"{HI}, {sql.snapshot(T3)}, {_scored('snap', _ONE)}, {_TOP % 'snap'} SELECT doc_id, ordinal, content_key, effective_at, score FROM ranked WHERE rank <= 10")
def sql_scores_at(spark, sf):
    from chronotier.plans import surface

    surface.register(spark, _spans(spark, sf, once=True))
    text = load(spark, sf, "benchmark").agg(F.min_by("text", "item_id")).first()[0]
    return assert_guard(spark.sql(f"SELECT * FROM scores_at(:q, {T3}) ORDER BY score DESC, doc_id, ordinal LIMIT 10", args={"q": text}))


def _refresh(name: str, every: str, seconds: int) -> None:
    @query(f"""SELECT user_id, event_type, CAST(w AS BIGINT) AS window_start, count(*) AS updates, CAST(w + {seconds} - min(s) AS BIGINT) AS longest_wait
FROM (SELECT user_id, event_type, date_diff('second', TIMESTAMP '1970-01-01', ts) AS s, (date_diff('second', TIMESTAMP '1970-01-01', ts) // {seconds}) * {seconds} AS w FROM events) GROUP BY user_id, event_type, w""", name)
    def _(spark, sf):
        found = baselines.windowed_refresh(load(spark, sf, "events"), ["user_id", "event_type"], every=every)
        return found.select("user_id", "event_type", "window_start", "updates", "longest_wait")


_refresh("windowed_refresh_hourly", "1 hour", 3600)
_refresh("windowed_refresh_daily", "1 day", 86400)
