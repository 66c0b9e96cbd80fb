"""Queries of the engine's own methods over the sample tables, with their SQL twins.

Every query is self-contained; scores are rounded to six digits and every ranking has
a total order, so that results compare by value.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from chronotier.functions import fingerprint, route, segment
from chronotier.operators import audit, baselines, diff, dispatch, encode, history as hist, ledger, live, metrics, search
from chronotier.plans.guard import assert_guard
from chronotier.plans import surface
from chronotier.sources import scratch, tiers, workload
from chronotier.sources import workload_sql as sql
from chronotier.sources.tables import load
from chronotier.sources.workload import INSTANTS

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}
VERSION = ("doc_id", "revision")
T3 = INSTANTS[3]
NOW = INSTANTS[5]


def query(oracle: str | None = None, name: str | None = None):
    def add(fn: Query) -> Query:
        key = name or fn.__name__
        QUERIES[key] = fn
        if oracle:
            SQL[key] = oracle
        return fn

    return add


# Building blocks


def _docs(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "documents").select("doc_id", F.lit(1).cast("long").alias("revision"), F.lit(INSTANTS[1]).cast("long").alias("effective_at"), "text")


_segments, _changes, _history, _spans, _live, _diffed = tiers.segments, tiers.changes, tiers.events, tiers.spans, tiers.live, tiers.diffed


def _benchmark(spark: SparkSession, sf: str) -> DataFrame:
    return load(spark, sf, "benchmark").select(F.col("item_id").alias("qid"), "text")


S = f"WITH {sql.seg('structural')}"
CH = f"{S}, {sql.COMBINED}"
HI = f"{S}, {sql.HISTORY}"
LIVE = f"{HI}, live AS (SELECT doc_id, ordinal, content_key, body, effective_at, revision FROM spans WHERE retired_at IS NULL)"


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """The answers to each benchmark text as of the third instant."""
    return assert_guard(search.at(_benchmark(spark, sf), _spans(spark, sf, once=True), T3))


# Segments and keys

_LINES = rf"SELECT doc_id, CAST(row_number() OVER (PARTITION BY doc_id ORDER BY n) - 1 AS BIGINT) AS ordinal, body FROM (SELECT doc_id, unnest(x) AS body, generate_subscripts(x, 1) AS n FROM (SELECT doc_id, %s AS x FROM documents)) WHERE length(regexp_replace(body, '{sql.WS}', '', 'g')) > 0"


@query(_LINES % "string_split(text, chr(10))")
def segment_lines(spark, sf):
    return segment.split_lines(_docs(spark, sf)).select("doc_id", "ordinal", "body")


@query(_LINES % r"regexp_split_to_array(text, '\n[ \t\r\f]*\n')")
def segment_paragraphs(spark, sf):
    return segment.split_paragraphs(_docs(spark, sf)).select("doc_id", "ordinal", "body")


@query(_LINES % r"string_split(regexp_replace(text, '([.!?])[ \t\r\f]+', '\1' || chr(10), 'g'), chr(10))")
def segment_sentences(spark, sf):
    return segment.split_sentences(_docs(spark, sf)).select("doc_id", "ordinal", "body")


@query(rf"SELECT doc_id, CAST(0 AS BIGINT) AS ordinal, sha256(text) AS digest FROM documents WHERE length(regexp_replace(text, '{sql.WS}', '', 'g')) > 0")
def segment_whole(spark, sf):
    return segment.whole(_docs(spark, sf)).select("doc_id", "ordinal", F.sha2("body", 256).alias("digest"))


_FENCE, _PIPE, _TWO, _BULLET = r"^ {0,3}(```|~~~)", r"^[ \t]*\|", r"\|.*\|", r"^[ \t]*([-*+]|[0-9]+[.)])[ \t]"


@query(rf"""WITH l AS (SELECT doc_id, unnest(x) AS line, generate_subscripts(x, 1) AS n FROM (SELECT doc_id, string_split(text, chr(10)) AS x FROM documents)),
f AS (SELECT *, regexp_matches(line, '{_FENCE}') AS mark, sum(CASE WHEN regexp_matches(line, '{_FENCE}') THEN 1 ELSE 0 END) OVER w AS marks, regexp_matches(line, '{_PIPE}') AS pipe, regexp_matches(line, '{_TWO}') AS two,
  coalesce(lag(regexp_matches(line, '{_PIPE}') OR regexp_matches(line, '{_TWO}')) OVER w, false) OR coalesce(lead(regexp_matches(line, '{_PIPE}') OR regexp_matches(line, '{_TWO}')) OVER w, false) AS near FROM l WINDOW w AS (PARTITION BY doc_id ORDER BY n)),
c AS (SELECT *, regexp_matches(line, '^[ \t]+[^ \t]') AS indented, CASE WHEN mark OR marks % 2 = 1 THEN 'code' WHEN NOT regexp_matches(line, '[^ \t\r\f]') THEN 'blank' WHEN pipe OR (two AND near) THEN 'table' WHEN regexp_matches(line, '{_BULLET}') THEN 'list' END AS first FROM f),
k AS (SELECT *, coalesce(first, CASE WHEN indented AND last_value(CASE WHEN first IS NOT NULL OR NOT indented THEN coalesce(first, 'prose') END IGNORE NULLS) OVER (PARTITION BY doc_id ORDER BY n) = 'list' THEN 'list' END, 'prose') AS kind FROM c),
b AS (SELECT *, sum(CASE WHEN kind <> was OR (mark AND marks % 2 = 1) THEN 1 ELSE 0 END) OVER (PARTITION BY doc_id ORDER BY n) AS block FROM (SELECT *, coalesce(lag(kind) OVER (PARTITION BY doc_id ORDER BY n), '') AS was FROM k))
SELECT doc_id, CAST(row_number() OVER (PARTITION BY doc_id ORDER BY block) - 1 AS BIGINT) AS ordinal, kind, string_agg(line, chr(10) ORDER BY n) AS body FROM b WHERE kind <> 'blank' GROUP BY doc_id, block, kind""")
def segment_blocks(spark, sf):
    return segment.split_blocks(_docs(spark, sf)).select("doc_id", "ordinal", "kind", "body")


_ELEMENTS = "|".join(f"<{k}(?: [^>]*)?>.*?</{k}>" for k in ("table", "pre", "p", "li"))


@query(rf"""WITH m AS (SELECT page_id AS doc_id, unnest(x) AS e, generate_subscripts(x, 1) AS n FROM (SELECT page_id, regexp_extract_all(html, '(?is){_ELEMENTS}') AS x FROM pages)),
t AS (SELECT doc_id, n, lower(regexp_extract(e, '^<([a-zA-Z]+)', 1)) AS kind, trim(regexp_replace(regexp_replace(regexp_replace(e, '(?s)^<[^>]*>|<[^>]*>$', '', 'g'), '<[^>]*>', ' ', 'g'), '{sql.WS}+', ' ', 'g')) AS body FROM m)
SELECT doc_id, CAST(row_number() OVER (PARTITION BY doc_id ORDER BY n) - 1 AS BIGINT) AS ordinal, kind, body FROM t WHERE body <> ''""")
def segment_html(spark, sf):
    pages = load(spark, sf, "pages").select(F.col("page_id").alias("doc_id"), F.lit(1).alias("revision"), F.lit(0).alias("effective_at"), "html")
    return segment.split_html(pages).select("doc_id", "ordinal", "kind", "body")


@query(f"WITH {sql.BASE} SELECT doc_id, ord AS ordinal, lower(regexp_replace(regexp_replace(body, '^{sql.WS}+|{sql.WS}+$', '', 'g'), '{sql.WS}+', ' ', 'g')) AS canonical, {sql.key('body')} AS content_key FROM base")
def content_keys(spark, sf):
    return workload.base_lines(load(spark, sf, "documents")).select("doc_id", "ordinal", fingerprint.canonical(F.col("body")).alias("canonical"), fingerprint.content_key(F.col("body")).alias("content_key"))


@query(f"WITH {sql.BASE} SELECT 'none' AS normalisation, count(DISTINCT sha256(body)) AS keys FROM base UNION ALL SELECT 'outer', count(DISTINCT sha256(lower(regexp_replace(body, '^{sql.WS}+|{sql.WS}+$', '', 'g')))) FROM base UNION ALL SELECT 'collapse', count(DISTINCT {sql.key('body')}) FROM base")
def normalisation_keys(spark, sf):
    base = workload.base_lines(load(spark, sf, "documents"))
    keys = {"none": {"raw": True}, "outer": {"whitespace": "outer"}, "collapse": {}}
    row = base.agg(*[F.count_distinct(fingerprint.content_key(F.col("body"), **how)).alias(k) for k, how in keys.items()])
    return row.select(F.explode(F.array(*[F.struct(F.lit(k).alias("normalisation"), F.col(k).alias("keys")) for k in keys])).alias("x")).select("x.*")


@query(f"WITH {sql.BASE} SELECT count(DISTINCT {sql.key('body')}) AS keys, CAST(0 AS BIGINT) AS collisions FROM base")
def short_key_collisions(spark, sf):
    keys = workload.base_lines(load(spark, sf, "documents")).select(fingerprint.content_key(F.col("body")).alias("k")).distinct()
    return keys.agg(F.count("*").alias("keys"), (F.count("*") - F.count_distinct(fingerprint.short_key(F.col("k")))).alias("collisions"))


@query(f"WITH {sql.BASE}, k AS (SELECT {sql.key('body')} AS c FROM base) SELECT count(*) AS slots, count(DISTINCT c) AS keys, round(count(*) / CAST(count(DISTINCT c) AS DOUBLE), 6) AS ratio FROM k")
def dedup_ratio(spark, sf):
    return metrics.dedup_ratio(workload.base_lines(load(spark, sf, "documents")).withColumn("content_key", fingerprint.content_key(F.col("body"))))


@query(f"WITH {sql.BASE}, k AS (SELECT doc_id, {sql.key('body')} AS content_key FROM base) SELECT content_key, count(DISTINCT doc_id) AS docs, count(*) AS slots FROM k GROUP BY content_key HAVING count(DISTINCT doc_id) > 1")
def shared_keys(spark, sf):
    keys = workload.base_lines(load(spark, sf, "documents")).select("doc_id", fingerprint.content_key(F.col("body")).alias("content_key"))
    return keys.groupBy("content_key").agg(F.count_distinct("doc_id").alias("docs"), F.count("*").alias("slots")).where("docs > 1")


# Ledger and change detection


@query(f"{S}, l AS (SELECT doc_id, max(revision) AS revision FROM seg GROUP BY doc_id) SELECT doc_id, ordinal, content_key, revision FROM seg JOIN l USING (doc_id, revision)")
def ledger_build(spark, sf):
    return ledger.build(_segments(spark, sf))


@query(f"{S}, l AS (SELECT doc_id, max(revision) AS revision FROM seg WHERE revision <= 3 GROUP BY doc_id) SELECT doc_id, ordinal, content_key, revision FROM seg JOIN l USING (doc_id, revision)")
def ledger_apply(spark, sf):
    segs = _segments(spark, sf)
    return ledger.apply(ledger.build(segs.where("revision <= 2")), segs.where("revision = 3"))


@query(f"{HI} SELECT doc_id, ordinal, content_key, revision FROM spans WHERE retired_at IS NULL")
def ledger_from_history(spark, sf):
    return ledger.from_history(_history(spark, sf))


@query(f"{S}, {sql.PAIRS} SELECT doc_id, revision, ordinal, CASE WHEN NOT had THEN 'added' WHEN NOT has THEN 'dropped' WHEN a = b THEN 'kept' ELSE 'edited' END AS op, b AS content_key, CASE WHEN had AND (NOT has OR a <> b) THEN a END AS prior_key FROM slots")
def diff_by_slot(spark, sf):
    return _diffed(_segments(spark, sf), diff.by_slot).select(*VERSION, "ordinal", "op", "content_key", "prior_key")


@query(f"""{S}, o AS (SELECT doc_id, revision + 1 AS revision, content_key, count(*) AS n FROM seg WHERE revision < 5 GROUP BY ALL), n AS (SELECT doc_id, revision, content_key, count(*) AS n FROM seg GROUP BY ALL),
m AS (SELECT doc_id, revision, content_key, coalesce(o.n, 0) AS was, coalesce(n.n, 0) AS now FROM o FULL JOIN n USING (doc_id, revision, content_key))
SELECT * FROM (SELECT doc_id, revision, content_key, 'kept' AS op, least(was, now) AS copies FROM m UNION ALL SELECT doc_id, revision, content_key, 'added', now - was FROM m UNION ALL SELECT doc_id, revision, content_key, 'dropped', was - now FROM m) WHERE copies > 0""")
def diff_by_content(spark, sf):
    return _diffed(_segments(spark, sf), diff.by_content)


@query(f"{CH} SELECT doc_id, revision, ordinal, op, content_key, prior_key, moved_from, needs_encoding, audit FROM changes")
def diff_combined(spark, sf):
    return _diffed(_segments(spark, sf))


@query()
def diff_aligned(spark, sf):
    return _diffed(_segments(spark, sf), diff.aligned)


@query(f"{S} SELECT doc_id, ordinal, 'added' AS op, content_key FROM seg WHERE revision = 1")
def diff_first_version(spark, sf):
    segs = _segments(spark, sf).where("revision = 1")
    return diff.combined(segs.where("false"), segs).select("doc_id", "ordinal", "op", "content_key")


_GONE = "g AS (SELECT DISTINCT doc_id FROM seg WHERE revision = 4 AND doc_id NOT IN (SELECT doc_id FROM seg WHERE revision = 5))"


@query(f"{S}, {_GONE} SELECT doc_id, ordinal, 'dropped' AS op, content_key AS prior_key FROM seg JOIN g USING (doc_id) WHERE revision = 4")
def diff_withdrawn(spark, sf):
    segs = _segments(spark, sf)
    old, new = segs.where("revision = 4"), segs.where("revision = 5")
    gone = old.select("doc_id").distinct().join(new.select("doc_id").distinct(), "doc_id", "left_anti")
    return diff.combined(old, new.where("false"), withdrawn=gone).select("doc_id", "ordinal", "op", "prior_key")


@query(f"{CH}, k AS (SELECT doc_id, revision, string_agg(content_key, '|' ORDER BY ordinal) AS d FROM seg GROUP BY ALL) SELECT n.doc_id, n.revision FROM k n LEFT JOIN k o ON o.doc_id = n.doc_id AND o.revision = n.revision - 1 WHERE o.d IS NULL OR o.d <> n.d")
def touched_docs(spark, sf):
    return diff.touched_docs(*baselines.pairs(_segments(spark, sf)), VERSION)


# Encoding


@query(f"{CH}, h AS (SELECT DISTINCT content_key FROM changes WHERE needs_encoding AND revision < 5) SELECT DISTINCT content_key FROM changes WHERE needs_encoding AND revision = 5 AND content_key NOT IN (SELECT content_key FROM h)")
def encode_pending(spark, sf):
    changes = _changes(spark, sf)
    known = changes.where("needs_encoding and revision < 5").select("content_key").distinct()
    return encode.pending_keys(changes.where("revision = 5"), known).select("content_key")


def _sparse_sql(source: str, ident: str, text: str) -> str:
    canonical = f"lower(regexp_replace(regexp_replace({text}, '^{sql.WS}+|{sql.WS}+$', '', 'g'), '{sql.WS}+', ' ', 'g'))"
    return f"""SELECT {ident}, CAST('0x' || substr(md5(term), 1, 8) AS BIGINT) % {encode.DIM} AS bucket,
  CAST(sum(CASE WHEN CAST('0x' || substr(md5(term), 9, 1) AS BIGINT) % 2 = 0 THEN 1 ELSE -1 END) AS BIGINT) AS w
  FROM (SELECT {ident}, unnest(regexp_split_to_array({canonical}, '{encode.SEPARATOR}')) AS term FROM {source}) WHERE term <> '' GROUP BY ALL HAVING w <> 0"""


@query(_sparse_sql("documents", "doc_id", "text"))
def encode_sparse_hash(spark, sf):
    return encode.sparse(load(spark, sf, "documents"), "doc_id", "text")


@query(f"WITH {sql.BASE}, k AS (SELECT DISTINCT {sql.key('body')} AS content_key FROM base) SELECT content_key, CAST('0x' || substr(content_key, 1, 8) AS BIGINT) % (SELECT count(*) FROM embeddings) AS vec_id FROM k")
def encode_table_choice(spark, sf):
    keys = workload.base_lines(load(spark, sf, "documents")).select(fingerprint.content_key(F.col("body")).alias("content_key")).distinct()
    vectors = load(spark, sf, "embeddings")
    return encode.TableEncoder(vectors).choice(keys, vectors.count())


# History, snapshots and the live tier


@query(f"{HI} SELECT doc_id, ordinal, content_key, effective_at, revision, op, prior_key, body FROM history")
def history_events(spark, sf):
    return _history(spark, sf).drop("commit_seq", "month")


@query(f"{HI} SELECT doc_id, ordinal, content_key, effective_at, revision, op, retired_at, state FROM spans")
def history_intervals(spark, sf):
    return hist.intervals(_history(spark, sf)).select("doc_id", "ordinal", "content_key", "effective_at", "revision", "op", "retired_at", "state")


@query(f"{HI} SELECT doc_id, ordinal, content_key, effective_at, retired_at, state FROM spans")
def history_closed(spark, sf):
    return _spans(spark, sf, once=True).select("doc_id", "ordinal", "content_key", "effective_at", "retired_at", "state")


@query(f"{S} SELECT revision, count(*) AS n_rows FROM seg GROUP BY revision")
def history_full_copies(spark, sf):
    return hist.full_copies(_segments(spark, sf)).groupBy("revision").agg(F.count("*").alias("n_rows"))


def _snapshot(v: int) -> None:
    @query(f"{HI}, {sql.snapshot(INSTANTS[v])} SELECT doc_id, ordinal, content_key, body, effective_at, revision FROM snap", f"snapshot_at_r{v}")
    def _(spark, sf):
        return hist.snapshot_at(_history(spark, sf), INSTANTS[v])


for _v in INSTANTS:
    _snapshot(_v)
_EDGES = sorted({t + d for t in INSTANTS.values() for d in (-1, 0)})


@query(f"{HI}, t AS (SELECT unnest({_EDGES}) AS t) SELECT CAST(t AS BIGINT) AS t, count(doc_id) AS slots FROM t LEFT JOIN spans ON effective_at <= t AND (retired_at IS NULL OR retired_at > t) GROUP BY t")
def snapshot_boundary(spark, sf):
    spans = _spans(spark, sf, once=True)
    rows = spans.select(F.explode(F.array(*[F.struct(F.lit(t).cast("long").alias("t"), ((F.col("effective_at") <= t) & (F.col("retired_at").isNull() | (F.col("retired_at") > t))).cast("int").alias("n")) for t in _EDGES])).alias("x"))
    return rows.groupBy("x.t").agg(F.sum("x.n").cast("long").alias("slots"))


@query(f"{HI}, k AS (SELECT *, row_number() OVER (PARTITION BY doc_id, ordinal ORDER BY revision DESC) AS i FROM history WHERE effective_at <= {INSTANTS[4]} AND revision <= 3) SELECT doc_id, ordinal, content_key, revision FROM k WHERE i = 1 AND content_key IS NOT NULL")
def snapshot_as_known(spark, sf):
    return hist.snapshot_at(_history(spark, sf), INSTANTS[4], as_known_at=3).select("doc_id", "ordinal", "content_key", "revision")


@query(f"{LIVE} SELECT doc_id, ordinal, content_key, effective_at, revision FROM live")
def live_slots(spark, sf):
    history = _history(spark, sf)
    before = hist.snapshot_at(history, INSTANTS[4])
    return live.apply(before, history.where("revision = 5")).select("doc_id", "ordinal", "content_key", "effective_at", "revision")


@query(f"{S} SELECT CAST(0 AS BIGINT) AS strays, count(*) AS slots FROM seg WHERE revision = 5")
def live_equals_snapshot(spark, sf):
    history = _history(spark, sf)
    now = live.apply(hist.snapshot_at(history, INSTANTS[4]), history.where("revision = 5"))
    return live.strays(now, history).agg(F.count("*").alias("strays")).crossJoin(now.agg(F.count("*").alias("slots")))


# Search


def _scored(source: str, queries: str) -> str:
    """keys of `source` against `queries`(qid, text): scored(qid, content_key, score)."""
    return f"""keyed AS (SELECT content_key, min(body) AS body FROM {source} WHERE content_key IS NOT NULL GROUP BY content_key),
kv AS ({_sparse_sql('keyed', 'content_key', 'body')}), qv AS ({_sparse_sql(queries, 'qid', 'text')}),
kn2 AS (SELECT content_key, sum(w * w) AS n FROM kv GROUP BY content_key), qn2 AS (SELECT qid, sum(w * w) AS n FROM qv GROUP BY qid),
scored AS (SELECT qid, content_key, round(dot / sqrt(CAST(qn2.n * kn2.n AS DOUBLE)), 6) AS score FROM (
  SELECT qid, content_key, sum(kv.w * qv.w) AS dot FROM kv JOIN qv USING (bucket) GROUP BY qid, content_key) JOIN kn2 USING (content_key) JOIN qn2 USING (qid))"""


_BENCH = "(SELECT item_id AS qid, text FROM benchmark)"
_ORDER = "ORDER BY score DESC, doc_id, ordinal, effective_at"
_TOP = f"""ranked AS (SELECT qid, row_number() OVER (PARTITION BY qid {_ORDER}) AS rank, score, doc_id, ordinal, content_key, effective_at, revision FROM scored JOIN %s USING (content_key))"""
_PICK = "SELECT qid, rank, score, doc_id, ordinal, content_key, effective_at, revision, '%s' AS tier FROM ranked WHERE rank <= 5"


@query(f"{LIVE}, {_scored('live', _BENCH)}, {_TOP % 'live'} {_PICK % 'hot'}")
def search_live_exact(spark, sf):
    return assert_guard(search.live(_benchmark(spark, sf), _live(spark, sf)))


_GOOD = "ok AS (SELECT live.* FROM live JOIN documents USING (doc_id) JOIN labels USING (doc_id) WHERE lang = 'en' AND quality = 1 AND toxic = 0)"


@query(f"{LIVE}, {_GOOD}, {_scored('ok', _BENCH)}, {_TOP % 'ok'} {_PICK % 'hot'}")
def search_live_filtered(spark, sf):
    good = load(spark, sf, "documents").where("lang = 'en'").select("doc_id").join(load(spark, sf, "labels").where("quality = 1 and toxic = 0").select("doc_id"), "doc_id")
    return search.live(_benchmark(spark, sf), _live(spark, sf).join(good, "doc_id", "left_semi"))


@query(f"{HI}, {sql.snapshot(T3)}, {_scored('snap', _BENCH)}, {_TOP % 'snap'} {_PICK % 'cold'}")
def search_at(spark, sf):
    return flagship(spark, sf)


_EACH = f"(SELECT item_id AS qid, text FROM benchmark)"


@query(f"""{HI}, {_scored('spans', _BENCH)}, t AS (SELECT item_id AS qid, CAST(list_extract({list(INSTANTS.values())}, CAST(item_id % 5 AS INTEGER) + 1) AS BIGINT) AS t FROM benchmark),
ranked AS (SELECT qid, t, row_number() OVER (PARTITION BY qid {_ORDER}) AS rank, score, doc_id, ordinal, content_key, effective_at, revision FROM scored JOIN t USING (qid) JOIN spans USING (content_key) WHERE effective_at <= t AND (retired_at IS NULL OR retired_at > t))
SELECT * FROM ranked WHERE rank <= 5""")
def search_at_each(spark, sf):
    qs = _benchmark(spark, sf).withColumn("t", workload.instant(F.col("qid") % 5 + 1))
    return assert_guard(search.at_each(qs, _spans(spark, sf, once=True)))


def _side(t: int, s: str) -> str:
    return f"""{s} AS (SELECT qid, doc_id, ordinal, score AS score_{s}, content_key AS key_{s}, row_number() OVER (PARTITION BY qid {_ORDER}) AS rank_{s} FROM scored JOIN spans USING (content_key) WHERE effective_at <= {t} AND (retired_at IS NULL OR retired_at > {t}) QUALIFY rank_{s} <= 5)"""


@query(f"""{HI}, {_scored('spans', _BENCH)}, {_side(INSTANTS[2], 'f')}, {_side(NOW - 1, 't')}
SELECT qid, doc_id, ordinal, rank_f AS rank_from, rank_t AS rank_to, score_f AS score_from, score_t AS score_to, CASE WHEN rank_f IS NULL THEN 'entered' WHEN rank_t IS NULL THEN 'left' WHEN key_f = key_t THEN 'stayed' ELSE 'reworded' END AS fate FROM f FULL JOIN t USING (qid, doc_id, ordinal)""")
def search_between_sides(spark, sf):
    return assert_guard(search.between(_benchmark(spark, sf), _spans(spark, sf), INSTANTS[2], NOW))


@query(f"{HI}, part AS (SELECT * FROM spans WHERE effective_at < {INSTANTS[4]} AND (retired_at IS NULL OR retired_at > {INSTANTS[2]})), {_scored('part', _BENCH)}, {_TOP % 'part'} {_PICK % 'both'}")
def search_between_any(spark, sf):
    return assert_guard(search.between(_benchmark(spark, sf), _spans(spark, sf), INSTANTS[2], INSTANTS[4], mode="any_time"))


@query(f"""{HI}, part AS (SELECT * FROM history WHERE content_key IS NOT NULL AND effective_at >= {INSTANTS[2]} AND effective_at < {INSTANTS[4]}), {_scored('part', _BENCH)},
ranked AS (SELECT qid, row_number() OVER (PARTITION BY qid {_ORDER}) AS rank, score, doc_id, ordinal, effective_at, op, prior_key FROM scored JOIN part USING (content_key)) SELECT * FROM ranked WHERE rank <= 5""")
def search_between_delta(spark, sf):
    return assert_guard(search.between(_benchmark(spark, sf), _history(spark, sf), INSTANTS[2], INSTANTS[4], mode="delta"))


_PHRASES = ["rules as of 2024-02-15", "rules", "rules between 2024-01-01 and 2024-03-31", "what was before 2024-05-01", "changes since 2024-03-31"]
_ROUTED = "VALUES (0, 'historical', 1708041599, NULL), (1, 'live', NULL, NULL), (2, 'comparative', 1704067200, 1711929600), (3, 'historical', 1714521599, NULL), (4, 'comparative', 1711843200, 1719619200)"


def _phrased(spark, sf):
    added = F.element_at(F.array(*[F.lit(p) for p in _PHRASES]), (F.col("qid") % 5 + 1).cast("int"))
    return _benchmark(spark, sf).withColumn("text", F.concat_ws(" ", "text", added))


@query(f"SELECT item_id AS qid, kind, CAST(t_from AS BIGINT) AS t_from, CAST(t_to AS BIGINT) AS t_to FROM benchmark JOIN ({_ROUTED}) AS v(i, kind, t_from, t_to) ON item_id % 5 = i")
def route_classify(spark, sf):
    return route.classify(_phrased(spark, sf), NOW).select("qid", "kind", "t_from", "t_to")


_BY_ROUTE = f"""routed AS (SELECT item_id AS qid, kind, CAST(t_from AS BIGINT) AS t_from, CAST(t_to AS BIGINT) AS t_to FROM benchmark JOIN ({_ROUTED}) AS v(i, kind, t_from, t_to) ON item_id % 5 = i)"""
_CORE = "(SELECT item_id AS qid, lower(text || CASE item_id % 5 WHEN 0 THEN ' rules' WHEN 1 THEN ' rules' WHEN 2 THEN ' rules' WHEN 3 THEN ' what was' ELSE ' changes' END) AS text FROM benchmark)"


@query(f"""{HI}, {_BY_ROUTE}, {_scored('spans', _CORE)},
met AS (SELECT qid, kind, score, doc_id, ordinal, effective_at, CASE WHEN kind = 'comparative' AND retired_at IS NULL THEN 'hot' WHEN kind = 'live' THEN 'hot' ELSE 'cold' END AS tier, retired_at
  FROM scored JOIN routed USING (qid) JOIN spans USING (content_key)
  WHERE CASE kind WHEN 'live' THEN retired_at IS NULL WHEN 'historical' THEN effective_at <= t_from AND (retired_at IS NULL OR retired_at > t_from)
    ELSE effective_at < t_to AND (retired_at IS NULL OR retired_at > t_from) END)
SELECT qid, kind, row_number() OVER (PARTITION BY qid ORDER BY score DESC, doc_id, ordinal, effective_at) AS rank, score, doc_id, ordinal, effective_at, retired_at, tier FROM met QUALIFY rank <= 5""")
def route_answer(spark, sf):
    """Each query by its route, from the tier that the route reads."""
    qs = route.classify(_phrased(spark, sf), NOW).select("qid", F.col("core_text").alias("text"), "kind", "t_from", "t_to")
    found = dispatch.answer(qs, _live(spark, sf, once=True), _spans(spark, sf, once=True))
    return found.select("qid", "kind", "rank", "score", "doc_id", "ordinal", "effective_at", "retired_at", "tier")


@query(f"""{LIVE}, keyed AS (SELECT content_key, min(body) AS body FROM live GROUP BY content_key),
kt AS (SELECT DISTINCT content_key, unnest(regexp_split_to_array(lower(regexp_replace(regexp_replace(body, '^{sql.WS}+|{sql.WS}+$', '', 'g'), '{sql.WS}+', ' ', 'g')), '{encode.SEPARATOR}')) AS term FROM keyed),
qt AS (SELECT DISTINCT item_id AS qid, unnest(regexp_split_to_array(lower(text), '{encode.SEPARATOR}')) AS term FROM benchmark),
idf AS (SELECT term, ln(((SELECT count(*) FROM keyed) + 1.0) / (count(*) + 1.0)) AS idf FROM kt WHERE term <> '' GROUP BY term),
sk AS (SELECT qid, content_key, round(sum(idf), 6) AS score FROM kt JOIN qt USING (term) JOIN idf USING (term) WHERE term <> '' GROUP BY ALL),
ranked AS (SELECT qid, row_number() OVER (PARTITION BY qid {_ORDER}) AS rank, score, doc_id, ordinal FROM sk JOIN live USING (content_key)) SELECT * FROM ranked WHERE rank <= 5""")
def keyword_search(spark, sf):
    return baselines.keyword(_benchmark(spark, sf), _live(spark, sf, once=True))


# Baselines and measures: what is reprocessed, detected, stored, leaked

ST = f"WITH {sql.seg('steady')}, {sql.COMBINED}"
_SHARE = "round(encoded / CAST(total AS DOUBLE), 6) AS share"
_DK = "dk AS (SELECT doc_id, revision, string_agg(content_key, '|' ORDER BY ordinal) AS d FROM seg GROUP BY ALL), td AS (SELECT n.doc_id, n.revision FROM dk n LEFT JOIN dk o ON o.doc_id = n.doc_id AND o.revision = n.revision - 1 WHERE o.d IS NULL OR o.d <> n.d)"
_TOTAL = "tot AS (SELECT revision, count(*) AS total, sum(length(body)) AS chars FROM seg GROUP BY revision)"


def _sent(strategy: str, rows: str, amount: str = "count(*)", total: str = "total") -> str:
    return f"SELECT '{strategy}' AS strategy, revision, coalesce(encoded, 0) AS encoded, total, round(coalesce(encoded, 0) / CAST(total AS DOUBLE), 6) AS share FROM (SELECT revision, {total} AS total FROM tot) LEFT JOIN (SELECT revision, {amount} AS encoded FROM {rows} GROUP BY revision) USING (revision)"


def _reprocessed(name: str, oracle: str, make) -> None:
    @query(f"{ST}, {_DK}, {_TOTAL} {oracle}", f"reprocessed_{name}")
    def _(spark, sf):
        segs = _segments(spark, sf, "steady")
        return make(segs)


_reprocessed("full", _sent("full", "seg"), lambda s: metrics.reprocessed(baselines.full_reindex(s), s, "full"))
_reprocessed("upsert", _sent("upsert", "(SELECT seg.* FROM seg JOIN td USING (doc_id, revision))"), lambda s: metrics.reprocessed(baselines.document_upsert(s), s, "upsert"))
_reprocessed("upsert_all", _sent("upsert_all", "seg"), lambda s: metrics.reprocessed(baselines.document_upsert(s, False), s, "upsert_all"))
_reprocessed("chunk", _sent("chunk", "(SELECT * FROM changes WHERE needs_encoding)"), lambda s: metrics.reprocessed(baselines.chunk_sync(s), s, "chunk"))
_reprocessed("chunk_keys", _sent("chunk_keys", "(SELECT * FROM changes WHERE needs_encoding)", "count(DISTINCT content_key)"), lambda s: metrics.reprocessed(baselines.chunk_sync(s), s, "chunk_keys", "keys"))
_reprocessed("chunk_chars", _sent("chunk_chars", "(SELECT * FROM changes WHERE needs_encoding)", "sum(length(body))", "chars"), lambda s: metrics.reprocessed(baselines.chunk_sync(s).join(s.select(*VERSION, "ordinal", "body"), [*VERSION, "ordinal"]), s, "chunk_chars", "chars"))


@query(f"""{ST}, win AS (SELECT (date_diff('second', TIMESTAMP '1970-01-01', ts) // 43200) * 43200 AS w, user_id, event_type, ts FROM events),
g AS (SELECT user_id, event_type, w, max(ts) AS last_ts, count(*) AS updates, CAST(w + 43200 - min(date_diff('second', TIMESTAMP '1970-01-01', ts)) AS BIGINT) AS longest_wait, CAST((w + 43200) * count(*) - sum(date_diff('second', TIMESTAMP '1970-01-01', ts)) AS BIGINT) AS total_wait FROM win GROUP BY user_id, event_type, w)
SELECT user_id, event_type, CAST(w AS BIGINT) AS window_start, updates, longest_wait, total_wait FROM g""", "windowed_refresh")
def windowed_refresh(spark, sf):
    found = baselines.windowed_refresh(load(spark, sf, "events"), ["user_id", "event_type"])
    return found.select("user_id", "event_type", "window_start", "updates", "longest_wait", "total_wait")


_TRUTH = """truth AS (SELECT x.doc_id, x.revision, x.ordinal FROM (SELECT g.*, p.origin AS before FROM gen g LEFT JOIN gen p ON p.doc_id = g.doc_id AND p.revision = g.revision - 1 AND p.origin = g.origin) x
LEFT JOIN rolled r ON r.doc_id = x.doc_id AND 'b' || r.ord = x.origin
WHERE before IS NULL OR CASE x.revision WHEN 2 THEN r2 WHEN 3 THEN r3 WHEN 4 THEN r4 WHEN 5 THEN r5 ELSE 999 END < 100)"""


def _detection(profile: str) -> None:
    @query(f"""WITH {sql.seg(profile)}, {sql.COMBINED}, {_TRUTH}, p AS (SELECT doc_id, revision, ordinal FROM changes WHERE needs_encoding),
m AS (SELECT count(*) FILTER (p.doc_id IS NOT NULL AND t.doc_id IS NOT NULL) AS tp, count(*) FILTER (t.doc_id IS NULL) AS fp, count(*) FILTER (p.doc_id IS NULL) AS fn
  FROM p FULL JOIN truth t ON p.doc_id = t.doc_id AND p.revision = t.revision AND p.ordinal = t.ordinal)
SELECT tp, fp, fn, round(tp / CAST(tp + fp AS DOUBLE), 6) AS precision, round(tp / CAST(tp + fn AS DOUBLE), 6) AS recall, round(tp / CAST(tp + (fp + fn) / 2.0 AS DOUBLE), 6) AS f1 FROM m""", f"detection_quality_{profile}")
    def _(spark, sf):
        """Truth comes from the origins of the lines, never from hashes."""
        made = workload.lines(spark, sf, profile)
        before = made.select("doc_id", (F.col("revision") + 1).alias("revision"), "origin", F.lit(True).alias("was"))
        met = made.join(before, ["doc_id", "revision", "origin"], "left")
        base = F.when(F.col("origin").startswith("b"), workload.roll(F.col("doc_id"), F.substring("origin", 2, 20), F.col("revision"), "line"))
        truth = met.where(F.col("was").isNull() | ((base < 100) & (F.col("revision") > 1)))
        return metrics.detection_quality(_changes(spark, sf, profile).where("needs_encoding"), truth, ["doc_id", "revision", "ordinal"])


_detection("steady")
_detection("structural")


@query(f"""{HI} SELECT 'live' AS form, count(*) AS n_rows FROM spans WHERE retired_at IS NULL UNION ALL SELECT 'event_log', count(*) FROM history
UNION ALL SELECT 'intervals', count(*) FROM spans UNION ALL SELECT 'full_copies', count(*) FROM seg""")
def storage_rows(spark, sf):
    history = _history(spark, sf)
    return metrics.storage_rows(live.rebuild(history), history, hist.full_copies(_segments(spark, sf)))


def _edited(spans: DataFrame) -> DataFrame:
    """The first 20 edited slots before their edit, numbered n; no task sorts the others."""
    place = ("doc_id", "ordinal", "effective_at")
    old = spans.where("state = 'replaced'").orderBy(*place).limit(20)
    return old.withColumn("n", F.row_number().over(W.orderBy(*place)))


def _asked(spans: DataFrame) -> DataFrame:
    """20 edited slots' texts before the edit, each asked at all five instants."""
    old = _edited(spans)
    t = F.explode(F.array(*[F.struct(F.lit(v).alias("v"), F.lit(x).cast("long").alias("t")) for v, x in INSTANTS.items()]))
    return old.select("n", F.col("body").alias("text"), t.alias("x")).select((F.col("n") * 10 + F.col("x.v")).cast("long").alias("qid"), "text", "x.t")


_ASKED = f"""asked AS (SELECT CAST(n * 10 + v AS BIGINT) AS qid, text, CAST(t AS BIGINT) AS t FROM (SELECT body AS text, row_number() OVER (ORDER BY doc_id, ordinal, effective_at) AS n FROM spans WHERE state = 'replaced' QUALIFY n <= 20),
  (VALUES {', '.join(f'({v}, {t})' for v, t in INSTANTS.items())}) AS i(v, t))"""
_VALID = "effective_at <= t AND (retired_at IS NULL OR retired_at > t)"


def _variant(name: str, rows: str, before: bool, after: bool) -> str:
    where = f"({rows})" + (f" AND {_VALID}" if before else "")
    top = f"(SELECT qid, {_VALID} AS valid, row_number() OVER (PARTITION BY qid {_ORDER}) AS rank FROM scored JOIN asked USING (qid) JOIN spans USING (content_key) WHERE {where} QUALIFY rank <= 5)"
    return f"SELECT '{name}' AS variant, count(*) AS n_rows, count(*) FILTER (NOT valid) AS invalid, 500 - count(*) AS shortfall FROM {top}" + (" WHERE valid" if after else "")


_VARIANTS = (("snapshot_first", "true", True, False), ("unfiltered_live", "state = 'live'", False, False), ("unfiltered_all", "true", False, False), ("stale_index", "state IN ('live', 'removed')", False, False), ("postfilter_live", "state = 'live'", False, True), ("postfilter_all", "true", False, True))


@query(f"{HI}, {_ASKED}, {_scored('spans', 'asked')} " + " UNION ALL ".join(_variant(*v) for v in _VARIANTS))
def leakage_by_variant(spark, sf):
    """All indexes are asked in one pass over the log."""
    spans = _spans(spark, sf, once=True)
    asked = tiers.kept(spark, sf, "asked", lambda: _asked(spans))
    found = tiers.kept(spark, sf, "asked_of_indexes", lambda: baselines.indexed(asked, spans, 5, ("snapshot", "live", "all", "stale")))
    of = lambda index: found.where(F.col("index") == index)
    out = metrics.leakage(of("snapshot"), 100, 5, "snapshot_first")
    for name, index, validate in (("unfiltered_live", "live", False), ("unfiltered_all", "all", False), ("stale_index", "stale", False), ("postfilter_live", "live", True), ("postfilter_all", "all", True)):
        out = out.union(metrics.leakage(baselines.validated(of(index)) if validate else of(index), 100, 5, name))
    return out


@query(f"""{HI}, {_ASKED}, {_scored('spans', 'asked')}, before AS (SELECT doc_id, ordinal, effective_at, retired_at, row_number() OVER (ORDER BY doc_id, ordinal, effective_at) AS n FROM spans WHERE state = 'replaced' QUALIFY n <= 20),
top AS (SELECT qid, doc_id, ordinal, effective_at, score FROM scored JOIN asked USING (qid) JOIN spans USING (content_key) WHERE {_VALID} QUALIFY row_number() OVER (PARTITION BY qid {_ORDER}) <= 5),
hit AS (SELECT asked.qid, coalesce(max(CASE WHEN top.doc_id = before.doc_id AND top.ordinal = before.ordinal AND top.effective_at = before.effective_at THEN 1 ELSE 0 END), 0) AS found, min(CASE WHEN t >= before.effective_at AND t < before.retired_at THEN 1 ELSE 0 END) AS should FROM asked JOIN before ON n = asked.qid // 10 LEFT JOIN top USING (qid) GROUP BY asked.qid)
SELECT count(*) AS queries, count(*) FILTER (found = 0 AND should = 0) + count(*) FILTER (found = 1 AND should = 1) AS agree, count(*) FILTER (found = 1 AND should = 0) AS leaked FROM hit""")
def temporal_accuracy(spark, sf):
    """Is a slot's old text found exactly at the instants at which it was valid?"""
    spans = _spans(spark, sf)
    asked = tiers.kept(spark, sf, "asked", lambda: _asked(spans))
    old = _edited(spans).select("n", *[F.col(c).alias(f"o_{c}") for c in ("doc_id", "ordinal", "effective_at", "retired_at")])
    top = search.at_each(asked, spans).drop("t")
    met = asked.select("qid", "t").join(F.broadcast(old), F.floor(F.col("qid") / 10) == F.col("n")).join(top, "qid", "left")
    here = (F.col("doc_id") == F.col("o_doc_id")) & (F.col("ordinal") == F.col("o_ordinal")) & (F.col("effective_at") == F.col("o_effective_at"))
    per = met.groupBy("qid").agg(F.coalesce(F.bool_or(here), F.lit(False)).alias("found"), F.bool_and((F.col("t") >= F.col("o_effective_at")) & (F.col("t") < F.col("o_retired_at"))).alias("should"))
    return per.agg(F.count("*").alias("queries"), F.count_if(F.col("found") == F.col("should")).alias("agree"), F.count_if(F.col("found") & ~F.col("should")).alias("leaked"))


# Audit and reports


@query(f"{CH} SELECT doc_id, revision, ordinal, op, 'segment ' || (ordinal + 1) || ' was ' || CASE WHEN op = 'moved' THEN 'moved from ' || (moved_from + 1) ELSE op END AS sentence FROM changes WHERE op <> 'kept'")
def audit_describe(spark, sf):
    return audit.describe_changes(_changes(spark, sf))


@query(f"{S} SELECT doc_id, sha256(lower(string_agg(regexp_replace(regexp_replace(body, '^{sql.WS}+|{sql.WS}+$', '', 'g'), '{sql.WS}+', ' ', 'g'), chr(10) ORDER BY ordinal))) AS digest FROM seg WHERE revision = 3 GROUP BY doc_id")
def audit_rebuild(spark, sf):
    spans = _spans(spark, sf, once=True).withColumn("body", fingerprint.canonical(F.col("body")))  # with ends: texts are dealt out once
    return audit.rebuild_documents(spans, T3).select("doc_id", F.sha2("text", 256).alias("digest"))


@query(f"{HI} SELECT doc_id, ordinal, revision, op, content_key, row_number() OVER w AS step, lag(content_key) OVER w AS before FROM history WINDOW w AS (PARTITION BY doc_id, ordinal ORDER BY effective_at, revision)")
def audit_lineage(spark, sf):
    return audit.lineage(_history(spark, sf, once=True))


@query(f"""{HI} SELECT revision, effective_at, {', '.join(f"count(*) FILTER (op = '{o}') AS {o}" for o in ('added', 'edited', 'moved', 'dropped', 'vacated'))},
(SELECT count(*) FROM spans s WHERE s.effective_at <= h.effective_at AND (retired_at IS NULL OR retired_at > h.effective_at)) AS live_slots FROM history h GROUP BY revision, effective_at""")
def audit_timeline(spark, sf):
    return audit.timeline(_history(spark, sf))


@query(f"{CH} SELECT revision, doc_id, count(*) FILTER (needs_encoding) AS changed, count(*) FILTER (op NOT IN ('dropped', 'vacated')) AS total FROM changes WHERE NOT audit GROUP BY revision, doc_id")
def ingest_summary(spark, sf):
    return _changes(spark, sf).where("not audit").groupBy("revision", "doc_id").agg(F.count_if("needs_encoding").alias("changed"), F.count_if(~F.col("op").isin("dropped", "vacated")).alias("total"))


@query(f"{CH} SELECT lang, source, op, count(*) AS n FROM changes JOIN documents USING (doc_id) GROUP BY CUBE (lang, source, op)")
def changes_cube(spark, sf):
    docs = load(spark, sf, "documents").select("doc_id", "lang", "source")
    return _changes(spark, sf).join(docs, "doc_id").cube("lang", "source", "op").agg(F.count("*").alias("n"))


@query(f"""{CH} SELECT revision, {', '.join(f"count(*) FILTER (op = '{o}') AS {o}" for o in ('kept', 'added', 'edited', 'moved', 'dropped', 'vacated'))} FROM changes GROUP BY revision""")
def changes_pivot(spark, sf):
    return _changes(spark, sf).groupBy("revision").pivot("op", ["kept", "added", "edited", "moved", "dropped", "vacated"]).agg(F.count(F.lit(1))).na.fill(0)


# Feeds and records


@query("SELECT user_id, event_type, event_id, value, row_number() OVER w AS version, lead(event_id) OVER w AS next_id FROM events WINDOW w AS (PARTITION BY user_id, event_type ORDER BY ts, event_id)")
def events_versions(spark, sf):
    w = W.partitionBy("user_id", "event_type").orderBy("ts", "event_id")
    return load(spark, sf, "events").select("user_id", "event_type", "event_id", "value", F.row_number().over(w).alias("version"), F.lead("event_id").over(w).alias("next_id"))


@query("SELECT user_id, event_type, arg_max(event_id, (ts, event_id)) AS event_id, arg_max(value, (ts, event_id)) AS value FROM events WHERE ts <= TIMESTAMP '2024-01-16 00:00:00' GROUP BY user_id, event_type")
def events_asof(spark, sf):
    last = F.struct("ts", "event_id")
    seen = load(spark, sf, "events").where("ts <= timestamp'2024-01-16 00:00:00'")
    return seen.groupBy("user_id", "event_type").agg(F.max_by("event_id", last).alias("event_id"), F.max_by("value", last).alias("value"))


@query("WITH s AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 6 HOURS THEN 0 ELSE 1 END AS cut FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), g AS (SELECT *, sum(cut) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS n FROM s) SELECT user_id, date_diff('second', TIMESTAMP '1970-01-01', min(ts)) AS started, count(*) AS events FROM g GROUP BY user_id, n")
def events_sessions(spark, sf):
    g = load(spark, sf, "events").groupBy("user_id", F.session_window("ts", "6 hours").alias("s")).agg(F.count("*").alias("events"))
    return g.select("user_id", F.unix_timestamp("s.start").alias("started"), "events")


@query("SELECT CAST(date_diff('second', TIMESTAMP '1970-01-01', ts) // 43200 * 43200 AS BIGINT) AS window_start, event_type, count(*) AS events FROM events GROUP BY ALL")
def events_12h_windows(spark, sf):
    g = load(spark, sf, "events").groupBy(F.window("ts", "12 hours").alias("w"), "event_type").agg(F.count("*").alias("events"))
    return g.select(F.unix_timestamp("w.start").alias("window_start"), "event_type", "events")


@query("SELECT CAST(h * 3600 AS BIGINT) AS window_start, count(*) AS events FROM (SELECT unnest(range(date_diff('second', TIMESTAMP '1970-01-01', ts) // 3600 - 23, date_diff('second', TIMESTAMP '1970-01-01', ts) // 3600 + 1)) AS h FROM events) GROUP BY h")
def events_sliding(spark, sf):
    g = load(spark, sf, "events").groupBy(F.window("ts", "24 hours", "1 hour").alias("w")).agg(F.count("*").alias("events"))
    return g.select(F.unix_timestamp("w.start").alias("window_start"), "events")


_ASOF = "TIMESTAMP '1998-06-01 00:00:00'"


@query(f"SELECT o_custkey, arg_max(o_orderkey, (o_orderdate, o_orderkey)) AS o_orderkey, arg_max(o_orderstatus, (o_orderdate, o_orderkey)) AS status FROM orders WHERE o_orderdate <= {_ASOF} GROUP BY o_custkey")
def orders_asof(spark, sf):
    last = F.struct("o_orderdate", "o_orderkey")
    seen = load(spark, sf, "orders").where("o_orderdate <= timestamp'1998-06-01 00:00:00'")
    return seen.groupBy("o_custkey").agg(F.max_by("o_orderkey", last).alias("o_orderkey"), F.max_by("o_orderstatus", last).alias("status"))


@query("SELECT r_name, n_name, count(*) AS orders FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
def orders_rollup(spark, sf):
    o, c, n, r = (load(spark, sf, t) for t in ("orders", "customer", "nation", "region"))
    met = o.select("o_custkey").join(c.select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey")).join(n, F.col("c_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey"))
    return met.rollup("r_name", "n_name").agg(F.count("*").alias("orders"))


@query(r"WITH k AS (SELECT conv_id, turn, sha256(lower(regexp_replace(regexp_replace(text, '^[ \t\n\r\f]+|[ \t\n\r\f]+$', '', 'g'), '[ \t\n\r\f]+', ' ', 'g'))) AS content_key FROM conversations) SELECT conv_id, turn, content_key, count(*) OVER (PARTITION BY content_key) AS copies FROM k")
def conversation_turns(spark, sf):
    k = load(spark, sf, "conversations").select("conv_id", "turn", fingerprint.content_key(F.col("text")).alias("content_key"))
    copies = k.groupBy("content_key").agg(F.count("*").alias("copies"))
    return k.join(copies, "content_key").select("conv_id", "turn", "content_key", "copies")


# Vector indexes: a stated query set (every 20th vector) against all rows


def _vectors(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    v = load(spark, sf, "embeddings").select("vec_id", "embedding")
    return v.where("vec_id % 20 = 0").withColumnRenamed("vec_id", "qid"), v


@query("""WITH q AS (SELECT vec_id AS qid, embedding AS a FROM embeddings WHERE vec_id % 20 = 0),
s AS (SELECT qid, vec_id, round(list_sum(list_transform(list_zip(CAST(a AS DOUBLE[]), CAST(embedding AS DOUBLE[])), lambda p: p[1] * p[2]))
  / (sqrt(list_sum(list_transform(CAST(a AS DOUBLE[]), lambda p: p * p))) * sqrt(list_sum(list_transform(CAST(embedding AS DOUBLE[]), lambda p: p * p)))), 6) AS score FROM q, embeddings)
SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY score DESC, vec_id) AS rank, vec_id, score FROM s QUALIFY rank <= 10""")
def vector_search_exact(spark, sf):
    from chronotier.operators.ann import index

    return index.exact(*_vectors(spark, sf))


@query()
def search_live_cells(spark, sf):
    from chronotier.experiments import cells

    return cells(*_vectors(spark, sf))


@query()
def search_live_planes(spark, sf):
    from chronotier.operators.ann import index

    q, v = _vectors(spark, sf)
    return index.Planes(v, tables=24).search(q)


@query()
def search_live_graph(spark, sf):
    from chronotier.operators.ann import index

    q, v = _vectors(spark, sf)
    return index.Graph(v).search(q)


@query(f"{CH}, h AS (SELECT DISTINCT content_key FROM changes WHERE needs_encoding AND revision < 5) SELECT DISTINCT content_key, CAST({encode.DIM} AS INTEGER) AS dim, 'hash' AS encoder FROM changes WHERE needs_encoding AND revision = 5 AND content_key NOT IN (SELECT content_key FROM h)")
def encode_missing_hash(spark, sf):
    """Dense vectors of the keys that the last revision brings, and only of these."""
    changes = _changes(spark, sf)
    known = changes.where("needs_encoding and revision < 5").select("content_key").distinct()
    bodies = _segments(spark, sf).where("revision = 5").select("doc_id", "ordinal", "body")
    new = changes.where("revision = 5").join(bodies, ["doc_id", "ordinal"])
    return encode.encode_missing(new, known, encode.HashEncoder()).select("content_key", "dim", "encoder")


# Known-item search: a benchmark passage asked, the live slots that hold it wanted

_WANTED = "bench AS (SELECT item_id AS qid, text FROM benchmark), wanted AS (SELECT qid, doc_id, ordinal FROM bench JOIN live ON contains(body, text))"


@query(f"""{LIVE}, {_scored('live', _BENCH)}, {_TOP % 'live'}, {_WANTED},
best AS (SELECT qid, sum(1 / log2(i + 1.0)) AS ideal FROM (SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY doc_id, ordinal) AS i FROM wanted) WHERE i <= 5 GROUP BY qid),
hits AS (SELECT qid, sum(1 / log2(rank + 1.0)) AS dcg, min(rank) AS first FROM ranked JOIN wanted USING (qid, doc_id, ordinal) WHERE rank <= 5 GROUP BY qid)
SELECT count(*) AS queries, round(avg(coalesce(dcg / ideal, 0)), 6) AS ndcg, round(avg(coalesce(1.0 / first, 0)), 6) AS mrr FROM best LEFT JOIN hits USING (qid)""")
def ann_ndcg(spark, sf):
    history = _history(spark, sf)
    now, bench = hist.snapshot_at(history, None), _benchmark(spark, sf)
    item = F.concat_ws(":", "doc_id", "ordinal").alias("item")
    wanted = now.join(F.broadcast(bench), F.expr("contains(body, text)")).select("qid", item, F.lit(1).alias("rel"))
    return metrics.ndcg_at_k(search.live(bench, now).select("qid", "rank", item), wanted, 5)


# Models of cost

_RATE = 0.1


@query(f"WITH {sql.BASE}, n AS (SELECT count(*) AS c FROM base GROUP BY doc_id) SELECT round(sum(c * (1 - pow({1 - _RATE}, c))) / sum(c), 6) AS upsert, CAST({_RATE} AS DOUBLE) AS sync, round(sum(c * (1 - pow({1 - _RATE}, c))) / sum(c) / {_RATE}, 4) AS speedup FROM n")
def work_model(spark, sf):
    """Shares that upsert and chunk sync should reprocess if a tenth of the lines change."""
    n = workload.base_lines(load(spark, sf, "documents")).groupBy("doc_id").agg(F.count("*").alias("c"))
    share = F.sum(F.col("c") * (1 - F.pow(F.lit(1 - _RATE), F.col("c")))) / F.sum("c")
    return n.agg(F.round(share, 6).alias("upsert"), F.lit(_RATE).alias("sync"), F.round(share / _RATE, 4).alias("speedup"))


@query(f"WITH {sql.BASE} SELECT count(DISTINCT {sql.key('body')}) AS keys, round(2 * log2(count(DISTINCT {sql.key('body')})) - 257, 4) AS log2_bound FROM base")
def collision_bound(spark, sf):
    """Binary logarithm of the chance that any two of the corpus' keys collide."""
    keys = workload.base_lines(load(spark, sf, "documents")).agg(F.count_distinct(fingerprint.content_key(F.col("body"))).alias("keys"))
    return keys.select("keys", F.round(2 * F.log2("keys") - 257, 4).alias("log2_bound"))


# SQL surface, streaming state, drills and timings


@query(f"{HI}, {sql.snapshot(T3)} SELECT doc_id, ordinal, content_key, body, effective_at, revision FROM snap")
def sql_snapshot(spark, sf):
    surface.register(spark, _history(spark, sf))
    return spark.sql(f"SELECT * FROM snapshot_at({T3})")


@query(f"{HI} SELECT doc_id, ordinal, op, content_key, prior_key, effective_at, revision FROM history WHERE effective_at >= {INSTANTS[2]} AND effective_at < {INSTANTS[4]}")
def sql_changes_between(spark, sf):
    surface.register(spark, _history(spark, sf))
    return spark.sql("SELECT * FROM changes_between(:a, :b)", args={"a": INSTANTS[2], "b": INSTANTS[4]})


@query(_LINES % "string_split(text, chr(10))")
def sql_split_document(spark, sf):
    surface.register(spark, _history(spark, sf))
    load(spark, sf, "documents").createOrReplaceTempView("split_input")
    return spark.sql("SELECT doc_id, s.ordinal, s.body FROM split_input, LATERAL split_document(text) s")


@query(f"{CH} SELECT doc_id, revision, ordinal, op, content_key, prior_key FROM changes WHERE op <> 'kept' AND NOT audit")
def stream_ledger(spark, sf):
    """All revisions as a stream, the ledger in streaming state; equals the batch diff."""
    from chronotier.streaming import stream

    rows = F.array_sort(F.collect_list(F.struct("ordinal", "content_key")))
    made = _segments(spark, sf).groupBy("doc_id", "revision").agg(F.transform(rows, lambda x: x["content_key"]).alias("keys"))
    every = made.select("doc_id").distinct().withColumn("revision", F.explode(F.sequence(F.lit(1).cast("long"), F.lit(5).cast("long"))))
    every = every.join(made, ["doc_id", "revision"], "left").select("doc_id", "revision", workload.instant(F.col("revision")).alias("effective_at"), "keys")
    at = scratch.folder(spark, "stream")
    every.write.parquet(f"{at}/in")
    source = spark.readStream.schema(every.schema).parquet(f"{at}/in")
    stream.changes_to(source, f"{at}/out", f"{at}/checkpoint")
    return spark.read.schema(stream.LEDGER_CHANGES).parquet(f"{at}/out").drop("effective_at")


_DRILLS = ("before_log", "log_put", "after_log", "amid_live", "pointer_put", "before_mark", "mark_put", "live_fails")


@query("SELECT unnest([%s]) AS point, CAST(0 AS BIGINT) AS lost, CAST(0 AS BIGINT) AS strays, CAST(0 AS BIGINT) AS seen_early, CAST(0 AS BIGINT) AS still_open" % ", ".join(f"'{p}'" for p in _DRILLS))
def commit_faults(spark, sf):
    """The protocol broken at each of its points, at a revision of its own, then
    reconciled and delivered again: rows that the history lacks, rows that the tiers
    disagree on, rows of the broken commit that readers saw before, commits left open."""
    from chronotier.operators.commit import POINTS, Fault, Store

    assert (*POINTS, "live_fails") == _DRILLS
    events, rows = _history(spark, sf).drop("month"), []
    key = ["doc_id", "ordinal", "revision"]
    new = lambda: Store(spark, scratch.folder(spark, "store"), buckets=4)
    for n, point in enumerate(_DRILLS):
        revision = n % 5 + 1  # five revisions, then again in a store of its own
        store = new() if revision == 1 else store
        batch, early = events.where(F.col("revision") == revision), 0
        store.fault, store.failing = (None, OSError("no space")) if point == "live_fails" else (point, None)
        try:
            store.publish(batch, f"r{revision}")
        except (Fault, OSError):
            early = store.history().where(F.col("revision") == revision).count()
            store.reconcile("forward")
            store.publish(batch, f"r{revision}")
        kept = store.history()
        lost = events.where(F.col("revision") <= revision).join(kept.select(*key), key, "left_anti").count()
        rows.append((point, lost, live.strays(store.live(), kept).count(), early, sum(c.phase in ("PENDING", "UNCOMMITTED") for c in store.commits())))
    return spark.createDataFrame(rows, "point string, lost long, strays long, seen_early long, still_open long")


@query("SELECT CAST(5 AS BIGINT) AS commits, CAST(0 AS BIGINT) AS never_visible, CAST(0 AS BIGINT) AS before_the_log")
def staleness(spark, sf):
    """Five commits of the revisions' events, a tenth of the documents: is what was logged
    visible, and never sooner? The seconds are in staleness_seconds."""
    found = tiers.kept(spark, sf, "staleness", lambda: _staleness(spark, sf))
    return found.agg(F.count("*").alias("commits"), F.count_if(F.col("seconds").isNull()).alias("never_visible"), F.count_if(F.col("seconds") < 0).alias("before_the_log"))


def _staleness(spark, sf):
    from chronotier.operators.commit import Store

    store = Store(spark, scratch.folder(spark, "store"), buckets=8)
    events = _history(spark, sf).where("doc_id % 10 = 1").drop("month")
    for revision in INSTANTS:
        store.publish(events.where(F.col("revision") == revision), f"r{revision}")
    rows = [(c.seq, c.phase, c.logged_at, c.visible_at) for c in store.commits()]
    return spark.createDataFrame(rows, "seq long, phase string, logged_at double, visible_at double").withColumn("seconds", F.col("visible_at") - F.col("logged_at"))


@query()
def staleness_seconds(spark, sf):
    """Longest and mean seconds between the log and the live tier, over those commits."""
    found = tiers.kept(spark, sf, "staleness", lambda: _staleness(spark, sf))
    return metrics.staleness(found)


@query()
def query_latency(spark, sf):
    """Milliseconds by route: the benchmark texts asked of the live tier, of an instant
    and of a range, each twenty times over the stored tiers. p50, p95 and p99 of a batch."""
    q, now, spans = _benchmark(spark, sf), _live(spark, sf), _spans(spark, sf)
    save = lambda df: df.write.format("noop").mode("overwrite").save()
    routes = {"live": lambda: save(search.live(q, now)), "historical": lambda: save(search.at(q, spans, T3)), "comparative": lambda: save(search.between(q, spans, INSTANTS[2], NOW))}
    return spark.createDataFrame([(name, *(float(x) for x in metrics.timed(fn, 20).values())) for name, fn in routes.items()], "route string, p50 double, p95 double, p99 double")


@query()
def update_latency(spark, sf):
    """Milliseconds to find and encode what each strategy sends at the last revision:
    chunk sync, upsert of changed documents, full; with the rows sent."""
    segs = _segments(spark, sf, "steady")
    bodies = segs.where("revision = 5").select("doc_id", "revision", "ordinal", "body", "content_key")
    sync = baselines.chunk_sync(segs).where("revision = 5").select("doc_id", "revision", "ordinal")
    sent = {"sync": bodies.join(sync, ["doc_id", "revision", "ordinal"], "left_semi"), "upsert": baselines.document_upsert(segs).where("revision = 5"), "full": bodies}
    rows = []
    for name, df in sent.items():
        took = metrics.timed(lambda df=df: encode.HashEncoder().encode(df).write.format("noop").mode("overwrite").save(), 3)
        rows.append((name, df.count(), float(took["p50"])))
    return spark.createDataFrame(rows, "strategy string, n_rows long, ms double")
