"""The workload and the engine's tables in DuckDB SQL, as named sub-queries."""

from __future__ import annotations

from chronotier.sources.workload import INSTANTS, LATER, LOWER, UPPER

WS = r"[ \t\n\r\f]"


def roll(*parts: str) -> str:
    return f"(CAST('0x' || substr(md5(concat_ws('|', {', '.join(parts)})), 1, 8) AS BIGINT) % 1000)"


def key(body: str) -> str:
    return rf"sha256(lower(regexp_replace(regexp_replace({body}, '^{WS}+|{WS}+$', '', 'g'), '{WS}+', ' ', 'g')))"


BASE = rf"""
base AS (SELECT doc_id, CAST(row_number() OVER (PARTITION BY doc_id ORDER BY n) - 1 AS BIGINT) AS ord, body FROM (
  SELECT doc_id, unnest(string_split(text, chr(10))) AS body, generate_subscripts(string_split(text, chr(10)), 1) AS n FROM documents)
  WHERE length(regexp_replace(body, '{WS}', '', 'g')) > 0)"""


def seg(profile: str = "steady", edits: int = 100) -> str:
    """base, gen and seg (doc_id, revision, effective_at, ordinal, body, content_key, origin)."""
    structural = profile == "structural"
    rolls = ", ".join(f"{roll('doc_id', 'ord', str(u), chr(39) + 'line' + chr(39))} AS r{u}" for u in LATER)
    last = "greatest(0, " + ", ".join(f"CASE WHEN r{u} < {edits} AND v >= {u} THEN {u} ELSE 0 END" for u in LATER) + ")"
    now = "CASE " + " ".join(f"WHEN v = {u} THEN r{u}" for u in LATER) + " ELSE 999 END"
    dropped = " OR ".join(f"(r{u} BETWEEN 130 AND 144 AND v >= {u})" for u in LATER)
    swap = " OR ".join(f"({roll('doc_id', chr(39) + 'swap' + chr(39), str(u))} < 20 AND v >= {u})" for u in LATER)
    gone = " OR ".join(f"({roll('doc_id', chr(39) + 'gone' + chr(39), str(u))} < 5 AND v >= {u})" for u in LATER)
    draw = lambda s: roll("doc_id", f"'{s}'", "u")
    place = f"CASE WHEN ({swap}) AND ord < 2 THEN 1 - ord ELSE ord END" if structural else "ord"
    instants = " ".join(f"WHEN {v} THEN {t}" for v, t in INSTANTS.items())
    head = f"""UNION ALL SELECT doc_id, v, 0, -u, 0, 'Notice r' || u || ' of document ' || doc_id, 'h' || u FROM grown WHERE {draw('head')} < 20""" if structural else ""
    return f"""{BASE},
rolled AS (SELECT *, {rolls} FROM base),
per AS (SELECT *, {last} AS e, {now} AS now FROM rolled, (SELECT unnest(range(1, 6)) AS v) {f'WHERE NOT ({dropped})' if structural else ''}),
edited AS (SELECT doc_id, v, ord, now, CASE WHEN e > 0 THEN body || ' ~r' || e ELSE body END AS body FROM per),
grown AS (SELECT doc_id, u, unnest(range(u, 6)) AS v FROM (SELECT DISTINCT doc_id FROM documents), (SELECT unnest(range(2, 6)) AS u)),
every AS (
  SELECT doc_id, v, 1 AS part, {place} AS a, 0 AS b, CASE WHEN now >= {edits} AND now < {edits + 30} THEN '  ' || translate(body, '{LOWER}', '{UPPER}') || ' ' ELSE body END AS body, 'b' || ord AS origin FROM edited
  UNION ALL SELECT doc_id, v, 2, u, 1, text, 't' || u FROM (SELECT *, {draw('tail')} AS r FROM grown) g JOIN benchmark ON item_id = r % (SELECT count(*) FROM benchmark) WHERE r < 150
  UNION ALL SELECT g.doc_id, v, 2, u, 0, body, 'c' || u FROM (SELECT * FROM grown WHERE {draw('copy')} < 10) g JOIN base ON base.doc_id + 1 = g.doc_id AND ord = 0
  {head}),
gen AS (SELECT doc_id, CAST(v AS BIGINT) AS revision, CAST(CASE v {instants} END AS BIGINT) AS effective_at,
  CAST(row_number() OVER (PARTITION BY doc_id, v ORDER BY part, a, b) - 1 AS BIGINT) AS ordinal, body, origin
  FROM every WHERE NOT ({gone}) AND NOT (doc_id % 50 = 49 AND v < 2)),
seg AS (SELECT *, {key('body')} AS content_key FROM gen)"""


#: Rows that were (revision shifted by one) and rows that are, slot by slot; sets of keys.
PAIRS = """
old AS (SELECT doc_id, revision + 1 AS revision, ordinal, content_key, body FROM seg WHERE revision < 5),
ko AS (SELECT doc_id, revision, content_key, min(ordinal) AS at FROM old GROUP BY ALL),
kn AS (SELECT doc_id, revision, content_key, min(ordinal) AS at FROM seg GROUP BY ALL),
slots AS (SELECT coalesce(o.doc_id, n.doc_id) AS doc_id, coalesce(o.revision, n.revision) AS revision, coalesce(o.ordinal, n.ordinal) AS ordinal,
  o.content_key AS a, n.content_key AS b, n.body, o.ordinal IS NOT NULL AS had, n.ordinal IS NOT NULL AS has
  FROM old o FULL JOIN seg n ON o.doc_id = n.doc_id AND o.revision = n.revision AND o.ordinal = n.ordinal)"""

COMBINED = PAIRS + """,
marked AS (SELECT s.*, ko.at AS came, kn.at IS NOT NULL AS stays FROM slots s
  LEFT JOIN ko ON ko.doc_id = s.doc_id AND ko.revision = s.revision AND ko.content_key = s.b
  LEFT JOIN kn ON kn.doc_id = s.doc_id AND kn.revision = s.revision AND kn.content_key = s.a),
main AS (SELECT *, CASE WHEN had AND has AND a = b THEN 'kept'
   WHEN has AND came IS NOT NULL THEN 'moved'
   WHEN had AND has AND NOT stays THEN 'edited'
   WHEN has THEN 'added' WHEN stays THEN 'vacated' ELSE 'dropped' END AS op FROM marked),
changes AS (
  SELECT doc_id, revision, ordinal, op, b AS content_key, CASE WHEN op IN ('edited', 'dropped', 'vacated') THEN a END AS prior_key,
    CASE WHEN op = 'moved' THEN came END AS moved_from, op IN ('added', 'edited') AS needs_encoding, false AS audit, body FROM main
  UNION ALL
  SELECT doc_id, revision, ordinal, 'dropped', NULL, a, NULL, false, true, NULL FROM main WHERE op = 'moved' AND had AND NOT stays)"""

INSTANT = "CASE revision " + " ".join(f"WHEN {v} THEN {t}" for v, t in INSTANTS.items()) + " END"
HISTORY = COMBINED + f""",
history AS (SELECT doc_id, ordinal, content_key, CAST({INSTANT} AS BIGINT) AS effective_at, revision, op, prior_key, body
  FROM changes WHERE op <> 'kept' AND NOT audit),
intervals AS (SELECT *, lead(effective_at) OVER w AS retired_at,
  CASE WHEN lead(op) OVER w IS NULL THEN 'live' WHEN lead(op) OVER w IN ('dropped', 'vacated') THEN 'removed' ELSE 'replaced' END AS state
  FROM history WINDOW w AS (PARTITION BY doc_id, ordinal ORDER BY effective_at, revision)),
spans AS (SELECT * FROM intervals WHERE content_key IS NOT NULL)"""


def snapshot(t: int, name: str = "snap") -> str:
    return f"{name} AS (SELECT doc_id, ordinal, content_key, body, effective_at, revision FROM spans WHERE effective_at <= {t} AND (retired_at IS NULL OR retired_at > {t}))"
