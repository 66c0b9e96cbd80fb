"""Licence scan with DataFrame functions only: sparse TF-IDF cosine of headers and
licence files to templates, then inheritance from the nearest ancestor folder.

A licence has templates: the line that states it and the text or notice that grants
it. Document frequencies of the templates' terms are counted over all documents. The
units of a file are its lines and its paragraphs, so that a header is found wherever it
stands; of a licence file also each run of two or three lines, and the whole. A unit is
compared with every template that shares a term with it, by one join on terms. Before
that, it must hold one of the templates' rare terms: the frequent ones together have too
little weight to reach the threshold even if they all matched, so the filter loses
nothing. It leaves about one line in a thousand to be exploded into terms; the
templates' postings are some thousand rows.

A file without a licence of its own takes that of the nearest folder above it which
has a licence file with a match, by one join of its ancestor folders with those.
"""

from __future__ import annotations

import math
from collections import Counter

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from chronotier.llm.common import broadcast_if_small, stage_table
from chronotier.llm.licence_texts import TEMPLATES

THRESHOLD = 0.6
LICENCE_FILES = r"(?i)^(license|licence|copying|notice)(\.[a-z]+)?$"
MAX_ROWS = 500_000


def terms(text: Column) -> Column:
    """Lower-cased runs of letters and digits."""
    return F.filter(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), lambda x: x != "")


def _local_terms(text: str) -> list[str]:
    return "".join(c if c.isalnum() else " " for c in text.lower()).split()


Templates = dict[str, tuple[str, ...]]


def weights(docs: DataFrame, templates: Templates) -> tuple[dict[str, float], float]:
    """Inverse document frequency of each template term, and that of unseen terms."""
    known = sorted({t for texts in templates.values() for x in texts for t in _local_terms(x)})
    wanted = F.array(*map(F.lit, known))
    met = docs.select(F.explode(F.array_intersect(terms(F.col("text")), wanted)).alias("term")).groupBy("term").count()
    df = {r["term"]: r["count"] for r in met.collect()}  # one row per template term
    n = docs.count()
    idf = lambda c: math.log((n + 1) / (c + 1)) + 1
    return {t: idf(df.get(t, 0)) for t in known}, idf(0)


def _vectors(templates: Templates, idf: dict[str, float]) -> list[tuple[str, dict[str, float]]]:
    """(licence, terms with weights of unit length) of each template."""
    found = []
    for name, texts in templates.items():
        for text in texts:
            words = Counter(_local_terms(text))
            norm = math.sqrt(sum((n * idf[t]) ** 2 for t, n in words.items()))
            found.append((name, {t: n * idf[t] / norm for t, n in words.items()}))
    return found


def _gate(vectors: list[tuple[str, dict[str, float]]], threshold: float, idf: dict[str, float]) -> list[str]:
    """Terms one of which any text within the threshold of a template must hold: of each
    template, the most frequent terms are left out as long as they could not reach the
    threshold even if they all matched, so that the rare ones decide what is looked at."""
    gate = set()
    for _, v in vectors:
        rest = 0.0
        for t, x in sorted(v.items(), key=lambda p: (idf[p[0]], p[0])):
            rest += x * x
            if math.sqrt(rest) >= threshold - 1e-9:
                gate.add(t)
    return sorted(gate)


def _units(path: Column, text: Column, lines: Column) -> Column:
    """The different strings of a file that are compared, as an array; lines is a column
    with the text's lines."""
    run = lambda k: F.transform(lines, lambda _, i: F.array_join(F.slice(lines, i + 1, k), "\n"))
    any_file = F.concat(lines, F.split(text, r"\n[ \t\r]*\n"))
    licence_file = F.element_at(F.split(path, "/"), -1).rlike(LICENCE_FILES)
    return F.array_distinct(F.when(licence_file, F.concat(any_file, run(2), run(3), F.array(text))).otherwise(any_file))


def matches(docs: DataFrame, path: Column, templates: Templates | None = None, threshold: float = THRESHOLD) -> DataFrame:
    """Best licence per (doc_id, path): license and score (rounded to 6 digits) of its
    best unit. Ties go to the name that comes first."""
    templates = templates or TEMPLATES
    spark = docs.sparkSession
    idf, unseen = weights(docs, templates)
    vectors = _vectors(templates, idf)
    postings = spark.createDataFrame([(k, n, t, x) for k, (n, v) in enumerate(vectors) for t, x in v.items()], "template int, license string, term string, w double")
    vocabulary = spark.createDataFrame(sorted(idf.items()), "term string, idf double")
    gate = F.array(*map(F.lit, _gate(vectors, threshold, idf)))
    files = docs.select("doc_id", path.alias("path"), "text").where("text is not null")
    # Whole texts without a term of the gate are passed over before they are cut up.
    files = files.where(F.arrays_overlap(terms(F.col("text")), gate)).withColumn("lines", F.split("text", "\n"))
    units = files.select("doc_id", "path", F.explode(_units(F.col("path"), F.col("text"), F.col("lines"))).alias("unit")).select("doc_id", "path", terms(F.col("unit")).alias("terms"))
    units = units.where(F.arrays_overlap("terms", gate)).withColumn("id", F.struct(F.monotonically_increasing_id().alias("n")))
    units = stage_table(units.select("doc_id", "path", F.col("id.n").alias("unit"), "terms"), "units")
    tf = units.select("unit", F.explode("terms").alias("term")).groupBy("unit", "term").count()
    tf = stage_table(tf.join(F.broadcast(vocabulary), "term", "left").withColumn("x", F.col("count") * F.coalesce("idf", F.lit(unseen))), "terms")
    norms = tf.groupBy("unit").agg(F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("norm"))
    dots = tf.join(F.broadcast(postings), "term").groupBy("unit", "template", "license").agg(F.sum(F.col("x") * F.col("w")).alias("dot"))
    scored = dots.join(norms, "unit").withColumn("score", F.round(F.col("dot") / F.col("norm"), 6)).where(F.col("score") >= threshold)
    scored = scored.join(units.drop("terms"), "unit")
    best = F.max_by(F.struct("license", "score"), F.struct("score", F.transform(F.split("license", ""), lambda c: -F.ascii(c)).alias("order")))
    return scored.groupBy("doc_id", "path").agg(best.alias("m")).select("doc_id", "path", "m.license", "m.score")


def scan(docs: DataFrame, path: Column, templates: Templates | None = None, threshold: float = THRESHOLD) -> DataFrame:
    """One row per row of docs: doc_id, path, own (its own licence or null), score,
    license (own or inherited, null if none), from_folder (null unless inherited).

    A null text or path has no licence of its own; a null path inherits none. Rows
    that share id and path get the best licence among their texts. An empty table
    gives an empty result; other columns are not read."""
    own = stage_table(matches(docs, path, templates, threshold), "licences")
    own = own.select(F.col("doc_id").alias("d"), F.col("path").alias("p"), F.col("license").alias("own"), "score")
    files = docs.select("doc_id", path.alias("path"))
    hint = broadcast_if_small(own, MAX_ROWS)
    met = files.join(hint, F.col("doc_id").eqNullSafe(F.col("d")) & F.col("path").eqNullSafe(F.col("p")), "left").select("doc_id", "path", "own", "score")
    folder = F.regexp_replace("p", "/?[^/]*$", "")
    heads = own.where(F.element_at(F.split("p", "/"), -1).rlike(LICENCE_FILES)).groupBy(folder.alias("folder")).agg(F.min(F.struct("p", "own")).alias("h"))
    heads = stage_table(heads.select("folder", F.col("h.own").alias("inherited")), "folders")
    parts = F.split(F.regexp_replace("path", "/?[^/]*$", ""), "/")
    above = F.transform(F.sequence(F.lit(0), F.size(parts)), lambda k: F.array_join(F.slice(parts, F.lit(1), k), "/"))
    lone = met.where("own is null and path is not null").select("path").distinct().select("path", F.explode(above).alias("folder"))
    near = lone.join(broadcast_if_small(heads, MAX_ROWS), "folder").groupBy("path").agg(F.max_by(F.struct("inherited", "folder"), F.length("folder")).alias("n"))
    near = near.select(F.col("path").alias("q"), "n.inherited", F.col("n.folder").alias("from_folder"))
    out = met.join(near, (F.col("path") == F.col("q")) & F.col("own").isNull(), "left")
    return out.select("doc_id", "path", "own", "score", F.coalesce("own", "inherited").alias("license"), "from_folder")


def oracle(path: str) -> str:
    """scan() in DuckDB over documents, with path as an expression; every unit is
    compared with every template, without the gate."""
    quoted = lambda x: "'" + x.replace("'", "''") + "'"
    rows = ", ".join(f"({k}, {quoted(n)}, {quoted(x)})" for k, (n, x) in enumerate((n, x) for n, texts in TEMPLATES.items() for x in texts))
    cut = lambda x: rf"list_filter(regexp_split_to_array(lower({x}), '[^\p{{L}}\p{{N}}]+'), lambda w: w <> '')"
    return rf"""
WITH d AS (SELECT doc_id, {path} AS path, text, row_number() OVER () AS row FROM documents),
templates AS (SELECT k, license, {cut('body')} AS words FROM (VALUES {rows}) AS v(k, license, body)),
tt AS (SELECT k, license, term, count(*) AS n FROM (SELECT k, license, unnest(words) AS term FROM templates) GROUP BY ALL),
df AS (SELECT term, count(*) AS n FROM (SELECT DISTINCT row, unnest({cut('text')}) AS term FROM d) WHERE term IN (SELECT term FROM tt) GROUP BY term),
top AS (SELECT ln(CAST(count(*) + 1 AS DOUBLE)) + 1 AS unseen, count(*) AS docs FROM d),
idf AS (SELECT term, ln((docs + 1) / CAST(coalesce(n, 0) + 1 AS DOUBLE)) + 1 AS idf FROM (SELECT DISTINCT term FROM tt) LEFT JOIN df USING (term), top),
tv AS (SELECT k, license, term, n * idf / sqrt(sum(n * idf * n * idf) OVER (PARTITION BY k)) AS w FROM tt JOIN idf USING (term)),
f AS (SELECT doc_id, path, text, string_split(text, chr(10)) AS ls, regexp_matches(regexp_extract(path, '[^/]*$'), '(?i)^(license|licence|copying|notice)(\.[a-z]+)?$') AS whole FROM d WHERE text IS NOT NULL),
u AS (SELECT doc_id, path, unit, row_number() OVER () AS id FROM (SELECT DISTINCT doc_id, path, unit FROM (
    SELECT doc_id, path, unnest(ls) AS unit FROM f UNION ALL SELECT doc_id, path, unnest(regexp_split_to_array(text, '
[ 	
]*
')) FROM f
    UNION ALL SELECT doc_id, path, text FROM f WHERE whole
    UNION ALL SELECT doc_id, path, unnest(list_transform(range(1, len(ls) + 1), lambda i: array_to_string(ls[i:i + 1], chr(10)))) FROM f WHERE whole
    UNION ALL SELECT doc_id, path, unnest(list_transform(range(1, len(ls) + 1), lambda i: array_to_string(ls[i:i + 2], chr(10)))) FROM f WHERE whole))),
x AS (SELECT id, term, count(*) AS n FROM (SELECT id, unnest({cut('unit')}) AS term FROM u) GROUP BY ALL),
xv AS (SELECT id, term, n * coalesce(idf, unseen) AS x FROM x LEFT JOIN idf USING (term), top),
nm AS (SELECT id, sqrt(sum(x * x)) AS norm FROM xv GROUP BY id),
sc AS (SELECT id, license, round(sum(x * w) / any_value(norm), 6) AS score FROM xv JOIN tv USING (term) JOIN nm USING (id) GROUP BY id, k, license),
own AS (SELECT doc_id, path, license AS own, score FROM sc JOIN u USING (id) WHERE score >= {THRESHOLD} QUALIFY row_number() OVER (PARTITION BY doc_id, path ORDER BY score DESC, license) = 1),
m AS (SELECT d.doc_id, d.path, own, score, string_split(regexp_replace(d.path, '/?[^/]*$', ''), '/') AS parts FROM d LEFT JOIN own ON d.doc_id = own.doc_id AND d.path = own.path),
h AS (SELECT regexp_replace(path, '/?[^/]*$', '') AS folder, arg_min(own, (path, own)) AS inherited FROM own WHERE regexp_matches(regexp_extract(path, '[^/]*$'), '(?i)^(license|licence|copying|notice)(\.[a-z]+)?$') GROUP BY ALL),
a AS (SELECT DISTINCT path, array_to_string(parts[1:k], '/') AS folder FROM (SELECT path, parts, unnest(range(0, len(parts) + 1)) AS k FROM m WHERE own IS NULL AND path IS NOT NULL)),
n AS (SELECT path, arg_max(inherited, length(folder)) AS inherited, arg_max(folder, length(folder)) AS from_folder FROM a JOIN h USING (folder) GROUP BY path)
SELECT m.doc_id, m.path, own, score, coalesce(own, inherited) AS license, CASE WHEN own IS NULL THEN from_folder END AS from_folder FROM m LEFT JOIN n ON m.path = n.path AND m.own IS NULL
"""
