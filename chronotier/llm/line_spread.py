"""Cross-site boilerplate lines, with DataFrame functions only.

A line that stands on `min_sites` or more sites is boilerplate. One HyperLogLog
sketch of sites per line hash is built by partial aggregation and merged after the
shuffle, so a line on a third of all pages is one row per task. Lines whose
estimate lies well above the threshold are boilerplate at once; those near it get
an exact distinct count over their own occurrences; a line below it has too few.
The first occurrence (least doc_id, then position) stays, so that no text leaves
the corpus altogether; all others go.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from chronotier.llm.common import broadcast_if_small, stage_table

#: Boilerplate lines up to which they are broadcast; beyond, the join is a shuffle.
MAX_LINES = 500_000
#: log2 of a sketch's registers; the relative error is 1.04 / sqrt(registers).
LOG_REGISTERS = 12
#: What does not count at either end of a line.
BLANKS = " \t\r"


def _occurrences(docs: DataFrame) -> DataFrame:
    """(doc_id, row, source, pos, h, g) of each line with more than blanks in it."""
    lines = docs.select("doc_id", F.xxhash64("text").alias("row"), "source", F.posexplode(F.split("text", "\n")).alias("pos", "line"))
    # Trimming a set of characters is slow; few lines need more than blanks trimmed.
    odd = F.contains("line", F.lit("\t")) | F.contains("line", F.lit("\r"))
    lines = lines.withColumn("line", F.when(odd, F.trim("line", F.lit(BLANKS))).otherwise(F.trim("line"))).where("line <> ''")
    return lines.select("doc_id", "row", "source", "pos", F.xxhash64("line").alias("h"), F.hash("line").alias("g"))


def boilerplate(docs: DataFrame, min_sites: int = 10) -> DataFrame:
    """(h, g, sites, first) of the lines on min_sites sites or more; sites is exact
    near the threshold and an estimate above. A null source is no site."""
    found = _occurrences(docs)
    sketch = F.hll_sketch_agg("source", F.lit(LOG_REGISTERS))
    per = found.groupBy("h", "g").agg(F.count("*").alias("n"), sketch.alias("sketch"), F.min(F.struct("doc_id", "pos")).alias("first"))
    margin = max(1.0, 5 * 1.04 / 2 ** (LOG_REGISTERS / 2) * min_sites)
    per = per.where(F.col("n") >= min_sites).withColumn("sites", F.hll_sketch_estimate("sketch"))
    per = stage_table(per.where(F.col("sites") >= min_sites - margin).drop("sketch", "n"), "spread")
    near = per.where(F.col("sites") <= min_sites + margin).select("h", "g")
    exact = found.join(broadcast_if_small(near, MAX_LINES), ["h", "g"]).groupBy("h", "g").agg(F.count_distinct("source").alias("exact"))
    sites = F.when(F.col("sites") > min_sites + margin, F.col("sites")).otherwise(F.col("exact"))
    per = per.join(exact, ["h", "g"], "left").select("h", "g", sites.alias("sites"), "first")
    return stage_table(per.where(F.col("sites") >= min_sites), "boilerplate")


def drop_boilerplate(docs: DataFrame, min_sites: int = 10) -> DataFrame:
    """docs with the lines that go taken out of text, and two more columns, n_lines
    and n_removed (BIGINT; 0 for a null text, which stays null), which replace columns
    of those names.

    Lines are compared without blanks, tabs and CR at either end; blank lines always stay. Rows
    that share an id are told apart by their texts; equal rows keep equal lines. A
    text that loses all its lines becomes empty. No row is dropped."""
    docs = docs.drop("n_lines", "n_removed")
    marks = broadcast_if_small(boilerplate(docs, min_sites), MAX_LINES)
    gone = _occurrences(docs).join(marks, ["h", "g"]).where(~F.struct("doc_id", "pos").eqNullSafe(F.col("first")))
    gone = gone.groupBy(F.col("doc_id").alias("__doc"), F.col("row").alias("__row")).agg(F.collect_set("pos").alias("__gone"))
    met = docs.join(gone, docs["doc_id"].eqNullSafe(F.col("__doc")) & (F.xxhash64(docs["text"]) == F.col("__row")), "left")
    # As a column of their own, so that the lambda below does not cut the text up again.
    met = met.withColumn("__lines", F.split(docs["text"], "\n"))
    lines = F.col("__lines")
    places = F.array_except(F.sequence(F.lit(0), F.size(lines) - 1), F.col("__gone"))  # by hashing, in order
    stay: Column = F.array_join(F.transform(places, lambda i: F.get(lines, i)), "\n")
    text = F.when(F.col("__gone").isNull(), docs["text"]).otherwise(stay)
    counts = [F.coalesce(F.size(x), F.lit(0)).cast("long") for x in (F.when(docs["text"].isNotNull(), lines), F.col("__gone"))]
    counts = [F.greatest(x, F.lit(0).cast("long")) for x in counts]
    kept = [text.alias(c) if c == "text" else docs[c] for c in docs.columns]
    return met.select(*kept, counts[0].alias("n_lines"), counts[1].alias("n_removed"))


ORACLE = r"""
WITH d AS (SELECT doc_id, source, string_split(text, chr(10)) AS ls FROM documents),
l AS (SELECT *, trim(line, chr(32) || chr(9) || chr(13)) AS bare FROM (SELECT doc_id, source, unnest(ls) AS line, generate_subscripts(ls, 1) AS pos FROM d)),
g AS (SELECT bare AS k FROM l WHERE bare <> '' GROUP BY bare HAVING count(DISTINCT source) >= 10),
m AS (SELECT l.doc_id, l.pos, l.line, g.k IS NOT NULL AND row_number() OVER (PARTITION BY bare ORDER BY l.doc_id, l.pos) > 1 AS gone
    FROM l LEFT JOIN g ON bare = g.k),
o AS (SELECT doc_id, count(*) AS n_lines, count(*) FILTER (WHERE gone) AS n_removed,
    coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '') AS text FROM m GROUP BY doc_id)
SELECT d.doc_id, coalesce(o.n_lines, 0) AS n_lines, coalesce(o.n_removed, 0) AS n_removed, o.text
FROM documents d LEFT JOIN o ON d.doc_id = o.doc_id
"""
