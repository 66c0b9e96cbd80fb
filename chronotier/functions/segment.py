"""Segments of a document: lines, paragraphs, blocks, sentences, HTML blocks, whole.

Every splitter takes rows with doc_id, revision, effective_at and text and gives
doc_id, revision, effective_at, ordinal (from 0), kind, body. Blank segments are
discarded before numbering; a null text has no segments.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

KEYS = ["doc_id", "revision", "effective_at"]
#: Blanks that both Java and RE2 mean alike.
BLANK = r"[ \t\n\r\f]"


def filled(body: Column) -> Column:
    """Is there anything but blanks?"""
    return body.rlike(f"[^{BLANK[1:-1]}]")


def _numbered(df: DataFrame, bodies: Column, kind: str) -> DataFrame:
    """Bodies in order without the blank ones; narrow, no shuffle."""
    full = F.filter(bodies, filled)
    out = df.select(*KEYS, F.posexplode(full).alias("ordinal", "body"))
    return out.select(*KEYS, F.col("ordinal").cast("long").alias("ordinal"), F.lit(kind).alias("kind"), "body")


def split_paragraphs(df: DataFrame, boundary: str = r"\n[ \t\r\f]*\n") -> DataFrame:
    return _numbered(df, F.split("text", boundary), "paragraph")


def split_lines(df: DataFrame) -> DataFrame:
    return _numbered(df, F.split("text", "\n"), "line")


def split_sentences(df: DataFrame) -> DataFrame:
    """Ends of sentences are kept with them; a line end also ends a sentence."""
    marked = F.regexp_replace("text", r"([.!?])[ \t\r\f]+", "$1\n")
    return _numbered(df, F.split(marked, "\n"), "sentence")


def whole(df: DataFrame) -> DataFrame:
    return _numbered(df, F.array("text"), "whole").where("body is not null")


def split_html(df: DataFrame, html: str = "html") -> DataFrame:
    """p, li, table and pre elements of a page, tags removed; table and pre whole."""
    pattern = r"(?is)<(table|pre|p|li)(?: [^>]*)?>(.*?)</\1>"
    found = df.select(*KEYS, F.posexplode(F.arrays_zip(F.regexp_extract_all(html, F.lit(pattern), F.lit(1)).alias("k"), F.regexp_extract_all(html, F.lit(pattern), F.lit(2)).alias("b"))).alias("at", "x"))
    body = F.trim(F.regexp_replace(F.regexp_replace("x.b", r"<[^>]*>", " "), rf"{BLANK}+", " "))
    found = found.select(*KEYS, "at", F.lower("x.k").alias("kind"), body.alias("body")).where("body <> ''")
    place = F.row_number().over(W.partitionBy(*KEYS).orderBy("at")) - 1
    return found.select(*KEYS, place.cast("long").alias("ordinal"), "kind", "body")


def split_blocks(df: DataFrame) -> DataFrame:
    """Tables, fenced code and lists stay whole, prose by paragraph.

    A line is a fence mark, inside a fence (odd number of marks so far), a table line
    (starts with a pipe, or has two pipes next to such a line), a list line (bullet or
    number, or indented below one), blank or prose. A block ends where the class
    changes or at a blank line outside fences."""
    lines = df.select(*KEYS, F.posexplode(F.split("text", "\n")).alias("n", "line"))
    w = W.partitionBy(*KEYS).orderBy("n")
    mark = F.col("line").rlike(r"^ {0,3}(```|~~~)")
    marks = F.sum(mark.cast("int")).over(w)
    lines = lines.withColumn("mark", mark).withColumn("marks", marks)
    fenced = F.col("mark") | (F.col("marks") % 2 == 1)
    pipe, two = F.col("line").rlike(r"^[ \t]*\|"), F.col("line").rlike(r"\|.*\|")
    near = F.coalesce(F.lag(pipe | two).over(w), F.lit(False)) | F.coalesce(F.lead(pipe | two).over(w), F.lit(False))
    bullet = F.col("line").rlike(r"^[ \t]*([-*+]|[0-9]+[.)])[ \t]")
    blank = ~F.col("line").rlike(r"[^ \t\r\f]")
    first = F.when(fenced, "code").when(blank, "blank").when(pipe | (two & near), "table").when(bullet, "list")
    lines = lines.withColumn("first", first).withColumn("indented", F.col("line").rlike(r"^[ \t]+[^ \t]"))
    above = F.last(F.when(F.col("first").isNotNull() | ~F.col("indented"), F.coalesce("first", F.lit("prose"))), ignorenulls=True).over(w)
    lines = lines.withColumn("kind", F.coalesce("first", F.when(F.col("indented") & (above == "list"), "list"), F.lit("prose")))
    opened = F.col("mark") & (F.col("marks") % 2 == 1)
    cut = (F.col("kind") != F.coalesce(F.lag("kind").over(w), F.lit(""))) | opened
    lines = lines.withColumn("block", F.sum(cut.cast("int")).over(w)).where("kind <> 'blank'")
    body = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("n", "line"))), lambda x: x["line"]), "\n")
    blocks = lines.groupBy(*KEYS, "block", "kind").agg(body.alias("body"))
    place = F.row_number().over(W.partitionBy(*KEYS).orderBy("block")) - 1
    return blocks.select(*KEYS, place.cast("long").alias("ordinal"), "kind", "body")
