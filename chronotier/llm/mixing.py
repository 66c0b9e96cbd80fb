"""Mixing sources to target weights, with DataFrame functions only.

A document's size is its number of words. Sources share 100 % of all sizes by
weight; a source's target stops at `most` times its own size and the excess is
shared by weight among the others. A source's repetition rate is target / size.
A document is emitted floor(rate) times, and once more with the rate's fraction
as probability, drawn from hashes, so that reruns agree.

Draws that do not know of each other would miss a target by the sizes' spread, a
tenth or more where a few documents hold most words. So they are dealt by size, the
longest documents first: each size class draws with the fraction that the words still
wanted are of the words still to come, and gets as many copies as that fraction says,
rounded up or down by a draw of the class; within it they go to the least draws of
ids. What long documents take too much or too little, shorter ones make good, so a
source ends within a few words of its target, and a document's probability is still
the fraction over all draws.

The targets follow from one pass over the sources in the order of their cap per
unit of weight. If the first k of them sit at their caps, the level of the others
is (all - their caps) / (all weights - their weights); any k gives no more than
the true level, and the right k gives it, so the level is the greatest of these.

Only (source, size class, a range of draws) is aggregated, with partial sums, so a
source or a class with a third of all rows is BUCKETS rows per task at most, and only
the one range in which a class's last copy lies is ranked row by row. The dealing
itself runs over a source's classes, which are 64 to an octave: some 1,300 up to a
million words. What a document needs to know is its source's rate and its class's
greatest draw, which are broadcast up to MAX_SOURCES rows; then no text is shuffled.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from chronotier.llm.common import WORD, broadcast_if_small, stage_table

#: Sources, and pairs of source and class, up to which they are broadcast; beyond, the
#: join is a shuffle.
MAX_SOURCES = 500_000
#: Binary digits of a draw, and ranges that they are counted in.
BITS, BUCKETS = 52, 1 << 8


def word_count(text: Column) -> Column:
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(WORD)).cast("long")


def targets(sizes: DataFrame, weights: tuple[int, ...] = (1, 2, 3), most: float = 3.0) -> DataFrame:
    """sizes(source, size) -> (source, source_size, target, rate): weights repeat
    over the sources by code point, null last. A source without words gets 0."""
    per = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    rank = F.row_number().over(W.orderBy(F.col("source").asc_nulls_last())) - 1
    per = per.withColumn("weight", F.element_at(F.array(*map(F.lit, weights)), (rank % len(weights) + 1).cast("int")))
    before = W.orderBy(F.col("source_size") / F.col("weight"), F.col("source").asc_nulls_last()).rowsBetween(W.unboundedPreceding, -1)
    every = W.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)
    full = F.coalesce(F.sum(F.col("source_size")).over(before), F.lit(0)).cast("double") * most
    used = F.coalesce(F.sum("weight").over(before), F.lit(0))
    level = (F.sum("source_size").over(every).cast("double") - full) / (F.sum("weight").over(every) - used)
    per = per.withColumn("level", level).withColumn("level", F.max("level").over(every))
    target = F.least(F.col("weight") * F.col("level"), F.col("source_size") * F.lit(float(most)))
    rate = F.when(F.col("source_size") > 0, F.least(target / F.col("source_size"), F.lit(float(most)))).otherwise(0.0)
    return per.select("source", "source_size", target.alias("target"), rate.alias("rate"))


def _draw(seed: str, value: Column) -> Column:
    """BITS bits from a hash."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(seed), value.cast("string"))), 1, BITS // 4), 16, 10).cast("long")


def size_class(size: Column) -> Column:
    """The size with all but its first seven binary digits set to 0."""
    low = F.greatest(F.length(F.bin(size)) - 7, F.lit(0))
    return F.call_function("shiftleft", F.call_function("shiftright", size, low), low)


def dealt(classes: DataFrame, rates: DataFrame, seed: str) -> DataFrame:
    """(of, of_class, take): how many documents of a source and class get the further
    copy. classes(source, class, n, words)."""
    rate = rates.select(F.col("source").alias("of"), (F.col("rate") - F.floor("rate")).alias("part"), F.col("source_size").cast("double").alias("rest"))
    draw = _draw(seed, F.concat_ws("|", "source", F.col("class").cast("string"))) / float(1 << BITS)
    one = F.struct((-F.col("class")).alias("c"), F.col("n").cast("double").alias("n"), F.col("words").cast("double").alias("words"), draw.alias("draw"))
    per = classes.groupBy("source").agg(F.array_sort(F.collect_list(one)).alias("classes"))
    per = per.join(rate, F.col("source").eqNullSafe(F.col("of")))
    none = F.array().cast("array<struct<c:bigint,take:bigint>>")
    first = F.struct((F.col("part") * F.col("rest")).alias("wanted"), F.col("rest").alias("rest"), none.alias("out"))

    def deal(s: Column, x: Column) -> Column:
        share = F.when(s["rest"] > 0, F.least(F.greatest(s["wanted"] / s["rest"], F.lit(0.0)), F.lit(1.0))).otherwise(0.0)
        take = F.least(F.floor(share * x["n"] + x["draw"]), x["n"].cast("long"))
        return F.struct((s["wanted"] - take * (x["words"] / x["n"])).alias("wanted"), (s["rest"] - x["words"]).alias("rest"), F.concat(s["out"], F.array(F.struct(x["c"].alias("c"), take.alias("take")))).alias("out"))

    rows = per.select("of", F.explode(F.aggregate("classes", first, deal)["out"]).alias("x"))
    return rows.select("of", (-F.col("x.c")).alias("of_class"), F.col("x.take").alias("take")).where("take > 0")


def cuts(sizes: DataFrame, rates: DataFrame, seed: str) -> DataFrame:
    """(source, class, cut): documents of that source and class whose draw is below cut
    get the further copy; a class without one has no row. sizes(doc_id, source, size)."""
    width = (1 << BITS) // BUCKETS
    per = sizes.withColumn("range", F.floor(_draw(seed, F.col("doc_id")) / width)).withColumn("class", size_class(F.col("size")))
    per = stage_table(per.groupBy("source", "class", "range").agg(F.count("*").alias("n"), F.sum("size").alias("words")), "ranges")
    take = dealt(per.groupBy("source", "class").agg(F.sum("n").alias("n"), F.sum("words").alias("words")), rates, seed)
    here = F.col("source").eqNullSafe(F.col("of")) & (F.col("class") == F.col("of_class"))
    met = per.join(broadcast_if_small(stage_table(take, "dealt"), MAX_SOURCES), here)
    met = met.withColumn("upto", F.sum("n").over(W.partitionBy("source", "class").orderBy("range")))
    last = met.where((F.col("upto") >= F.col("take")) & (F.col("upto") - F.col("n") < F.col("take")))
    last = stage_table(last.select("of", "of_class", F.col("range").alias("of_range"), "n", (F.col("take") - F.col("upto") + F.col("n")).alias("need")), "last")
    whole = last.where("need = n").select(F.col("of").alias("source"), F.col("of_class").alias("class"), ((F.col("of_range") + 1) * width).alias("cut"))
    some = broadcast_if_small(last.where("need < n").drop("n"), MAX_SOURCES)
    rows = sizes.select("source", size_class(F.col("size")).alias("class"), _draw(seed, F.col("doc_id")).alias("draw"))
    rows = rows.join(some, here & (F.floor(F.col("draw") / width) == F.col("of_range")))
    at = F.row_number().over(W.partitionBy("source", "class").orderBy("draw"))
    rows = rows.withColumn("at", at).where("at = need").select("source", "class", (F.col("draw") + 1).alias("cut"))
    return stage_table(whole.union(rows), "cuts")


def _with_copies(df: DataFrame, sizes: DataFrame, weights: tuple[int, ...], most: float, seed: str) -> DataFrame:
    """df(doc_id, source, __size, ...) with __source_size, __target and __copies."""
    rates = stage_table(targets(sizes, weights, most), "rates")
    cut = cuts(sizes, rates, seed).select(F.col("source").alias("__from"), F.col("class").alias("__class"), F.col("cut").alias("__cut"))
    rates = rates.select(F.col("source").alias("__of"), F.col("source_size").alias("__source_size"), F.col("target").alias("__target"), F.col("rate").alias("__rate"))
    met = df.join(broadcast_if_small(rates, MAX_SOURCES), df["source"].eqNullSafe(F.col("__of")))
    met = met.join(broadcast_if_small(cut, MAX_SOURCES), df["source"].eqNullSafe(F.col("__from")) & (size_class(F.col("__size")) == F.col("__class")), "left")
    more = F.coalesce(_draw(seed, df["doc_id"]) < F.col("__cut"), F.lit(False)).cast("long")
    return met.withColumn("__copies", F.floor("__rate") + more)


def mix_plan(docs: DataFrame, weights: tuple[int, ...] = (1, 2, 3), most: float = 3.0, seed: str = "mix") -> DataFrame:
    """One row per row of docs: doc_id, source, size, source_size, target, copies,
    taken (size times copies). Null texts have size 0; rows that share an id draw
    alike; an empty table gives an empty result."""
    sizes = stage_table(docs.select("doc_id", "source", word_count(F.col("text")).alias("size")), "sizes")
    met = _with_copies(sizes.withColumn("__size", F.col("size")), sizes, weights, most, seed)
    return met.select("doc_id", "source", "size", F.col("__source_size").alias("source_size"), F.col("__target").alias("target"), F.col("__copies").alias("copies"), (F.col("size") * F.col("__copies")).alias("taken"))


def mix(docs: DataFrame, weights: tuple[int, ...] = (1, 2, 3), most: float = 3.0, seed: str = "mix", copy: str = "copy") -> DataFrame:
    """Every row of docs as often as the mix takes it, numbered from 1 in the
    column `copy`. All columns of docs pass through, but for one of that name, which
    gives way."""
    sizes = stage_table(docs.select("doc_id", "source", word_count(F.col("text")).alias("size")), "sizes")
    met = _with_copies(docs.withColumn("__size", word_count(F.col("text"))), sizes, weights, most, seed)
    met = met.where("__copies > 0")
    return met.select(*[c for c in docs.columns if c != copy], F.explode(F.sequence(F.lit(1), F.col("__copies").cast("int"))).alias(copy))


ORACLE = r"""
WITH RECURSIVE s AS (SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size,
    CAST('0x' || substr(md5(concat_ws('|', 'mix', CAST(doc_id AS VARCHAR))), 1, 13) AS BIGINT) AS draw FROM documents),
p AS (SELECT source, CAST(sum(size) AS BIGINT) AS source_size FROM s GROUP BY source),
w AS (SELECT *, 1 + (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 AS weight FROM p),
l AS (SELECT *, (CAST(sum(source_size) OVER () AS DOUBLE) - CAST(coalesce(sum(source_size) OVER b, 0) AS DOUBLE) * 3.0)
    / CAST(sum(weight) OVER () - coalesce(sum(weight) OVER b, 0) AS DOUBLE) AS level FROM w
    WINDOW b AS (ORDER BY source_size / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
t AS (SELECT source, source_size, least(weight * (SELECT max(level) FROM l), source_size * CAST(3.0 AS DOUBLE)) AS target FROM l),
r AS (SELECT *, CASE WHEN source_size > 0 THEN least(target / source_size, 3.0) ELSE 0.0 END AS rate FROM t),
c AS (SELECT *, (size >> CAST(greatest(length(bin(size)) - 7, 0) AS BIGINT)) << CAST(greatest(length(bin(size)) - 7, 0) AS BIGINT) AS class FROM s),
k AS (SELECT source, class, CAST(count(*) AS DOUBLE) AS n, CAST(sum(size) AS DOUBLE) AS words, row_number() OVER (PARTITION BY source ORDER BY class DESC) AS i,
    CAST(CAST('0x' || substr(md5(concat_ws('|', 'mix', source, CAST(class AS VARCHAR))), 1, 13) AS BIGINT) AS DOUBLE) / 4503599627370496.0 AS u FROM c GROUP BY source, class),
v AS (SELECT source, CAST(0 AS BIGINT) AS i, CAST(0 AS BIGINT) AS class, CAST(0 AS BIGINT) AS take, (rate - floor(rate)) * CAST(source_size AS DOUBLE) AS wanted, CAST(source_size AS DOUBLE) AS rest FROM r
    UNION ALL SELECT source, i, class, take, wanted - take * (words / n), rest - words FROM (SELECT k.source, k.i, k.class, v.wanted, v.rest, k.words, k.n, CAST(least(floor(
      CASE WHEN v.rest > 0 THEN least(greatest(v.wanted / v.rest, 0.0), 1.0) ELSE 0.0 END * k.n + u), k.n) AS BIGINT) AS take
    FROM v JOIN k ON k.source IS NOT DISTINCT FROM v.source AND k.i = v.i + 1) AS nx),
o AS (SELECT c.*, rank() OVER (PARTITION BY source, class ORDER BY draw) AS place FROM c)
SELECT o.doc_id, o.size, r.source_size, r.target, o.size * (CAST(floor(rate) AS BIGINT) + CASE WHEN place <= v.take THEN 1 ELSE 0 END) AS taken
FROM o JOIN r ON o.source IS NOT DISTINCT FROM r.source JOIN v ON v.i > 0 AND o.source IS NOT DISTINCT FROM v.source AND o.class = v.class
"""
