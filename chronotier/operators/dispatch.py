"""Questions to tiers: live ones read the live tier, those of an instant the history,
those of a range both, and the three answers meet."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronotier.operators import search


def answer(queries: DataFrame, live: DataFrame, spans: DataFrame, k: int = 5) -> DataFrame:
    """queries(qid, text, kind, t_from, t_to), as route.classify gives them -> qid, kind,
    rank, score, PLACE, retired_at and tier, the tier that the row was read from.

    A range takes what is still valid from the live tier and what has ended from the
    history, each with its k best, and ranks both. Each tier is read once for all the
    questions that go to it, and only if there are any."""
    queries = queries.persist()  # read once by each tier below, when its blocks are made
    kinds = {r["kind"] for r in queries.select("kind").distinct().collect()}  # three rows
    of = lambda *some: queries.where(F.col("kind").isin(*some))
    now = live.withColumn("retired_at", F.lit(None).cast("long"))
    ranged, always = F.col("kind") == "comparative", F.lit(search.ALWAYS)
    out = ["qid", "score", *search.PLACE, "retired_at"]
    parts = []
    if kinds & {"live", "comparative"}:
        asked = of("live", "comparative").select("qid", "text", F.when(ranged, F.col("t_from")).otherwise(F.lit(search.NEVER)).alias("t"), F.when(ranged, F.col("t_to")).otherwise(always).alias("until"))
        parts.append(search.best(asked, now, k, ("retired_at",)).select(*out, F.lit("hot").alias("tier")))
    if kinds & {"historical", "comparative"}:
        asked = of("historical", "comparative").select("qid", "text", F.col("t_from").alias("t"), F.when(ranged, F.col("t_to")).alias("until"), ranged.alias("ended"))
        parts.append(search.best(asked, spans, k).select(*out, F.lit("cold").alias("tier")))
    if not parts:
        queries.unpersist()
        return search.best(queries.select("qid", "text"), now, k, ("retired_at",)).select("qid", F.lit("live").alias("kind"), "rank", "score", *search.PLACE, "retired_at", F.lit("hot").alias("tier"))
    queries.unpersist()
    met = parts[0]
    for p in parts[1:]:
        met = met.union(p)
    return search.rank(met, k).join(F.broadcast(queries.select("qid", "kind")), "qid").select("qid", "kind", "rank", "score", *search.PLACE, "retired_at", "tier")
