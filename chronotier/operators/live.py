"""The live tier: current slots only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronotier.operators import history as hist

SLOT = ["doc_id", "ordinal"]


def apply(live: DataFrame, events: DataFrame) -> DataFrame:
    """live after these events: touched slots go, those that hold a key come back."""
    last = events.groupBy(*SLOT).agg(F.max(F.struct("effective_at", "revision")).alias("e")).select(*SLOT, "e.effective_at", "e.revision")
    new = events.join(last, [*SLOT, "effective_at", "revision"]).where("content_key is not null").select(*live.columns)
    return live.join(events.select(*SLOT).distinct(), SLOT, "left_anti").select(*live.columns).union(new)


def rebuild(history: DataFrame) -> DataFrame:
    return hist.snapshot_at(history, None)


def strays(live: DataFrame, history: DataFrame) -> DataFrame:
    """Rows of live that are not the present of history, and the reverse; empty if the
    tiers agree."""
    cols = ["doc_id", "ordinal", "content_key", "revision"]
    a, b = live.select(*cols), rebuild(history).select(*cols)
    return a.exceptAll(b).withColumn("side", F.lit("live")).union(b.exceptAll(a).withColumn("side", F.lit("history")))
