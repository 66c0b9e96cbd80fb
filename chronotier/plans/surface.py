"""The engine from SQL: views of the tiers and table functions over them.

The functions are SQL table functions, which the optimizer inlines: an instant given
to snapshot_at reaches the scan of the history as a filter. The scores of live_scores and
scores_at are over all slots that share a term with the question; ORDER BY score DESC,
doc_id, ordinal LIMIT k makes a top-k of them that no single task has to sort. Slots are
scored in Arrow batches by the function closeness, once each: the condition on a score
stands over a generator, below which the optimizer does not take it.
"""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import arrow_udf

from chronotier.functions.segment import BLANK
from chronotier.operators import history as hist
from chronotier.operators.search import closeness

_COLUMNS = "doc_id BIGINT, ordinal BIGINT, content_key STRING, body STRING, effective_at BIGINT, revision BIGINT"
_BLANK = BLANK.replace("\\", "\\\\")


def _closeness(texts: pa.Array, questions: pa.Array) -> pa.Array:
    return closeness(texts, questions)


def register(spark: SparkSession, history: DataFrame) -> None:
    """Views history_events, history_intervals and live_slots; table functions
    snapshot_at(t), changes_between(t1, t2), split_document(text), live_scores(question) and
    scores_at(question, t)."""
    history.createOrReplaceTempView("history_events")
    spans = history if "retired_at" in history.columns else hist.intervals(history)
    spans.createOrReplaceTempView("history_intervals")
    spans.where("retired_at is null").createOrReplaceTempView("live_slots")
    names = "doc_id, ordinal, content_key, body, effective_at, revision"
    spark.sql(f"""CREATE OR REPLACE TEMPORARY FUNCTION snapshot_at(t BIGINT) RETURNS TABLE({_COLUMNS}) RETURN
        SELECT {names} FROM history_intervals
        WHERE effective_at <= snapshot_at.t AND (retired_at IS NULL OR retired_at > snapshot_at.t)""")
    spark.sql("""CREATE OR REPLACE TEMPORARY FUNCTION changes_between(t1 BIGINT, t2 BIGINT)
        RETURNS TABLE(doc_id BIGINT, ordinal BIGINT, op STRING, content_key STRING, prior_key STRING, effective_at BIGINT, revision BIGINT) RETURN
        SELECT doc_id, ordinal, op, content_key, prior_key, effective_at, revision FROM history_events
        WHERE effective_at >= changes_between.t1 AND effective_at < changes_between.t2""")
    spark.sql(f"""CREATE OR REPLACE TEMPORARY FUNCTION split_document(text STRING) RETURNS TABLE(ordinal BIGINT, body STRING) RETURN
        SELECT CAST(at AS BIGINT), line FROM (SELECT posexplode(filter(split(split_document.text, '\\n'),
        x -> length(regexp_replace(x, '{_BLANK}', '')) > 0)) AS (at, line))""")

    spark.udf.register("closeness", arrow_udf(_closeness, "double"))
    text = "codes" if "codes" in spans.columns else "body"
    scores = f"""SELECT doc_id, ordinal, content_key, effective_at, round(score, 6) AS score
        FROM (SELECT doc_id, ordinal, content_key, effective_at, closeness({text}, {{name}}.question) AS found FROM history_intervals WHERE {{valid}})
        LATERAL VIEW OUTER explode(array(found)) AS score WHERE score IS NOT NULL"""
    out = "TABLE(doc_id BIGINT, ordinal BIGINT, content_key STRING, effective_at BIGINT, score DOUBLE)"
    live = scores.format(name="live_scores", valid="retired_at IS NULL")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION live_scores(question STRING) RETURNS {out} RETURN {live}")
    past = scores.format(name="scores_at", valid="effective_at <= scores_at.t AND (retired_at IS NULL OR retired_at > scores_at.t)")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION scores_at(question STRING, t BIGINT) RETURNS {out} RETURN {past}")
