"""Query intent: live, historical or comparative, from arguments or from the text.

Rules in order, the first match wins, times in UTC: "between X and Y" and "from X to
Y" give a range to the end of Y's unit; "since X" a range up to now; "before X" the
second before X; "as of", "on", "at", "in", "back in" X, or a bare ISO date, the last
second of X's unit; anything else is live, as is an instant after now. X is an ISO
date or date-time, a month name with a year, a quarter or a year.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: The months' names.
MONTHS = ("january", "february", "march", "april", "may", "june", "july", "august", "september", "october", "november", "december")
NAMES = "|".join(MONTHS)
X = rf"((?:[0-9]{{4}}-[0-9]{{2}}-[0-9]{{2}})(?:[t ][0-9]{{2}}:[0-9]{{2}}(?::[0-9]{{2}})?)?|(?:{NAMES}) [0-9]{{4}}|q[1-4] [0-9]{{4}}|[0-9]{{4}})"


def _start(x: Column) -> Column:
    """First moment of a time phrase, or null."""
    year = F.regexp_extract(x, "([0-9]{4})", 1)
    month = F.lit(None).cast("int")
    for i, name in enumerate(MONTHS, 1):
        month = F.when(x.startswith(name), i).otherwise(month)
    quarter = F.try_to_number(F.regexp_extract(x, "^q([1-4]) ", 1), F.lit("9")).cast("int") * 3 - 2
    named = F.concat(year, F.lit("-"), F.lpad(F.coalesce(month, quarter, F.lit(1)).cast("string"), 2, "0"), F.lit("-01"))
    iso = x.rlike("^[0-9]{4}-")
    return F.unix_timestamp(F.try_to_timestamp(F.when(iso, F.upper(F.replace(x, F.lit("t"), F.lit(" ")))).otherwise(named)))


def _end(x: Column, start: Column) -> Column:
    """First moment after it, from its first moment."""
    months = F.when(x.rlike("^q"), 3).when(x.rlike("^[0-9]{4}$"), 12).when(x.rlike("^[a-z]"), 1)
    seconds = F.when(x.rlike(":[0-9]{2}:"), 1).when(x.rlike(":"), 60).otherwise(86400)
    return F.when(months.isNotNull(), F.unix_timestamp(F.add_months(F.timestamp_seconds(start), months).cast("timestamp"))).otherwise(start + seconds)


def classify(queries: DataFrame, now: int, text: str = "text") -> DataFrame:
    """queries with kind, t_from, t_to (exclusive for ranges) and core_text. Phrases,
    moments and kinds are found in steps, each kept as columns, so that no pattern is
    matched twice."""
    pair = rf"(?:between {X} and {X}|from {X} to {X})"
    got = lambda p, i: F.nullif(F.regexp_extract("__low", p, i), F.lit(""))
    out = queries.withColumn("__low", F.lower(text))
    phrases = {"x": F.coalesce(got(pair, 1), got(pair, 3)), "y": F.coalesce(got(pair, 2), got(pair, 4)), "since": got(rf"since {X}", 1), "before": got(rf"before {X}", 1)}
    phrases["on"] = F.coalesce(got(rf"(?:as of|back in|on|at|in|when\b.*?) {X}", 1), got(r"([0-9]{4}-[0-9]{2}-[0-9]{2})", 1))
    out = out.withColumns({f"__{k}": v for k, v in phrases.items()})
    out = out.withColumns({f"__{k}_at": _start(F.col(f"__{k}")) for k in phrases})
    out = out.withColumns({f"__{k}_end": _end(F.col(f"__{k}"), F.col(f"__{k}_at")) for k in ("y", "on")})
    at = {k: F.col(f"__{k}_at") for k in phrases}
    ranged, since = at["x"].isNotNull() & at["y"].isNotNull(), at["since"].isNotNull() & (at["since"] <= now)
    before, on = at["before"].isNotNull() & (at["before"] - 1 <= now), at["on"].isNotNull() & (F.col("__on_end") - 1 <= now)
    out = out.withColumn("__rule", F.when(ranged, 1).when(since, 2).when(before, 3).when(on, 4).otherwise(0))
    rule = F.col("__rule")
    kind = F.when(rule.isin(1, 2), "comparative").when(rule.isin(3, 4), "historical").otherwise("live")
    t_from = F.when(rule == 1, at["x"]).when(rule == 2, at["since"]).when(rule == 3, at["before"] - 1).when(rule == 4, F.col("__on_end") - 1)
    t_to = F.when(rule == 1, F.col("__y_end")).when(rule == 2, F.lit(now))
    core = F.trim(F.regexp_replace(F.regexp_replace("__low", rf"(?:{pair}|since {X}|before {X}|(?:as of|back in|on|at|in) {X})", " "), r"[ \t]+", " "))
    out = out.withColumns({"kind": kind, "t_from": t_from.cast("long"), "t_to": t_to.cast("long"), "core_text": core})
    return out.drop("__low", "__rule", *[f"__{k}{s}" for k in phrases for s in ("", "_at", "_end")])


def explicit(queries: DataFrame, at: int | None = None, between: tuple[int, int] | None = None) -> DataFrame:
    """Arguments instead of text."""
    kind = "comparative" if between else "historical" if at is not None else "live"
    first, last = between or (at, None)
    return queries.withColumn("kind", F.lit(kind)).withColumn("t_from", F.lit(first).cast("long")).withColumn("t_to", F.lit(last).cast("long")).withColumn("core_text", F.col("text"))
