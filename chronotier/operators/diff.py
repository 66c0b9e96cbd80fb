"""Change detection between two versions of documents.

old and new hold (by…, ordinal, content_key[, body]); `by` is doc_id, or doc_id and
revision when many pairs of versions are compared in one job. Documents are those of
new and of `withdrawn`; others that old holds are left alone. All joins are equi-joins
on the document, so a ledger bucketed by doc_id is read without a shuffle.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

BY = ("doc_id",)
OUT = ["ordinal", "op", "content_key", "prior_key", "moved_from", "needs_encoding", "audit"]


def _touched(old: DataFrame, new: DataFrame, by: tuple[str, ...], withdrawn: DataFrame | None) -> DataFrame:
    ids = new.select(*by)
    ids = ids.union(withdrawn.select(*by)) if withdrawn is not None else ids
    return old.join(ids.distinct(), list(by), "left_semi")


def _slots(old: DataFrame, new: DataFrame, by: tuple[str, ...]) -> DataFrame:
    a = old.select(*by, "ordinal", F.col("content_key").alias("a"), F.lit(True).alias("had"))
    b = new.select(*by, "ordinal", F.col("content_key").alias("b"), F.lit(True).alias("has"))
    met = a.join(b, [*by, "ordinal"], "full_outer")
    return met.withColumns({c: F.coalesce(F.col(c), F.lit(False)) for c in ("had", "has")})


def by_slot(old: DataFrame, new: DataFrame, by: tuple[str, ...] = BY, withdrawn: DataFrame | None = None) -> DataFrame:
    """Position decides: kept, edited, added or dropped at each (document, ordinal)."""
    met = _slots(_touched(old, new, by, withdrawn), new, by)
    op = F.when(~F.col("had"), "added").when(~F.col("has"), "dropped").when(F.col("a") == F.col("b"), "kept").otherwise("edited")
    met = met.withColumn("op", op)
    prior = F.when(F.col("op").isin("edited", "dropped"), F.col("a"))
    return met.select(*by, "ordinal", "op", F.col("b").alias("content_key"), prior.alias("prior_key"), F.lit(None).cast("long").alias("moved_from"), F.col("op").isin("added", "edited").alias("needs_encoding"), F.lit(False).alias("audit"))


def by_content(old: DataFrame, new: DataFrame, by: tuple[str, ...] = BY, withdrawn: DataFrame | None = None) -> DataFrame:
    """Keys decide, position doesn't: how many copies of each key were kept, added or
    dropped: (by…, content_key, op, copies)."""
    old = _touched(old, new, by, withdrawn)
    n = lambda df, c: df.groupBy(*by, "content_key").agg(F.count("*").alias(c))
    met = n(old, "was").join(n(new, "is"), [*by, "content_key"], "full_outer").na.fill(0, ["was", "is"])
    parts = [("kept", F.least("was", "is")), ("added", F.col("is") - F.col("was")), ("dropped", F.col("was") - F.col("is"))]
    rows = F.explode(F.array(*[F.struct(F.lit(k).alias("op"), v.alias("copies")) for k, v in parts]))
    return met.select(*by, "content_key", rows.alias("x")).select(*by, "content_key", "x.op", "x.copies").where("copies > 0")


def combined(old: DataFrame, new: DataFrame, by: tuple[str, ...] = BY, withdrawn: DataFrame | None = None) -> DataFrame:
    """Position and content: kept, edited, added, moved, dropped, vacated. One state
    row per slot; a key that a move overwrites for good adds an audit row `dropped`.

    Both versions are dealt out by document once; the places of a key, the slots and
    the documents to be looked at are then found within a task."""
    side = lambda df, n: df.select(*by, "ordinal", "content_key", F.lit(n).alias("side"))
    rows = side(old, 0).union(side(new, 1))
    if withdrawn is not None:
        none = [F.lit(None).cast(rows.schema[c].dataType).alias(c) for c in ("ordinal", "content_key")]
        rows = rows.union(withdrawn.select(*by, *none, F.lit(2).alias("side")))
    was, now = F.col("side") == 0, F.col("side") == 1
    rows = rows.repartition(*by)
    rows = rows.withColumn("looked", F.max("side").over(W.partitionBy(*by))).where("looked > 0 and side < 2")
    key = W.partitionBy(*by, "content_key")
    rows = rows.withColumn("came", F.min(F.when(was, F.col("ordinal"))).over(key)).withColumn("goes", F.min(F.when(now, F.col("ordinal"))).over(key))
    of = lambda side, c, name: F.max(F.when(side, F.col(c))).alias(name)
    met = rows.groupBy(*by, "ordinal").agg(of(was, "content_key", "a"), of(now, "content_key", "b"), F.bool_or(was).alias("had"), F.bool_or(now).alias("has"), of(now, "came", "came"), of(was, "goes", "goes"))
    had, has, came, stays = F.col("had"), F.col("has"), F.col("came").isNotNull(), F.col("goes").isNotNull()
    op = F.when(had & has & (F.col("a") == F.col("b")), "kept").when(has & came, "moved").when(had & has & ~stays, "edited").when(has, "added").when(stays, "vacated").otherwise("dropped")
    met = met.withColumn("op", op).withColumn("stays", stays)
    prior = F.when(F.col("op").isin("edited", "dropped", "vacated"), F.col("a"))
    state = F.struct(F.col("op"), F.col("b").alias("content_key"), prior.alias("prior_key"), F.when(F.col("op") == "moved", F.col("came")).alias("moved_from"), F.col("op").isin("added", "edited").alias("needs_encoding"), F.lit(False).alias("audit"))
    lost = F.struct(F.lit("dropped").alias("op"), F.lit(None).cast("string").alias("content_key"), F.col("a").alias("prior_key"), F.lit(None).cast("long").alias("moved_from"), F.lit(False).alias("needs_encoding"), F.lit(True).alias("audit"))
    found = F.when((F.col("op") == "moved") & had & ~F.col("stays"), F.array(state, lost)).otherwise(F.array(state))
    return met.select(*by, "ordinal", F.explode(found).alias("x")).select(*by, "ordinal", "x.*")


def _matcher(was: list[str], now: list[str]):
    """difflib's matcher with the same longest runs, found by arrays: a line that is
    repeated thousands of times costs one array operation per occurrence."""
    import difflib

    import numpy as np

    class Matcher(difflib.SequenceMatcher):
        def find_longest_match(self, alo=0, ahi=None, blo=0, bhi=None):
            ahi, bhi = len(self.a) if ahi is None else ahi, len(self.b) if bhi is None else bhi
            none, last, best = np.empty(0, np.int64), np.empty(0, np.int64), (alo, blo, 0)
            for i in range(alo, ahi):
                at = places.get(self.a[i], none)
                at = at[np.searchsorted(at, blo) : np.searchsorted(at, bhi)] if len(at) else at
                run = length[at] + 1  # length[j] is the run that ends at i - 1, j - 1
                length[last + 1] = 0
                length[at + 1] = run
                last = at
                if len(at) and run.max() > best[2]:
                    x = run.argmax()
                    best = (i - int(run[x]) + 1, int(at[x]) - int(run[x]) + 1, int(run[x]))
            length[last + 1] = 0
            return difflib.Match(*best)

    found = Matcher(None, was, now, autojunk=False)
    places, length = {k: np.array(v) for k, v in found.b2j.items()}, np.zeros(len(now) + 1, np.int64)
    return found


def aligned(old: DataFrame, new: DataFrame, by: tuple[str, ...] = BY, withdrawn: DataFrame | None = None) -> DataFrame:
    """Longest matching runs decide: added, dropped and edited lines by alignment, so a
    line on top shifts nothing. Time grows with the number of equal pairs of slots."""
    old = _touched(old, new, by, withdrawn)
    lists = lambda df, c: df.groupBy(*by).agg(F.transform(F.array_sort(F.collect_list(F.struct("ordinal", "content_key"))), lambda x: x["content_key"]).alias(c))
    met = lists(old, "was").join(lists(new, "is"), list(by), "full_outer")
    schema = ", ".join(f"{c} long" for c in by) + ", ordinal long, op string, content_key string, prior_key string"

    def run(frames):
        import pandas as pd

        for f in frames:
            out = []
            for row in f.itertuples(index=False):
                ids, was, now = row[: len(by)], list(row[len(by)]) if row[len(by)] is not None else [], list(row[len(by) + 1]) if row[len(by) + 1] is not None else []
                for tag, i, j, k, m in _matcher(was, now).get_opcodes():
                    both = min(j - i, m - k) if tag == "replace" else 0
                    out += [(*ids, x, "kept", now[x], None) for x in range(k, m) if tag == "equal"]
                    out += [(*ids, k + x, "edited", now[k + x], was[i + x]) for x in range(both)]
                    if tag in ("replace", "insert"):
                        out += [(*ids, x, "added", now[x], None) for x in range(k + both, m)]
                    if tag in ("replace", "delete"):
                        out += [(*ids, x, "dropped", None, was[x]) for x in range(i + both, j)]
            yield pd.DataFrame(out, columns=[*by, "ordinal", "op", "content_key", "prior_key"])

    return met.select(*by, "was", "is").mapInPandas(run, schema)


def replay(old: DataFrame, changes: DataFrame, by: tuple[str, ...] = BY) -> DataFrame:
    """old with a diff's state rows applied: gives the new version back."""
    state = changes.where("not audit")
    kept = old.select(*by, "ordinal", "content_key").join(state.select(*by, "ordinal"), [*by, "ordinal"], "left_anti")
    return kept.union(state.where("content_key is not null").select(*by, "ordinal", "content_key"))


def document_keys(segments: DataFrame, by: tuple[str, ...] = BY) -> DataFrame:
    """One key per document version, over its keys in order."""
    rows = F.array_sort(F.collect_list(F.struct("ordinal", "content_key")))
    return segments.groupBy(*by).agg(F.sha2(F.array_join(F.transform(rows, lambda x: x["content_key"]), "|"), 256).alias("doc_key"))


def touched_docs(old: DataFrame, new: DataFrame, by: tuple[str, ...] = BY) -> DataFrame:
    """Documents whose key differs or that are new."""
    was = document_keys(old, by).withColumnRenamed("doc_key", "was")
    return document_keys(new, by).join(was, list(by), "left").where(~F.col("doc_key").eqNullSafe(F.col("was"))).select(*by)


def semantic_change(changes: DataFrame, vectors: DataFrame, threshold: float = 0.9) -> DataFrame:
    """Edited slots with the cosine of the old and the new vector, and whether the
    change is one of meaning."""
    from chronotier.functions.score import cosine

    old = vectors.select(F.col("content_key").alias("prior_key"), F.col("embedding").alias("ov"))
    new = vectors.select("content_key", F.col("embedding").alias("nv"))
    met = changes.where("op = 'edited'").join(old, "prior_key").join(new, "content_key")
    met = met.withColumn("similarity", cosine(F.col("ov"), F.col("nv"))).drop("ov", "nv")
    return met.withColumn("meaning_changed", F.col("similarity") < threshold)
