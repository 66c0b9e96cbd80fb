"""The index behind the live tier: graphs over the different texts that are valid now.

Equal lines are one vector, so a line on a third of all documents is one node. A query
walks the graphs to the k nearest texts and meets their slots by key. A predicate on
slots goes into the walk as the set of texts that some slot allows, before any is
ranked."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from chronotier.operators import encode, search
from chronotier.operators.ann.index import Graph


def dense(coded: DataFrame, ident: str) -> DataFrame:
    """(ident, embedding) from rows with hashed terms (codes)."""

    def run(frames: Iterator) -> Iterator:
        for f in frames:
            if len(f):
                yield f.assign(codes=list(encode.matrix(list(f["codes"])).astype("float32"))).rename(columns={"codes": "embedding"})

    return coded.select(ident, "codes").mapInPandas(run, f"{ident} long, embedding array<float>")


def narrow(slots: DataFrame) -> DataFrame:
    """Slots with their hashed terms (codes) in place of their texts, made within the task,
    once for equal texts of a batch: what the index needs of the tier, to be stored."""
    rows = slots.select(*search.PLACE, "body")
    schema = ", ".join([*(f"{c} {rows.schema[c].dataType.simpleString()}" for c in search.PLACE), "codes array<int>"])

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        coder = encode.Coder()
        for b in batches:
            different = b.column(len(search.PLACE)).cast(pa.binary()).dictionary_encode("encode")
            codes = pa.array([coder.codes(c) for c in different.dictionary.to_pylist()], pa.list_(pa.int32()))
            yield pa.RecordBatch.from_arrays([*b.columns[:-1], codes.take(different.indices)], names=[*search.PLACE, "codes"])

    return rows.mapInArrow(run, schema)


def _keyed(slots: DataFrame) -> DataFrame:
    return search.coded(slots, "body").withColumn("vec_id", F.xxhash64("content_key"))


def build(slots: DataFrame) -> DataFrame:
    """The graphs as a table, to be stored beside the tier; texts without terms, which no
    question can find, are left out."""
    texts = _keyed(slots).where(F.size("codes") > 0).groupBy("vec_id").agg(F.first("codes").alias("embedding"))
    return Graph(texts, dense=encode.matrix, at_once=True).graphs  # shuffled as terms, which are narrow


def find(queries: DataFrame, slots: DataFrame, graphs: DataFrame, k: int = 5, ef: int = 64, filtered: bool = False) -> DataFrame:
    """As search.live, but by the index: approximate, and with the tie of equal scores
    broken among the texts that it finds. slots: those that may be answered; filtered
    says that they are not all that the index holds."""
    held = _keyed(slots)
    asked = dense(search.coded(queries, "text").where(F.size("codes") > 0), "qid")
    near = Graph(None, graphs=graphs).search(asked, k, ef, held.select("vec_id") if filtered else None)
    met = held.join(F.broadcast(near.select("qid", "vec_id", "score")), "vec_id")  # k rows a question
    return search.rank(met, k).select("qid", "rank", "score", *search.PLACE, F.lit("hot").alias("tier"))
