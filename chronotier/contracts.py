"""Schemas of the engine's tables, checked on read and write."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import types as T

_L, _S, _B = T.LongType(), T.StringType(), T.BooleanType()


def _schema(**fields: T.DataType) -> T.StructType:
    return T.StructType([T.StructField(k, v) for k, v in fields.items()])


REVISIONS = _schema(doc_id=_L, revision=_L, effective_at=_L, text=_S, gone=_B)
SEGMENTS = _schema(doc_id=_L, revision=_L, effective_at=_L, ordinal=_L, kind=_S, body=_S, content_key=_S)
LEDGER = _schema(doc_id=_L, ordinal=_L, content_key=_S, revision=_L)
CHANGES = _schema(doc_id=_L, ordinal=_L, op=_S, content_key=_S, prior_key=_S, moved_from=_L, needs_encoding=_B)
VECTORS = _schema(content_key=_S, embedding=T.ArrayType(T.FloatType()), dim=T.IntegerType(), encoder=_S)
LIVE_SLOTS = _schema(doc_id=_L, ordinal=_L, content_key=_S, effective_at=_L, revision=_L, body=_S)
HISTORY = _schema(doc_id=_L, ordinal=_L, content_key=_S, effective_at=_L, revision=_L, op=_S, prior_key=_S, body=_S, commit_seq=_L)


def check(df: DataFrame, schema: T.StructType) -> DataFrame:
    """df with exactly the schema's columns in its order; raises on a missing column
    or another type. Further columns are dropped."""
    have = dict(df.dtypes)
    for f in schema:
        if f.name not in have:
            raise ValueError(f"column {f.name} is missing")
        if have[f.name] != f.dataType.simpleString():
            raise ValueError(f"column {f.name} is {have[f.name]}, not {f.dataType.simpleString()}")
    return df.select(*schema.fieldNames())
