"""Encoders, and encoding only what has no vector yet."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from chronotier.functions.fingerprint import canonical

#: What separates terms; the same class in Java and RE2.
SEPARATOR = "[^a-z0-9à-öø-ÿß]+"
DIM = 384


def pending_keys(changes: DataFrame, vectors: DataFrame | None, scope: str = "corpus") -> DataFrame:
    """Rows to encode: changed slots whose key has no vector. scope: corpus (one row per
    key), document (one per document and key) or none (every slot)."""
    rows = changes.where("needs_encoding")
    rows = rows.join(vectors.select("content_key"), "content_key", "left_anti") if vectors is not None else rows
    return {"corpus": lambda: rows.dropDuplicates(["content_key"]), "document": lambda: rows.dropDuplicates(["doc_id", "content_key"]), "none": lambda: rows}[scope]()


def sparse(df: DataFrame, id_col: str, text: str = "body", dim: int = DIM) -> DataFrame:
    """(id, bucket, w): hashed terms of each row's text with signed integer counts."""
    term = F.explode(F.split(canonical(F.col(text)), SEPARATOR))
    rows = df.select(id_col, term.alias("term")).where("term <> ''").groupBy(id_col, "term").count()
    h = F.md5("term")
    hex_at = lambda a, n: F.conv(F.substring(h, a, n), 16, 10).cast("long")
    rows = rows.select(id_col, (hex_at(1, 8) % dim).alias("bucket"), F.when(hex_at(9, 1) % 2 == 0, F.col("count")).otherwise(-F.col("count")).alias("c"))
    return rows.groupBy(id_col, "bucket").agg(F.sum("c").alias("w")).where("w <> 0")


def codes(text: Column, dim: int = DIM) -> Column:
    """The hashed terms of a text in its own row, one number per term: its bucket + 1,
    negative where the sign is. Narrow, so a tier can hold them beside the text."""

    def one(term: Column) -> Column:
        h = F.md5(term)
        hex_at = lambda a, n: F.conv(F.substring(h, a, n), 16, 10).cast("long")
        return (F.when(hex_at(9, 1) % 2 == 0, 1).otherwise(-1) * (hex_at(1, 8) % dim + 1)).cast("int")

    return F.transform(F.filter(F.split(canonical(text), SEPARATOR), lambda x: x != ""), one)


class Coder(dict):
    """codes of texts in Python: terms to their numbers, kept as they are met."""

    #: Terms that are kept.
    MOST = 200_000

    def __init__(self, dim: int = DIM):
        import re

        self.dim, self.words = dim, re.compile(f"[{SEPARATOR[2:-2]}]+").findall

    def __missing__(self, term: str) -> int:
        h = hashlib.md5(term.encode()).hexdigest()
        if len(self) >= self.MOST:
            self.clear()
        self[term] = n = (1 if int(h[8], 16) % 2 == 0 else -1) * (int(h[:8], 16) % self.dim + 1)
        return n

    def codes(self, text: bytes | None) -> list[int]:
        """As `codes`, of UTF-8 bytes."""
        return [self[w] for w in self.words(text.decode("utf-8", "replace").lower())] if text else []


def matrix(rows: list, dim: int = DIM):
    """Rows of codes as a dense matrix of signed counts."""
    import numpy as np

    n = np.fromiter((len(r) for r in rows), np.int64, len(rows))
    flat = np.fromiter((c for r in rows for c in r), np.int64, int(n.sum()))
    at = np.repeat(np.arange(len(rows)), n) * dim + np.abs(flat) - 1
    return np.bincount(at, weights=np.sign(flat), minlength=len(rows) * dim).reshape(len(rows), dim)


def _dense(text: str, dim: int):
    import re

    import numpy as np

    v = np.zeros(dim, np.float32)
    for t in re.split(SEPARATOR, text):
        if t:
            h = hashlib.md5(t.encode()).hexdigest()
            v[int(h[:8], 16) % dim] += 1 if int(h[8], 16) % 2 == 0 else -1
    n = np.linalg.norm(v)
    return v / n if n else v


class HashEncoder:
    """Feature hashing of terms, dense and of unit length; runs in Arrow batches."""

    name = "hash"

    def __init__(self, dim: int = DIM):
        self.dim = dim

    def encode(self, df: DataFrame, id_col: str = "content_key", text: str = "body") -> DataFrame:
        dim, kind = self.dim, dict(df.dtypes)[id_col]

        def run(batches: Iterator) -> Iterator:
            import pyarrow as pa

            for b in batches:
                rows = [_dense(t or "", dim) for t in b.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array([r.tolist() for r in rows], pa.list_(pa.float32()))], names=[id_col, "embedding"])

        made = df.select(id_col, canonical(F.col(text)).alias(text)).mapInArrow(run, f"{id_col} {kind}, embedding array<float>")
        return made.withColumn("dim", F.lit(dim)).withColumn("encoder", F.lit(self.name))


class PacedEncoder:
    """Another encoder that takes a stated time per row, as a model does that is not
    installed here: what a change of strategy saves shows only if encoding costs."""

    def __init__(self, inner, ms: float):
        self.inner, self.ms, self.name = inner, ms, f"{inner.name}+{ms:g}ms"

    def encode(self, df: DataFrame, id_col: str = "content_key", text: str = "body") -> DataFrame:
        ms = self.ms

        def run(batches: Iterator) -> Iterator:
            import time

            for b in batches:
                time.sleep(len(b) * ms / 1000)
                yield b

        made = self.inner.encode(df, id_col, text)
        return made.mapInArrow(run, made.schema).withColumn("encoder", F.lit(self.name))


class TableEncoder:
    """Chooses among given vectors by the key, so equal texts have equal vectors."""

    name = "table"

    def __init__(self, vectors: DataFrame):
        self.vectors = vectors.select(F.col("vec_id").alias("__v"), "embedding")

    def choice(self, df: DataFrame, n: int) -> DataFrame:
        return df.withColumn("vec_id", F.conv(F.substring("content_key", 1, 8), 16, 10).cast("long") % n)

    def encode(self, df: DataFrame, id_col: str = "content_key", text: str = "body") -> DataFrame:
        met = self.choice(df, self.vectors.count()).join(self.vectors, F.col("vec_id") == F.col("__v"))
        return met.select(id_col, "embedding", F.size("embedding").alias("dim"), F.lit(self.name).alias("encoder"))


class TransformerEncoder:
    """A sentence encoder from an installed model; loaded once per worker."""

    name = "transformer"

    def __init__(self, model: str):
        self.model = model

    def encode(self, df: DataFrame, id_col: str = "content_key", text: str = "body") -> DataFrame:
        model, kind = self.model, dict(df.dtypes)[id_col]

        def run(frames):
            from sentence_transformers import SentenceTransformer

            encoder = SentenceTransformer(model)
            for f in frames:
                f["embedding"] = [x.tolist() for x in encoder.encode(f.pop(text).tolist(), normalize_embeddings=True)]
                yield f

        made = df.select(id_col, text).mapInPandas(run, f"{id_col} {kind}, embedding array<float>")
        return made.withColumn("dim", F.size("embedding")).withColumn("encoder", F.lit(self.name))


def encode_missing(changes: DataFrame, vectors: DataFrame | None, encoder, scope: str = "corpus") -> DataFrame:
    """Vectors of the new keys only; append them to vectors. changes carries body."""
    return encoder.encode(pending_keys(changes, vectors, scope).select("content_key", "body"))
