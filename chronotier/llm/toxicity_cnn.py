"""Toxicity by a small convolutional text classifier, trained in numpy.

A word's vector is the sum of hashed embeddings of the word and of two of its
prefixes, so that unseen inflections of a known stem are recognised. Filters of
several widths slide over the whole text; each filter's greatest response feeds a
logistic output. Embeddings start from the smoothed log-odds of each feature; those
that fewer than LEAST training texts hold are zero, so unknown words are neutral
however long the text. Neither labels nor lang, source or doc_id enter a score;
thresholds by language are fitted on the training rows and used only by `reject`.

Training takes every labelled row with its whole text: one pass counts the features,
each round is a pass in which every task teaches a copy of the model its rows and the
mean of what the copies have changed is taken, and a last pass counts scores for the
thresholds. So the model depends on how rows lie in files as far as the order of steps
does, and is the same for the same files. It is a few MB whatever the corpus.
Scoring is one narrow pass over the whole texts, in runs of at most RUN characters.
"""

from __future__ import annotations

import re
from bisect import bisect_right
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronotier.llm.common import drop_staged, stage_table

BUCKETS, DIM, FILTERS, WIDTHS = 1 << 17, 12, 8, (1, 2, 3)
PAD = max(WIDTHS) - 1
#: Rounds of training, at least and at most; between, as many as make up so many texts.
ROUNDS, TEXTS = (2, 6), 24_000
#: Learners of a round at most, and rows that make up for one more; texts to a step; texts
#: and their characters that are put in a random order at a time.
LEARNERS, LEAST_ROWS, STEP, MIXED, MIXED_CHARS = 64, 2000, 32, 1024, 1 << 24
#: Embeddings of a learner that are summed at a time.
PART = 1 << 11
#: Labels that are broadcast; beyond, they meet the texts by a shuffle.
MAX_LABELS = 1_000_000
#: Scores that may become a threshold.
CUTS = [0.2 + i / 100 for i in range(61)]
#: Training texts that must hold a feature before it gets an embedding.
LEAST = 5
#: Characters that are scored at a time.
RUN = 1 << 18
_TABLES: dict = {}


def _tables():
    """Letters, and the powers and inverse powers of the rolling hash's base."""
    import numpy as np

    if not _TABLES:
        base = 0x9E3779B97F4A7C15
        _TABLES["letter"] = np.array([chr(i).isalnum() or i == 95 for i in range(0x3000)] + [True])
        for name, x in (("up", base), ("down", pow(base, -1, 1 << 64))):
            p = np.full(RUN + 1, x, np.uint64)
            p[0] = 1
            _TABLES[name] = np.cumprod(p, dtype=np.uint64)
    return _TABLES


def features(text: str):
    """Embedding rows of each word of at most RUN characters: an array (words, 3)
    for the word and its prefixes of 4 and 5 letters. A word is a run of letters,
    digits or underscores of the lower-cased text."""
    import numpy as np

    t = _tables()
    code = np.frombuffer(text.encode("utf-32-le", "replace"), np.uint32)[:RUN]
    inside = np.concatenate(([False], t["letter"][np.minimum(code, 0x3000)], [False]))
    edge = np.flatnonzero(inside[1:] != inside[:-1])
    start, end = edge[::2], edge[1::2]
    sums = np.zeros(len(code) + 1, np.uint64)
    np.cumsum((code.astype(np.uint64) + np.uint64(1)) * t["up"][: len(code)], out=sums[1:])
    found = np.empty((len(start), 3), np.int64)
    for k, length in enumerate((1 << 30, 4, 5)):
        h = (sums[np.minimum(start + length, end)] - sums[start]) * t["down"][start]
        h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9 + 2 * k)
        found[:, k] = (h >> np.uint64(40)) % np.uint64(BUCKETS)
    return found


def runs(text: str | None) -> Iterator[str]:
    """The lower-cased text in runs of at most RUN characters, cut at blanks where they
    can be; each but the first begins with the last PAD words of the one before, so that
    every filter meets every place of the text in some run."""
    text, at = (text or "").lower(), 0
    while at < len(text):
        if at + RUN >= len(text):
            yield text[at:]
            return
        middle = at + RUN // 2
        stop = text.rfind(" ", middle, at + RUN)
        if stop < 0:  # a word of half a run
            stop = at + RUN
        yield text[at:stop]
        back = stop
        while back > middle and len(re.findall(r"\w+", text[back:stop])) < PAD:
            back = max(text.rfind(" ", middle, back), middle)
        at = back


@dataclass
class Model:
    rows: object  # (BUCKETS, DIM) embeddings
    filters: list  # one (width, DIM, FILTERS) array a width
    bias: list
    out: object
    base: float
    thresholds: dict = field(default_factory=dict)

    def score(self, text: str | None) -> float:
        import numpy as np

        best = np.concatenate([np.maximum(b, 0) for b in self.bias])
        before, parts = np.zeros((PAD, DIM), np.float32), list(runs(text))
        for i, part in enumerate(parts):
            f = features(part)
            after = PAD if i + 1 == len(parts) else 0  # nothing but the text's ends is padded
            x = np.concatenate((before if i == 0 else before[:0], self.rows[f[:, 0]] + self.rows[f[:, 1]] + self.rows[f[:, 2]], before[:after]))
            best = np.maximum(best, np.concatenate([respond(x, w, b).max(0, initial=-np.inf) for w, b in zip(self.filters, self.bias, strict=True)]))
        z = float(best @ self.out + self.base)
        return float(1 / (1 + np.exp(-np.clip(z, -30, 30))))


def respond(x, w, b):
    """Responses of one width's filters at every position."""
    n = max(0, len(x) - len(w) + 1)
    return sum(x[j : j + n] @ w[j] for j in range(len(w))) + b


def document_counts(counts, text: str, toxic: int) -> None:
    """Add the features of one text to counts (2, BUCKETS): texts of a class that hold each."""
    import numpy as np

    held = np.zeros(BUCKETS, bool)
    for part in runs(text):
        held[features(part).reshape(-1)] = True
    counts[toxic][held] += 1


class Learner:
    """Weights, and the sums of their squared steps that set the size of the next. counts:
    as of document_counts over all training texts, n0 and n1 of each class; classes
    weigh the same in total. Before any step the model is sums of log-odds."""

    def __init__(self, counts, n0: int, n1: int, seed: int = 5):
        import numpy as np

        rng = np.random.default_rng(seed)
        total = counts.sum(0)
        odds = np.log((counts[1] + 0.5) / (n1 + 1)) - np.log((counts[0] + 0.5) / (n0 + 1))
        self.e = rng.normal(0, 0.02, (BUCKETS, DIM)).astype(np.float32)
        self.e[:, 0] = 0.25 * np.clip(odds, -4, 4) * total / (total + 20)
        self.live = total >= LEAST
        self.e *= self.live[:, None]
        w = [rng.normal(0, 0.1, (k, DIM, FILTERS)).astype(np.float32) for k in WIDTHS]
        for x in w:
            x[rng.integers(0, len(x), FILTERS), 0, np.arange(FILTERS)] = 1.0
        self.rest = [*w, *[np.zeros(FILTERS, np.float32) for _ in WIDTHS], np.full(FILTERS * len(WIDTHS), 0.05, np.float32), np.full(1, -1.0, np.float32)]
        self.e_sums = np.full(BUCKETS, 1e-3, np.float32)
        self.sums = [np.full(x.shape, 1e-3, np.float32) for x in self.rest]
        self.weights = [(n0 + n1) / (2 * max(1, n)) for n in (n0, n1)]

    def copy(self) -> Learner:
        from copy import deepcopy

        return deepcopy(self)

    def model(self) -> Model:
        n = len(WIDTHS)
        return Model(self.e, self.rest[:n], self.rest[n : 2 * n], self.rest[-2], float(self.rest[-1][0]))

    def _meet(self, text: str | None) -> tuple[list, list]:
        """By width the greatest response of each filter, and the features of the words that
        gave it, (FILTERS, width, 3), -1 beyond the text. One run is held at a time."""
        import numpy as np

        n, pad = len(WIDTHS), np.full((PAD, 3), -1, np.int64)
        best = [np.full(FILTERS, -np.inf, np.float32) for _ in WIDTHS]
        words = [np.full((FILTERS, k, 3), -1, np.int64) for k in WIDTHS]
        parts = runs(text)
        part, first = next(parts, ""), True
        while part is not None:
            after = next(parts, None)
            f = features(part)
            g = np.concatenate((pad[: PAD * first], f, pad[: PAD * (after is None)]))
            x = np.zeros((len(g), DIM), np.float32)
            x[PAD * first : PAD * first + len(f)] = self.e[f[:, 0]] + self.e[f[:, 1]] + self.e[f[:, 2]]
            for k, width in enumerate(WIDTHS):
                r = respond(x, self.rest[k], self.rest[n + k])
                if len(r):
                    top = r.argmax(0)
                    found = r[top, np.arange(FILTERS)]
                    better = found > best[k]
                    best[k][better] = found[better]
                    words[k][better] = g[top[better][:, None] + np.arange(width)]
            part, first = after, False
        return best, words

    def step(self, texts: list, toxic: list[int]) -> None:
        """One step of logistic loss down the mean gradient of these texts."""
        import numpy as np

        n, m = len(WIDTHS), len(texts)
        met = [self._meet(t) for t in texts]
        pool = np.maximum(np.stack([np.concatenate(b) for b, _ in met]), 0)
        y = np.array(toxic, np.float32)
        g = 1 / (1 + np.exp(-np.clip(pool @ self.rest[-2] + self.rest[-1], -30, 30))) - y
        g = (g * np.where(y == 1, self.weights[1], self.weights[0]) / m).astype(np.float32)
        grads: list = [None] * len(self.rest)
        grads[-2], grads[-1] = g @ pool, g.sum(keepdims=True)
        rows, moves = [], []
        for k in range(n):
            mine = slice(k * FILTERS, (k + 1) * FILTERS)
            gf = g[:, None] * self.rest[-2][mine] * (pool[:, mine] > 0)
            words = np.stack([w[k] for _, w in met])  # (texts, FILTERS, width, 3)
            inside = words[..., 0] >= 0
            x = self.e[words].sum(3) * inside[..., None]
            grads[k] = np.einsum("tfjd,tf->jdf", x, gf)
            grads[n + k] = gf.sum(0)
            some = inside & (gf != 0)[..., None]
            move = gf[..., None, None] * self.rest[k].transpose(2, 0, 1)  # (texts, FILTERS, width, DIM)
            rows.append(words[some])
            moves.append(move[some])
        hit, inverse = np.unique(np.concatenate(rows).reshape(-1), return_inverse=True)
        if len(hit):
            acc = np.zeros((len(hit), DIM), np.float32)
            np.add.at(acc, inverse.reshape(-1), np.repeat(np.concatenate(moves), 3, 0))
            acc *= self.live[hit][:, None]
            self.e_sums[hit] += (acc**2).mean(1)
            self.e[hit] -= 0.05 * acc / np.sqrt(self.e_sums[hit])[:, None]
        for p, v, s in zip(self.rest, grads, self.sums, strict=True):
            s += v**2
            p -= 0.05 * v / np.sqrt(s)

    def changes(self, since: Learner, n: int) -> Iterator[tuple[int, bytes]]:
        """What n texts have changed, in parts that can be summed over learners: -1 is all
        but the embeddings times n, and n; part p is the embeddings from p * PART on, their
        sums, and 1 where they moved."""
        import numpy as np

        small = np.concatenate([(a - b).reshape(-1) for a, b in zip(self.rest + self.sums, since.rest + since.sums, strict=True)])
        yield -1, np.append(small * n, n).astype(np.float64).tobytes()
        for p in range(0, BUCKETS, PART):
            mine = slice(p, p + PART)
            moved = self.e_sums[mine] != since.e_sums[mine]
            if moved.any():
                table = np.column_stack((self.e[mine] - since.e[mine], self.e_sums[mine] - since.e_sums[mine], moved))
                yield p // PART, table.astype(np.float64).tobytes()

    def add(self, part: int, total) -> None:
        """Take the mean of what learners have changed: of those that moved an embedding, and
        by their texts of the rest."""
        import numpy as np

        if part < 0:
            at, total = 0, total[:-1] / total[-1]
            for x in self.rest + self.sums:
                x += total[at : at + x.size].reshape(x.shape).astype(np.float32)
                at += x.size
            return
        total = total.reshape(-1, DIM + 2)
        mean = (total[:, :-1] / np.maximum(total[:, -1:], 1)).astype(np.float32)
        mine = slice(part * PART, part * PART + len(mean))
        self.e[mine] += mean[:, :DIM]
        self.e_sums[mine] += mean[:, DIM]


def train(texts: list[str], toxic: list[int], lang: list[str | None], epochs: int = 6, seed: int = 5) -> Model:
    """The model of texts at hand, by one learner."""
    import numpy as np

    rng, counts = np.random.default_rng(seed), np.zeros((2, BUCKETS))
    for t, y in zip(texts, toxic, strict=True):
        document_counts(counts, t, int(y))
    learner = Learner(counts, len(texts) - sum(map(int, toxic)), sum(map(int, toxic)), seed)
    for _ in range(epochs):
        for batch in np.array_split(rng.permutation(len(texts)), max(1, len(texts) // STEP)):
            learner.step([texts[i] for i in batch], [toxic[i] for i in batch])
    m = learner.model()
    cuts = [bisect_right(CUTS, m.score(t)) for t in texts]
    m.thresholds = calibrate(Counter((x, int(y), c) for x, y, c in zip(lang, toxic, cuts, strict=True)))
    return m


def calibrate(counts: dict[tuple[str | None, int, int], int], least: int = 10) -> dict[str, float]:
    """By language the middle of the cuts with the best F1, within 0.2 and 0.8; 0.5
    for a language with fewer than `least` rows of a class. counts: rows by language, class
    and number of CUTS that the score reaches."""
    import numpy as np

    found, tables = {}, {}
    for (name, y, reached), n in counts.items():
        if name is not None:
            tables.setdefault(name, np.zeros((2, len(CUTS) + 1), np.int64))[y, reached] += n
    cuts = np.array(CUTS)
    for name, rows in sorted(tables.items()):
        if rows.sum(1).min() < least:
            continue
        over = rows[:, ::-1].cumsum(1)[:, ::-1][:, 1:]  # by class, those that reach each cut
        f1 = 2 * over[1] / np.maximum(1, over.sum(0) + rows[1].sum())
        best = cuts[f1 >= f1.max() - 1e-12]
        found[name] = float(best[np.abs(best - np.median(best)).argmin()])
    return found


def _labelled(docs: DataFrame, labels: DataFrame) -> tuple[DataFrame, int] | None:
    """(text, lang, toxic) of all documents with a label whose CRC-32 of doc_id is no multiple
    of 5, and the number of such labels; None if one of the classes has no label."""
    rows = labels.where("doc_id is not null and toxic is not null").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    rows = rows.where(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 != 0).where("toxic in (0, 1)")
    n = {r["toxic"]: r["n"] for r in rows.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    if len(n) < 2:
        return None
    texts = docs.where("text is not null").select("doc_id", "text", "lang")
    if sum(n.values()) <= MAX_LABELS:
        return texts.join(F.broadcast(rows), "doc_id").select("text", "lang", "toxic"), sum(n.values())
    met = texts.hint("shuffle_hash").join(rows, "doc_id").select("text", "lang", "toxic")
    return stage_table(met, "labelled"), sum(n.values())  # shuffled once, not with each pass


def _summed(parts: DataFrame) -> Iterator[tuple[int, object]]:
    """The sums of rows (part, task, data) by part, data being doubles, in the order of tasks."""
    import numpy as np

    def add(f):
        import pandas as pd

        f = f.sort_values("task", kind="stable")
        total = np.zeros(len(f["data"].iloc[0]) // 8)
        for x in f["data"]:
            total += np.frombuffer(x)
        return pd.DataFrame({"part": [int(f["part"].iloc[0])], "data": [total.tobytes()]})

    for r in parts.groupBy("part").applyInPandas(add, "part int, data binary").collect():  # BUCKETS / PART rows
        yield r["part"], np.frombuffer(bytes(r["data"]))


def _parts(found: Iterator[tuple[int, bytes]]) -> Iterator[pa.RecordBatch]:
    from pyspark import TaskContext

    for part, data in found:
        yield pa.RecordBatch.from_arrays([pa.array([part], pa.int32()), pa.array([TaskContext.get().partitionId()], pa.int32()), pa.array([data], pa.binary())], names=["part", "task", "data"])


PARTS = "part int, task int, data binary"


def _counted(rows: DataFrame) -> tuple[object, int, int]:
    """document_counts over all rows, and the texts of each class."""
    import numpy as np

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts, n = np.zeros((2, BUCKETS)), np.zeros(2)
        for b in batches:
            for text, toxic in zip(b.column(0), b.column(1).to_pylist(), strict=True):
                document_counts(counts, text.as_py(), toxic)
                n[toxic] += 1
        if n.any():
            yield from _parts([(-1, n.tobytes()), *((p // PART, counts[:, p : p + PART].tobytes()) for p in range(0, BUCKETS, PART))])

    counts, n = np.zeros((2, BUCKETS)), np.zeros(2)
    for part, total in _summed(rows.select("text", "toxic").mapInArrow(run, PARTS)):
        if part < 0:
            n = total
        else:
            counts[:, part * PART : (part + 1) * PART] = total.reshape(2, -1)
    return counts, int(n[0]), int(n[1])


def _round(rows: DataFrame, learner: Learner, seed: int) -> None:
    """Learners start from this one, each goes through the rows of its task once, and what
    they have changed comes back."""
    shared = rows.sparkSession.sparkContext.broadcast(learner)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np
        from pyspark import TaskContext

        mine, n, held, size = shared.value.copy(), 0, [], 0
        rng = np.random.default_rng([seed, TaskContext.get().partitionId()])

        def learn() -> None:
            for batch in np.array_split(rng.permutation(len(held)), max(1, len(held) // STEP)):
                mine.step([held[i][0] for i in batch], [held[i][1] for i in batch])

        for b in batches:
            for text, toxic in zip(b.column(0), b.column(1).to_pylist(), strict=True):
                held.append((text.as_py(), toxic))
                n, size = n + 1, size + len(held[-1][0])
                if len(held) == MIXED or size >= MIXED_CHARS:  # an order by class would mislead
                    learn()
                    held, size = [], 0
        if held:
            learn()
        if n:
            yield from _parts(mine.changes(shared.value, n))

    for part, total in _summed(rows.select("text", "toxic").mapInArrow(run, PARTS)):
        learner.add(part, total)
    shared.unpersist()


def fit(docs: DataFrame, labels: DataFrame) -> Model | None:
    """The model from all labelled rows whose CRC-32 of doc_id is no multiple of 5; None if
    one of the classes has no row."""
    found = _labelled(docs, labels)
    if found is None:
        return None
    rows, n = found
    counts, n0, n1 = _counted(rows)
    if n0 + n1 == 0:
        return None
    learner = Learner(counts, n0, n1)
    learners = max(1, min(LEARNERS, n // LEAST_ROWS))
    for i in range(max(ROUNDS[0], min(ROUNDS[1], -(-TEXTS // (n0 + n1))))):
        _round(rows.coalesce(learners), learner, i)
    model = learner.model()
    cuts = F.lit(0)
    for c in CUTS:
        cuts = cuts + (F.col("score") >= c).cast("int")
    reached = score(rows.where("lang is not null"), model).groupBy("lang", "toxic", cuts.alias("reached")).count()
    model.thresholds = calibrate({(r["lang"], r["toxic"], r["reached"]): r["count"] for r in reached.collect()})
    drop_staged(rows)
    return model


def score(docs: DataFrame, model: Model | None) -> DataFrame:
    """All columns of docs and score DOUBLE, which replaces a column of that name. A
    null or empty text is scored as a text without words; without a model every
    score is 0. Rows that share an id are scored by their own texts."""
    docs = docs.drop("score")
    if model is None:
        return docs.withColumn("score", F.lit(0.0))
    shared = docs.sparkSession.sparkContext.broadcast(model)
    names, text = docs.columns, docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for b in batches:
            scores = pa.array([m.score(t.as_py()) for t in b.column(text)], pa.float64())
            yield pa.RecordBatch.from_arrays([*b.columns, scores], names=[*names, "score"])

    schema = docs.withColumn("score", F.lit(0.0)).schema
    return docs.mapInArrow(run, schema)


def threshold(model: Model | None, lang=None):
    """The language's threshold as a column; 0.5 where none was fitted."""
    found = (model.thresholds if model else {}).items()
    whens = F.lit(0.5)
    for name, cut in found:
        whens = F.when(F.col("lang") == name, cut).otherwise(whens)
    return whens


def reject(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """docs without the rows whose score reaches their language's threshold."""
    model = fit(docs, labels)
    return score(docs, model).where(F.col("score") < threshold(model)).select(*docs.columns)
