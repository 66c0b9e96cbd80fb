"""Removal of repeated byte strings by prefix-free parsing.

A byte goes if it lies in a string of LENGTH bytes that also starts anywhere else in
the corpus. The windows of LENGTH bytes are parsed into phrases by rolling-hash
triggers: a window's trigger is its least hash of GRAM bytes, so equal windows have
their trigger at the same place, and consecutive windows that share a trigger make
one phrase, which holds all their bytes. The sequence of phrases is the parse, the
different phrases are the dictionary, sharded by trigger.

In corpus order (all suffixes sorted) a window is repeated if the suffix before or
after it agrees in LENGTH bytes. That order has two parts:

* the parse: suffixes that start at the same place of equal phrases are neighbours, so
  a phrase that occurs twice in the parse has only repeated windows. Nothing further
  of the parse is needed, as a phrase holds its windows whole;
* the dictionary: suffixes of different phrases are neighbours in LENGTH bytes only if
  the phrases have the trigger in common. So the suffixes of each shard's phrases are
  sorted by their bytes, in a sparse suffix array: only of window starts, and only of
  those whose rolling hash occurs twice in the shard, since others have no neighbour.
  A trigger with one phrase has no shard, and most of a corpus ends there.

A trigger with more than SHARD phrases (a passage in a third of all documents, each
time between other words) would make a shard without bound. Its phrases are parsed
finer, into blocks of BLOCK windows, which are classified like phrases; what still has
more than SHARD different strings is compared window by window, by an aggregation of
digests with partial sums.

Phrases, blocks and such windows are equal if their 128-bit BLAKE2 digests are, and
windows within a shard if their bytes are; triggers and rolling hashes only propose.

Texts are shuffled once to meet their triggers; those without a repeated trigger
stop there, with the digest that the first pass made.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import reduce

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronotier.llm.common import broadcast_if_small, drop_staged, sorted_groups, stage_table

LENGTH, GRAM, BLOCK = 400, 100, 20
SEGMENT = 900_000  # bytes parsed at a time; with its margins under 2**20
MARGIN = LENGTH + GRAM
OUT = 100_000  # rows to a batch
#: Different phrases of a trigger whose suffixes one task sorts together; BYTES of
#: phrases are sorted at a time.
SHARD, BYTES = 400, 300_000
#: Documents with repeated triggers up to which their keys (16 bytes) are broadcast;
#: beyond, their texts are shuffled once more.
MAX_DOCS = 500_000
_POWERS: dict = {}


def _tables():
    """A random word per byte value; powers and inverse powers of an odd base."""
    import numpy as np

    if not _POWERS:
        n, base = 1 << 20, 0x9E3779B97F4A7C15
        _POWERS["byte"] = np.random.default_rng(400).integers(0, 1 << 63, 256, dtype=np.uint64) * np.uint64(2)
        for name, x in (("up", base), ("down", pow(base, -1, 1 << 64))):
            p = np.full(n, x, np.uint64)
            p[0] = 1
            _POWERS[name] = np.cumprod(p, dtype=np.uint64)
    return _POWERS


def _mix(h):
    import numpy as np

    h = (h ^ (h >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return h ^ (h >> np.uint64(32))


class Rolling:
    """Hashes of any substrings of a segment, from sums over its bytes."""

    def __init__(self, data: bytes):
        import numpy as np

        t = _tables()
        self.sums = np.zeros(len(data) + 1, np.uint64)
        np.cumsum(t["byte"][np.frombuffer(data, np.uint8)] * t["up"][: len(data)], out=self.sums[1:])

    def of(self, start, end):
        return _mix((self.sums[end] - self.sums[start]) * _tables()["down"][start])


def _digests(data: bytes, start, end):
    """Two arrays with the 128-bit digests of these substrings."""
    import numpy as np

    made = b"".join([hashlib.blake2b(data[a:b], digest_size=16).digest() for a, b in zip(start.tolist(), end.tolist(), strict=True)])
    both = np.frombuffer(made, np.uint64).reshape(-1, 2)
    return both[:, 0], both[:, 1]


def _least(x, width: int):
    """Least of each `width` consecutive values."""
    import numpy as np

    n = len(x) - width + 1
    full = np.full(-(-len(x) // width) * width, np.iinfo(np.uint64).max, np.uint64)
    full[: len(x)] = x
    grid = full.reshape(-1, width)
    ahead = np.minimum.accumulate(grid, axis=1).ravel()
    back = np.minimum.accumulate(grid[:, ::-1], axis=1)[:, ::-1].ravel()
    return np.minimum(back[:n], ahead[width - 1 : width - 1 + n])


def phrases(data: bytes) -> Iterator[tuple]:
    """Arrays (at, lo, hi, core, s1, s2) of the phrases of a text, segment by
    segment: the trigger's place, the first and last start of its windows, the hash
    of the trigger and the digest of the phrase, all bytes of its windows."""
    import numpy as np

    span, held = LENGTH - GRAM, None
    for first in range(0, max(1, len(data) - LENGTH + 1), SEGMENT):
        last = min(first + SEGMENT, len(data) - LENGTH + 1)  # window starts first <= s < last
        if last <= first:
            break
        base = max(0, first - MARGIN)
        roll = Rolling(data[base : last + LENGTH + MARGIN])
        p = np.arange(first - base, last - base + span, dtype=np.int64)
        gram = roll.of(p, p + GRAM)
        place = np.uint64((1 << 20) - 1)
        least = _least((gram & ~place) | p.astype(np.uint64), span + 1)
        at = (least & place).astype(np.int64)
        cut = np.flatnonzero(np.concatenate(([True], at[1:] != at[:-1])))
        at, lo = at[cut], first + cut
        hi = np.append(lo[1:], last) - 1
        found = [at + base, lo, hi, gram[at - (first - base)]]
        if held is not None:  # a trigger may serve windows of two segments
            if held[0][-1] == found[0][0]:
                found[1][0] = held[1][-1]
                held = [x[:-1] for x in held]
            yield from _whole(data, held)
        held = found
    if held is not None:
        yield from _whole(data, held)


def _whole(data: bytes, found: list) -> Iterator[tuple]:
    """Adds the digests of the phrases."""
    at, lo, hi, core = found
    for i in range(0, len(at), OUT):
        j = slice(i, i + OUT)
        yield at[j], lo[j], hi[j], core[j], *_digests(data, lo[j], hi[j] + LENGTH)


def blocks(data: bytes, at, lo, hi) -> Iterator[tuple]:
    """Arrays (at, lo, hi, core, s1, s2) of the blocks of BLOCK windows, by
    their distance before the trigger, that phrases at, lo, hi consist of."""
    import numpy as np

    for roll, base, mine in _segments(data, at):
        a, l, h = at[mine], lo[mine], hi[mine]
        near, far = (a - h) // BLOCK, (a - l) // BLOCK
        n = far - near + 1
        item = np.repeat(np.arange(len(a)), n)
        block = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + near[item]
        top, low = a[item] - block * BLOCK, a[item] - block * BLOCK - BLOCK + 1
        core = roll.of(top - base, low + LENGTH - base) ^ _mix(block.astype(np.uint64) + np.uint64(77))
        low, top = np.maximum(low, l[item]), np.minimum(top, h[item])
        yield a[item], low, top, core, *_digests(data, low, top + LENGTH)


def windows(data: bytes, at, lo, hi) -> Iterator[tuple]:
    """Arrays (at, start, s1, s2) of the single windows of blocks at, lo, hi."""
    import numpy as np

    for i in range(0, len(at), OUT // BLOCK):
        j = slice(i, i + OUT // BLOCK)
        n = hi[j] - lo[j] + 1
        item = np.repeat(np.arange(len(n)), n)
        start = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + lo[j][item]
        yield at[j][item], start, *_digests(data, start, start + LENGTH)


def repeated(strings: list[bytes]) -> list:
    """For each string the starts of its windows that occur again in these strings, by
    a sparse suffix array over all of them."""
    import numpy as np

    data, n = b"".join(strings), np.array([len(x) - LENGTH + 1 for x in strings])
    ends = np.cumsum([len(x) for x in strings])
    first = ends - [len(x) for x in strings]
    start = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + np.repeat(first, n)
    _, back, times = np.unique(Rolling(data).of(start, start + LENGTH), return_inverse=True, return_counts=True)
    order = [(data[i : i + LENGTH], i) for i in start[times[back] > 1].tolist()]
    order.sort()
    found = [i for k, (x, i) in enumerate(order) if (k and order[k - 1][0] == x) or (k + 1 < len(order) and order[k + 1][0] == x)]
    found = np.sort(np.array(found, np.int64))
    cut = np.searchsorted(found, ends)
    return [found[a:b] - f for a, b, f in zip(np.append(0, cut[:-1]), cut, first, strict=True)]


def _segments(data: bytes, at):
    """Rolling hashes over the part of a text around each run of sorted triggers."""
    import numpy as np

    i = 0
    while i < len(at):
        j = min(int(np.searchsorted(at, at[i] + SEGMENT)), i + 20_000)
        base = max(0, int(at[i]) - MARGIN)
        yield Rolling(data[base : int(at[j - 1]) + LENGTH + MARGIN]), base, np.arange(i, j)
        i = j


def hash_of(data: bytes) -> int:
    """What Spark's xxhash64 gives, unsigned."""
    from xxhash import xxh64_intdigest

    return xxh64_intdigest(data, 42)


def _signed(x):
    import numpy as np

    return pa.array(np.asarray(x).astype(np.uint64).view(np.int64), pa.int64())


def _emit(rows: list[list], names: list[str]) -> pa.RecordBatch:
    """One batch from [doc_id, row, arrays...] entries; the arrays are 64-bit."""
    import numpy as np

    n = [len(r[2]) for r in rows]
    which = pa.array(np.repeat(np.arange(len(rows)), n))
    head = [pa.array([r[0] for r in rows], pa.int64()).take(which), _signed(np.repeat(np.array([r[1] for r in rows], np.uint64), n))]
    return pa.RecordBatch.from_arrays([*head, *(_signed(np.concatenate([r[c] for r in rows])) for c in range(2, len(rows[0])))], names=names)


def _gathered(made: Iterator[list], names: list[str]) -> Iterator[pa.RecordBatch]:
    rows, n = [], 0
    for r in made:
        rows.append(r)
        n += len(r[2])
        if n >= OUT:
            yield _emit(rows, names)
            rows, n = [], 0
    if rows:
        yield _emit(rows, names)


ITEM = ["doc_id", "row", "at", "lo", "hi", "core", "s1", "s2"]


def _classify(items: DataFrame, name: str) -> DataFrame:
    """Items with a core that others share: + full (the same string occurs twice),
    refine (it stands for its string among others of that core) and crowded (there are
    more than SHARD of these)."""
    crowd = stage_table(items.groupBy("core").count().where("count > 1").select("core"), name + "-shared")
    cand = stage_table(items.join(crowd, "core"), name)
    mark = F.struct("doc_id", "row", "at", "lo")
    per = cand.groupBy("core", "s1", "s2").agg(F.count("*").alias("n"), F.min(mark).alias("first"))
    per = stage_table(per, name + "-dictionary")
    many = stage_table(per.groupBy("core").count().where("count > 1").select("core", (F.col("count") > SHARD).alias("crowded")), name + "-many")
    met = cand.join(per.join(many, "core", "left").where("crowded is not null or n > 1"), ["core", "s1", "s2"])
    refine = F.col("crowded").isNotNull() & ((F.col("n") == 1) | mark.eqNullSafe(F.col("first")))
    out = met.select("doc_id", "row", "at", "lo", "hi", "core", (F.col("n") > 1).alias("full"), refine.alias("refine"), F.coalesce("crowded", F.lit(False)).alias("crowded"))
    out = stage_table(out.where("full or refine"), name + "-classes")
    for x in (cand, crowd, per, many):
        drop_staged(x)
    return out


def _met(texts: DataFrame, lists: DataFrame) -> DataFrame:
    """texts(doc_id, row, data) with the lists of the same row."""
    lists = lists.withColumnsRenamed({"doc_id": "of", "row": "of_row"})
    return texts.join(lists, texts["doc_id"].eqNullSafe(F.col("of")) & (texts["row"] == F.col("of_row"))).drop("of", "of_row")


def _refined(texts: DataFrame, items: DataFrame, step, names: list[str]) -> DataFrame:
    """What `step` makes of the items of each text."""
    if items.isEmpty():
        return items.sparkSession.createDataFrame([], ", ".join(f"{n} long" for n in names))
    lists = items.groupBy("doc_id", "row").agg(F.array_sort(F.collect_set(F.struct("at", "lo", "hi"))).alias("items"))

    def made(batches: Iterator[pa.RecordBatch]) -> Iterator[list]:
        import numpy as np

        for b in batches:
            for doc, row, data, got in zip(*(b.column(i) for i in range(4)), strict=True):
                got = got.values
                at, lo, hi = (got.field(i).to_numpy() for i in range(3))
                for out in step(data.as_py(), at, lo, hi):
                    yield [doc.as_py(), np.uint64(row.as_py() & (1 << 64) - 1), *out]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        return _gathered(made(batches), names)

    met = _met(texts, lists).select("doc_id", "row", "data", "items")
    return met.mapInArrow(run, ", ".join(f"{n} long" for n in names))


def _sorted_shards(texts: DataFrame, items: DataFrame) -> DataFrame:
    """(doc_id, row, lo, hi): the runs of windows of these items that the suffix arrays
    of their shards find repeated. A shard is a core; SHARD items at most have it."""
    lists = items.groupBy("doc_id", "row").agg(F.collect_set(F.struct("lo", "hi", "core")).alias("items"))
    names = ["doc_id", "row", "lo", "core", "data"]

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        for b in batches:
            for doc, row, data, got in zip(*(b.column(i) for i in range(4)), strict=True):
                doc, row, data, got = doc.as_py(), row.as_py(), data.as_py(), got.values
                lo, hi, core = (got.field(i).to_numpy() for i in range(3))
                for i in range(0, len(lo), OUT // 10):
                    part = slice(i, i + OUT // 10)
                    n = len(lo[part])
                    strings = pa.array([data[x : y + LENGTH] for x, y in zip(lo[part].tolist(), hi[part].tolist(), strict=True)], pa.binary())
                    yield pa.RecordBatch.from_arrays([pa.array([doc] * n, pa.int64()), pa.array(np.full(n, row)), pa.array(lo[part]), pa.array(core[part]), strings], names=names)

    def order(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        def settle(docs, rows, los, strings):
            out = [[], [], [], []]
            for doc, row, lo, at in zip(docs, rows, los, repeated(strings), strict=True):
                if len(at):
                    new = np.flatnonzero(np.diff(at) > 1)
                    a, z = at[np.append(0, new + 1)] + lo, at[np.append(new, len(at) - 1)] + lo
                    for col, x in zip(out, ([doc] * len(a), [row] * len(a), a.tolist(), z.tolist()), strict=True):
                        col += x
            return pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in out], names=["doc_id", "row", "lo", "hi"])

        held, size = [[], [], [], []], 0
        for table in sorted_groups(batches, ["core"]):
            cores = table.column("core").to_numpy()
            ends = np.append(np.flatnonzero(cores[1:] != cores[:-1]) + 1, len(cores))
            cols, done = [table.column(c).to_pylist() for c in ("doc_id", "row", "lo", "data")], 0
            for end in ends.tolist():  # whole shards only
                for h, c in zip(held, cols, strict=True):
                    h += c[done:end]
                size, done = size + sum(map(len, cols[3][done:end])), end
                if size >= BYTES:
                    yield settle(*held)
                    held, size = [[], [], [], []], 0
        if size:
            yield settle(*held)

    strings = _met(texts, lists).select("doc_id", "row", "data", "items").mapInArrow(cut, "doc_id long, row long, lo long, core long, data binary")
    return strings.repartition("core").sortWithinPartitions("core").mapInArrow(order, "doc_id long, row long, lo long, hi long")


def remove_repeats(docs: DataFrame, doc: str = "doc_id", text: str = "text", keep_bytes: bool = False) -> DataFrame:
    """One row per row of docs: doc_id, n_bytes, n_removed, n_spans (BIGINT) and
    kept_sha256; with keep_bytes also kept BINARY, the bytes that stay.

    A null text counts as empty. Texts under LENGTH bytes lose nothing. Rows that
    share an id are told apart by their texts; equal rows repeat each other, so all
    their windows go. An empty table gives an empty result, and other columns of
    docs are not read."""
    spark = docs.sparkSession
    raw = docs.select(F.col(doc).cast("long").alias("doc_id"), F.coalesce(F.col(text).cast("binary"), F.lit(b"")).alias("data"))

    def parse(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        def made(ids, texts):
            for i, t in zip(ids, texts, strict=True):
                data = t.as_py()
                row = hash_of(data)
                for out in phrases(data):
                    yield [i.as_py(), np.uint64(row), *out]

        for b in batches:
            ids, texts = b.column(0), b.column(1)
            rows = _signed(np.array([hash_of(t.as_py()) for t in texts], np.uint64))
            lens = pa.array([len(t.as_py()) for t in texts], pa.int64())
            shas = pa.array([hashlib.sha256(t.as_py()).hexdigest() for t in texts], pa.string())
            none = pa.nulls(len(ids), pa.int64())
            yield pa.RecordBatch.from_arrays([ids, rows, *[none] * 6, lens, shas], names=[*ITEM, "n_bytes", "sha"])
            for part in _gathered(made(ids, texts), ITEM):
                yield pa.RecordBatch.from_arrays([*part.columns, pa.nulls(len(part), pa.int64()), pa.nulls(len(part), pa.string())], names=[*ITEM, "n_bytes", "sha"])

    parsed = stage_table(raw.mapInArrow(parse, ", ".join(f"{n} long" for n in ITEM) + ", n_bytes long, sha string"), "parse")
    whole = stage_table(parsed.where("sha is not null").select("doc_id", "row", "n_bytes", "sha"), "whole")
    top = _classify(parsed.where("sha is null").select(*ITEM), "phrases")
    drop_staged(parsed)

    seen = stage_table(top.select("doc_id", "row").distinct(), "seen")
    hashed = raw.select("doc_id", F.xxhash64("data").alias("row"), "data")
    texts = stage_table(_met(hashed, broadcast_if_small(seen, MAX_DOCS)), "texts")
    runs = [stage_table(_sorted_shards(texts, top.where("refine and not crowded")), "runs")]
    finer = stage_table(_refined(texts, top.where("refine and crowded"), blocks, ITEM), "finer")
    middle = _classify(finer, "blocks")
    drop_staged(finer)
    runs.append(stage_table(_sorted_shards(texts, middle.where("refine and not crowded")), "runs"))
    single = stage_table(_refined(texts, middle.where("refine and crowded"), windows, ["doc_id", "row", "at", "lo", "s1", "s2"]), "windows")
    twice = stage_table(single.groupBy("s1", "s2").count().where("count > 1").select("s1", "s2"), "twice")
    runs.append(single.join(twice, ["s1", "s2"]).select("doc_id", "row", "lo", F.col("lo").alias("hi")))
    runs += [x.where("full").select("doc_id", "row", "lo", "hi") for x in (top, middle)]
    spans = reduce(DataFrame.union, runs).groupBy("doc_id", "row").agg(F.array_sort(F.collect_set(F.struct("lo", "hi"))).alias("spans"))
    spans = stage_table(spans, "spans")
    for x in (top, seen, middle, single, twice, *runs[:2]):
        drop_staged(x)

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        for b in batches:
            out = []
            for doc, data, got in zip(*(b.column(i) for i in range(3)), strict=True):
                data, got = data.as_py(), got.values
                lo, hi = got.field(0).to_numpy(), np.maximum.accumulate(got.field(1).to_numpy()) + LENGTH
                new = np.concatenate(([True], lo[1:] > hi[:-1]))
                starts, ends = lo[new], np.append(hi[:-1][new[1:]], hi[-1])
                kept, at = [], 0
                for s, e in zip(starts.tolist(), ends.tolist(), strict=True):
                    kept.append(data[at:s])
                    at = e
                kept = b"".join([*kept, data[at:]])
                out.append((doc.as_py(), len(data), len(data) - len(kept), len(starts), hashlib.sha256(kept).hexdigest(), kept if keep_bytes else None))
            kinds = [pa.int64()] * 4 + [pa.string(), pa.binary()]
            cols = [pa.array(c, k) for c, k in zip(zip(*out, strict=True), kinds, strict=True)] if out else [pa.array([], k) for k in kinds]
            yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])

    schema = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary"
    changed = _met(texts, spans).select("doc_id", "data", "spans").mapInArrow(cut, schema)
    lost = spans.select(F.col("doc_id").alias("of"), F.col("row").alias("of_row"))
    zero = F.lit(0).cast("long")
    same = F.col("of").eqNullSafe(F.col("doc_id")) & (F.col("of_row") == F.col("row"))
    rest = whole.join(lost, same, "left_anti").select("doc_id", "row", "n_bytes", zero.alias("n_removed"), zero.alias("n_spans"), F.col("sha").alias("kept_sha256"))
    if not keep_bytes:
        return changed.drop("kept").union(rest.drop("row"))
    hashed = hashed.dropDuplicates(["doc_id", "row"])
    return changed.unionByName(_met(hashed.select("doc_id", "row", F.col("data").alias("kept")), rest).select(*changed.columns))

