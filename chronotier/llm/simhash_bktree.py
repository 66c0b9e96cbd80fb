"""SimHash near-duplicates with BK-trees.

A document's fingerprint has 64 bits; a bit is set where more than half of the
document's word shingles have it set in their XXH64. Fingerprints that differ in
at most `radius` bits are linked, and linked documents form groups.

The search runs over distinct fingerprints. They are cut into radius + 2 bands
of bits; two fingerprints within the radius agree on two bands at least, so each
goes to one bucket per pair of bands and no link can be missed. A bucket beyond
`shard` fingerprints is dealt into shards, and every pair of shards becomes one
task of its own. In a task a BK-tree of one shard is built, children keyed by
their distance to the parent, and the other shard's fingerprints follow only
edges within the radius. A task returns a spanning forest of its links, never all
pairs. Shard trees travel by shuffle, not by way of the driver, since there are
as many fingerprints as different texts.

Texts that are similar, but not within a few bits, are linked by `group_similar`:
at a Jaccard similarity of 0.8 of word shingles about ten of 64 bits differ, and a
band of bits would hold random pairs as well. There the buckets are bands of
min-hashes of the shingles, and the BK-trees take a wide radius; they join most of
a bucket, and pairs of it that are still apart are then met whatever their distance. A
sketch of minima by bin passes over pairs that are far from similar; the Jaccard
similarity of the two sets of shingles decides a link. The sets travel only for texts
that share a bucket with another.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import cache
from itertools import combinations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronotier.llm.common import Forest, broadcast_if_small, connected_components, drop_staged, group_bounds, sorted_groups, stage_table

#: Shingles hashed at a time, which bounds memory for a very long text.
CHUNK = 1 << 16


def words_of(text: str | None) -> list[bytes]:
    """Lower-cased (A-Z only) words; bytes.split knows just the six ASCII blanks."""
    return text.encode().lower().split() if text else []


def shingle_hashes(words: list[bytes], width: int) -> Iterator:
    """XXH64 of the shingles of one word at least, in arrays of CHUNK."""
    import numpy as np
    from xxhash import xxh64_intdigest

    line = b" ".join(words)
    ends, at = [], -1
    for w in words:
        at += len(w) + 1
        ends.append(at)
    if len(words) <= width:
        starts, ends = [0], [ends[-1]]
    else:
        starts, ends = [0, *(e + 1 for e in ends[: len(words) - width])], ends[width - 1 :]
    for i in range(0, len(ends), CHUNK):
        yield np.array([xxh64_intdigest(line[a:b], 42) for a, b in zip(starts[i : i + CHUNK], ends[i : i + CHUNK], strict=True)], np.uint64)


def _bit_counts(h):
    """How many of the hashes have each of the 64 bits set."""
    import numpy as np

    return np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)


def _packed(bits, n: int) -> int:
    import numpy as np

    return int(np.packbits(2 * bits > n, bitorder="little").view(np.int64)[0])


def fingerprint(text: str | None, width: int = 3) -> int:
    """The fingerprint as a signed 64-bit integer; zero for a text without words."""
    words = words_of(text)
    if not words:
        return 0
    n = bits = 0
    for h in shingle_hashes(words, width):
        n, bits = n + len(h), bits + _bit_counts(h)
    return _packed(bits, n)


def fingerprints(docs: DataFrame, width: int = 3, doc: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id BIGINT, fp BIGINT) per row of docs."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = [fingerprint(t.as_py(), width) for t in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps, pa.int64())], names=["doc_id", "fp"])

    return docs.select(F.col(doc).cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, "doc_id long, fp long")


class BKTree:
    """Children of a node are keyed by their Hamming distance to it."""

    __slots__ = ("at", "kids")

    def __init__(self, keys: list[int]):
        self.at, self.kids = [], []
        for i, k in enumerate(keys):
            self.at.append(k)
            self.kids.append({})
            x = 0
            while x != i:
                d = (self.at[x] ^ k).bit_count()
                x = self.kids[x].setdefault(d, i)

    def within(self, key: int, radius: int) -> list[int]:
        """Positions of all keys within the radius."""
        found, todo = [], [0] if self.at else []
        while todo:
            x = todo.pop()
            d = (self.at[x] ^ key).bit_count()
            if d <= radius:
                found.append(x)
            if kids := self.kids[x]:
                if len(kids) <= 2 * radius + 1:
                    todo += [c for e, c in kids.items() if -radius <= e - d <= radius]
                else:
                    todo += [kids[e] for e in range(d - radius, d + radius + 1) if e in kids]
        return found


def _band(k: int, m: int) -> tuple[int, int]:
    """First bit and width of band k of m."""
    return 64 * k // m, 64 * (k + 1) // m - 64 * k // m


def links(nodes: DataFrame, radius: int = 2, shard: int = 2048) -> DataFrame:
    """Edges (a, b) among nodes(rep BIGINT, fp BIGINT, fp distinct) that connect
    all fingerprints within the radius."""
    m = radius + 2
    band = lambda k: F.shiftrightunsigned("fp", _band(k, m)[0]).bitwiseAND(F.lit((1 << _band(k, m)[1]) - 1))
    keys = [F.struct(F.lit(i).alias("pair"), F.shiftleft(band(a), _band(b, m)[1]).bitwiseOR(band(b)).alias("value")) for i, (a, b) in enumerate(combinations(range(m), 2))]
    spread = nodes.select("rep", "fp", F.explode(F.array(*keys)).alias("k")).select("rep", "fp", "k.pair", "k.value")
    crowd = spread.groupBy("pair", "value").count().where("count > 1")
    shards = F.ceil(F.col("count") / shard).cast("int")
    own = F.pmod(F.xxhash64("fp"), F.col("shards")).cast("int")
    # The own shard's trees meet the shards from 0 to shards - 1, each pair once.
    met = spread.join(crowd, ["pair", "value"]).withColumn("shards", shards).withColumn("own", own)
    met = met.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("shards") - 1)))
    met = met.select("pair", "value", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), (F.col("own") <= F.col("other")).alias("tree"), "fp", "rep")
    block = ["pair", "value", "i", "j"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in sorted_groups(batches, block):
            bounds = group_bounds(table, block).tolist()
            fps, reps = table.column("fp").to_pylist(), table.column("rep").to_pylist()
            tree, same = table.column("tree").to_pylist(), (table.column("i").to_numpy() == table.column("j").to_numpy()).tolist()
            a, b = [], []
            mask = (1 << 64) - 1
            for lo, hi in zip(bounds, bounds[1:], strict=False):
                if hi - lo == 2:
                    if (tree[lo] or tree[lo + 1]) and ((fps[lo] ^ fps[lo + 1]) & mask).bit_count() <= radius:
                        a.append(reps[lo])
                        b.append(reps[lo + 1])
                    continue
                rows = [x for x in range(lo, hi) if tree[x]]
                bk, forest = BKTree([fps[x] & mask for x in rows]), Forest(hi - lo)
                for q in rows if same[lo] else (x for x in range(lo, hi) if not tree[x]):
                    for p in bk.within(fps[q] & mask, radius):
                        if rows[p] != q and forest.join(rows[p] - lo, q - lo):
                            a.append(reps[rows[p]])
                            b.append(reps[q])
            if a:
                yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], names=["a", "b"])

    return met.repartition(*block).sortWithinPartitions(*block).mapInArrow(run, "a long, b long")


def group_near_duplicates(docs: DataFrame, width: int = 3, radius: int = 2, doc: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per row of docs: doc_id, fp BIGINT, fingerprint STRING (16 hex
    digits), component_id (the least doc_id that links reach, itself included).

    A null or empty text has the fingerprint zero and is linked like any other.
    Rows that share an id are rows of their own with their own texts. A row whose
    id is null is linked only through other rows of its fingerprint. An empty
    table gives an empty result; other columns of docs are not read."""
    own = stage_table(fingerprints(docs, width, doc, text), "fingerprints")
    nodes = own.groupBy("fp").agg(F.min("doc_id").alias("rep"))
    nodes = stage_table(nodes, "nodes")
    edges = links(nodes.where("rep is not null"), radius)
    comp = connected_components(edges)
    known = nodes.join(comp.withColumnRenamed("node", "rep"), "rep", "left")
    known = known.select("fp", F.coalesce("component", "rep").alias("component_id"))
    hexed = F.lower(F.lpad(F.hex("fp"), 16, "0"))
    return own.join(known, "fp").select("doc_id", "fp", hexed.alias("fingerprint"), "component_id")


def keep_one(docs: DataFrame, width: int = 3, radius: int = 2) -> DataFrame:
    """The rows of docs whose doc_id is the least of its group, or null. Of rows
    that share an id, all stay or go together."""
    groups = group_near_duplicates(docs, width, radius)
    gone = groups.where("doc_id <> component_id").select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)


#: Bands of min-hashes and min-hashes in a band: of pairs at similarity 0.8, a
#: share of 0.99997 agree on a band; of those at 0.3, 0.15.
BANDS, ROWS = 20, 4
#: Bins of the sketch; its estimate has a standard deviation of 0.025 at 0.8.
BINS = 256
#: Pairs whose sketches agree on a lesser share than this of the bins in use are passed
#: over, where FEW bins or more are in use: six standard deviations at 0.8 and FEW bins.
LOOSE, FEW = 0.5, 64
#: Shingles in a shard of a bucket, which bounds the memory of a task.
SHARD_SHINGLES = 2_000_000
#: Texts that share a bucket, up to which their keys are broadcast.
MAX_SHARED = 500_000
#: Bits between fingerprints that a BK-tree search follows: ten are expected at 0.8.
#: It finds most links early; those beyond it are found by `rest`.
WIDE = 20


def shingle_set(words: list[bytes], width: int):
    """The hashes of the different shingles, in order."""
    import numpy as np

    return np.unique(np.concatenate([*shingle_hashes(words, width)])) if words else np.empty(0, np.uint64)


def words_key(words: list[bytes]) -> int:
    """A signed 64-bit hash of the words."""
    from xxhash import xxh64_intdigest

    key = xxh64_intdigest(b" ".join(words), 7)
    return key - ((key >> 63) << 64)


def profile(text: str | None, width: int = 5) -> tuple[int, int, int, bytes, list[int]]:
    """Fingerprint, hash of the words, number of different shingles, sketch and bands
    of one text. This fingerprint counts each different shingle once.

    The sketch has one byte per bin of shingle hashes: 1 to 255 from the least hash
    of the bin, 0 where no shingle falls. A text without words has no bands."""
    import numpy as np
    from xxhash import xxh64_intdigest

    words = words_of(text)
    key = words_key(words)
    if not words:
        return 0, key, 0, bytes(BINS), []
    top = np.uint64(2**64 - 1)
    bits, bins, mins = 0, np.full(BINS, top), np.full(BANDS * ROWS, top)
    own, factors = shingle_set(words, width), _odd_factors()[:, None]
    for i in range(0, len(own), CHUNK):
        bits = bits + _bit_counts(own[i : i + CHUNK])
    np.minimum.at(bins, (own % np.uint64(BINS)).astype(np.int64), own // np.uint64(BINS))
    for i in range(0, len(own), 1 << 12):
        mixed = own[i : i + (1 << 12)] * factors
        mins = np.minimum(mins, (mixed ^ (mixed >> np.uint64(32))).min(1))
    sketch = np.where(bins == top, 0, bins % np.uint64(255) + np.uint64(1)).astype(np.uint8)
    bands = [xxh64_intdigest(b.tobytes(), 42) for b in mins.reshape(BANDS, ROWS)]
    return _packed(bits, len(own)), key, len(own), sketch.tobytes(), [b - ((b >> 63) << 64) for b in bands]


@cache
def _odd_factors():
    """Multipliers of the min-hash functions, by a rule: hashes of 0, 1, 2, ..., made odd."""
    import numpy as np
    from xxhash import xxh64_intdigest

    return np.array([xxh64_intdigest(i.to_bytes(4, "little"), 42) | 1 for i in range(BANDS * ROWS)], np.uint64)


def jaccard(a, b) -> float:
    """Jaccard similarity of two sets of shingle hashes in order."""
    import numpy as np

    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / (len(a) + len(b) - both)


def maybe(sketches, sizes, x, y, least: float):
    """Whether texts x (positions) may be similar to y: by the numbers of shingles,
    which loses nothing, and by the sketches."""
    import numpy as np

    a, b = sketches[x], sketches[y]
    used, same = np.count_nonzero(a | b, -1), np.count_nonzero((a == b) & (a > 0), -1)
    low, high = np.minimum(sizes[x], sizes[y]), np.maximum(sizes[x], sizes[y])
    return (low / high >= least) & ((used < FEW) | (same >= LOOSE * used))


def profiles(docs: DataFrame, width: int = 5) -> DataFrame:
    """(doc_id, fp, words_key, n, sketch, bands) per row of docs."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = [profile(t.as_py(), width) for t in b.column(1)]
            fp, key, n, sketch, bands = zip(*rows, strict=True) if rows else ((),) * 5
            cols = [b.column(0), pa.array(fp, pa.int64()), pa.array(key, pa.int64()), pa.array(n, pa.int64()), pa.array(sketch, pa.binary()), pa.array(bands, pa.list_(pa.int64()))]
            yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "fp", "words_key", "n", "sketch", "bands"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, fp long, words_key long, n long, sketch binary, bands array<long>")


def shingle_sets(docs: DataFrame, width: int) -> DataFrame:
    """(rep, words_key, shingles) per row of docs: its id, and its shingle hashes as bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            words = [words_of(t.as_py()) for t in b.column(1)]
            cols = [b.column(0), pa.array([words_key(w) for w in words], pa.int64()), pa.array([shingle_set(w, width).tobytes() for w in words], pa.binary())]
            yield pa.RecordBatch.from_arrays(cols, names=["rep", "words_key", "shingles"])

    return docs.select("rep", "text").mapInArrow(run, "rep long, words_key long, shingles binary")


class ForestTree(BKTree):
    """A BK-tree that joins similar texts into a forest. Once all nodes of a subtree
    are in one component, a search from that component passes it by, so a large
    group of near copies is not compared in pairs, and no link between components
    is missed."""

    __slots__ = ("rows", "forest", "alike", "radius", "whole")

    def __init__(self, fps: list[int], rows: list[int], forest: Forest, alike, radius: int):
        super().__init__(fps)
        self.rows, self.forest, self.alike, self.radius = rows, forest, alike, radius
        self.whole = [True] * len(rows)

    def settle(self) -> Iterator[tuple[int, int]]:
        """Links between parents and children; then marks subtrees of one component."""
        for x, kids in enumerate(self.kids):
            for d, c in kids.items():
                if d <= self.radius and self.alike(self.rows[x], self.rows[c]) and self.forest.join(self.rows[x], self.rows[c]):
                    yield self.rows[x], self.rows[c]
        root = self.forest.root
        for x in range(len(self.rows) - 1, -1, -1):
            self.whole[x] = all(self.whole[c] and root(self.rows[c]) == root(self.rows[x]) for c in self.kids[x].values())

    def search(self, fp: int, row: int) -> Iterator[tuple[int, int]]:
        """Links that join row's component with others of the tree."""
        todo, root, r = [0] if self.at else [], self.forest.root, self.radius
        while todo:
            x = todo.pop()
            if self.whole[x] and root(self.rows[x]) == root(row):
                continue
            d = (self.at[x] ^ fp).bit_count()
            if d <= r and root(self.rows[x]) != root(row) and self.alike(self.rows[x], row):
                self.forest.join(self.rows[x], row)
                yield self.rows[x], row
            todo += [c for e, c in self.kids[x].items() if -r <= e - d <= r]


def shared_buckets(nodes: DataFrame, shard: int = 2048) -> DataFrame:
    """(fp, words_key, rep, band, value, i, j, tree) of nodes(fp, words_key, rep, n,
    bands) that share a band with another, per pair of shards i and j of the bucket.
    Of buckets that hold the same nodes, one stays."""
    ids = ["fp", "words_key"]
    spread = nodes.where("rep is not null").select(*ids, "rep", "n", F.posexplode("bands").alias("band", "value"))
    marks = [F.bit_xor(F.xxhash64(F.lit(k), *ids)).alias(f"x{k}") for k in (0, 1)]
    crowd = spread.groupBy("band", "value").agg(F.count("*").alias("count"), F.sum("n").alias("n"), *marks).where("count > 1")
    crowd = crowd.groupBy("count", "n", "x0", "x1").agg(F.min(F.struct("band", "value")).alias("k"))
    shards = F.ceil(F.greatest(F.col("count") / shard, F.col("n") / SHARD_SHINGLES)).cast("int")
    met = spread.drop("n").join(crowd.select("k.band", "k.value", shards.alias("shards")), ["band", "value"])
    met = met.withColumn("own", F.pmod(F.xxhash64(*ids), F.col("shards")).cast("int"))
    met = met.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("shards") - 1)))
    return met.select(*ids, "rep", "band", "value", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), (F.col("own") <= F.col("other")).alias("tree"))


def rest(bk: ForestTree, queries: list[int], close) -> Iterator[tuple[int, int]]:
    """Links of queries with the tree's rows in other components, at any distance of
    fingerprints; close(rows, row) marks the rows that are worth a comparison."""
    import numpy as np

    root, join = bk.forest.root, bk.forest.join
    if len({root(x) for x in bk.rows} | {root(q) for q in queries}) == 1:
        return
    for q in queries:
        apart = np.array([x for x in bk.rows if root(x) != root(q)], np.int64)
        for x in apart[close(apart, q)].tolist() if len(apart) else ():
            if root(x) != root(q) and bk.alike(x, q):
                join(x, q)
                yield x, q


def similar_links(met: DataFrame, sets: DataFrame, least: float = 0.8, radius: int = WIDE) -> DataFrame:
    """Edges (a, b) that connect all rows of shared_buckets that share a bucket and have
    a Jaccard similarity of `least` or more, those within the radius first; sets has
    (rep, words_key, sketch, shingles)."""
    met = met.join(sets, ["rep", "words_key"]).drop("words_key")
    block = ["band", "value", "i", "j"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        mask = (1 << 64) - 1
        for table in sorted_groups(batches, block):
            bounds = group_bounds(table, block).tolist()
            fps, reps = [f & mask for f in table.column("fp").to_pylist()], table.column("rep").to_pylist()
            tree, same = table.column("tree").to_pylist(), (table.column("i").to_numpy() == table.column("j").to_numpy()).tolist()
            sketch = np.frombuffer(b"".join(table.column("sketch").to_pylist()), np.uint8).reshape(-1, BINS)
            sets = [np.frombuffer(x.as_buffer(), np.uint64) for x in table.column("shingles")]
            sizes = np.array([len(x) for x in sets])
            found = []
            for lo, hi in zip(bounds, bounds[1:], strict=False):
                rows = [x for x in range(hi - lo) if tree[lo + x]]
                alike = lambda x, y, at=lo: maybe(sketch, sizes, at + x, at + y, least) and jaccard(sets[at + x], sets[at + y]) >= least
                bk = ForestTree([fps[lo + x] for x in rows], rows, Forest(hi - lo), alike, radius)
                found += [(lo + x, lo + y) for x, y in bk.settle()]
                queries = rows if same[lo] else [x for x in range(hi - lo) if not tree[lo + x]]
                for q in queries:
                    found += [(lo + x, lo + y) for x, y in bk.search(fps[lo + q], q)]
                close = lambda x, y, at=lo: maybe(sketch, sizes, at + x, at + y, least)
                found += [(lo + x, lo + y) for x, y in rest(bk, queries, close)]
            if found:
                a, b = zip(*found, strict=True)
                yield pa.RecordBatch.from_arrays([pa.array([reps[x] for x in e], pa.int64()) for e in (a, b)], names=["a", "b"])

    return met.repartition(*block).sortWithinPartitions(*block).mapInArrow(run, "a long, b long")


def group_similar(docs: DataFrame, width: int = 5, least: float = 0.8, radius: int = WIDE) -> DataFrame:
    """(doc_id, component_id) per row of docs; component_id is the least doc_id that
    links reach. Texts of the same words are linked, and those that similar_links
    finds.

    Null and empty texts are texts of no words, linked with each other only; a text
    of fewer than `width` words is one shingle. Rows that share an id, null ids and
    an empty table are treated as in group_near_duplicates."""
    staged = stage_table(profiles(docs, width), "profiles")
    ids = ["fp", "words_key"]
    own = staged.select("doc_id", *ids)
    nodes = stage_table(staged.groupBy(*ids).agg(F.min("doc_id").alias("rep"), *[F.any_value(c).alias(c) for c in ("n", "sketch", "bands")]), "nodes")
    met = stage_table(shared_buckets(nodes), "buckets")
    shared = stage_table(met.select("rep", "words_key").distinct(), "shared")
    few = broadcast_if_small(shared, MAX_SHARED)
    texts = docs.select(F.col("doc_id").cast("long").alias("rep"), "text").join(few.select("rep"), "rep", "left_semi")
    sets = shingle_sets(texts, width).join(few, ["rep", "words_key"], "left_semi").dropDuplicates(["rep", "words_key"])
    sets = stage_table(sets.join(nodes.select("rep", "words_key", "sketch"), ["rep", "words_key"]), "sets")
    comp = connected_components(similar_links(met, sets, least, radius))
    for x in (met, shared, sets):
        drop_staged(x)
    known = nodes.select(*ids, "rep").join(comp.withColumnRenamed("node", "rep"), "rep", "left")
    known = known.select(*ids, F.coalesce("component", "rep").alias("component_id"))
    return own.join(known, ids).select("doc_id", "component_id")


def keep_one_similar(docs: DataFrame, width: int = 5, least: float = 0.8) -> DataFrame:
    """The rows of docs whose doc_id is the least of its group by group_similar, or
    null. Of rows that share an id, all stay or go together."""
    gone = group_similar(docs, width, least).where("doc_id <> component_id").select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*docs.columns)
