"""Helpers that the training-data operators share: staged tables, checked
broadcasts, streaming over sorted groups, and connected components."""

from __future__ import annotations

import atexit
import contextlib
import shutil
import tempfile
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Folders of the tables that this process has staged and not dropped.
STAGED: list[str] = []
#: Bytes of a table up to which it may be broadcast.
MAX_BYTES = 256 << 20
#: One word: a run of anything but blank, tab, LF, VT, FF, CR.
WORD = r"[^\x20\x09-\x0D]+"


def shared_dir(spark: SparkSession) -> str:
    """The folder for staged tables: under spark.checkpoint.dir, which every
    executor and the driver can reach; a temporary one only on a local master."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        base = spark.sparkContext._jvm.System.getProperty("chronotier.staging")  # one per JVM
        if not base:
            at = tempfile.mkdtemp(prefix="chronotier-")
            atexit.register(shutil.rmtree, at, ignore_errors=True)
            base = f"file://{at}"
            spark.sparkContext._jvm.System.setProperty("chronotier.staging", base)
    return f"{base.rstrip('/')}/staged-{spark.sparkContext.applicationId}"


@contextlib.contextmanager
def shuffle_files_dropped(spark: SparkSession):
    """Within this, a query's shuffle files go when it ends, rather than when the driver
    happens to collect its garbage. What a later query needs, it makes again."""
    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(name, None)
    spark.conf.set(name, "true")
    try:
        yield
    finally:
        spark.conf.set(name, before) if before is not None else spark.conf.unset(name)


def stage_table(df: DataFrame, name: str) -> DataFrame:
    """Write df as Parquet in the shared folder and read it back: the lineage is
    cut, sizes are known to the planner, and a lost executor loses nothing."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex[:12]}"
    with shuffle_files_dropped(spark):
        df.write.parquet(path)
    staged = spark.read.schema(df.schema).parquet(path)
    staged._staged_path = path
    STAGED.append(path)
    return staged


def _remove(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)
    if path in STAGED:
        STAGED.remove(path)


def drop_staged(df: DataFrame) -> None:
    """Remove a table that stage_table wrote; df must not be used afterwards."""
    if path := getattr(df, "_staged_path", None):
        _remove(df.sparkSession, path)


def drop_staged_since(spark: SparkSession, mark: int, keep: DataFrame | None = None) -> None:
    """Remove the tables staged since len(STAGED) was mark, but for keep: what operators
    leave behind for results that have not been read yet. For when all of these are."""
    for path in STAGED[mark:]:
        if path != getattr(keep, "_staged_path", None):
            _remove(spark, path)


def broadcast_if_small(df: DataFrame, max_rows: int, max_bytes: int = MAX_BYTES) -> DataFrame:
    """df with a broadcast hint if it has no more than max_rows rows and, by the
    planner's sizes, max_bytes; else df as it is, which leaves the join to a shuffle.
    df should be a staged table, whose sizes are those of its files."""
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return F.broadcast(df) if size <= max_bytes and df.limit(max_rows + 1).count() <= max_rows else df


def sorted_groups(batches: Iterator[pa.RecordBatch], key: list[str]) -> Iterator[pa.Table]:
    """Tables of whole groups from batches that are sorted by key. A group that
    runs over the end of a batch waits for the next one, so memory holds one
    batch and the current group."""
    import numpy as np

    held: list[pa.RecordBatch] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        change = np.zeros(batch.num_rows, bool)
        for k in key:
            v = batch.column(k).to_numpy(zero_copy_only=False)
            change[1:] |= v[1:] != v[:-1]
        if held and any(held[-1].column(k)[-1] != batch.column(k)[0] for k in key):
            yield pa.Table.from_batches(held)
            held = []
        ends = np.flatnonzero(change)
        if len(ends):
            yield pa.Table.from_batches([*held, batch.slice(0, ends[-1])])
            held = [batch.slice(ends[-1])]
        else:
            held.append(batch)
    if held:
        yield pa.Table.from_batches(held)


def group_bounds(table: pa.Table, key: list[str]):
    """Start of each group in a table sorted by key, and its end at last."""
    import numpy as np

    change = np.zeros(table.num_rows, bool)
    change[0] = True
    for k in key:
        v = table.column(k).to_numpy()
        change[1:] |= v[1:] != v[:-1]
    return np.append(np.flatnonzero(change), table.num_rows)


class Forest:
    """Union-find over the positions 0..n-1; the root is the least position."""

    def __init__(self, n: int):
        self.up = list(range(n))

    def root(self, x: int) -> int:
        up = self.up
        while up[x] != x:
            up[x] = up[up[x]]
            x = up[x]
        return x

    def join(self, a: int, b: int) -> bool:
        a, b = self.root(a), self.root(b)
        if a == b:
            return False
        self.up[max(a, b)] = min(a, b)
        return True


def connected_components(edges: DataFrame, rounds: int = 60) -> DataFrame:
    """Components of the graph of edges(a, b BIGINT): one row (node, component)
    per node that has an edge to another node, component its least node.

    Alternates two steps until nothing changes: every node hands its larger
    neighbours to its least neighbour, then its smaller ones. Both are one
    aggregation and one equi-join, so no component meets in one task, and the
    number of rounds grows with the logarithm of the longest chain. Rows with a
    null end and loops are ignored."""
    spark = edges.sparkSession
    e = edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    e = stage_table(e, "edges")
    seen = None
    for _ in range(rounds):
        both = e.union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        done = stage_table(small.union(low.select("u", F.col("m").alias("v"))).distinct(), "edges")
        drop_staged(e)
        e = done
        mark = tuple(e.agg(F.count("*"), F.expr("bit_xor(xxhash64(u, v))")).first())
        if mark == seen:
            break
        seen = mark
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    stars = e.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return stars.union(e.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
