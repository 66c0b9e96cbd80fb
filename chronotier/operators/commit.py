"""Two-tier commit: log to the history first, then the live tier, then mark.

A store folder holds the history by commit, the live tier by generation and bucket of
documents, and two logs of small files that are only ever added to: a file per phase of
a commit, and a file per state of the live tier, which names the generation of every
bucket. A file is written under another name and renamed, which is the commit point;
nothing that a reader needs is deleted before its successor is in place, so a crash at
any moment leaves the state before or after it. Readers take only commits marked
COMMITTED. A commit writes the buckets that its documents fall into and no others. If
the live tier cannot be written, the commit is flagged UNCOMMITTED, and reconcile
finishes it or takes it back. A batch id that was committed once is not written again.
One writer per folder is assumed.
"""

from __future__ import annotations

import json
import time
import uuid
from dataclasses import asdict, dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chronotier.operators import live as live_ops

COLUMNS = "doc_id long, ordinal long, content_key string, effective_at long, revision long, op string, prior_key string, body string, commit_seq long"
LIVE = "doc_id long, ordinal long, content_key string, body string, effective_at long, revision long"
#: Where a drill can stop the protocol: between a small file's writing and its renaming
#: (log_put, pointer_put, mark_put), and between the steps.
POINTS = ("before_log", "log_put", "after_log", "amid_live", "pointer_put", "before_mark", "mark_put")
OPEN = ("PENDING", "UNCOMMITTED")
BUCKETS = 64


class Fault(BaseException):
    """Raised at the point of the protocol that a drill names: nothing runs after it, as
    if the process had died."""


@dataclass
class Commit:
    seq: int
    batch_id: str
    phase: str
    logged_at: float
    visible_at: float | None = None
    error: str | None = None


class Store:
    """fault: a point at which a drill stops; failing: an error that the next writing of
    the live tier meets."""

    def __init__(self, spark: SparkSession, root: str, fault: str | None = None, buckets: int = BUCKETS):
        self.spark, self.root, self.fault, self.buckets, self.failing = spark, root.rstrip("/"), fault, buckets, None
        self.fs = self._path("").getFileSystem(spark._jsc.hadoopConfiguration())

    def _path(self, name: str):
        return self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.root}/{name}")

    def _put(self, name: str, text: str, point: str) -> None:
        """A new small file, in place at once or not at all."""
        tmp, to = self._path(f"tmp/{uuid.uuid4().hex}"), self._path(name)
        out = self.fs.create(tmp, True)
        out.write(bytearray(text.encode()))
        out.close()
        self._point(point)
        self.fs.mkdirs(to.getParent())
        if not self.fs.rename(tmp, to):
            raise OSError(f"{name} could not be put in place")

    def _get(self, name: str) -> str:
        stream = self.fs.open(self._path(name))
        text = self.spark._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8")
        stream.close()
        return text

    def _names(self, folder: str) -> list[str]:
        at = self._path(folder)
        return sorted(f.getPath().getName() for f in self.fs.listStatus(at)) if self.fs.exists(at) else []

    def _point(self, name: str) -> None:
        if self.fault == name:
            self.fault = None
            raise Fault(name)

    def commits(self) -> list[Commit]:
        """The last phase of each commit, in order."""
        last = {n.split(".")[0]: n for n in self._names("commits")}  # phases are numbered
        return [Commit(**json.loads(self._get(f"commits/{n}"))) for _, n in sorted(last.items())]

    def _mark(self, c: Commit, point: str) -> None:
        n = sum(x.startswith(f"{c.seq:010d}.") for x in self._names("commits"))
        self._put(f"commits/{c.seq:010d}.{n:03d}.json", json.dumps(asdict(c)), point)

    def history(self, committed_only: bool = True, as_known_at: int | None = None) -> DataFrame:
        """The events of the visible commits, by listing their folders only."""
        shown = [c for c in self.commits() if c.phase == "COMMITTED" or not committed_only and c.phase in OPEN]
        shown = [f"{self.root}/history/{c.seq:010d}" for c in shown if as_known_at is None or c.seq <= as_known_at]
        return self.spark.read.schema(COLUMNS).parquet(*shown) if shown else self.spark.createDataFrame([], COLUMNS)

    def _pointer(self) -> dict:
        """The newest state of the live tier: seq, and the folder of each bucket."""
        names = self._names("pointers")
        return json.loads(self._get(f"pointers/{names[-1]}")) if names else {"seq": 0, "folders": {}, "buckets": self.buckets}

    def _rows(self, folders: list[str]) -> DataFrame:
        return self.spark.read.schema(LIVE).parquet(*(f"{self.root}/live/{f}" for f in folders)) if folders else self.spark.createDataFrame([], LIVE)

    def live(self) -> DataFrame:
        return self._rows(sorted(set(self._pointer()["folders"].values())))

    def _swap(self, c: Commit, events: DataFrame) -> None:
        """The touched buckets' next generation beside the current one, then the pointer."""
        now = self._pointer()
        if now["seq"] >= c.seq:
            return
        if self.failing:
            error, self.failing = self.failing, None
            raise error
        bucket = F.pmod(F.xxhash64("doc_id"), F.lit(now["buckets"])).cast("int")
        touched = sorted(str(r[0]) for r in events.select(bucket).distinct().collect())  # buckets, a fixed number
        old = self._rows(sorted({now["folders"][b] for b in touched if b in now["folders"]}))
        generation = f"g{c.seq:010d}-{int(time.time() * 1000)}"
        made = live_ops.apply(old, events).withColumn("bucket", bucket)
        made.repartition("bucket").write.partitionBy("bucket").parquet(f"{self.root}/live/{generation}")
        self._point("amid_live")
        written = set(self._names(f"live/{generation}"))
        folders = {b: f for b, f in now["folders"].items() if b not in touched}
        folders |= {b: f"{generation}/bucket={b}" for b in touched if f"bucket={b}" in written}
        self._put(f"pointers/{c.seq:010d}.json", json.dumps({"seq": c.seq, "folders": folders, "buckets": now["buckets"]}), "pointer_put")

    def _finish(self, c: Commit) -> None:
        try:
            self._swap(c, self.spark.read.schema(COLUMNS).parquet(f"{self.root}/history/{c.seq:010d}"))
        except Exception as error:
            c.phase, c.error = "UNCOMMITTED", str(error)[:500]
            self._mark(c, "none")
            raise
        self._point("before_mark")
        c.phase, c.visible_at, c.error = "COMMITTED", time.time(), None
        self._mark(c, "mark_put")

    def publish(self, events: DataFrame, batch_id: str) -> Commit:
        """Write one batch of events to both tiers."""
        done = self.commits()
        if again := next((c for c in done if c.batch_id == batch_id and c.phase != "ABORTED"), None):
            if again.phase in OPEN:
                self.reconcile("forward")
            return next(c for c in self.commits() if c.seq == again.seq)
        c = Commit(max([x.seq for x in done], default=0) + 1, batch_id, "PENDING", 0.0)
        path = f"{self.root}/history/{c.seq:010d}"
        events.select([x.split()[0] for x in COLUMNS.split(", ")[:-1]]).withColumn("commit_seq", F.lit(c.seq).cast("long")).write.mode("overwrite").parquet(path)
        self._point("before_log")
        c.logged_at = time.time()
        self._mark(c, "log_put")
        self._point("after_log")
        self._finish(c)
        return c

    def reconcile(self, mode: str = "forward") -> int:
        """Finish open commits (forward), or take them back where the live tier has not
        moved yet; then drop what no commit and no state of the live tier names."""
        n = 0
        for c in self.commits():
            if c.phase in OPEN:
                n += 1
                if mode == "back" and self._pointer()["seq"] < c.seq:
                    c.phase = "ABORTED"
                    self._mark(c, "none")
                else:
                    self._finish(c)
        kept = {f"{c.seq:010d}" for c in self.commits() if c.phase != "ABORTED"}
        for name in set(self._names("history")) - kept:
            self.fs.delete(self._path(f"history/{name}"), True)
        used = {f.split("/")[0] for f in self._pointer()["folders"].values()}
        for name in set(self._names("live")) - used:
            self.fs.delete(self._path(f"live/{name}"), True)
        self.fs.delete(self._path("tmp"), True)
        return n
