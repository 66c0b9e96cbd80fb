"""Vector search over (vec_id, embedding): exact, by cells, by planes, by graph.

Queries (qid, embedding) are few against the vectors, and travel in broadcast blocks of
MAX_QUERIES or by a join. Every method returns (qid, rank, vec_id, score); ties go to the
smaller vec_id.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from chronotier.functions.score import MEASURES, cosine
from chronotier.operators.ann.graph import LayeredGraph

MAX_QUERIES, AT_ONCE = 100_000, 256
#: Vectors of a graph; their number sets the number of graphs.
PER_GRAPH = 4000


def _rank(scored: DataFrame, k: int) -> DataFrame:
    w = W.partitionBy("qid").orderBy(F.col("score").desc(), "vec_id")
    return scored.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("qid", "rank", "vec_id", "score")


def _query_blocks(queries: DataFrame) -> list:
    """All queries as broadcast lists of (qid, embedding), MAX_QUERIES in each at most."""
    from itertools import batched

    rows = ((r["qid"], r["embedding"]) for r in queries.select("qid", "embedding").toLocalIterator())
    return [queries.sparkSession.sparkContext.broadcast(list(b)) for b in batched(rows, MAX_QUERIES)]


def exact(queries: DataFrame, vectors: DataFrame, k: int = 10, measure: str = "cosine") -> DataFrame:
    """A stated query set against all rows, in built-in functions: the oracle of small
    tests, by cosine, dot or l2; exact_blocks gives the same by cosine in one pass of
    matrix products."""
    met = vectors.crossJoin(F.broadcast(queries.select("qid", F.col("embedding").alias("q"))))
    return _rank(met.select("qid", "vec_id", F.round(MEASURES[measure](F.col("q"), F.col("embedding")), 6).alias("score")), k)


def exact_blocks(queries: DataFrame, vectors: DataFrame, k: int = 10) -> DataFrame:
    """The same by matrix products in Arrow batches; each keeps its k best only."""
    import numpy as np

    shared = _query_blocks(queries)

    def run(frames: Iterator) -> Iterator:
        import pandas as pd

        blocks = []
        for b in shared:
            ids, q = zip(*b.value, strict=True)
            q = np.array(q, np.float64)
            blocks.append((ids, q / np.maximum(np.linalg.norm(q, axis=1), 1e-300)[:, None]))
        for f, (ids, q) in ((f, b) for f in frames if len(f) for b in blocks):
            x = np.stack(f["embedding"]).astype(np.float64)
            s = q @ (x / np.maximum(np.linalg.norm(x, axis=1), 1e-300)[:, None]).T
            best = np.argsort(-s, axis=1, kind="stable")[:, :k]
            yield pd.DataFrame({"qid": np.repeat(ids, best.shape[1]), "vec_id": f["vec_id"].to_numpy()[best.ravel()], "score": np.round(np.take_along_axis(s, best, 1).ravel(), 6)})

    return _rank(vectors.select("vec_id", "embedding").mapInPandas(run, "qid long, vec_id long, score double"), k)


class Cells:
    """k-means cells, about as many as the root of the number of vectors unless said
    otherwise; a query probes the nearest ones only."""

    def __init__(self, vectors: DataFrame, n_cells: int | None = None, seed: int = 1, sample: int = 20_000):
        from pyspark.ml.clustering import KMeans
        from pyspark.ml.functions import array_to_vector

        # The centres come from a bounded sample; every vector gets a cell.
        n = vectors.count()
        n_cells = n_cells or max(8, min(4096, round(n**0.5)))
        seen = vectors.where(F.pmod(F.xxhash64("vec_id"), F.lit(1 << 20)) < (1 << 20) * min(1.0, sample / max(1, n)))
        model = KMeans(k=n_cells, seed=seed, maxIter=10, featuresCol="f").fit(seen.select(array_to_vector("embedding").alias("f")))
        self.centres = [c.tolist() for c in model.clusterCenters()]
        self.vectors = self._nearest(vectors, "vec_id", 1)

    def _nearest(self, df: DataFrame, ident: str, n: int) -> DataFrame:
        """(ident, embedding, cell) for the n nearest centres of each row."""
        import numpy as np

        c = np.array(self.centres)
        c /= np.maximum(np.linalg.norm(c, axis=1), 1e-300)[:, None]

        def run(frames: Iterator) -> Iterator:
            for f in frames:
                if len(f):
                    near = np.argsort(-(np.stack(f["embedding"]) @ c.T), axis=1, kind="stable")[:, :n]
                    out = f.loc[f.index.repeat(near.shape[1])]
                    yield out.assign(cell=near.ravel())

        return df.select(ident, "embedding").mapInPandas(run, f"{ident} long, embedding array<float>, cell long")

    def search(self, queries: DataFrame, k: int = 10, nprobe: int = 8) -> DataFrame:
        """Every query against all vectors of its nprobe nearest cells, by matrix products:
        each task marks the cells of each query as bits and keeps the k best of what it
        meets. Vectors without a direction are no answer."""
        import numpy as np

        shared = _query_blocks(queries)
        c = np.array(self.centres)
        c /= np.maximum(np.linalg.norm(c, axis=1), 1e-300)[:, None]

        def unit(rows):
            x = np.stack(rows).astype(np.float64)
            return x / np.maximum(np.linalg.norm(x, axis=1), 1e-300)[:, None]

        def run(frames: Iterator) -> Iterator:
            import pandas as pd

            sets = []
            for block in (b.value[i : i + AT_ONCE] for b in shared for i in range(0, len(b.value), AT_ONCE)):
                ids, q = zip(*block, strict=True)
                near = np.argsort(-(np.stack(q) @ c.T), axis=1, kind="stable")[:, :nprobe]
                probed = np.zeros((len(ids), len(c)), bool)
                np.put_along_axis(probed, near, True, 1)
                none = np.empty(0, np.int64)
                sets.append([np.array(ids), unit(q), np.packbits(probed, axis=1), np.full(len(ids), -np.inf), (none, none, np.empty(0))])
            for f in frames:
                x, vec, cell = unit(f["embedding"]), f["vec_id"].to_numpy(), f["cell"].to_numpy()
                some = (x * x).sum(1) > 0.5
                x, vec, cell = x[some], vec[some], cell[some]
                for one in sets:
                    ids, q, bits, least, held = one
                    scores = np.where(np.unpackbits(bits, axis=1, count=len(c)).view(bool)[:, cell], q @ x.T, -np.inf)
                    if len(held[0]) == 0 and len(vec) > k:  # nothing to beat yet
                        least = np.partition(scores, len(vec) - k, axis=1)[:, len(vec) - k]
                    row, col = np.nonzero((scores >= least[:, None] - 1e-6) & (scores > -np.inf))
                    row, v, s = (np.concatenate(p) for p in zip(held, (row, vec[col], np.round(scores[row, col], 6)), strict=True))
                    order = np.lexsort((v, -s, row))
                    row, v, s = row[order], v[order], s[order]
                    place = np.arange(len(row)) - np.searchsorted(row, row)
                    one[3] = np.full(len(ids), -np.inf)
                    one[3][row[place == k - 1]] = s[place == k - 1]
                    one[4] = row[place < k], v[place < k], s[place < k]
            for ids, _, _, _, (row, v, s) in sets:
                yield pd.DataFrame({"qid": ids[row], "vec_id": v, "score": s})

        return _rank(self.vectors.mapInPandas(run, "qid long, vec_id long, score double"), k)


class Planes:
    """Sign bits of random planes; candidates share all bits of a table."""

    def __init__(self, vectors: DataFrame, dim: int = 64, bits: int = 4, tables: int = 16, seed: int = 1):
        import numpy as np

        self.planes = np.random.default_rng(seed).normal(size=(tables, bits, dim)).tolist()
        self.vectors = vectors
        self.coded = self._codes(vectors, "vec_id")

    def _codes(self, df: DataFrame, ident: str) -> DataFrame:
        import numpy as np

        planes = np.array(self.planes)
        tables, bits, _ = planes.shape

        def run(frames: Iterator) -> Iterator:
            import pandas as pd

            for f in frames:
                if len(f):
                    sign = np.einsum("nd,tbd->ntb", np.stack(f["embedding"]).astype(np.float64), planes) > 0
                    code = (sign << np.arange(bits)).sum(2)
                    yield pd.DataFrame({ident: np.repeat(f[ident].to_numpy(), tables), "tab": np.tile(np.arange(tables), len(f)), "code": code.ravel()})

        return df.select(ident, "embedding").mapInPandas(run, f"{ident} long, tab long, code long")

    def search(self, queries: DataFrame, k: int = 10) -> DataFrame:
        pairs = self.coded.join(F.broadcast(self._codes(queries, "qid")), ["tab", "code"]).select("qid", "vec_id").distinct()
        met = pairs.join(self.vectors, "vec_id").join(F.broadcast(queries.select("qid", F.col("embedding").alias("q"))), "qid")
        return _rank(met.select("qid", "vec_id", F.round(cosine(F.col("q"), F.col("embedding")), 6).alias("score")), k)


class Graph:
    """Layered proximity graphs, one per shard of about PER_GRAPH vectors, as bytes in a
    table that may be stored; a query visits all shards and the k best of each meet. The
    same vectors give the same graphs. dense: makes a matrix of what the column embedding
    holds, where that travels in a narrower form. at_once: see LayeredGraph."""

    def __init__(self, vectors: DataFrame | None, shards: int | None = None, m: int = 16, ef_build: int = 200, graphs: DataFrame | None = None, dense: Callable | None = None, at_once: bool = False):
        if graphs is not None:
            self.graphs = graphs
            return
        shards = shards or max(1, -(-vectors.count() // PER_GRAPH))

        def build(f):
            import pickle
            import zlib

            import numpy as np
            import pandas as pd

            f = f.sort_values("vec_id", kind="stable")
            g = LayeredGraph((dense or np.stack)(list(f["embedding"])), f["vec_id"].to_numpy(), m, ef_build, at_once)
            return pd.DataFrame({"shard": [int(f["shard"].iloc[0])], "n": [len(f)], "graph": [zlib.compress(pickle.dumps(g), 1)]})

        rows = vectors.select("vec_id", "embedding", self.shard_of("vec_id", shards).alias("shard"))
        self.graphs = rows.groupBy("shard").applyInPandas(build, "shard int, n long, graph binary")

    @staticmethod
    def shard_of(ident: str, shards: int):
        return F.pmod(F.xxhash64(ident), F.lit(shards)).cast("int")

    def _found(self, queries: DataFrame, k: int, ef: int, allowed: DataFrame | None) -> DataFrame:
        shared = _query_blocks(queries)
        rows = self.graphs.select("shard", "graph")
        if allowed is not None:
            n = self.graphs.agg(F.max("shard")).first()[0] + 1
            ids = allowed.select(self.shard_of("vec_id", n).alias("shard"), "vec_id").groupBy("shard").agg(F.collect_set("vec_id").alias("ids"))
            rows = self.graphs.join(ids, "shard").select("shard", "graph", "ids")

        def run(frames: Iterator) -> Iterator:
            import pickle
            import zlib

            import pandas as pd

            for f in frames:
                for row in f.itertuples(index=False):
                    g = pickle.loads(zlib.decompress(row[1]))
                    allow = set(row[2].tolist()).__contains__ if len(row) > 2 else None
                    for b in shared:
                        out = [(q, i, s, row[0], g.visited, len(g.ids)) for q, v in b.value for i, s in g.search(v, k, ef, allow)]
                        yield pd.DataFrame(out, columns=["qid", "vec_id", "score", "shard", "visited", "n"])

        return rows.mapInPandas(run, "qid long, vec_id long, score double, shard int, visited long, n long")

    def search(self, queries: DataFrame, k: int = 10, ef: int = 50, allowed: DataFrame | None = None) -> DataFrame:
        """allowed(vec_id): only these are answered; the graph is walked through all."""
        return _rank(self._found(queries, k, ef, allowed), k)

    def hops(self, queries: DataFrame, k: int = 10, ef: int = 50) -> DataFrame:
        """(qid, visited, n): vectors that a query looked at in all shards, of how many."""
        per = self._found(queries, k, ef, None).select("qid", "shard", "visited", "n").distinct()
        return per.groupBy("qid").agg(F.sum("visited").alias("visited"), F.sum("n").alias("n"))
