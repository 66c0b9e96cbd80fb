"""Exact threshold pairs of embeddings by cover trees that are traversed in pairs.

Vectors are compared within their label by cosine; on unit vectors a cosine of at
least c is a distance of at most sqrt(2 - 2c). Equal vectors of a label are one
point with a weight, so copies are never expanded into pairs.

Top level: a label with more than CELL points gets pivots (a hash sample, PIVOTS in
all at most); each point belongs to its nearest pivot's cell and is a guest in each
later cell whose bisecting plane is within the threshold's distance. That is exact:
two linked points in different cells both lie that near to the plane between them.
A cell beyond BLOCK points is dealt into blocks, and each pair of blocks is a task,
so a dense cell is spread instead of meeting in one task.

In a task each block becomes a cover tree: nested nets whose radii halve, every node
with its covering radius. Pairs of nodes are pruned when their centres are further
apart than the threshold and both radii, taken as a whole when they are closer than
the threshold less both radii, and split otherwise; only pairs of leaves compare
vectors. A task returns sums of weights and a spanning forest, never the pairs.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from chronotier.llm.common import Forest, connected_components, drop_staged, group_bounds, sorted_groups, stage_table

CELL, BLOCK, LEAF = 1024, 1024, 12
PIVOTS = 20_000
SLACK = 1e-6
CHUNK = 16_384  # pairs of leaves held at a time
ROWS = 512  # nodes of one side whose distances are taken at a time


class CoverTree:
    """Nodes in arrays: centre (a position of x), radius, children or members."""

    def __init__(self, x):
        import numpy as np

        self.x, self.centre, self.radius, self.kids, self.members = x, [], [], [], []
        todo = [self._node(0, np.arange(len(x)), np.linalg.norm(x - x[0], axis=1), 2.0)]
        while todo:
            me, members, far, net = todo.pop()
            if len(members) <= LEAF or self.radius[me] < 1e-9:
                continue
            while net >= self.radius[me]:
                net /= 2
            # A net of this radius over the members; the node's own centre comes first.
            own = members == self.centre[me]
            order = np.concatenate((np.flatnonzero(own), np.flatnonzero(~own)))
            left = np.ones(len(members), bool)
            while len(order):
                some = order[:64]  # their distances at once, then one after another
                d = np.sqrt(np.maximum(0, 2 - 2 * x[members[some]] @ x[members].T))
                for k, first in enumerate(some):
                    if left[first]:
                        mine = np.flatnonzero(left & (d[k] <= net))
                        left[mine] = left[first] = False
                        mine = mine if (mine == first).any() else np.append(mine, first)
                        node = self._node(int(members[first]), members[mine], d[k][mine], net)
                        self.kids[me].append(node[0])
                        todo.append(node)
                order = order[64:]
                order = order[left[order]]
        self.radius = np.array(self.radius)
        self.centre = np.array(self.centre)

    def _node(self, centre: int, members, far, net: float):
        self.centre.append(centre)
        self.radius.append(float(far.max()))
        self.kids.append([])
        self.members.append(members)
        return len(self.centre) - 1, members, far, net


def dual(a: CoverTree, b: CoverTree, threshold: float, whole, pair) -> None:
    """Traverse two trees (or one against itself). whole(p, q) gets the members of
    node pairs that are linked throughout, pair(p, q) arrays of candidate points."""
    import numpy as np

    eps, same, leaves = float(np.sqrt(2 - 2 * threshold)), a is b, []

    def compare() -> None:
        for at in range(0, len(leaves), 256):
            ps, qs = [], []
            for i, j in leaves[at : at + 256]:
                m, n = a.members[i], b.members[j]
                if same and i == j:
                    u, v = np.triu_indices(len(m), 1)
                    ps.append(m[u])
                    qs.append(m[v])
                else:
                    ps.append(np.repeat(m, len(n)))
                    qs.append(np.tile(n, len(m)))
            pair(np.concatenate(ps), np.concatenate(qs))
        leaves.clear()

    todo = [(np.array([0]), np.array([0]), same)]
    while todo:
        p, q, twin = todo.pop()  # all nodes of p with all of q; twin: p is q, each pair once
        if len(p) > ROWS:
            todo += [(p[k : k + ROWS], q[k:] if twin else q, "edge" if twin else False) for k in range(0, len(p), ROWS)]
            continue
        d = np.sqrt(np.maximum(0, 2 - 2 * a.x[a.centre[p]] @ b.x[b.centre[q]].T))
        reach = a.radius[p][:, None] + b.radius[q][None, :]
        near = d <= reach + eps + SLACK
        if twin:  # of the rows' own square only the upper half
            near[np.tril_indices(len(p), -1)] = False
        for k, m in np.argwhere(near):
            i, j = int(p[k]), int(q[m])
            if same and i == j:
                if a.kids[i]:
                    todo.append((np.array(a.kids[i]), np.array(a.kids[i]), True))
                else:
                    leaves.append((i, i))
            elif d[k, m] + reach[k, m] <= eps - SLACK:
                whole(a.members[i], b.members[j])
            elif a.kids[i] or b.kids[j]:
                todo.append((np.array(a.kids[i] or [i]), np.array(b.kids[j] or [j]), False))
            else:
                leaves.append((i, j))
        if len(leaves) >= CHUNK:
            compare()
    compare()


def scaled(x):
    """Rows times a power of two each, so that their greatest component is near 1: exact,
    and squares of huge or tiny components stay finite and above zero."""
    import numpy as np

    return np.ldexp(x, -np.frexp(np.abs(x).max(axis=1))[1][:, None])


def _task(table: pa.Table, threshold: float):
    """(reps, sums of weights) and (a, b) of one pair of blocks."""
    import numpy as np

    side = table.column("side").to_numpy()
    rep, weight = table.column("rep").to_numpy(), table.column("n").to_numpy()
    raw = table.column("v").combine_chunks()
    raw = scaled(raw.flatten().to_numpy(zero_copy_only=False).reshape(len(side), -1).astype(np.float64))
    norm = np.sqrt(np.einsum("ij,ij->i", raw, raw))
    unit = raw / norm[:, None]
    left, right = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
    self_pair = table.column("a")[0].as_py() == table.column("b")[0].as_py()
    if not len(left) or not (self_pair or len(right)):
        return None
    one = CoverTree(unit[left])
    two, right = (one, left) if self_pair else (CoverTree(unit[right]), right)
    sums, forest, edges = np.zeros(len(side), np.int64), Forest(len(side)), []

    def link(i: int, j: int) -> None:
        if forest.join(i, j):
            edges.append((rep[i], rep[j]))

    def whole(p, q) -> None:
        p, q = left[p], right[q]
        sums[p] += weight[q].sum()
        sums[q] += weight[p].sum()
        for i in p:
            link(int(i), int(q[0]))
        for j in q:
            link(int(p[0]), int(j))

    def pair(p, q) -> None:
        p, q = left[p], right[q]
        ok = np.einsum("ij,ij->i", raw[p], raw[q]) / (norm[p] * norm[q]) >= threshold
        p, q = p[ok], q[ok]
        np.add.at(sums, p, weight[q])
        np.add.at(sums, q, weight[p])
        for i, j in zip(p.tolist(), q.tolist(), strict=True):
            link(i, j)

    dual(one, two, threshold, whole, pair)
    hit = np.flatnonzero(sums)
    return rep[hit], sums[hit], edges


def _home_and_guests(unit, pivots, eps: float):
    """Cell of each point, and (point, later cell) of the guests."""
    import numpy as np

    d2 = np.maximum(0, 2 - 2 * unit @ pivots.T)
    home = d2.argmin(1)
    apart = np.sqrt(np.maximum(0, 2 - 2 * pivots @ pivots.T))[home]
    with np.errstate(divide="ignore", invalid="ignore"):
        to_plane = (d2 - d2[np.arange(len(unit)), home][:, None]) / (2 * apart)
    near = ~(to_plane > eps + SLACK)  # equal pivots count as near
    near &= np.arange(len(pivots))[None, :] > home[:, None]
    return home, np.nonzero(near)


def near_duplicates(vectors: DataFrame, threshold: float = 0.98, vec: str = "vec_id", embedding: str = "embedding", label: str = "label") -> DataFrame:
    """One row per row of vectors: vec_id, n_links, component_id, kept.

    Only vectors of one label and length are compared. A row with a null label, or a
    vector that is null, empty, zero or holds a null, NaN or infinite component, links
    with nothing. Labels that are no integers are told apart by a 64-bit hash. Rows that share an id count as vectors of their own; a null id has a
    null component_id and kept. An empty table gives an empty result."""
    import numpy as np

    spark, eps = vectors.sparkSession, float(np.sqrt(2 - 2 * threshold))
    whole = dict(vectors.dtypes)[label] in ("tinyint", "smallint", "int", "bigint")
    name = F.col(label).cast("long") if whole else F.when(F.col(label).isNotNull(), F.xxhash64(F.col(label).cast("string")))
    rows = vectors.select(F.col(vec).cast("long").alias("vec_id"), name.alias("label"), F.col(embedding).alias("v"))
    v = F.col("v")
    sound = F.col("label").isNotNull() & F.coalesce(F.size(v) > 0, F.lit(False)) & ~F.coalesce(F.exists(v, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))), F.lit(False)) & F.coalesce(F.exists(v, lambda x: x != 0), F.lit(False))
    rows = rows.withColumn("sound", F.coalesce(sound, F.lit(False)))
    points = rows.where("sound").groupBy("label", F.size("v").alias("dim"), "v").agg(F.min("vec_id").alias("first"), F.count("*").alias("n"))
    # Points whose ids are all null get negative names of their own.
    points = points.withColumn("rep", F.coalesce("first", -1 - F.abs(F.xxhash64("label", "v") % (1 << 61))))
    points = stage_table(points.withColumn("draw", F.pmod(F.xxhash64("label", "v"), F.lit(1 << 30)) / float(1 << 30)), "points")

    big = points.groupBy("label", "dim").agg(F.count("*").alias("points")).where(F.col("points") > CELL)
    total = big.agg(F.sum("points")).first()[0] or 0
    rate = min(1.0 / CELL, PIVOTS / total) if total else 0.0
    chosen = points.where(F.col("draw") < rate).join(big, ["label", "dim"], "left_semi").select("label", "dim", "v").collect()  # PIVOTS rows or so
    pivots: dict = {}
    for r in sorted(chosen, key=lambda r: (r["label"], r["dim"], list(r["v"]))):
        x = scaled(np.array([r["v"]], np.float64))[0]
        pivots.setdefault((r["label"], r["dim"]), []).append(x / np.linalg.norm(x))
    shared = spark.sparkContext.broadcast({k: np.array(x) for k, x in pivots.items()})

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lab, dim = b.column("label").to_numpy(), b.column("dim").to_numpy()
            take, cell, guest = [np.arange(len(lab))], [np.zeros(len(lab), np.int64)], [np.zeros(len(lab), bool)]
            for key in sorted(set(zip(lab.tolist(), dim.tolist(), strict=True)) & shared.value.keys()):
                mine = np.flatnonzero((lab == key[0]) & (dim == key[1]))
                x = b.column("v").take(pa.array(mine)).flatten().to_numpy(zero_copy_only=False).reshape(len(mine), -1).astype(np.float64)
                x = scaled(x)
                home, (who, where) = _home_and_guests(x / np.linalg.norm(x, axis=1)[:, None], shared.value[key], eps)
                cell[0][mine] = home
                take.append(mine[who])
                cell.append(where.astype(np.int64))
                guest.append(np.ones(len(who), bool))
            cols = b.select(["label", "dim", "rep", "n", "v"]).take(pa.array(np.concatenate(take))).columns
            yield pa.RecordBatch.from_arrays([*cols, pa.array(np.concatenate(cell)), pa.array(np.concatenate(guest))], names=["label", "dim", "rep", "n", "v", "cell", "guest"])

    kind = dict(points.dtypes)["v"]
    placed = points.select("label", "dim", "rep", "n", "v").mapInArrow(place, f"label long, dim int, rep long, n long, v {kind}, cell long, guest boolean")
    placed = stage_table(placed, "placed")
    cells = placed.groupBy("label", "dim", "cell").agg(F.count_if(~F.col("guest")).alias("home"), F.count_if("guest").alias("guests"))
    blocks = [F.ceil(F.col(c) / BLOCK).cast("int").alias(c) for c in ("home", "guests")]
    met = placed.join(cells.select("label", "dim", "cell", *blocks), ["label", "dim", "cell"])
    own = F.pmod(F.xxhash64("rep"), F.when(F.col("guest"), F.col("guests")).otherwise(F.col("home"))).cast("int")
    met = met.withColumn("own", own)
    # Home blocks are 0..home-1, guest blocks follow; a task is a pair of blocks.
    other = F.when(F.col("guest"), F.sequence(F.lit(0), F.col("home") - 1)).otherwise(F.sequence(F.lit(0), F.col("home") + F.col("guests") - 1))
    met = met.where("home > 0").withColumn("other", F.explode(other)).withColumn("own", F.when(F.col("guest"), F.col("home") + F.col("own")).otherwise(F.col("own")))
    met = met.select("label", "dim", "cell", F.least("own", "other").alias("a"), F.greatest("own", "other").alias("b"), (F.col("own") > F.col("other")).cast("int").alias("side"), "rep", "n", "v")
    key = ["label", "dim", "cell", "a", "b"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in sorted_groups(batches, key):
            at = group_bounds(table, key).tolist()
            for lo, hi in zip(at, at[1:], strict=False):
                if got := _task(table.slice(lo, hi - lo), threshold):
                    rep, sums, edges = got
                    a = np.concatenate([rep, np.array([x for x, _ in edges], np.int64)])
                    b = pa.array([None] * len(rep) + [y for _, y in edges], pa.int64())
                    yield pa.RecordBatch.from_arrays([pa.array(a), b, pa.array(np.concatenate([sums, np.zeros(len(edges), np.int64)]))], names=["a", "b", "links"])

    found = stage_table(met.repartition(*key).sortWithinPartitions(*key).mapInArrow(run, "a long, b long, links long"), "pairs")
    drop_staged(placed)
    links = found.where("b is null").groupBy(F.col("a").alias("rep")).agg(F.sum("links").alias("links"))
    comp = connected_components(found.where("b is not null").select("a", "b")).withColumnRenamed("node", "rep")
    known = points.select("label", "v", "rep", "first", "n").join(links, "rep", "left").join(comp, "rep", "left")
    # The least id that is one: names of points without ids are negative.
    best = known.groupBy(F.coalesce("component", "rep").alias("component")).agg(F.min("first").alias("component_id"))
    known = known.withColumn("component", F.coalesce("component", "rep")).join(best, "component")
    known = known.select(F.col("label").alias("l"), F.col("v").alias("w"), (F.col("n") - 1 + F.coalesce("links", F.lit(0))).alias("links"), "component_id")
    linked = rows.where("sound").join(known, (F.col("label") == F.col("l")) & (F.col("v") == F.col("w"))).select("vec_id", F.col("links").alias("n_links"), "component_id")
    alone = rows.where("not sound").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    every = linked.union(alone)
    component = F.when(F.col("vec_id").isNotNull(), F.col("component_id"))
    return every.select("vec_id", "n_links", component.alias("component_id"), (F.col("vec_id") == component).alias("kept"))


def keep_one(vectors: DataFrame, threshold: float = 0.98) -> DataFrame:
    """The rows of vectors that are the least of their component; null ids stay."""
    found = near_duplicates(vectors, threshold)
    gone = found.where("not kept").select("vec_id").distinct()
    return vectors.join(gone, "vec_id", "left_anti").select(*vectors.columns)
