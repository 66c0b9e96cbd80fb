"""Benchmark decontamination by spaced-seed hashing, with DataFrame functions only.

Every SPAN tokens of a text are hashed under fixed masks that ignore some of the
positions; equal hashes join a text with a benchmark item. Around each hit the two
are laid against each other on that diagonal, and the item counts as overlapped if
some WINDOW aligned tokens differ in at most SUBSTITUTIONS. The masks were chosen
by exhaustive check so that any WINDOW tokens with so many substitutions, wherever
they fall, keep at least one seed whole: the seeds lose no overlap of that kind.

An item of fewer than WINDOW tokens is overlapped as a whole, with substitutions in
proportion to its length. It is cut into one block more than it may have
substitutions, so one block at least is whole, and the blocks are its seeds.

A text is cut into pieces of PIECE tokens with enough overlap, so a very long text is
many small rows. The benchmark side is broadcast up to MAX_SEEDS rows; then hits are
verified in the same stage, and only the distinct verified pairs are shuffled. Beyond,
seeds are shuffled with the place they stand at and nothing else, and the pieces meet
their hits afterwards.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from chronotier.llm.common import broadcast_if_small, stage_table

#: The token positions that each mask keeps.
MASKS = ((0, 1, 2, 3, 4, 8), (0, 1, 2, 4, 6, 8), (0, 3, 5, 6, 7, 8), (0, 2, 3, 6, 7, 8))
SPAN = 9
WINDOW, SUBSTITUTIONS = 16, 3
PIECE = 2048
MAX_SEEDS = 1_000_000


def tokens(text: Column) -> Column:
    """Lower-cased runs of letters and digits."""
    return F.filter(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), lambda x: x != "")


def _allowed(n: int) -> int:
    """Substitutions in an overlap of n tokens, WINDOW at most."""
    return n * SUBSTITUTIONS // WINDOW


def _block(n: int) -> int:
    """Tokens of a block of an item of n tokens, fewer than WINDOW."""
    return n // (_allowed(n) + 1)


def _block_seed(width: int, tokens: list[Column]) -> Column:
    return F.xxhash64(F.lit(len(MASKS) + width), *tokens)


def _item_blocks(item: DataFrame, lengths: list[int]) -> DataFrame:
    """(item, at, seed) for each block of the items of fewer than WINDOW tokens."""
    seeds = [(n, at) for n in lengths for at in range(0, (_allowed(n) + 1) * _block(n), _block(n))]
    found = [F.when(F.size("ih") == n, F.struct(F.lit(at).alias("at"), _block_seed(_block(n), [F.get("ih", F.lit(at + i)) for i in range(_block(n))]).alias("seed"))) for n, at in seeds]
    return item.select("item", F.explode(F.array(*found)).alias("s")).where("s is not null").select("item", "s.at", "s.seed")


def _seeds(df: DataFrame, keep: list[str], hashes: str, widths: list[int] = ()) -> DataFrame:
    """keep + (at, seed) for each position and mask of the array `hashes`, and for each
    block of one of `widths`."""
    # With blocks, positions run to the end, and those beyond it are null.
    n = F.size(hashes) if widths else F.greatest(F.size(hashes) - (SPAN - 1), F.lit(0))
    shifted = F.arrays_zip(*[F.slice(F.col(hashes), i + 1, n).alias(f"t{i}") for i in range(SPAN)])
    rows = df.select(*keep, F.posexplode(shifted).alias("at", "w"))
    seed = [F.xxhash64(F.lit(k), *[F.col(f"w.t{i}") for i in mask]) for k, mask in enumerate(MASKS)]
    if widths:
        seed = [F.when(F.col(f"w.t{SPAN - 1}").isNotNull(), s) for s in seed]
        seed += [F.when(F.col(f"w.t{m - 1}").isNotNull(), _block_seed(m, [F.col(f"w.t{i}") for i in range(m)])) for m in widths]
    return rows.select(*keep, "at", F.explode(F.array(*seed)).alias("seed"))


def _overlapping(docs: DataFrame, bench: DataFrame) -> DataFrame:
    """(doc_id, row, item_id, matched), docs told apart by id and the text's hash."""
    item = bench.select("item_id", F.transform(tokens(F.col("text")), lambda x: F.xxhash64(x)).alias("ih"))
    item = stage_table(item.where(F.size("ih") > 0).withColumn("item", F.monotonically_increasing_id()), "items")
    lengths = sorted(r["n"] for r in item.select(F.size("ih").alias("n")).where(F.col("n") < WINDOW).distinct().collect())
    widths = sorted({_block(n) for n in lengths})
    seeds = _seeds(item.where(F.size("ih") >= WINDOW), ["item"], "ih")
    seeds = seeds.union(_item_blocks(item, lengths)) if lengths else seeds
    seeds = stage_table(seeds.withColumnRenamed("at", "iat").distinct(), "seeds")

    side = WINDOW - 1  # tokens of context that verification may need at either end
    part = docs.select("doc_id", F.xxhash64("text").alias("row"), F.transform(tokens(F.col("text")), lambda x: F.xxhash64(x)).alias("h")).where(F.size("h") >= min([*lengths, WINDOW]))
    part = part.select("doc_id", "row", "h", F.explode(F.sequence(F.lit(0), F.size("h") - 1, F.lit(PIECE))).alias("from"))
    lead = F.least(F.col("from"), F.lit(side))
    part = part.select("doc_id", "row", "from", F.slice("h", F.col("from") - lead + 1, F.lit(PIECE + 2 * side) + lead).alias("h"))
    if seeds.limit(MAX_SEEDS + 1).count() <= MAX_SEEDS:
        hit = _seeds(part, ["doc_id", "row", "h"], "h", widths).join(F.broadcast(seeds), "seed").join(F.broadcast(item), "item")
    else:
        found = _seeds(part, ["doc_id", "row", "from"], "h", widths).join(seeds, "seed")
        found = found.select(F.col("doc_id").alias("of"), F.col("row").alias("of_row"), F.col("from").alias("of_from"), "at", "item", "iat").distinct()
        here = F.col("doc_id").eqNullSafe(F.col("of")) & (F.col("row") == F.col("of_row")) & (F.col("from") == F.col("of_from"))
        hit = part.join(stage_table(found, "hits"), here).join(item, "item")
    # Both sides around the hit, from the same distance before it to the same after.
    back = F.least("at", "iat", F.lit(side))
    long = F.least(F.size("h") - F.col("at"), F.size("ih") - F.col("iat"), F.lit(WINDOW)) + back
    need = F.least(F.size("ih"), F.lit(WINDOW))
    pair = ["doc_id", "row", "item_id", "need"]
    hit = hit.select("doc_id", "row", "item_id", need.alias("need"), F.slice("h", F.col("at") - back + 1, long).alias("x"), F.slice("ih", F.col("iat") - back + 1, long).alias("y")).where(F.size("x") >= F.col("need"))
    # Equal diagonals give equal pairs of slices again and again; count each once.
    same = F.zip_with("x", "y", lambda a, b: (a == b).cast("int"))
    hit = hit.select(*pair, same.alias("same"))
    sums = F.transform(F.sequence(F.lit(1), F.size("same") - F.col("need") + 1), lambda k: F.aggregate(F.slice("same", k, F.col("need")), F.lit(0), lambda a, b: a + b))
    allowed = F.floor(F.col("need") * SUBSTITUTIONS / WINDOW)
    hit = hit.select(*pair, F.array_max(sums).alias("matched")).where(F.col("matched") >= F.col("need") - allowed)
    return hit.groupBy("doc_id", "row", "item_id").agg(F.max("matched").alias("matched"))


def overlaps(docs: DataFrame, bench: DataFrame) -> DataFrame:
    """(doc_id, item_id, matched) of the pairs that overlap; matched is the most
    equal tokens among the WINDOW aligned ones, or among all of a shorter item.

    Items and texts without tokens, nulls included, overlap with nothing. Rows that
    share an id count as one document with several texts, and so do those without an
    id; repeated items are found each. An empty table gives an empty result, and other
    columns are not read."""
    return _overlapping(docs, bench).groupBy("doc_id", "item_id").agg(F.max("matched").alias("matched"))


def drop_contaminated(docs: DataFrame, bench: DataFrame) -> DataFrame:
    """docs without the rows whose text overlaps with an item, whether they have an id
    or share it with others."""
    found = stage_table(_overlapping(docs, bench).select(F.col("doc_id").alias("of"), F.col("row").alias("of_row")).distinct(), "leaks")
    same = docs["doc_id"].eqNullSafe(F.col("of")) & (F.xxhash64(docs["text"]) == F.col("of_row"))
    return docs.join(broadcast_if_small(found, MAX_SEEDS), same, "left_anti").select(*docs.columns)


ORACLE = r"""
WITH d AS (SELECT doc_id, list_filter(regexp_split_to_array(lower(text), '[^\p{L}\p{N}]+'), lambda x: x <> '') AS t FROM documents),
b AS (SELECT item_id, list_filter(regexp_split_to_array(lower(text), '[^\p{L}\p{N}]+'), lambda x: x <> '') AS u FROM benchmark),
m AS (SELECT * FROM (VALUES (0, [1, 2, 3, 4, 5, 9]), (1, [1, 2, 3, 5, 7, 9]), (2, [1, 4, 6, 7, 8, 9]), (3, [1, 3, 4, 7, 8, 9])) AS v(mask, keep)),
dp AS (SELECT doc_id, t, unnest(range(0, len(t) - 8)) AS p FROM d WHERE len(t) >= 16),
bp AS (SELECT item_id, u, unnest(range(0, len(u) - 8)) AS q FROM b WHERE len(u) >= 16),
ds AS (SELECT doc_id, p, mask, [t[p + keep[1]], t[p + keep[2]], t[p + keep[3]], t[p + keep[4]], t[p + keep[5]], t[p + keep[6]]] AS s FROM dp, m),
bs AS (SELECT item_id, q, mask, [u[q + keep[1]], u[q + keep[2]], u[q + keep[3]], u[q + keep[4]], u[q + keep[5]], u[q + keep[6]]] AS s FROM bp, m),
h AS (SELECT DISTINCT doc_id, item_id, p, q FROM ds JOIN bs USING (mask, s)),
r AS (SELECT doc_id, item_id, t, u, p, q, least(p, q, 15) AS k, least(len(t) - p, len(u) - q, 16) AS a FROM h JOIN d USING (doc_id) JOIN b USING (item_id)),
f AS (SELECT doc_id, item_id, list_transform(range(1, k + a + 1), lambda i: CASE WHEN t[p - k + i] = u[q - k + i] THEN 1 ELSE 0 END) AS e FROM r WHERE k + a >= 16),
g AS (SELECT doc_id, item_id, list_max(list_transform(range(1, len(e) - 14), lambda i: list_sum(e[i:i + 15]))) AS matched FROM f)
SELECT doc_id, item_id, CAST(max(matched) AS INTEGER) AS matched FROM g WHERE matched >= 13 GROUP BY doc_id, item_id
"""
