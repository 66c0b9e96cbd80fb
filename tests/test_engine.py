"""Hand-sized cases of the engine's methods."""

import pytest
from pyspark.sql import functions as F

from chronotier.functions import fingerprint, route, segment
from chronotier.operators import diff, history as hist, metrics, search
from chronotier.plans.guard import LeakyPlan, assert_guard


def keys(spark, docs):
    rows = [(d, i, k) for d, ks in docs.items() for i, k in enumerate(ks)]
    return spark.createDataFrame(rows, "doc_id long, ordinal long, content_key string")


CASES = [
    ("abc", "Xabc", {("added", 0), ("moved", 1), ("moved", 2), ("moved", 3)}),
    ("abc", "ac", {("kept", 0), ("moved", 1), ("dropped", 1), ("vacated", 2)}),
    ("abc", "aBc", {("kept", 0), ("edited", 1), ("kept", 2)}),
    ("abc", "aC", {("kept", 0), ("edited", 1), ("dropped", 2)}),
    ("ab", "ba", {("moved", 0), ("moved", 1)}),
    ("aa", "a", {("kept", 0), ("vacated", 1)}),
    ("", "ab", {("added", 0), ("added", 1)}),
    ("ab", "", {("dropped", 0), ("dropped", 1)}),
]


def test_combined_table_and_replay(spark):
    old = keys(spark, {i: c[0] for i, c in enumerate(CASES)})
    new = keys(spark, {i: c[1] for i, c in enumerate(CASES)})
    ids = spark.createDataFrame([(i,) for i in range(len(CASES))], "doc_id long")
    found = diff.combined(old, new, withdrawn=ids)
    got = {}
    for r in found.collect():
        got.setdefault(r["doc_id"], set()).add((r["op"], r["ordinal"]))
    assert got == {i: c[2] for i, c in enumerate(CASES)}
    assert sorted(map(tuple, diff.replay(old, found).collect())) == sorted(map(tuple, new.collect()))


def test_untouched_documents_stay(spark):
    found = diff.combined(keys(spark, {1: "ab", 2: "cd"}), keys(spark, {1: "ab"}))
    assert {r["doc_id"] for r in found.collect()} == {1}


def test_aligned_sees_one_insertion(spark):
    got = diff.aligned(keys(spark, {1: "abc"}), keys(spark, {1: "Xabc"})).collect()
    assert sorted((r["op"], r["ordinal"]) for r in got) == [("added", 0), ("kept", 1), ("kept", 2), ("kept", 3)]


HISTORY = "doc_id long, ordinal long, content_key string, effective_at long, revision long, op string, prior_key string, body string, commit_seq long"


def events(spark):
    return spark.createDataFrame([(1, 0, "a", 100, 1, "added", None, "old text here", 1), (1, 0, "b", 200, 2, "edited", "a", "new words there", 2), (2, 0, "c", 100, 1, "added", None, "old thing", 1), (2, 0, None, 200, 2, "dropped", "c", None, 2)], HISTORY)


def test_snapshot_boundaries(spark):
    h = events(spark)
    at = lambda t: {(r["doc_id"], r["content_key"]) for r in hist.snapshot_at(h, t).collect()}
    assert at(99) == set()
    assert at(100) == at(199) == {(1, "a"), (2, "c")}
    assert at(200) == at(10**9) == {(1, "b")}
    spans = hist.intervals(h)
    assert {(r["doc_id"], r["content_key"]) for r in hist.valid_at(spans, 199).collect()} == at(199)
    assert {(r["content_key"], r["state"]) for r in spans.collect()} == {("a", "replaced"), ("b", "live"), ("c", "removed")}
    assert {r["content_key"] for r in hist.snapshot_at(h, 300, as_known_at=1).collect()} == {"a", "c"}


def test_late_revision_is_spliced(spark):
    h = events(spark).union(spark.createDataFrame([(1, 0, "m", 150, 9, "edited", "a", "middle", 3)], HISTORY))
    got = {(r["content_key"], r["retired_at"]) for r in hist.intervals(h).where("doc_id = 1").collect()}
    assert got == {("a", 150), ("m", 200), ("b", None)}


def test_answers_do_not_change_with_the_future(spark):
    q = spark.createDataFrame([(1, "old text")], "qid long, text string")
    h = events(spark)
    later = h.union(spark.createDataFrame([(3, 0, "z", 300, 3, "added", None, "old text", 3)], HISTORY))
    assert search.at(q, h, 150).collect() == search.at(q, later, 150).collect()


def test_guard(spark):
    q = spark.createDataFrame([(1, "old text")], "qid long, text string")
    assert_guard(search.at(q, events(spark), 150))
    late = events(spark).orderBy("revision").limit(2).where("effective_at < 150")
    ranked = search.rank(events(spark).selectExpr("1 qid", "1.0 score", "*"), 2).where("effective_at < 150")
    joined = ranked.drop("score").join(q, "qid").where("effective_at < 150 or revision > 7")
    for leaky in (late, ranked, joined, search.rank(events(spark).selectExpr("1 qid", "1.0 score", "*"), 2).join(q.selectExpr("qid", "150 t"), F.expr("effective_at <= t"))):
        with pytest.raises(LeakyPlan):
            assert_guard(leaky)


def test_guard_looks_at_the_plan_only(spark):
    """Numbering rows is no choice, questions may be limited, and what was cached before
    by another query changes nothing."""
    from pyspark.sql import Window as W

    numbered = events(spark).withColumn("n", F.row_number().over(W.partitionBy("doc_id").orderBy("ordinal", "revision")))
    q = spark.createDataFrame([(1, "old text", 150)], "qid long, text string, t long").limit(5)
    spans = hist.closed(events(spark))
    plans = lambda: [numbered.where("effective_at < 150"), search.at(q, numbered, 150), search.at_each(q, spans), *(search.between(q, spans if m != "delta" else events(spark), 100, 200, mode=m) for m in ("side_by_side", "any_time", "delta"))]
    for df in plans():
        assert_guard(df)
    warm = [df.persist() for df in (numbered, spans, search.rank(events(spark).selectExpr("1 qid", "1.0 score", "*"), 2))]
    for df in warm:
        df.count()
    for df in plans():
        assert_guard(df)
    for df in warm:
        df.unpersist()


def test_blocks(spark):
    text = "One line.\nmore\n\n| a | b |\n|---|---|\n| 1 | 2 |\n\n```\nx = 1\n\ny = 2\n```\n- one\n- two\n  more\n- three\n\nlast"
    df = spark.createDataFrame([(1, 1, 0, text)], "doc_id long, revision long, effective_at long, text string")
    got = [(r["kind"], r["body"].count("\n") + 1) for r in segment.split_blocks(df).orderBy("ordinal").collect()]
    assert got == [("prose", 2), ("table", 3), ("code", 5), ("list", 4), ("prose", 1)]


def test_canonical(spark):
    df = spark.createDataFrame([("Foo  bar ", " foo bar"), ("Straße", "STRASSE")], "a string, b string")
    same = lambda **k: [r[0] for r in df.select(fingerprint.content_key(F.col("a"), **k) == fingerprint.content_key(F.col("b"), **k)).collect()]
    assert same() == [True, False]
    assert same(raw=True) == [False, False]
    assert same(fold="full") == [True, True]


def test_routes(spark):
    texts = ["price between 2024-01-01 and 2024-03-31", "changes since march 2024", "policy as of 2024-02-15", "what was it before 2024-05-01", "plain", "as of 2030-01-01", "rule 2024-02-30"]
    df = spark.createDataFrame(list(enumerate(texts)), "qid long, text string")
    got = [(r["kind"], r["t_from"], r["t_to"]) for r in route.classify(df, 1719619200).orderBy("qid").collect()]
    assert got == [("comparative", 1704067200, 1711929600), ("comparative", 1709251200, 1719619200), ("historical", 1708041599, None), ("historical", 1714521599, None), ("live", None, None), ("live", None, None), ("live", None, None)]


def test_work_model():
    m = metrics.work_model(0.1, [18] * 10)
    assert abs(m["upsert"] - 0.85) < 0.01 and m["sync"] == 0.1
    assert metrics.collision_bound(2) == -255


def test_sql_surface(spark):
    from chronotier.plans import surface

    surface.register(spark, events(spark))
    for t in (99, 150, 200):
        want = {(r["doc_id"], r["content_key"]) for r in hist.snapshot_at(events(spark), t).collect()}
        assert {(r[0], r[1]) for r in spark.sql(f"SELECT doc_id, content_key FROM snapshot_at({t})").collect()} == want
    lines = spark.sql("SELECT s.* FROM VALUES ('a\\n \\t\\nb') v(x), LATERAL split_document(x) s").collect()
    assert [tuple(r) for r in lines] == [(0, "a"), (1, "b")]


def test_scores_in_sql(spark):
    """Texts are scored once each, whatever stands above; terms that cancel out are no terms;
    a function takes a column of questions."""
    from chronotier.operators import encode
    from chronotier.plans import surface

    coder, met = encode.Coder(), {}
    a, b = next((met[-n], w) for w in (f"w{i}" for i in range(5000)) for n in [coder[w]] if -n in met or met.update({n: w}))
    rows = [(1, 0, "k1", f"{a} {b}", 10, None, 1), (2, 0, "k2", f"{a} old text", 10, 20, 1), (3, 0, "k3", f"New {a} {b} text", 10, None, 1), (4, 0, "k4", "", 10, None, 1), (5, 0, "k5", None, 10, None, 1), (6, 0, "k3", f"New {a} {b} text", 20, None, 1)]
    spans = spark.createDataFrame(rows, "doc_id long, ordinal long, content_key string, body string, effective_at long, retired_at long, revision long")
    asked = spark.createDataFrame([(1, f"{a} text"), (2, "text"), (3, f"{a} {b}"), (4, None)], "qid long, text string")
    for form in (spans, spans.withColumn("codes", encode.codes(F.col("body")))):
        surface.register(spark, form.withColumn("op", F.lit("added")).withColumn("prior_key", F.lit(None).cast("string")))
        for name, slots in (("live_scores(text)", form.where("retired_at is null")), ("scores_at(text, 15)", hist.valid_at(form, 15))):
            found = spark.sql(f"SELECT qid, doc_id, score FROM VALUES (1, '{a} text'), (2, 'text'), (3, '{a} {b}'), (4, NULL) AS q(qid, text), LATERAL {name}")
            want = {(r["qid"], r["doc_id"], r["score"]) for r in search.best(asked, slots, 9).collect()}
            assert want and {tuple(r) for r in found.collect()} == want
        top = spark.sql("SELECT * FROM live_scores('text') WHERE score > 0.1 ORDER BY score DESC, doc_id, ordinal LIMIT 1")
        assert [r["doc_id"] for r in top.collect()] == [3]
        plan = top._jdf.queryExecution().optimizedPlan().toString()
        assert plan.count("ArrowEvalPython") == 1 and "aggregate(" not in plan


def test_stored_terms_score_the_same(spark):
    from chronotier.operators import encode

    q = spark.createDataFrame([(1, "old text"), (2, "")], "qid long, text string")
    spans = hist.closed(events(spark))
    want = search.at(q, events(spark), 150).collect()
    assert want and want == search.at(q, spans, 150).collect() == search.at(q, spans.withColumn("codes", encode.codes(F.col("body"))), 150).collect()


def test_best_against_brute_force(spark):
    """Ties, slots that share no term, questions by instant, several batches."""
    import random

    rng = random.Random(12)
    words = [f"w{i}" for i in range(12)]
    text = lambda n: " ".join(rng.choice(words) for _ in range(n))
    rows = [(d, o, f"k{d}{o}", text(rng.randrange(1, 5)), 10 * rng.randrange(5), rng.choice([None, 60, 70]), 1) for d in range(40) for o in range(5)] + [(99, 0, "e", "", 0, None, 1)]
    slots = spark.createDataFrame(rows, "doc_id long, ordinal long, content_key string, body string, effective_at long, retired_at long, revision long").repartition(3)
    qs = [(i, text(3), 5 * i) for i in range(16)] + [(50, "unheard", 30), (51, "", 30)]

    def vector(t):
        v = {}
        for w in t.split():
            h = __import__("hashlib").md5(w.encode()).hexdigest()
            b = int(h[:8], 16) % 384
            v[b] = v.get(b, 0) + (1 if int(h[8], 16) % 2 == 0 else -1)
        return {b: x for b, x in v.items() if x}

    def brute(q, t):
        a = vector(q)
        found = []
        for d, o, _, body, start, end, _ in rows:
            b = vector(body)
            if set(a) & set(b) and (t is None or start <= t and (end is None or end > t)):
                s = sum(x * b.get(i, 0) for i, x in a.items()) / (sum(x * x for x in a.values()) * sum(x * x for x in b.values())) ** 0.5
                found.append((-round(s, 6), d, o))
        return [(d, o, -s) for s, d, o in sorted(found)[:4]]

    for instants in (False, True):
        asked = spark.createDataFrame(qs, "qid long, text string, t long")
        got = {}
        for r in search.best(asked if instants else asked.drop("t"), slots, 4).orderBy("qid", "rank").collect():
            got.setdefault(r["qid"], []).append((r["doc_id"], r["ordinal"], r["score"]))
        for qid, q, t in qs:
            assert got.get(qid, []) == brute(q, t if instants else None)


def test_aligned_long_documents(spark):
    """Edits keep their prior key and repeated lines are counted, whatever the length."""
    was = [f"l{i}" if i % 3 else "same" for i in range(3000)]
    now = ["top", *was]
    now[1500] = "changed"  # was[1499]
    del now[2701]  # a copy of "same", was[2700]
    got = diff.aligned(keys(spark, {1: was}), keys(spark, {1: now})).where("op <> 'kept'").collect()
    assert sorted((r["op"], r["ordinal"], r["content_key"], r["prior_key"]) for r in got) == [("added", 0, "top", None), ("dropped", 2700, None, "same"), ("edited", 1500, "changed", "l1499")]


def test_aligned_matches_difflib():
    import difflib
    import random

    rng = random.Random(3)
    for n in range(200):
        a, b = ([rng.choice("abcdefgh"[: 1 + n % 8]) for _ in range(rng.randrange(30))] for _ in range(2))
        assert diff._matcher(a, b).get_opcodes() == difflib.SequenceMatcher(None, a, b, autojunk=False).get_opcodes()


def test_query_blocks_answer_all(spark, monkeypatch):
    """Queries beyond a block are answered like the others."""
    import random

    from chronotier.operators.ann import index

    rng = random.Random(4)
    rows = [(i, [rng.gauss(0, 1) for _ in range(8)]) for i in range(60)]
    vectors = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    queries = vectors.where("vec_id < 25").withColumnRenamed("vec_id", "qid")
    want = {(r.qid, r["rank"], r.vec_id) for r in index.exact(queries, vectors, 3).collect()}
    monkeypatch.setattr(index, "MAX_QUERIES", 10)
    assert {(r.qid, r["rank"], r.vec_id) for r in index.exact_blocks(queries, vectors, 3).collect()} == want
    assert {r.qid for r in index.Graph(vectors, 2).search(queries, 3).collect()} == set(range(25))
