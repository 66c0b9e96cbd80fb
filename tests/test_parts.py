"""Parts that no query of the registry reaches by itself."""

import json

import pytest
from pyspark.sql import functions as F

from chronotier import cli, contracts
from chronotier.functions import fingerprint, score, segment
from chronotier.operators import audit, diff, encode, history as hist, ledger, search
from chronotier.operators.ann import index
from chronotier.operators.ann import live as live_index
from chronotier.operators.commit import Store
from chronotier.streaming import stream


def test_ledger_as_json(spark, tmp_path):
    segs = spark.createDataFrame([(1, 1, 0, "a"), (1, 2, 0, "b"), (1, 2, 1, "a"), (2, 1, 0, "c")], "doc_id long, revision long, ordinal long, content_key string")
    made = ledger.build(segs)
    ledger.to_json(made, f"{tmp_path}/l")
    rows = [json.loads(x) for f in sorted((tmp_path / "l").glob("*.json")) for x in f.read_text().splitlines()]
    assert sorted((r["doc_id"], r["revision"], r["keys"]) for r in rows) == [(1, 2, ["b", "a"]), (2, 1, ["c"])]
    back = ledger.from_json(spark, f"{tmp_path}/l").select(*made.columns)
    assert sorted(map(tuple, back.collect())) == sorted(map(tuple, made.collect()))


def test_ancestry(spark):
    rows = [("b", "a"), ("c", "b"), ("d", "c"), ("y", "x")]
    h = spark.createDataFrame([("edited", k, p) for k, p in rows] + [("added", "a", None)], "op string, content_key string, prior_key string")
    assert sorted((r["hop"], r["content_key"]) for r in audit.ancestry(h, "d").collect()) == [(0, "d"), (1, "c"), (2, "b"), (3, "a")]
    assert sorted(r["hop"] for r in audit.ancestry(h, "d", max_hops=1).collect()) == [0, 1]


def test_semantic_change(spark):
    vectors = spark.createDataFrame([("a", [1.0, 0.0]), ("b", [0.99, 0.1]), ("c", [0.0, 1.0])], "content_key string, embedding array<double>")
    changes = spark.createDataFrame([(1, "edited", "b", "a"), (2, "edited", "c", "a"), (3, "added", "c", None)], "ordinal long, op string, content_key string, prior_key string")
    got = {r["ordinal"]: r["meaning_changed"] for r in diff.semantic_change(changes, vectors).collect()}
    assert got == {1: False, 2: True}


def test_measures_and_zero_vectors(spark):
    df = spark.createDataFrame([([3.0, 4.0], [4.0, 3.0]), ([0.0, 0.0], [1.0, 0.0]), (None, [1.0, 0.0])], "a array<double>, b array<double>")
    got = df.select(*[f(F.col("a"), F.col("b")).alias(n) for n, f in score.MEASURES.items()]).collect()
    assert [round(x, 9) for x in got[0]] == [0.96, 24.0, -round(2**0.5, 9)]
    assert got[1]["cosine"] is None and got[1]["dot"] == 0 and got[1]["l2"] == -1 and got[2]["cosine"] is None
    ranked = df.select(score.cosine(F.col("a"), F.col("b")).alias("s")).orderBy(F.col("s").desc()).collect()
    assert ranked[0]["s"] is not None  # nulls come last


def test_unicode_forms(spark):
    df = spark.createDataFrame([("été", "été", "ﬁx", "fix")], "a string, b string, c string, d string")
    same = lambda x, y, **k: df.select(fingerprint.content_key(F.col(x), **k) == fingerprint.content_key(F.col(y), **k)).first()[0]
    assert not same("a", "b") and same("a", "b", unicode_form="NFC") and not same("c", "d", unicode_form="NFC") and same("c", "d", unicode_form="NFKC")


def test_invalid_bytes(spark):
    df = spark.createDataFrame([(bytearray(b"a\xffb"), "a\ufffdb")], "raw binary, good string").withColumn("bad", F.col("raw").cast("string"))
    assert df.select(fingerprint.content_key(F.col("bad"), repair=True) == fingerprint.content_key(F.col("good"))).first()[0]


def test_html(spark):
    page = "<html><p class='x'>One <b>two</b></p><ul><li>a</li>\n<LI>b  c</LI></ul><table><tr><td>1</td><td>2</td></tr></table><pre>x\n y</pre><p> </p><p>end</p>"
    df = spark.createDataFrame([(1, 1, 0, page)], "doc_id long, revision long, effective_at long, html string")
    got = [(r["ordinal"], r["kind"], r["body"]) for r in segment.split_html(df).orderBy("ordinal").collect()]
    assert got == [(0, "p", "One two"), (1, "li", "a"), (2, "li", "b c"), (3, "table", "1 2"), (4, "pre", "x y"), (5, "p", "end")]


def test_table_encoder_and_scopes(spark):
    vectors = spark.createDataFrame([(i, [float(i), 1.0]) for i in range(3)], "vec_id long, embedding array<float>")
    keys = spark.createDataFrame([("00000004",), ("00000002",)], "content_key string")
    got = {r["content_key"]: list(r["embedding"]) for r in encode.TableEncoder(vectors).encode(keys).collect()}
    assert got == {"00000004": [1.0, 1.0], "00000002": [2.0, 1.0]}
    rows = [(1, "a", True), (1, "a", True), (2, "a", True), (2, "b", True), (2, "c", False)]
    changes = spark.createDataFrame(rows, "doc_id long, content_key string, needs_encoding boolean")
    known = spark.createDataFrame([("b",)], "content_key string")
    assert [encode.pending_keys(changes, known, s).count() for s in ("none", "document", "corpus")] == [3, 2, 1]


def test_contracts(spark):
    df = spark.createDataFrame([(1, 0, "k", 1, "more")], "doc_id long, ordinal long, content_key string, revision long, other string")
    assert contracts.check(df, contracts.LEDGER).columns == ["doc_id", "ordinal", "content_key", "revision"]
    with pytest.raises(ValueError, match="missing"):
        contracts.check(df.drop("revision"), contracts.LEDGER)
    with pytest.raises(ValueError, match="not bigint"):
        contracts.check(df.withColumn("revision", F.lit(1)), contracts.LEDGER)


def test_history_by_month_opens_no_later_month(spark, tmp_path):
    rows = [(1, 0, "a", 1704067200, 1, "added", None, "x", 1), (1, 0, "b", 1719619200, 2, "edited", "a", "y", 2)]
    h = spark.createDataFrame(rows, contracts.HISTORY)
    hist.write(h, f"{tmp_path}/h")
    read = spark.read.schema("doc_id long, ordinal long, content_key string, effective_at long, revision long, op string, prior_key string, body string, commit_seq long, month string").parquet(f"{tmp_path}/h")
    then = hist.snapshot_at(read, 1706000000)
    assert [r["content_key"] for r in then.collect()] == ["a"]
    assert "month#" in (plan := then._jdf.queryExecution().executedPlan().toString()) and "PartitionFilters: [isnotnull(month" in plan.replace("\n", " ")
    assert [r["content_key"] for r in hist.snapshot_at(read, None).collect()] == ["b"]


def test_live_index(spark):
    """Equal to exact search where the walk is wide, filters inside, shared and empty lines."""
    import random

    rng = random.Random(21)
    words = [f"w{i}" for i in range(60)]
    rows = [(d, o, f"k{(d * 5 + o) % 150}", "", 0, 1) for d in range(60) for o in range(5)]
    body = {k: " ".join(rng.choice(words) for _ in range(6)) for k in sorted({r[2] for r in rows})}
    rows = [(*r[:3], body[r[2]], *r[4:]) for r in rows] + [(99, 0, "none", "?!", 0, 1)]
    slots = spark.createDataFrame(rows, "doc_id long, ordinal long, content_key string, body string, effective_at long, revision long")
    q = spark.createDataFrame([(i, " ".join(rng.choice(words) for _ in range(6))) for i in range(12)] + [(50, "")], "qid long, text string")
    graphs = live_index.build(slots).persist()
    scores = lambda df: {(r["qid"], r["rank"]): r["score"] for r in df.collect()}
    assert scores(live_index.find(q, slots, graphs, 5, 200)) == scores(search.live(q, slots, 5))
    some = slots.where("doc_id % 20 = 0")
    assert scores(live_index.find(q, some, graphs, 5, 8, filtered=True)) == {k: v for k, v in scores(search.live(q, some, 5)).items()}
    v = live_index.dense(search.coded(q, "text").where("qid < 50"), "qid")
    hops = index.Graph(None, graphs=graphs).hops(v, 5, 10).collect()
    assert len(hops) == 12 and all(0 < r["visited"] <= r["n"] == 150 for r in hops)
    graphs.unpersist()


def test_command_line(spark, tmp_path, capsys, monkeypatch):
    monkeypatch.setattr(cli.session, "build", lambda: spark)
    rows = [(1, 1, 100, "alpha beta\ngamma", False), (2, 1, 100, "delta", False), (1, 2, 200, "alpha beta\nomega", False)]
    spark.createDataFrame(rows, stream.SCHEMA).write.parquet(f"{tmp_path}/in")
    run = lambda *a: (cli.main([f"file://{tmp_path}/store", *a]), capsys.readouterr().out)[1]
    run("ingest", f"{tmp_path}/in", "--batch", "b1")
    run("ingest", f"{tmp_path}/in", "--batch", "b1")
    assert len(Store(spark, f"file://{tmp_path}/store").commits()) == 2
    assert "omega" in run("search", "omega", "-k", "1") and "gamma" not in run("search", "omega gamma", "-k", "5")
    assert "gamma" in run("at", "gamma", "150", "-k", "1") and "omega" not in run("at", "omega", "150")
    assert "entered" in run("between", "omega", "100", "300") and "edited" in run("timeline")
    assert "0 commits settled" in run("reconcile")


def test_folded_log_equals_the_operators(spark):
    """The log made within rows holds the events of diff.combined, stamp and intervals, and
    its plan deals out no text but that of documents that copy a line."""
    from chronotier.operators import history as hist
    from chronotier.sources import tiers

    sf = "/root/testdata/sf0.001"
    for profile in ("structural", "steady"):
        want = hist.intervals(hist.stamp(tiers.changes(spark, sf, profile), tiers.segments(spark, sf, profile)))
        got = tiers.made_log(spark, sf, profile)
        cols = ["doc_id", "ordinal", "content_key", "effective_at", "revision", "op", "prior_key", "body", "retired_at", "state"]
        rows = lambda df: sorted(df.where("content_key is not null").select(*cols).collect(), key=repr)
        assert rows(got) == rows(want) and rows(want)
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") <= 2 and "Window" not in plan  # the copies' join only


def test_folded_odd_versions(spark):
    """Withdrawn, reborn, repeated and empty versions against the joins."""
    from chronotier.operators import diff, history as hist

    docs = {1: ["aab", "", "ba"], 2: ["", "xyz", "zyx"], 3: ["abc", "abcd", "bcd"], 4: ["a", "b", "a"], 5: ["", "", ""]}
    flat = [(d, v, v * 10, i, k, f"{k}{v}") for d, vs in docs.items() for v, t in enumerate(vs, 1) for i, k in enumerate(t)]
    segs = spark.createDataFrame(flat, "doc_id long, revision long, effective_at long, ordinal long, content_key string, body string")
    old = segs.where("revision < 3").withColumn("revision", segs["revision"] + 1)
    by = ("doc_id", "revision")
    want = hist.intervals(hist.stamp(diff.combined(old, segs, by, old.select(*by).distinct()), segs)).select(*[c for c in hist.NAMES])
    nested = [(d, [(v, v * 10, [(k, f"{k}{v}") for k in t]) for v, t in enumerate(vs, 1)]) for d, vs in docs.items()]
    kind = "doc_id long, revs array<struct<revision:long,effective_at:long,rows:array<struct<content_key:string,body:string>>>>"
    got = hist.folded(spark.createDataFrame(nested, kind)).where("content_key is not null")
    assert sorted(map(repr, got.collect())) == sorted(map(repr, want.collect()))


def test_cells_score_by_products(spark):
    """The k best of the probed cells as a plain computation gives them, ties, a zero vector
    and more batches than one included; no pair of a query and a vector becomes a row."""
    import numpy as np

    from chronotier.operators.ann import index

    x = np.random.default_rng(3).integers(-3, 4, (700, 6)).astype(float)
    x[5] = 0
    v = spark.createDataFrame([(i, r.tolist()) for i, r in enumerate(x)], "vec_id long, embedding array<float>")
    q = v.where("vec_id % 20 = 1").withColumnRenamed("vec_id", "qid")
    made = index.Cells(v, 9)
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", 50)
    got = made.search(q, 10, 4)
    found = {(r["qid"], r["rank"]): (r["vec_id"], r["score"]) for r in got.collect()}
    cell = {r["vec_id"]: r["cell"] for r in made.vectors.collect()}
    spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    c = np.array(made.centres)
    c /= np.linalg.norm(c, axis=1)[:, None]
    n = np.linalg.norm(x, axis=1)
    for i in range(1, 700, 20):
        near = set(np.argsort(-(x[i] @ c.T), kind="stable")[:4].tolist())
        best = sorted((-round(float(x[i] @ x[j] / (n[i] * n[j])), 6), j) for j in range(700) if cell[j] in near and n[j])[:10]
        assert [(j, -s) for s, j in best] == [found[i, r] for r in range(1, 11)]
    assert "BroadcastHashJoin" not in got._jdf.queryExecution().executedPlan().toString()


def test_log_read_once_is_not_written(spark, monkeypatch):
    """Queries that read the log once or twice leave no log on disk, and take it as written
    where it is."""
    from chronotier import experiments, registry
    from chronotier.sources import tiers

    assert experiments.query is registry.query
    sf = "/root/testdata/sf0.001"
    monkeypatch.setattr(tiers, "_WRITTEN", {})
    for name in ("history_closed", "snapshot_boundary", "audit_lineage", "audit_rebuild", "search_at", "search_at_each", "route_answer", "leakage_by_variant", "ablation_oversampling", "postfilter_wrong_answers", "sql_live_scores", "sql_scores_at"):
        registry.QUERIES[name](spark, sf)
    assert {at[2] for at in tiers._WRITTEN} == {"asked", "asked_of_indexes", "asked_of_all", "asked_of_two"}
    made = tiers.spans(spark, sf, once=True).drop("month")
    tiers.log(spark, sf)
    again = tiers.spans(spark, sf, once=True)
    assert "month" in again.columns and sorted(map(repr, made.collect())) == sorted(map(repr, again.select(*made.columns).collect()))


def test_graph_built_at_once():
    """Every vector is reached, copies and islands included, levels are
    those of the graph built one by one, and recall is 0.9 or more."""
    import numpy as np
    from chronotier.operators.ann.graph import LayeredGraph

    rng = np.random.default_rng(24)
    x = np.concatenate([np.repeat(rng.normal(size=(1, 24)), 80, 0), 5 + 0.01 * rng.normal(size=(80, 24)), rng.normal(size=(440, 24))])
    one, many = LayeredGraph(x, range(600), 8, 100), LayeredGraph(x, range(600), 8, at_once=True)
    assert [len(v) for v in many.links] == [len(v) for v in one.links] and len(many.links) > 1
    assert sorted(i for i, _ in many.search(x[0], 600, 600)) == list(range(600))
    hits = {1: 0, 2: 0}
    for v in rng.normal(size=(40, 24)):
        last = np.sort(one.x @ (v / np.linalg.norm(v)))[-5] - 1e-6
        for i, g in ((1, one), (2, many)):
            hits[i] += sum(s >= last for _, s in g.search(v, 5, 64))
    assert hits[2] >= 180, hits  # 0.9
    few = LayeredGraph(x[:1], [7], at_once=True)
    assert few.search(x[0], 5, 8) == [(7, 1.0)] and LayeredGraph(x[:0], [], at_once=True).top == -1


def test_graphs_are_stored_narrow(spark, monkeypatch):
    """The index behind the live tier leaves neither the log nor dense vectors on disk, and
    what it stores in place of texts are the tier's slots and terms."""
    from chronotier import experiments, registry
    from chronotier.sources import tiers

    assert experiments.query is registry.query
    sf = "/root/testdata/sf0.001"
    monkeypatch.setattr(tiers, "_WRITTEN", {})
    for name in ("search_live_indexed", "search_live_indexed_filtered"):
        assert registry.QUERIES[name](spark, sf).count() > 0
    assert {at[2] for at in tiers._WRITTEN} == {"live_terms/structural", "graphs/structural"}
    held = tiers.graphs(spark, sf).selectExpr("sum(n) AS n", "sum(length(graph)) AS bytes").first()
    assert held["bytes"] < 1000 * held["n"]
    want = search.coded(tiers.live(spark, sf, once=True), "body").select(*search.PLACE, "codes")
    assert sorted(map(repr, tiers.live_terms(spark, sf).collect())) == sorted(map(repr, want.collect()))


def test_keys_and_codes_of_python(spark):
    """Keys and hashed terms made in tasks are those of the expressions."""
    from chronotier.functions import fingerprint
    from chronotier.operators import encode

    texts = ["", " \t\r\n", "A  b\tC\f", "\x0b x \x0b", "ÀÉ ß ΟΔΟΣ İ Straße ÖL", "one one, two. ONE-two ñandú", "a\u00a0b 漢字 🙂", None]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "i long, text string")
    coder = encode.Coder()
    for r in df.select("text", fingerprint.content_key(df["text"]).alias("key"), encode.codes(df["text"]).alias("codes")).collect():
        raw = None if r["text"] is None else r["text"].encode()
        assert (fingerprint.key_of(raw), coder.codes(raw)) == (r["key"], r["codes"] or [])


def test_questions_of_all_sorts_in_one_pass(spark, monkeypatch):
    """Instants, ranges, ended slots and flags, asked together or one by one."""
    from pyspark.sql import functions as F

    from chronotier.operators import search

    words = ["red", "green", "blue", "grey"]
    rows = [(d, o, f"k{d}{o}", 100 * o, 1, " ".join(words[(d + o + i) % 4] for i in range(1 + d % 3)), None if o == 2 else 100 * o + 150, d % 2 == 0) for d in range(30) for o in range(3)]
    slots = spark.createDataFrame(rows, "doc_id long, ordinal long, content_key string, effective_at long, revision long, body string, retired_at long, even boolean")
    qs = [(1, "red blue", 120, None, None, None), (2, "green", 50, 210, None, None), (3, "grey red", 0, 500, True, None), (4, "blue", search.NEVER, search.ALWAYS, None, "even"), (5, "red", None, None, None, None)]
    monkeypatch.setattr(search, "SLOTS_AT_ONCE", 7)
    asked = lambda some: spark.createDataFrame(some, "qid long, text string, t long, until long, ended boolean, among string")
    got = sorted(map(tuple, search.best(asked(qs), slots, 4).collect()))
    assert got == sorted(tuple(r) for q in qs for r in search.best(asked([q]), slots, 4).collect())
    where = {1: "effective_at <= 120 and (retired_at is null or retired_at > 120)", 2: "effective_at < 210 and (retired_at is null or retired_at > 50)", 3: "effective_at < 500 and retired_at is not null", 4: "even", 5: "false"}
    for qid, text, *_ in qs:
        want = search.best(spark.createDataFrame([(qid, text)], "qid long, text string"), slots.where(F.expr(where[qid])), 4, ("retired_at",)).collect()
        assert sorted(map(tuple, want)) == [r for r in got if r[0] == qid] and (want or qid == 5)


def test_keyword_makes_no_row_per_question_and_slot(spark, monkeypatch):
    """Scores against brute force, by slices, with frequent words, repeated keys, empty
    texts and questions; the plan joins nothing."""
    import math

    from chronotier.operators import baselines, search

    monkeypatch.setattr(search, "SLOTS_AT_ONCE", 16)
    monkeypatch.setattr(baselines, "TERMS_AT_ONCE", 5)
    words = ["the", "red", "green", "blue", "grey"]
    body = lambda d, o: "" if d == 7 else " ".join(["The", *(words[(d * o + i) % 5] for i in range(d % 4))])
    rows = [(d, o, body(d, o).lower() or "-", 100, 1, body(d, o)) for d in range(40) for o in range(3)]
    slots = spark.createDataFrame(rows, "doc_id long, ordinal long, content_key string, effective_at long, revision long, body string")
    qs = {1: "the Red, red blue", 2: "GREEN", 3: "", 4: "unknown", 5: "the"}
    got = baselines.keyword(spark.createDataFrame(list(qs.items()), "qid long, text string"), slots, 4)
    keys = {r[2]: set(r[2].split()) - {"-"} for r in rows}
    idf = {w: math.log((len(keys) + 1) / (1 + sum(w in x for x in keys.values()))) for w in words}
    want = []
    for q, text in qs.items():
        asked = set(text.lower().replace(",", "").split())
        found = sorted((-round(sum(idf[w] for w in sorted(asked & keys[r[2]])), 6), r[0], r[1]) for r in rows if asked & keys[r[2]])[:4]
        want += [(q, i, -s, d, o) for i, (s, d, o) in enumerate(found, 1)]
    assert sorted(map(tuple, got.collect())) == sorted(want) and {q for q, *_ in want} == {1, 2, 5}
    assert "Join" not in got._jdf.queryExecution().executedPlan().toString()
