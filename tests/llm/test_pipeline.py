"""Each stage of the pipeline against a plain version of what it is to do, on its own
input, and the whole."""

import itertools
import re
import sys
from collections import Counter, defaultdict
from pathlib import Path

import pytest
from pyspark.sql import functions as F

sys.path.insert(0, str(Path(__file__).resolve().parents[2]))

import corpus_pipeline
from chronotier.llm import common, mixing, toxicity_cnn

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def staged(spark):
    """name -> (rows in, rows out) of each stage."""
    docs, found = spark.read.parquet(f"{SF}/documents.parquet"), {}
    for name, stage in corpus_pipeline.STAGES:
        out = common.stage_table(stage(spark, docs, SF), name)
        found[name] = [r.asDict() for r in docs.collect()], [r.asDict() for r in out.collect()], out.columns
        docs = out
    return found


def ids(rows):
    return sorted(r["doc_id"] for r in rows)


def words(text):
    return re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))


def test_toxicity(spark, staged):
    before, after, columns = staged["toxicity"]
    docs, labels = (spark.read.parquet(f"{SF}/{t}.parquet") for t in ("documents", "labels"))
    model = toxicity_cnn.fit(docs, labels)
    want = [r["doc_id"] for r in before if model is None or model.score(r["text"]) < model.thresholds.get(r["lang"], 0.5)]
    assert ids(after) == sorted(want) and columns == docs.columns


def test_line_dedup(staged):
    before, after, _ = staged["line_dedup"]
    sites, first = defaultdict(set), {}
    for r in sorted(before, key=lambda r: r["doc_id"]):
        for i, line in enumerate((r["text"] or "").split("\n")):
            if k := line.strip(" \t\r"):
                sites[k].add(r["source"])
                first.setdefault(k, (r["doc_id"], i))
    drop = lambda r, i, line: (k := line.strip(" \t\r")) and len(sites[k]) >= 10 and first[k] != (r["doc_id"], i)
    want = {r["doc_id"]: r["text"] and "\n".join(x for i, x in enumerate(r["text"].split("\n")) if not drop(r, i, x)) for r in before}
    assert {r["doc_id"]: r["text"] for r in after} == want
    assert all(r["n_chars"] == len(r["text"] or "") for r in after if want[r["doc_id"]] != r["text"])


def test_near_duplicates(staged):
    before, after, _ = staged["near_duplicates"]
    sets = {}
    for r in before:
        w = words(r["text"])
        sets[r["doc_id"]] = {tuple(w[i : i + 5]) for i in range(len(w) - 4)} or {tuple(w)}
    forest, order = common.Forest(len(sets)), sorted(sets)
    for i, j in itertools.combinations(range(len(order)), 2):
        a, b = sets[order[i]], sets[order[j]]
        if min(len(a), len(b)) >= 0.8 * max(len(a), len(b)) and len(a & b) >= 0.8 * len(a | b):
            forest.join(i, j)
    assert ids(after) == [order[i] for i in range(len(order)) if forest.root(i) == i]


def test_decontamination(spark, staged):
    before, after, _ = staged["decontamination"]
    cut = lambda t: [x for x in re.split(r"[\W_]+", (t or "").lower()) if x]
    bench = [cut(r["text"]) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    want = []
    for r in before:
        t = cut(r["text"])
        hit = False
        for u in bench:
            n = min(16, len(u))
            for shift in range(-len(u) + n, len(t) - n + 1):
                same = [a == b for a, b in zip(t[max(0, shift) :], u[max(0, -shift) :], strict=False)]
                if sum(same) >= n - n * 3 // 16 and any(sum(same[k : k + n]) >= n - n * 3 // 16 for k in range(len(same) - n + 1)):
                    hit = True
                    break
            if hit:
                break
        want += [] if hit else [r["doc_id"]]
    assert ids(after) == sorted(want) and len(want) < len(before)


def test_mixing(spark, staged):
    before, after, columns = staged["mixing"]
    docs = spark.createDataFrame(before, "doc_id long, text string, lang string, source string, n_chars long")
    plan = {r["doc_id"]: r["copies"] for r in mixing.mix_plan(docs).collect()}
    assert Counter(ids(after)) == +Counter(plan)
    assert columns == [*docs.columns, "copy"] and all(c == list(range(1, len(c) + 1)) for c in (sorted(r["copy"] for r in after if r["doc_id"] == i) for i in set(ids(after))))


def test_the_whole(spark, staged):
    mark = len(common.STAGED)
    out = corpus_pipeline.run(spark, SF)
    assert Counter((r["doc_id"], r["copy"]) for r in out.collect()) == Counter((r["doc_id"], r["copy"]) for r in staged["mixing"][1])
    common.drop_staged_since(spark, mark)
    assert len(common.STAGED) == mark
    assert corpus_pipeline.near_duplicates(spark, out.drop("copy").limit(0), SF).count() == 0
