"""Command line over a store folder: ingest, search, at, timeline, reconcile."""

from __future__ import annotations

import argparse

from chronotier import session
from chronotier.operators import audit, history as hist, search
from chronotier.operators.commit import Store
from chronotier.streaming import stream


def main(argv: list[str] | None = None) -> None:
    p = argparse.ArgumentParser(prog="chronotier", description=__doc__)
    p.add_argument("root", help="store folder, e.g. file:///data/store")
    sub = p.add_subparsers(dest="what", required=True)
    one = sub.add_parser("ingest", help="a Parquet folder of versions")
    one.add_argument("path")
    one.add_argument("--batch", required=True, help="id of the batch; given twice it is taken once")
    for name in ("search", "at", "between"):
        one = sub.add_parser(name)
        one.add_argument("text")
        one.add_argument("-k", type=int, default=5)
        if name == "at":
            one.add_argument("instant", type=int, help="UTC seconds")
        if name == "between":
            one.add_argument("first", type=int)
            one.add_argument("last", type=int)
            one.add_argument("--mode", choices=("side_by_side", "any_time", "delta"), default="side_by_side")
    sub.add_parser("timeline")
    one = sub.add_parser("reconcile")
    one.add_argument("--mode", choices=("forward", "back"), default="forward")
    a = p.parse_args(argv)
    spark = session.build()
    store = Store(spark, a.root)
    if a.what == "ingest":
        stream.ingest_batch(store, spark.read.schema(stream.SCHEMA).parquet(a.path), a.batch)
    elif a.what == "reconcile":
        print(store.reconcile(a.mode), "commits settled")
    elif a.what == "timeline":
        audit.timeline(store.history()).orderBy("revision").show(truncate=False)
    else:
        q = spark.createDataFrame([(0, a.text)], "qid long, text string")
        if a.what == "search":
            search.with_bodies(search.live(q, store.live(), a.k), store.live()).orderBy("rank").show(truncate=80)
        elif a.what == "at":
            slots = hist.snapshot_at(store.history(), a.instant)
            search.with_bodies(search.at(q, store.history(), a.instant, a.k), slots).orderBy("rank").show(truncate=80)
        else:
            search.between(q, store.history(), a.first, a.last, a.k, a.mode).show(a.k * 2, truncate=80)


if __name__ == "__main__":
    main()
