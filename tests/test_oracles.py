"""Every query against its SQL twin on the smallest sample, in a shuffled order; those that
others might disturb are run a second time in the same session."""

import os
import random

import pytest

from chronotier import experiments, registry

SF = "/root/testdata/sf0.001"
AGAIN = ["search_at", "live_slots", "route_answer", "search_at_each", "changes_pivot", "snapshot_at_r3", "leakage_by_variant", "sql_snapshot"]
NAMES = sorted(registry.SQL)
random.Random(20).shuffle(NAMES)
assert experiments.query is registry.query  # its queries are among them


@pytest.fixture(scope="module")
def duck():
    import duckdb

    if not os.path.isdir(SF):
        pytest.skip("no sample tables")
    c = duckdb.connect()
    for f in os.listdir(SF):
        c.sql(f"create view {f.removesuffix('.parquet')} as select * from '{SF}/{f}'")
    return c


def plain(v):
    return round(v, 9) if isinstance(v, float) else v


@pytest.mark.parametrize("name", [*NAMES, *(f"{n} again" for n in AGAIN)])
def test_query(spark, duck, name):
    name = name.removesuffix(" again")
    df = registry.QUERIES[name](spark, SF)
    want = duck.sql(registry.SQL[name])
    assert sorted(df.columns) == sorted(want.columns)
    order = sorted(df.columns)
    at = [want.columns.index(c) for c in order]
    key = lambda r: tuple(repr(x) for x in r)
    a = sorted((tuple(plain(r[c]) for c in order) for r in df.collect()), key=key)
    b = sorted((tuple(plain(r[i]) for i in at) for r in want.fetchall()), key=key)
    assert a == b and (a or name == "diff_withdrawn")  # nobody withdraws at this size
