"""Every query against its SQL in DuckDB, on the smallest tables."""

import datetime
import math
import os
from collections import Counter

import duckdb
import pytest
from conftest import SMALL

import __spark_entry__ as entry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
QUERIES, ORACLE = entry.queries(), entry.oracle_sql()
OURS = [k for k in QUERIES if not (k[:2] == "op" and k[2].isdigit()) and k != "pipeline"]


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        path = f"{SMALL}/{t}.parquet"
        con.execute(f"create view {t} as select * from '{path + '/*.parquet' if os.path.isdir(path) else path}'")
    return con


def plain(v):
    if isinstance(v, float):
        return None if math.isnan(v) else round(v, 6) + 0.0
    return v.replace(tzinfo=None) if isinstance(v, datetime.datetime) else v


@pytest.mark.parametrize("key", [k for k in OURS if k in ORACLE])
def test_equals_sql(spark, duck, key):
    df = QUERIES[key](spark, SMALL)
    cols = sorted(df.columns)
    got = Counter(tuple(plain(r[c]) for c in cols) for r in df.collect())
    result = duck.execute(ORACLE[key])
    names = [d[0] for d in result.description]
    assert sorted(names) == cols
    want = Counter(tuple(plain(r[names.index(c)]) for c in cols) for r in result.fetchall())
    assert got == want


@pytest.mark.parametrize("key", [k for k in OURS if k not in ORACLE])
def test_gives_rows(spark, key):
    assert QUERIES[key](spark, SMALL).count() > 0


def test_whole_graph(spark, duck):
    """All triples, against the SQL of counts and, for every building, of three predicates."""
    rows = [tuple(r) for r in QUERIES["kg_triples_all"](spark, SMALL).select("s", "p", "o").collect()]
    counts = Counter(p for _, p, _ in rows)
    assert counts == {r.p: r.n for r in QUERIES["kg_triples_per_predicate_all"](spark, SMALL).collect()}
    assert {p: n for p, n in counts.items() if p != "rdf:type"} == dict(duck.execute(ORACLE["kg_triples_per_predicate"]).fetchall()) and counts["rdf:type"] > 0
    want = duck.execute(ORACLE["kg_building_triples"]).fetchall()
    got = [r for r in rows if r[1] in ("cw:height", "cw:roofLabel", "cw:hasSolid") and r[0].startswith("cw:b/")]
    assert Counter(got) == Counter(want) and len(want) > 3 * 50


def test_entry(spark):
    assert entry.entry(spark).count() > 0
