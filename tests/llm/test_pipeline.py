"""The pipeline's stages in a row, each against what it should do to its own input."""

import brute
from conftest import SMALL

import corpus_pipeline
from cityweave.llm import queries


def test_stages(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    columns = docs.columns
    before = {r.doc_id: r.text for r in docs.collect()}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, SMALL).cache()
        after = {r.doc_id: r.text for r in docs.collect()}
        assert docs.columns == columns and set(after) <= set(before) and docs.count() == len(after)
        if name == "language_id":
            assert set(after) == {k for k, t in before.items() if any(c.isalpha() for c in t or "")}
        elif name == "simhash_near_dedup":
            assert set(after) == {c for _, c in brute.simhash_rows(before.items()).values()}
        elif name == "pii":
            assert set(after) == set(before) and not any(brute.base_spans(t) for t in after.values() if "<" not in t)
            assert all(before[k] == t for k, t in after.items() if not brute.base_spans(before[k]) and "<" not in t)
        else:
            assert all(before[k] == t for k, t in after.items())
        before = after
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, SMALL)
    assert {r.doc_id for r in packed.collect()} == set(before)


def test_run(spark):
    assert corpus_pipeline.run(spark, SMALL).count() > 0
    assert set(queries.QUERIES) >= {k for k in queries.ORACLE}


def test_url_query_equals_sql(spark):
    import duckdb

    con = duckdb.connect()
    con.execute(f"create view pages as select * from '{SMALL}/pages.parquet'")
    key = "op2_weighted_url_terms"
    result = con.execute(queries.ORACLE[key])
    names = [d[0] for d in result.description]
    want = sorted(map(str, result.fetchall()))
    assert sorted(str(tuple(r[c] for c in names)) for r in queries.QUERIES[key](spark, SMALL).collect()) == want
