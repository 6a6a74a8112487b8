import os

import duckdb
import pytest

SMALL = "/root/testdata/sf0.001"
pytestmark = pytest.mark.skipif(not os.path.isdir(SMALL), reason="needs the given tables")


def test_pipeline_stages(spark):
    import corpus_pipeline as p
    from graphkw.llm.base import Stage, table

    docs = table(spark, SMALL, "documents")
    columns, seen = docs.columns, []
    for name, stage in p.STAGES:
        out = stage(spark, docs, SMALL)
        if name != "packing":
            assert out.columns == columns, name
        docs = Stage(out, name).df
        seen.append(docs.count())
        if name != "packing":
            last = {r.doc_id for r in docs.select("doc_id").collect()}
    assert [n for n, _ in p.STAGES] == ["quality_classifier", "line_dedup", "minhash_dedup", "decontamination", "packing"]
    assert seen[0] >= seen[1] >= seen[2] >= seen[3] > 0
    assert {r.doc_id for r in docs.select("doc_id").collect()} == last


@pytest.mark.parametrize("name", ["op3_minhash_dedup", "op4_decontamination", "op6_url_filter"])
def test_against_sql(spark, name):
    from graphkw.llm.queries import ORACLE_SQL, QUERIES

    con = duckdb.connect()
    for t in ("documents", "benchmark", "pages", "labels"):
        con.sql(f"create view {t} as select * from '{SMALL}/{t}.parquet'")
    got = QUERIES[name](spark, SMALL)
    want = con.sql(ORACLE_SQL[name])
    order = [want.columns.index(c) for c in got.columns]
    assert sorted(map(tuple, got.collect()), key=str) == sorted((tuple(r[k] for k in order) for r in want.fetchall()), key=str)
