import os
import shutil
import subprocess
import sys

import duckdb
import pytest

import __spark_entry__ as entry

SMALL = "/root/testdata/sf0.001"
pytestmark = pytest.mark.skipif(not os.path.isdir(SMALL), reason="needs the given tables")
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
CHECKED = "g1_edges g1_postings g2_edges g3_edges g4_edges g6c_postings kw_topk_q2 kw_distances frag_edge_cut frag_local_topk op_join_theta_range op_pivot op_window_ntile_pct op_json_parse op_recursive_cte st_tumbling st_session".split()


@pytest.mark.parametrize("name", CHECKED)
def test_against_sql(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"create view {t} as select * from '{SMALL}/{t}.parquet'")
    got = entry.queries()[name](spark, SMALL)
    want = con.sql(entry.oracle_sql()[name])
    assert sorted(got.columns) == sorted(want.columns)
    order = [want.columns.index(c) for c in got.columns]
    assert sorted(map(tuple, got.collect()), key=str) == sorted((tuple(r[k] for k in order) for r in want.fetchall()), key=str)


def test_entry_answers(spark):
    rows = entry.entry(spark).orderBy("rank").collect()
    assert [(r.root % 10**12, r.score) for r in rows[:4]] == [(328, 5), (611, 5), (20, 6), (29, 6)]


@pytest.mark.parametrize("pipeline_on_path", [False, True])
def test_engine_stands_without_the_corpus_operators(tmp_path, pipeline_on_path):
    here = os.path.dirname(os.path.abspath(entry.__file__))
    shutil.copytree(f"{here}/graphkw", tmp_path / "graphkw", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    shutil.copy(f"{here}/__spark_entry__.py", tmp_path)
    if pipeline_on_path and os.path.exists(f"{here}/corpus_pipeline.py"):
        shutil.copy(f"{here}/corpus_pipeline.py", tmp_path)
    code = "import sys; sys.path.insert(0, '.'); import __spark_entry__ as m; q = m.queries(); assert 'pipeline' not in q and 'op1_quality_classifier' not in q and len(q) > 100 and set(m.oracle_sql()) <= set(q)"
    env = {k: v for k, v in os.environ.items() if k != "PYTHONPATH"}
    for path in ({}, {"PYTHONPATH": str(tmp_path)}):
        subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, env=env | path)
