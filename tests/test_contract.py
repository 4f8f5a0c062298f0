"""Registered queries against their SQL, and the entry file without the corpus subpackage."""

import os
import shutil
import subprocess
import sys

import duckdb
import pandas as pd
import pytest

from deltaring import queries as q

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return con


def rows(p):
    p = p[sorted(p.columns)]
    plain = lambda x: None if x is None or x is pd.NaT or x != x else repr(float(x)) if isinstance(x, float) else str(x)
    return sorted((tuple(plain(x) for x in r) for r in p.astype(object).values.tolist()), key=repr)


@pytest.mark.parametrize("name", sorted(set(q.oracle_sql()) - {"ridge_gd_j1"}))
def test_query_equals_its_sql(spark, duck, name):
    got, want = q.queries()[name](spark, SF).toPandas(), duck.execute(q.oracle_sql()[name]).df()
    assert sorted(got.columns) == sorted(want.columns) and rows(got) == rows(want)


@pytest.mark.parametrize("name", sorted(set(q.queries()) - set(q.oracle_sql())))
def test_query_without_sql_runs(spark, name):
    assert q.queries()[name](spark, SF).count() > 0


def test_entry_without_the_corpus_operators(tmp_path):
    shutil.copytree(ROOT, tmp_path / "repo", ignore=shutil.ignore_patterns(".git", "__pycache__", "llm", "corpus_pipeline.py"))
    code = "import __spark_entry__ as e; n = e.queries(); assert 'moments_j1_cont' in n and not any(k.startswith('op') for k in n) and 'pipeline' not in n and e.oracle_sql()"
    assert subprocess.run([sys.executable, "-c", code], cwd=tmp_path / "repo", env={**os.environ, "PYTHONPATH": ""}).returncode == 0


def test_nothing_else_imports_the_corpus_operators():
    for top, _, names in os.walk(f"{ROOT}/deltaring"):
        for n in names:
            if n.endswith(".py") and "/llm" not in top:
                with open(f"{top}/{n}") as f:
                    assert "llm" not in f.read()
