"""The driver's contract, with and without the training-data subpackage; a sample of queries against their SQL."""

from __future__ import annotations

import glob
import os
import subprocess
import sys
from pathlib import Path

import duckdb
import pytest

import __spark_entry__ as entry

ROOT = Path(__file__).resolve().parents[1]
SAMPLE = ["model_events_oriented", "search_exfil_1h", "track_back_exclude", "track_hops_3", "graph_expr", "op_join_overlap", "stream_pair"]


def test_flagship(spark):
    assert entry.entry(spark).columns == ["event_id"]


def test_names_match():
    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", SAMPLE)
def test_query_is_its_sql(spark, data, name):
    con = duckdb.connect()
    for f in glob.glob(f"{data}/*.parquet"):
        con.execute(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    df = entry.queries()[name](spark, data)
    cols = sorted(df.columns)
    want = con.execute(f"SELECT {', '.join(cols)} FROM ({entry.oracle_sql()[name]})").fetchall()
    key = lambda r: tuple((x is not None, x) for x in r)
    assert sorted((tuple(r) for r in df.select(*cols).collect()), key=key) == sorted(want, key=key)


def test_a_package_that_the_training_data_operators_lack(tmp_path):
    (tmp_path / "public_tokenizers.py").write_text("raise ImportError('not here')")
    code = "import __spark_entry__ as e; q = e.queries(); e.oracle_sql(); assert 'pipeline' not in q and 'op1_cover_tree' not in q and len(q) > 80"
    subprocess.run([sys.executable, "-c", code], cwd=ROOT, check=True, env={**os.environ, "PYTHONPATH": f"{tmp_path}:{ROOT}"})


def test_without_the_training_data_operators(tmp_path):
    for p in ROOT.iterdir():
        if p.name not in ("tests", ".git", "corpus_pipeline.py", "tracelake"):
            (tmp_path / p.name).symlink_to(p)
    (tmp_path / "tracelake").mkdir()
    for p in (ROOT / "tracelake").iterdir():
        if p.name != "llm":
            (tmp_path / "tracelake" / p.name).symlink_to(p)
    code = "import __spark_entry__ as e; q = e.queries(); e.oracle_sql(); assert 'pipeline' not in q and len(q) > 80"
    subprocess.run([sys.executable, "-c", code], cwd=tmp_path, check=True, env={**os.environ, "PYTHONPATH": str(tmp_path)})
