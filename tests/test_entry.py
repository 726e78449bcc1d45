"""The driver's contract, and a sample of queries against their SQL."""

import os

import duckdb
import pytest

import __spark_entry__ as entry
from tools.compare import TABLES, rows_of

SF = "/root/testdata/sf0.001"
pytestmark = pytest.mark.skipif(not os.path.isdir(SF), reason="the given tables are not here")
SAMPLE = ["km_moves_lineitem", "km_k4_localized_buffered", "pr_delta_pages", "pr_classic_trade", "mm_padded", "sort_all_pairs", "overlap_cover", "once_rollup", "once_asof", "shard_cover_range", "stream_windows", "stream_sessions", "stream_minibatch_km"]


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return c


def test_names():
    q, s = entry.queries(), entry.oracle_sql()
    assert set(s) <= set(q) and len(q) > 90


def test_without_the_llm_folder(tmp_path):
    """The rest works where the subpackage is gone, whether the pipeline is or not."""
    import shutil
    import subprocess
    import sys

    top = os.path.dirname(os.path.abspath(entry.__file__))
    shutil.copytree(f"{top}/quiesce", tmp_path / "quiesce", ignore=shutil.ignore_patterns("llm", "__pycache__"))
    for name in ("__spark_entry__.py", "corpus_pipeline.py"):
        if os.path.exists(f"{top}/{name}"):
            shutil.copy(f"{top}/{name}", tmp_path)
    code = "import __spark_entry__ as e; q = e.queries(); s = e.oracle_sql(); print(len(q) > 90 and 'pipeline' not in q and set(s) <= set(q))"
    out = subprocess.run([sys.executable, "-c", code], cwd=tmp_path, capture_output=True, text=True)
    assert out.stdout.strip().endswith("True"), out.stderr


def test_flagship(spark):
    df = entry.entry(spark)
    assert df.columns == ["id", "pr"] and df.count() > 0


@pytest.mark.parametrize("name", SAMPLE)
def test_equals_sql(spark, con, name):
    df = entry.queries()[name](spark, SF)
    cur = con.execute(entry.oracle_sql()[name])
    columns = [c[0] for c in cur.description]
    assert sorted(columns) == sorted(df.columns)
    assert rows_of(columns, cur.fetchall()) == rows_of(df.columns, df.collect())
