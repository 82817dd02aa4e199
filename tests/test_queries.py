"""Every query that has SQL gives what the SQL gives, on the smallest tables."""

import os
import shutil
import subprocess
import sys

import duckdb
import numpy as np
import pytest

from linefault.plans import registry

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


#: Queries after detection that are also compared where the detector finds faults; the smallest tables hold too few tickets.
FITTED = ("c_detector", "w_faults", "m_scores_node", "q_xy", "q_window_overlap", "k_combined", "q_lift", "d_call", "st_life", "q_monitor")


def connected(folder):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{folder}/{t}.parquet'")
    return c


@pytest.fixture(scope="module")
def con(sf):
    return connected(sf)


def rows(df):
    def plain(v):
        if v is None or (isinstance(v, float) and v != v) or str(v) in ("NaT", "<NA>"):
            return ""
        return str(bool(v)) if isinstance(v, (bool, np.bool_)) else f"{float(v):.5f}" if isinstance(v, (int, float, np.number)) else str(v)

    return sorted(tuple(plain(v) for v in r) for r in df[sorted(df.columns)].itertuples(index=False))


@pytest.mark.parametrize("name", sorted(registry.SQL))
def test_query(spark, sf, con, name):
    got, want = registry.QUERIES[name](spark, sf).toPandas(), con.execute(registry.SQL[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


@pytest.mark.parametrize("name", FITTED)
def test_query_with_faults(spark, sf, name):
    folder = sf.replace("0.001", "0.01")
    got, want = registry.QUERIES[name](spark, folder).toPandas(), connected(folder).execute(registry.SQL[name]).df()
    assert len(want) and rows(got) == rows(want)


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() >= 0
    assert set(registry.QUERIES) <= set(__spark_entry__.queries())


def test_entry_survives_without_the_training_data_part(tmp_path):
    """A copy of the repository without the two folders and the pipeline still gives all other queries."""
    root = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))
    left_out = shutil.ignore_patterns("llm", ".git", "corpus_pipeline.py", "__pycache__")
    shutil.copytree(root, tmp_path / "repo", ignore=left_out)
    told = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; print(len(e.queries()), len(e.oracle_sql()), sum(n.startswith('op') for n in e.queries()))"], cwd=tmp_path / "repo", capture_output=True, text=True, check=True)
    assert told.stdout.split() == [str(len(registry.QUERIES)), str(len(registry.SQL)), "0"]
