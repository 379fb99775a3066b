"""A sample of the registered queries against their SQL, and the entry module without the optional subpackage."""

import subprocess
import sys
from pathlib import Path

import duckdb
import pytest

from kernmill.workloads import oracles, tables

ROOT = Path(__file__).resolve().parents[1]
SAMPLE = ["gram_rbf", "sweep_scores", "fit_mixed_15d_k10", "fit_tile_2d_k10", "empty_origin", "wide28_points", "userfeat_fit_k4", "lobes_poly", "cost_table", "asof_label_events", "stream_tumbling", "stream_dedup", "report_cube", "traffic_all", "empty_reseed", "sweep_sqdist", "means_by_tile", "cost_table_function", "rolling_events", "stream_late"]


def plain(v):
    return repr(v) if isinstance(v, float) else str(v)


@pytest.mark.parametrize("name", SAMPLE)
def test_query_equals_sql(spark, sf_dir, name):
    con = duckdb.connect()
    for t in ("customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf_dir}/{t}.parquet')")
    got = tables.QUERIES[name](spark, sf_dir)
    want = con.sql(oracles.ORACLES[name])
    cols = sorted(got.columns)
    assert sorted(want.columns) == cols
    at = [want.columns.index(c) for c in cols]
    assert sorted(tuple(plain(r[c]) for c in cols) for r in got.collect()) == sorted(tuple(plain(r[i]) for i in at) for r in want.fetchall())


def test_every_oracle_has_a_query():
    assert set(oracles.ORACLES) <= set(tables.QUERIES)


def test_entry_imports():
    out = subprocess.run([sys.executable, "-c", "import __spark_entry__ as e; print(len(e.queries()) >= len(e.oracle_sql()))"], cwd=ROOT, capture_output=True, text=True, check=True)
    assert out.stdout.strip().endswith("True")
