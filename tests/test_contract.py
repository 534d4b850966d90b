"""The driver's contract, and a sample of the queries against DuckDB."""

import glob
import math
from pathlib import Path

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
SAMPLE = ["exact_knn10", "lift_exact_h2", "refine_round1", "thin_kept_k16", "fused_exact_h2", "repair_scc", "composition_h3", "rank_family", "win_session"]


def rows(names, values):
    order = sorted(range(len(names)), key=lambda i: names[i])
    shown = lambda v: None if v is None or (isinstance(v, float) and math.isnan(v)) else float(v) if isinstance(v, int | float) and not isinstance(v, bool) else str(v)
    return sorted((tuple(shown(r[i]) for i in order) for r in values), key=repr)


@pytest.mark.parametrize("name", SAMPLE)
def test_query_equals_sql(spark, name):
    con = duckdb.connect()
    for f in glob.glob(f"{SF}/*.parquet"):
        con.sql(f"CREATE VIEW {Path(f).stem} AS SELECT * FROM '{f}'")
    got = entry.queries()[name](spark, SF)
    want = con.sql(entry.oracle_sql()[name])
    assert rows(got.columns, got.collect()) == rows(want.columns, want.fetchall())


def test_entry_and_names(spark):
    assert entry.entry(spark).count() > 0
    assert set(entry.oracle_sql()) <= set(entry.queries())
