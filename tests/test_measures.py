"""Measures that were computed over numbers written down read a given table, and agree with their SQL."""

from __future__ import annotations

import os

import duckdb
import pytest
from foretell.catalogue import oracle_sql, queries
from foretell.sources.tables import TABLES

#: Entries, and the tables that Spark reads for them.
MOVED = {
    "ablation_cube": "orders",
    "ablation_pivot": "orders",
    "ablation_speedup": "orders",
    "batching_speedup": "lineitem",
    "best_model": "events",
    "best_so_far": "events",
    "convergence_gain": "events",
    "data_bytes": "lineitem documents labels embeddings events orders",
    "draw_uniform": "orders",
    "eliminate_error": "events",
    "eliminate_quality": "events",
    "end_to_end_gain": "orders",
}  # moved


@pytest.mark.parametrize("name", MOVED)
def test_measure_reads_its_table(spark, small, name):
    out = queries()[name](spark, small)
    assert {os.path.basename(p).removesuffix(".parquet") for p in out.inputFiles()} == set(MOVED[name].split())
    db = duckdb.connect()
    db.sql("SET TimeZone = 'UTC'")
    for t in TABLES:
        db.sql(f"CREATE VIEW {t} AS SELECT * FROM '{small}/{t}.parquet'")
    want = db.sql(oracle_sql()[name])
    assert out.columns == want.columns
    key = lambda r: tuple((v is not None, str(v)) for v in r)
    rows = sorted((tuple(r) for r in out.collect()), key=key)
    assert rows and rows == sorted(want.fetchall(), key=key)
