"""Queries against their DuckDB twins on the smallest tables, as the driver compares them on larger ones."""

import os

import duckdb
import pytest

from gapweave import catalog

FAST = ["wl_supplier_week", "wl_type_hour_count", "zscore_windows", "lloyd_two_steps", "assign_first_choice", "pair_reuse", "structure_ratio", "masked_sets_counts", "mcar_exact_50", "mnar_value_50", "mnar_burst_50", "gap_runs", "impute_linear", "impute_locf", "pair_moments", "windows_needed", "waterfill_sizes", "join_asof", "join_interval", "agg_cube", "fn_array", "win_range"]
STREAMS = ["stream_tumbling", "stream_sessions", "stream_dedup", "stream_join", "stream_carry_forward"]


def plain(v):
    if isinstance(v, float):
        return None if v != v else v
    return v if v is None or isinstance(v, (int, str, bool)) else str(v)


@pytest.mark.parametrize("name", FAST + STREAMS)
def test_twin(spark, data, name):
    con = duckdb.connect()
    for f in os.listdir(data):
        con.sql(f"CREATE VIEW {f[:-8]} AS SELECT * FROM '{data}/{f}'")
    df = catalog.queries()[name](spark, data)
    cols = sorted(df.columns)
    got = sorted((tuple(plain(r[c]) for c in cols) for r in df.collect()), key=repr)
    res = con.sql(catalog.oracle_sql()[name])
    assert sorted(res.columns) == cols
    at = [res.columns.index(c) for c in cols]
    want = sorted((tuple(plain(r[i]) for i in at) for r in res.fetchall()), key=repr)
    assert [tuple(map(str, g)) for g in got] == [tuple(map(str, w)) for w in want] and got


def test_every_oracle_has_its_query():
    assert set(catalog.oracle_sql()) <= set(catalog.queries())
    assert len(catalog.queries()) > 150
