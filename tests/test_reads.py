"""Queries that once made their rows up: they read a given table, agree with their twins, and keep the literal cases."""

import os

import duckdb
import pytest
from pyspark.sql import functions as F

from gapweave import catalog
from gapweave.operators import minmask, series
from tests.test_twins import plain

MOVED = ["mask_argmin", "mask_last_within", "mask_search_rule", "mask_schedule", "sample_need", "sql_surface", "worked_example"]


@pytest.mark.parametrize("name", MOVED)
def test_reads_the_line_items(spark, data, name):
    df = catalog.queries()[name](spark, data)
    assert [os.path.basename(f) for f in df.inputFiles()].count("lineitem.parquet")
    con, cols = duckdb.connect(), sorted(df.columns)
    con.sql(f"CREATE VIEW lineitem AS SELECT * FROM '{data}/lineitem.parquet'")
    res = con.sql(catalog.oracle_sql()[name])
    at = [res.columns.index(c) for c in cols]
    want = sorted((tuple(map(str, (plain(r[i]) for i in at))) for r in res.fetchall()), key=repr)
    assert sorted((tuple(map(str, (plain(r[c]) for c in cols))) for r in df.collect()), key=repr) == want and want


def test_literal_row_of_nineteen_slots(spark):
    x = [10, None, 7, None, 6, 8, None, None, 14, 12, None, 9, 8, 7, None, 10, 13, None, 14]
    df = spark.createDataFrame([("1", 0, [None if v is None else float(v) for v in x])], "series_id string, win long, x array<double>")
    r = series.described(df, 19).first()
    assert (r.n_obs, r.words[0]) == (12, sum(1 << i for i, v in enumerate(x) if v is not None))


TRACE = [(0, 0, 0.01, 0.5, 0.2), (0, 1, 0.02, 0.1, 0.2), (0, 2, 0.04, 0.15, 0.2), (0, 3, 0.08, 0.6, 0.2), (1, 0, 0.01, 0.9, 0.1), (1, 1, 0.02, 0.4, 0.1), (1, 2, 0.04, 0.4, 0.1), (2, 0, 0.01, 0.05, 0.1), (2, 1, 0.02, 0.05, 0.1), (2, 2, 0.04, 0.3, 0.1)]


@pytest.mark.parametrize("rule, want", [("first_within", [(0, 1, True), (1, 1, False), (2, 0, True)]), ("last_within", [(0, 1, False), (1, 1, False), (2, 1, True)]), ("argmin", [(0, 1, False), (1, 1, False), (2, 0, False)])])
def test_rules_on_a_literal_trace(spark, rule, want):
    t = spark.createDataFrame(TRACE, "cluster int, step int, mask double, gap double, limit double")
    got = sorted((r.cluster, r.step, r.within) for r in minmask.pick_mask(t, rule).collect())
    assert got == want


def test_a_step_without_a_limit_is_not_within(spark):
    t = spark.createDataFrame([(0, 0, 0.01, 0.5, None), (0, 1, 0.02, 0.1, 0.2)], "cluster int, step int, mask double, gap double, limit double")
    assert minmask.pick_mask(t, "last_within").select("within").first()[0] is False
    assert minmask.pick_mask(t.where(F.col("step") == 1), "last_within").select("within").first()[0] is True
