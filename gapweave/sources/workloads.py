"""The experiment workloads: which table is a collection of series, on which grid, in which windows."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .tables import read_table


@dataclass(frozen=True)
class SeriesSpec:
    """A series table: key, time, value, grid step in seconds, fold of readings in a slot, window length.

    Key and value are SQL expressions that read the same in Spark and DuckDB. Without a time column the slot is
    ``slot`` itself.
    """

    table: str
    key: str
    value: str
    fold: str
    w: int
    time: str | None = None
    step: int = 1
    slot: str | None = None


DAY = 86400
WORKLOADS = {
    "supplier_week": SeriesSpec("lineitem", "l_suppkey", "l_quantity", "avg", 8, "l_shipdate", 7 * DAY),
    "user_halfday": SeriesSpec("events", "user_id", "value", "avg", 6, "ts", DAY // 2),
    "user_day": SeriesSpec("events", "user_id", "value", "avg", 10, "ts", DAY),
    "flag_day": SeriesSpec("lineitem", "l_returnflag || l_linestatus", "l_quantity", "sum", 28, "l_shipdate", DAY),
    "type_hour_value": SeriesSpec("events", "event_type", "value", "avg", 24, "ts", 3600),
    "type_hour_count": SeriesSpec("events", "event_type", "1.0", "sum", 24, "ts", 3600),
    "type_15min": SeriesSpec("events", "event_type", "value", "avg", 96, "ts", 900),
    "priority_day": SeriesSpec("orders", "o_orderpriority", "o_totalprice", "avg", 8, "o_orderdate", DAY),
    "turn_length": SeriesSpec("conversations", "conv_id", "length(text)", "avg", 4, slot="turn"),
}


def readings(spark: SparkSession, folder: str, spec: SeriesSpec) -> DataFrame:
    """(series_id, at, value): the three columns that a workload reads, times as microseconds or slot numbers."""
    df = read_table(spark, folder, spec.table)
    at = F.unix_micros(F.col(spec.time).cast("timestamp")) if spec.time else F.expr(spec.slot).cast("long")
    return df.select(F.expr(spec.key).cast("string").alias("series_id"), at.alias("at"), F.expr(spec.value).cast("double").alias("value"))


def embedding_windows(spark: SparkSession, folder: str, w: int = 64) -> DataFrame:
    """Vectors as complete sequences, positions standing for time."""
    df = read_table(spark, folder, "embeddings").where(F.size("embedding") == w)
    return df.select(F.col("vec_id").cast("string").alias("series_id"), F.lit(0).cast("long").alias("win"), F.transform("embedding", lambda v: v.cast("double")).alias("x"))


# ---- the same in DuckDB ---------------------------------------------------------------------------------------


def slots_sql(spec: SeriesSpec) -> str:
    """CTEs that end in slots(series_id, slot, value)."""
    slot = f"CAST(floor(epoch({spec.time}) / {spec.step}) AS BIGINT)" if spec.time else f"CAST({spec.slot} AS BIGINT)"
    return f"""raw AS (SELECT CAST({spec.key} AS VARCHAR) AS series_id, {slot} AS s, CAST({spec.value} AS DOUBLE) AS v FROM {spec.table}),
 slots AS (SELECT series_id, s - (SELECT min(s) FROM raw) AS slot, {spec.fold}(v) AS value FROM raw WHERE v IS NOT NULL GROUP BY series_id, s)"""


def grid_sql(spec: SeriesSpec) -> str:
    """CTEs that end in grid(series_id, win, pos, value): every slot of every whole window, also the empty ones."""
    return f"""{slots_sql(spec)},
 grid AS (SELECT k.series_id, n.win, p.pos, s.value
  FROM (SELECT DISTINCT series_id FROM slots) k
  CROSS JOIN (SELECT unnest(range((max(slot) + 1) // {spec.w})) AS win FROM slots) n
  CROSS JOIN (SELECT unnest(range({spec.w})) AS pos) p
  LEFT JOIN slots s ON s.series_id = k.series_id AND s.slot = n.win * {spec.w} + p.pos)"""


def windows_sql(spec: SeriesSpec) -> str:
    """CTEs that end in wins(series_id, win, n_obs, word, mu, sd) beside grid; one-word masks."""
    return f"""{grid_sql(spec)},
 wins AS (SELECT series_id, win, count(value) AS n_obs, CAST(sum(CASE WHEN value IS NOT NULL AND pos < 63 THEN 1::BIGINT << pos ELSE 0 END) AS BIGINT) AS word,
  avg(value) AS mu, stddev_pop(value) AS sd FROM grid GROUP BY series_id, win)"""
