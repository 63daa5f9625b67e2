"""Relational operators that users need around the methods. The SQL text runs in both engines where dialects agree."""

from __future__ import annotations

import re

import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.hashing import draw, draw_sql
from ..sources.tables import read_table
from .windows import W, slots, wins

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "embeddings", "conversations", "documents", "labels")

#: name -> (SQL of both engines, or Spark's and DuckDB's); {table} stands for a table.
SQL: dict[str, str | tuple[str, str]] = {
    "scan_projected": "SELECT l_orderkey, l_linenumber, l_quantity FROM {lineitem} WHERE l_quantity > 45",
    "filter_range": "SELECT o_orderkey, o_totalprice FROM {orders} WHERE o_totalprice BETWEEN 1000 AND 50000 AND o_orderdate >= TIMESTAMP '1997-01-01 00:00:00'",
    "filter_in_like": "SELECT p_partkey, p_brand, p_type FROM {part} WHERE p_size IN (1, 5, 9, 13) AND p_brand LIKE 'Brand#1%'",
    "nulls_safe_eq": "SELECT count(*) AS n, count(CASE WHEN a.s_nationkey IS NOT DISTINCT FROM b.s_nationkey THEN 1 END) AS same FROM {supplier} a JOIN {supplier} b ON a.s_suppkey = b.s_suppkey",
    "case_when": "SELECT CASE WHEN l_quantity < 10 THEN 'low' WHEN l_quantity < 40 THEN 'mid' ELSE 'high' END AS level, count(*) AS n FROM {lineitem} GROUP BY 1",
    "join_inner": "SELECT n.n_name AS nation, count(*) AS n FROM {lineitem} l JOIN {supplier} s ON s.s_suppkey = l.l_suppkey JOIN {nation} n ON n.n_nationkey = s.s_nationkey GROUP BY 1",
    "join_left": "SELECT s.s_suppkey, count(l.l_orderkey) AS n FROM {supplier} s LEFT JOIN (SELECT * FROM {lineitem} WHERE l_quantity = 50) l ON l.l_suppkey = s.s_suppkey GROUP BY 1",
    "join_full": "SELECT coalesce(a.k, b.k) AS k, coalesce(a.n, -1) AS a, coalesce(b.n, -1) AS b FROM (SELECT l_suppkey % 50 AS k, count(*) AS n FROM {lineitem} GROUP BY 1) a FULL JOIN (SELECT 25 + user_id % 50 AS k, count(*) AS n FROM {events} GROUP BY 1) b ON a.k = b.k",
    "join_semi": ("SELECT c_custkey FROM {customer} LEFT SEMI JOIN {orders} ON o_custkey = c_custkey AND o_totalprice > 300000", "SELECT c_custkey FROM {customer} WHERE EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey AND o_totalprice > 300000)"),
    "join_anti": ("SELECT c_custkey FROM {customer} LEFT ANTI JOIN {orders} ON o_custkey = c_custkey", "SELECT c_custkey FROM {customer} WHERE NOT EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey)"),
    "join_cross": "SELECT r.r_name, t.event_type, count(*) AS n FROM {region} r CROSS JOIN (SELECT DISTINCT event_type FROM {events}) t GROUP BY 1, 2",
    "join_theta": "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM {nation} a JOIN {nation} b ON a.n_nationkey < b.n_nationkey AND a.n_regionkey = b.n_regionkey",
    "join_lateral": "SELECT s.s_suppkey, t.q FROM {supplier} s, LATERAL (SELECT max(l.l_quantity) AS q FROM {lineitem} l WHERE l.l_suppkey = s.s_suppkey) t",
    "agg_basic": "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(l_quantity AS DECIMAL(18,2))) AS DOUBLE) AS total, min(l_quantity) AS least, max(l_quantity) AS most FROM {lineitem} GROUP BY 1, 2",
    "agg_distinct": "SELECT event_type, count(DISTINCT user_id) AS users, count(*) AS n FROM {events} GROUP BY 1",
    "agg_filter": "SELECT event_type, count(*) FILTER (WHERE value > 50) AS above, count(*) FILTER (WHERE value <= 50) AS under FROM {events} GROUP BY 1",
    "agg_cube": "SELECT l_returnflag, l_linestatus, count(*) AS n FROM {lineitem} GROUP BY CUBE (l_returnflag, l_linestatus)",
    "agg_rollup": "SELECT r_name, n_name, count(*) AS n FROM {nation} JOIN {region} ON r_regionkey = n_regionkey GROUP BY ROLLUP (r_name, n_name)",
    "agg_sets": "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM {orders} GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())",
    "agg_stats": "SELECT event_type, round(stddev_samp(value), 4) AS sd, round(var_pop(value), 4) AS v, round(corr(value, user_id), 4) AS c, round(covar_pop(value, user_id), 3) AS cv FROM {events} GROUP BY 1",
    "agg_bit": ("SELECT event_type, bit_or(user_id) AS o, bit_and(user_id) AS a, bit_xor(user_id) AS x FROM {events} GROUP BY 1", "SELECT event_type, bit_or(user_id) AS o, bit_and(user_id) AS a, bit_xor(user_id) AS x FROM {events} GROUP BY 1"),
    "agg_min_by": ("SELECT l_suppkey, max_by(l_orderkey, struct(l_quantity, l_orderkey, l_linenumber)) AS k FROM {lineitem} GROUP BY 1", "SELECT l_suppkey, arg_max(l_orderkey, struct_pack(a := l_quantity, b := l_orderkey, c := l_linenumber)) AS k FROM {lineitem} GROUP BY 1"),
    "agg_median": ("SELECT event_type, round(percentile(value, 0.5), 6) AS med FROM {events} GROUP BY 1", "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS med FROM {events} GROUP BY 1"),
    "agg_having": "SELECT l_suppkey, count(*) AS n FROM {lineitem} GROUP BY 1 HAVING count(*) > 600",
    "win_rank": "SELECT o_orderkey, rank() OVER w AS r, dense_rank() OVER w AS dr, ntile(4) OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice, o_orderkey) AS q FROM {orders} WINDOW w AS (PARTITION BY o_orderpriority ORDER BY o_totalprice)",
    "win_lag": "SELECT event_id, coalesce(lag(event_id) OVER w, -1) AS before, coalesce(lead(event_id, 2) OVER w, -1) AS after FROM {events} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
    "win_rows": "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND 1 FOLLOWING) AS n, max(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS m FROM {events}",
    "win_range": ("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY unix_micros(CAST(ts AS TIMESTAMP)) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS n FROM {events}", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS n FROM {events}"),
    "topk_per_group": "SELECT l_suppkey, l_orderkey, l_linenumber FROM (SELECT *, row_number() OVER (PARTITION BY l_suppkey ORDER BY l_quantity DESC, l_orderkey, l_linenumber) AS k FROM {lineitem}) t WHERE k <= 3",
    "topk_sort_limit": "SELECT o_orderkey, o_totalprice FROM {orders} ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 5",
    "set_union": "SELECT l_suppkey AS k FROM {lineitem} WHERE l_quantity = 1 UNION SELECT s_suppkey FROM {supplier} WHERE s_acctbal > 5000",
    "set_intersect": "SELECT o_custkey AS k FROM {orders} WHERE o_orderstatus = 'F' INTERSECT SELECT o_custkey FROM {orders} WHERE o_orderstatus = 'O'",
    "set_except": "SELECT c_custkey AS k FROM {customer} EXCEPT SELECT o_custkey FROM {orders}",
    "fn_string": "SELECT p_partkey, upper(p_brand) AS u, substring(p_type, 1, 3) AS s, length(p_name) AS n, concat_ws('|', p_brand, p_type) AS c, md5(p_name) AS m, regexp_replace(p_brand, '[0-9]+', '') AS r FROM {part}",
    "fn_date": ("SELECT o_orderkey, extract(YEAR FROM o_orderdate) AS y, extract(MONTH FROM o_orderdate) AS m, CAST(CAST(date_trunc('MONTH', o_orderdate) AS DATE) AS VARCHAR(10)) AS t, CAST(CAST(o_orderdate + INTERVAL 7 DAYS AS DATE) AS VARCHAR(10)) AS d FROM {orders}", "SELECT o_orderkey, CAST(extract(YEAR FROM o_orderdate) AS INTEGER) AS y, CAST(extract(MONTH FROM o_orderdate) AS INTEGER) AS m, CAST(CAST(date_trunc('MONTH', o_orderdate) AS DATE) AS VARCHAR(10)) AS t, CAST(CAST(o_orderdate + INTERVAL 7 DAYS AS DATE) AS VARCHAR(10)) AS d FROM {orders}"),
    "fn_math": "SELECT event_id, round(ln(value + 1), 6) AS l, round(sqrt(value), 6) AS q, round(pow(value, 2), 4) AS p, greatest(value, 50.0) AS g, least(value, 50.0) AS s FROM {events} WHERE value >= 0",
    "fn_json": ("SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM {events}", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM {events}"),
    "fn_array": ("SELECT vec_id, round(aggregate(transform(embedding, v -> CAST(v AS DOUBLE) * v), 0D, (a, v) -> a + v), 4) AS norm, size(filter(embedding, v -> v > 0)) AS positive, round(CAST(array_max(slice(embedding, 1, 8)) AS DOUBLE), 5) AS head FROM {embeddings}", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda v: v::DOUBLE * v::DOUBLE)), 4) AS norm, CAST(len(list_filter(embedding, lambda v: v > 0)) AS INTEGER) AS positive, round(list_max(embedding[1:8])::DOUBLE, 5) AS head FROM {embeddings}"),
    "fn_map": ("SELECT event_type, map_from_arrays(array('a', 'b'), array(min(event_id), max(event_id)))['b'] AS b FROM {events} GROUP BY event_type", "SELECT event_type, map(['a', 'b'], [min(event_id), max(event_id)])['b'] AS b FROM {events} GROUP BY event_type"),
    "fn_bits": ("SELECT user_id, user_id & 12 AS a, user_id | 3 AS o, shiftleft(user_id, 2) AS l, CAST(bit_count(user_id) AS INT) AS c FROM (SELECT DISTINCT user_id FROM {events}) t", "SELECT user_id, user_id & 12 AS a, user_id | 3 AS o, user_id << 2 AS l, CAST(bit_count(user_id) AS INTEGER) AS c FROM (SELECT DISTINCT user_id FROM {events}) t"),
    "sub_scalar": "SELECT event_id FROM {events} WHERE value > (SELECT avg(value) FROM {events})",
    "sub_exists": "SELECT s_suppkey FROM {supplier} s WHERE EXISTS (SELECT 1 FROM {lineitem} l WHERE l.l_suppkey = s.s_suppkey AND l.l_quantity = 50)",
    "sub_correlated": "SELECT o_orderkey FROM {orders} o WHERE o_totalprice > (SELECT avg(i.o_totalprice) FROM {orders} i WHERE i.o_orderpriority = o.o_orderpriority)",
    "cte_chain": "WITH a AS (SELECT l_suppkey AS k, count(*) AS n FROM {lineitem} GROUP BY 1), b AS (SELECT k % 10 AS g, sum(n) AS n FROM a GROUP BY 1) SELECT g, CAST(n AS BIGINT) AS n FROM b WHERE n > 10",
    "union_by_name": ("SELECT 'o' AS kind, count(*) AS n FROM {orders} UNION ALL SELECT 'e', count(*) FROM {events}", "SELECT 'o' AS kind, count(*) AS n FROM {orders} UNION ALL SELECT 'e', count(*) FROM {events}"),
}


def _run(text: str):
    used = sorted(set(re.findall(r"\{(\w+)\}", text)))
    return lambda s, d: s.sql(text, **{t: read_table(s, d, t) for t in used})


def agg_pivot(s, d):
    return read_table(s, d, "orders").groupBy("o_orderstatus").pivot("o_orderpriority", ["1-URGENT", "2-HIGH"]).agg(F.count(F.lit(1))).withColumnsRenamed({"1-URGENT": "urgent", "2-HIGH": "high"})


def agg_unpivot(s, d):
    return read_table(s, d, "supplier").selectExpr("s_suppkey", "cast(s_nationkey as double) AS nation", "s_acctbal AS balance").unpivot("s_suppkey", ["nation", "balance"], "field", "number")


def agg_approx(s, d):
    """Approximate distinct users, within 5 % of the exact count."""
    e = read_table(s, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id", 0.01).alias("a"), F.countDistinct("user_id").alias("n"))
    return e.select("event_type", (F.abs(F.col("a") - F.col("n")) <= 0.05 * F.col("n")).alias("near"))


def _cells(s, d):
    return wins(s, d).select("series_id", "win", F.posexplode("x").alias("pos", "value")).select("series_id", (F.col("win") * W + F.col("pos")).alias("slot"), "value")


def win_locf(s, d):
    by = Window.partitionBy("series_id").orderBy("slot")
    return _cells(s, d).select("series_id", "slot", F.round(F.last("value", ignorenulls=True).over(by), 6).alias("carried"), F.round(F.first("value", ignorenulls=True).over(by.rowsBetween(0, Window.unboundedFollowing)), 6).alias("next"))


def win_running(s, d):
    """Running observed shares in hash order, as admission sums them."""
    by = Window.partitionBy("series_id").orderBy(draw(103, "series_id", "win"), "win")
    w = wins(s, d).withColumn("g", F.col("n_obs") / F.lit(float(W)))
    return w.select("series_id", "win", F.round(F.sum("g").over(by.rowsBetween(Window.unboundedPreceding, 0)), 6).alias("running"))


def join_asof(s, d):
    """The last reading of a supplier at or before each of the window starts: equi-join on the bucket, then max_by."""
    left = wins(s, d).where("n_obs < 8").select("series_id", "win", (F.col("win") * W + 3).alias("at"))
    both = left.select("series_id", F.col("at").alias("slot"), "win", F.lit(None).cast("double").alias("value"), F.lit(1).alias("ask")).unionByName(slots(s, d).select("series_id", "slot", F.lit(None).cast("long").alias("win"), "value", F.lit(0).alias("ask")))
    by = Window.partitionBy("series_id").orderBy("slot", "ask").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("last", F.last("value", ignorenulls=True).over(by)).where("ask = 1").select("series_id", "win", F.round("last", 6).alias("last"))


def join_range(s, d):
    """Slots inside each series' longest gap's neighbourhood: a range join, bucketed by window."""
    from ..operators.gaps import gap_runs

    runs = gap_runs(_cells(s, d)).where("length >= 3").select("series_id", "start", (F.col("start") + F.col("length")).alias("stop"))
    near = runs.withColumn("b", F.explode(F.sequence(F.floor((F.col("start") - 2) / 64), F.floor((F.col("stop") + 2) / 64))))
    cells = slots(s, d).withColumn("b", F.floor(F.col("slot") / 64))
    j = cells.join(near, ["series_id", "b"]).where((F.col("slot") >= F.col("start") - 2) & (F.col("slot") < F.col("stop") + 2))
    return j.select("series_id", "start", "slot", F.round("value", 6).alias("value"))


def join_interval(s, d):
    """Pairs of events of one user within an hour, bucketed by hour."""
    e = read_table(s, d, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    hour = 3_600_000_000
    a = e.select(F.col("event_id").alias("a"), "user_id", F.col("t").alias("ta"), F.floor(F.col("t") / hour).alias("h"))
    b = e.select(F.col("event_id").alias("b"), "user_id", F.col("t").alias("tb"), F.explode(F.array(F.floor(F.col("t") / hour), F.floor(F.col("t") / hour) - 1)).alias("h"))
    j = a.join(b, ["user_id", "h"]).where((F.col("a") != F.col("b")) & (F.col("tb") >= F.col("ta")) & (F.col("tb") - F.col("ta") <= hour))
    return j.select("a", "b").distinct()


def sample_by_hash(s, d):
    return read_table(s, d, "orders").where(draw(42, "o_orderkey") < 0.1 * (1 << 32)).select("o_orderkey")


def udf_gap_dtw(s, d):
    """Warping distance of each window to the one before, by a pandas UDF over pairs."""
    from ..functions.gapdtw import gap_dtw
    import numpy as np

    @F.pandas_udf("double")
    def dist(x: pd.Series, y: pd.Series) -> pd.Series:
        if not len(x):
            return pd.Series([], dtype=float)
        return pd.Series(gap_dtw(np.array([np.array(v, dtype=float) for v in x]), np.array([np.array(v, dtype=float) for v in y])))

    z = wins(s, d)
    prev = z.select("series_id", (F.col("win") + 1).alias("win"), F.col("x").alias("y"))
    return z.join(prev, ["series_id", "win"]).select("series_id", "win", F.round(dist("x", "y"), 4).alias("dist"))


def udtf_readings(s, d):
    """A Python UDTF that opens a window into readings."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="slot: bigint, value: double")
    class Readings:
        def eval(self, win: int, x: list):
            for i, v in enumerate(x):
                if v is not None:
                    yield win * W + i, v

    s.udtf.register("window_readings", Readings)
    return s.sql("SELECT w.series_id, r.slot, round(r.value, 6) AS value FROM {w} w, LATERAL window_readings(w.win, w.x) r", w=wins(s, d))


def sql_surface(s, d):
    """The framework's functions called from SQL, on the line items by discount and tax."""
    from ..plans.pipeline import register

    register(s)
    return s.sql(_SURFACE, lineitem=read_table(s, d, "lineitem"))


_GROUPS = "SELECT l_discount AS eps, l_tax AS delta, count(*) AS n, min(l_quantity) AS least, max(l_quantity) AS most FROM {lineitem} WHERE l_discount > 0 AND l_tax > 0 GROUP BY 1, 2"
_SURFACE = f"SELECT eps, delta, n, round(sample_need(eps, delta), 4) AS need, round(gap_dtw(array(least, NULL, most), array(most, least, least)), 4) AS dist, size(mask_schedule(eps, 1D, 6)) AS steps FROM ({_GROUPS}) g"


QUERIES = {
    **{k: _run(v if isinstance(v, str) else v[0]) for k, v in SQL.items()},
    "scan_parquet": lambda s, d: read_table(s, d, "lineitem").agg(F.count("*").alias("n"), F.max("l_orderkey").alias("top")),
    "agg_pivot": agg_pivot,
    "agg_unpivot": agg_unpivot,
    "agg_approx": agg_approx,
    "win_locf": win_locf,
    "win_running_gamma": win_running,
    "join_asof": join_asof,
    "join_range": join_range,
    "join_interval": join_interval,
    "sample_by_hash": sample_by_hash,
    "udf_gap_dtw": udf_gap_dtw,
    "udtf_readings": udtf_readings,
    "sql_surface": sql_surface,
}


def _oracles() -> dict[str, str]:
    from ..sources.workloads import WORKLOADS, slots_sql, windows_sql

    a = WORKLOADS["supplier_week"]
    cells = f"WITH {windows_sql(a)}, cells AS (SELECT series_id, win * {W} + pos AS slot, value FROM grid)"
    out = {k: re.sub(r"\{(\w+)\}", r"\1", v if isinstance(v, str) else v[1]) for k, v in SQL.items()}
    return out | {
        "scan_parquet": "SELECT count(*) AS n, max(l_orderkey) AS top FROM lineitem",
        "agg_pivot": "SELECT o_orderstatus, nullif(count(*) FILTER (WHERE o_orderpriority = '1-URGENT'), 0) AS urgent, nullif(count(*) FILTER (WHERE o_orderpriority = '2-HIGH'), 0) AS high FROM orders GROUP BY 1",
        "agg_unpivot": "SELECT s_suppkey, 'nation' AS field, CAST(s_nationkey AS DOUBLE) AS number FROM supplier UNION ALL SELECT s_suppkey, 'balance', s_acctbal FROM supplier",
        "agg_approx": "SELECT DISTINCT event_type, true AS near FROM events",
        "win_locf": f"{cells} SELECT series_id, slot, round(last_value(value IGNORE NULLS) OVER (PARTITION BY series_id ORDER BY slot ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 6) AS carried, round(first_value(value IGNORE NULLS) OVER (PARTITION BY series_id ORDER BY slot ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING), 6) AS next FROM cells",
        "win_running_gamma": f"WITH {windows_sql(a)} SELECT series_id, win, round(sum(n_obs / {float(W)}) OVER (PARTITION BY series_id ORDER BY {draw_sql(103, 'series_id', 'win')}, win ROWS UNBOUNDED PRECEDING), 6) AS running FROM wins",
        "join_asof": f"WITH {windows_sql(a)} SELECT w.series_id, w.win, round(s.value, 6) AS last FROM (SELECT series_id, win, win * {W} + 3 AS at FROM wins WHERE n_obs < 8) w ASOF LEFT JOIN slots s ON s.series_id = w.series_id AND w.at >= s.slot",
        "join_range": f"{cells}, isl AS (SELECT *, slot - row_number() OVER (PARTITION BY series_id, value IS NULL ORDER BY slot) AS island FROM cells), runs AS (SELECT series_id, min(slot) AS start, count(*) AS length FROM isl WHERE value IS NULL GROUP BY series_id, island HAVING count(*) >= 3) SELECT r.series_id, r.start, s.slot, round(s.value, 6) AS value FROM runs r JOIN slots s ON s.series_id = r.series_id AND s.slot >= r.start - 2 AND s.slot < r.start + r.length + 2",
        "join_interval": "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id <> b.event_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR",
        "sample_by_hash": f"SELECT o_orderkey FROM orders WHERE {draw_sql(42, 'o_orderkey')} < 0.1 * 4294967296",
        "udtf_readings": f"WITH {slots_sql(a)} SELECT series_id, slot, round(value, 6) AS value FROM slots WHERE slot < (SELECT (max(slot) + 1) // {W} * {W} FROM slots)",
        "sql_surface": f"SELECT eps, delta, n, round((3 * ln(1 / eps) + ln(1 / delta)) / eps, 4) AS need, round(sqrt(2 * (most - least) * (most - least) * 6 / 5.0), 4) AS dist, CAST(len(list_filter(range(6), lambda i: eps * pow(2.0, i) < 1)) AS INTEGER) AS steps FROM ({_GROUPS.replace('{lineitem}', 'lineitem')})",
    }


ORACLES = _oracles()
