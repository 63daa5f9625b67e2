"""Queries of the window layer and of clustering: supplier weeks unless the name says otherwise."""

from __future__ import annotations

import uuid
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.gapdtw import distances_to, euclid_to, nearest
from ..functions.hashing import SEEDS, draw_sql, unit_sql
from ..operators import cluster, series
from ..sources.scratch import materialise
from ..sources.workloads import WORKLOADS, embedding_windows, slots_sql, windows_sql

A = WORKLOADS["supplier_week"]
W = A.w


def slots(spark: SparkSession, d: str, name: str = "supplier_week") -> DataFrame:
    return series.slots_of(spark, d, WORKLOADS[name])


def wins(spark: SparkSession, d: str, name: str = "supplier_week") -> DataFrame:
    return series.windows(slots(spark, d, name), WORKLOADS[name].w)


def z_wins(spark: SparkSession, d: str) -> DataFrame:
    return series.normalise(wins(spark, d))


def train_complete(spark: SparkSession, d: str) -> DataFrame:
    return z_wins(spark, d).where("complete").where(~series.holdout()).select("series_id", "win", "z")


def base_centroids(spark: SparkSession, d: str, k: int = 3) -> np.ndarray:
    """Two full k-means steps from the first k windows in hash order: the fixed clustering of the exact queries."""
    return cluster.lloyd(materialise(train_complete(spark, d), "complete"), k, iterations=2, init="hash")


class Base:
    """What the exact queries start from, made once a query: normalised windows, written, and the fixed clustering."""

    def __init__(self, spark: SparkSession, d: str) -> None:
        z = materialise(z_wins(spark, d).where(~series.holdout()), "windows")
        self.train = z.where("complete").select("series_id", "win", "z")
        self.gone = z.where("NOT complete AND n_obs > 0")
        self.centroids = cluster.lloyd(self.train, 3, iterations=2, init="hash")

    def complete(self) -> DataFrame:
        return cluster.cluster_sequences(self.train, self.centroids)

    def incomplete(self) -> DataFrame:
        near = nearest(euclid_to("z", self.centroids))
        return self.gone.withColumn("_n", near).select("series_id", "win", "z", "n_obs", "words", F.col("_n.cluster").alias("cluster"), F.col("_n.dist").alias("dist"))


# ---- DuckDB twins ---------------------------------------------------------------------------------------------

TEXT = "string_agg(coalesce(CAST(CAST(round({v} * 10000) AS BIGINT) AS VARCHAR), '-'), ',' ORDER BY pos)"
HOLD = f"{unit_sql(SEEDS['hold'], 'series_id', 'win')} < 0.2"
#: zs: the normalised grid; zc: complete training windows in long form.
Z_SQL = f"""{windows_sql(A)},
 zs AS (SELECT g.series_id, g.win, g.pos, g.value, n.n_obs, n.word, n.mu, n.sd, n.n_obs = {W} AS complete, {HOLD.replace("series_id", "g.series_id").replace("win AS", "g.win AS")} AS held,
  CASE WHEN g.value IS NULL THEN NULL WHEN n.n_obs < 2 OR n.sd < 1e-12 THEN 0.0 ELSE (g.value - n.mu) / n.sd END AS z
  FROM grid g JOIN wins n ON n.series_id = g.series_id AND n.win = g.win),
 zc AS (SELECT series_id, win, pos, z FROM zs WHERE complete AND NOT held)"""


def _step(i: int) -> str:
    return f"""
 d{i} AS (SELECT zc.series_id, zc.win, c.cluster, sum((zc.z - c.c) * (zc.z - c.c)) AS d FROM zc JOIN c{i} c ON c.pos = zc.pos GROUP BY 1, 2, 3),
 a{i} AS (SELECT series_id, win, cluster, sqrt(d) AS dist FROM d{i} QUALIFY row_number() OVER (PARTITION BY series_id, win ORDER BY d, cluster) = 1)"""


def _next(i: int) -> str:
    return f""",
 c{i + 1} AS (SELECT a.cluster, zc.pos, avg(zc.z) AS c FROM a{i} a JOIN zc ON zc.series_id = a.series_id AND zc.win = a.win GROUP BY 1, 2)"""


#: c2: the fixed centroids; a2: complete training windows by cluster.
CLUSTER_SQL = (
    Z_SQL
    + f""",
 i0 AS (SELECT series_id, win, row_number() OVER (ORDER BY {draw_sql(SEEDS['init'], 'series_id', 'win')}, series_id, win) - 1 AS cluster FROM (SELECT DISTINCT series_id, win FROM zc)),
 c0 AS (SELECT i0.cluster, zc.pos, zc.z AS c FROM i0 JOIN zc ON zc.series_id = i0.series_id AND zc.win = i0.win WHERE i0.cluster < 3),"""
    + _step(0)
    + _next(0)
    + ","
    + _step(1)
    + _next(1)
    + ","
    + _step(2)
)
#: inc: incomplete training windows with their nearest fixed centroid by the diagonal distance.
INC_SQL = (
    CLUSTER_SQL
    + f""",
 gd AS (SELECT z.series_id, z.win, c.cluster, sqrt(sum(coalesce((z.z - c.c) * (z.z - c.c), 0)) * {2.0 * W} / (max(z.n_obs) + {W})) AS dist, max(z.n_obs) AS n_obs, max(z.word) AS word
  FROM zs z JOIN c2 c ON c.pos = z.pos WHERE NOT z.complete AND NOT z.held AND z.n_obs > 0 GROUP BY 1, 2, 3),
 inc AS (SELECT series_id, win, CAST(cluster AS INTEGER) AS cluster, dist, n_obs, word FROM gd QUALIFY row_number() OVER (PARTITION BY series_id, win ORDER BY dist, cluster) = 1)"""
)


def incomplete_assigned(spark: SparkSession, d: str) -> DataFrame:
    """Incomplete training windows with their nearest fixed centroid."""
    return Base(spark, d).incomplete()


def complete_assigned(spark: SparkSession, d: str) -> DataFrame:
    return Base(spark, d).complete()


# ---- queries --------------------------------------------------------------------------------------------------


def _regular(name: str):
    return lambda s, d: slots(s, d, name).select("series_id", "slot", F.round("value", 4).alias("value"))


def _regular_sql(name: str) -> str:
    return f"WITH {slots_sql(WORKLOADS[name])} SELECT series_id, slot, round(value, 4) AS value FROM slots"


def _windows(name: str):
    def run(s, d):
        w = wins(s, d, name)
        return w.select("series_id", "win", F.col("n_obs").cast("long").alias("n_obs"), "complete", series.to_text("x").alias("x_text"))

    return run


def _windows_sql(name: str) -> str:
    spec = WORKLOADS[name]
    return f"WITH {windows_sql(spec)} SELECT series_id, win, count(value) AS n_obs, count(value) = {spec.w} AS complete, {TEXT.format(v='value')} AS x_text FROM grid GROUP BY series_id, win"


def split_counts(s, d):
    return wins(s, d).groupBy("complete").agg(F.count("*").alias("n"), F.sum("n_obs").alias("observed"))


def window_spine(s, d):
    return series.spine(slots(s, d), W).select("series_id", F.col("win").cast("long").alias("win"))


def window_masks(s, d):
    return wins(s, d).select("series_id", "win", F.col("words")[0].alias("word"), F.round((W - F.bit_count(F.col("words")[0])) / F.lit(float(W)), 4).alias("missing"))


def zscore_windows(s, d):
    return z_wins(s, d).where("n_obs > 0").select("series_id", "win", F.round("mu", 6).alias("mu"), F.round("sd", 6).alias("sd"), series.to_text("z", 3).alias("z_text"))


def zscore_series(s, d):
    return series.normalise(wins(s, d), "series").where("complete").select("series_id", "win", F.round("mu", 4).alias("mu"), F.round("sd", 4).alias("sd"), F.round(F.aggregate("z", F.lit(0.0), lambda a, v: a + v), 3).alias("z_sum"))


def lloyd_two_steps(s, d):
    c = base_centroids(s, d)
    return s.createDataFrame([(k, j, float(v)) for k, row in enumerate(c) for j, v in enumerate(row)], "cluster long, pos long, c double").withColumn("c", F.round("c", 4))


def assign_complete(s, d):
    return complete_assigned(s, d).select("series_id", "win", F.col("cluster").cast("long").alias("cluster"), F.round("dist", 4).alias("dist"))


def dbi_pairs(s, d):
    b = Base(s, d)
    pairs = cluster.dbi_pairs(b.complete(), b.centroids)
    return pairs.select(F.col("i").cast("long").alias("i"), F.col("j").cast("long").alias("j"), F.round("similarity", 4).alias("similarity"))


def dbi(s, d):
    b = Base(s, d)
    return cluster.davies_bouldin(b.complete(), b.centroids).select(F.round("dbi", 4).alias("dbi"))


def find_k(how: str):
    def run(s, d):
        sample = materialise(train_complete(s, d), "sample")
        found, _ = cluster.find_k(sample, 2, 6, how, restarts=1)
        return s.createDataFrame([(k, float(v), k == found.k) for k, v in found.trace.items()], "k int, dbi double, chosen boolean")

    return run


def minibatch(s, d):
    c = cluster.best_of(materialise(train_complete(s, d), "sample"), 3)
    return cluster.centroid_table(s, c)


def dbi_by_k(s, d):
    train = materialise(train_complete(s, d), "complete")
    made = [cluster.initial_centroids(train, k) for k in (2, 3, 4)]
    rows = [cluster.davies_bouldin(cluster.cluster_sequences(train, c), c).select(F.lit(len(c)).cast("long").alias("k"), F.round("dbi", 4).alias("dbi")) for c in made]
    return reduce(DataFrame.unionByName, rows)


def _dbi_k_sql(k: int) -> str:
    return f"""SELECT CAST({k} AS BIGINT) AS k, round(avg(worst), 4) AS dbi FROM (SELECT a.cluster, max((a.s + b.s) / g.gap) AS worst FROM s{k} a JOIN s{k} b ON a.cluster <> b.cluster
 JOIN (SELECT x.cluster AS i, y.cluster AS j, sqrt(sum((x.c - y.c) * (x.c - y.c))) AS gap FROM k{k} x JOIN k{k} y ON x.pos = y.pos GROUP BY 1, 2) g ON g.i = a.cluster AND g.j = b.cluster GROUP BY 1)"""


def _dbi_k_ctes(k: int) -> str:
    return f""",
 k{k} AS (SELECT i0.cluster, zc.pos, zc.z AS c FROM i0 JOIN zc ON zc.series_id = i0.series_id AND zc.win = i0.win WHERE i0.cluster < {k}),
 e{k} AS (SELECT zc.series_id, zc.win, c.cluster, sqrt(sum((zc.z - c.c) * (zc.z - c.c))) AS d FROM zc JOIN k{k} c ON c.pos = zc.pos GROUP BY 1, 2, 3),
 s{k} AS (SELECT cluster, avg(d) AS s FROM (SELECT * FROM e{k} QUALIFY row_number() OVER (PARTITION BY series_id, win ORDER BY d, cluster) = 1) GROUP BY 1)"""


def gap_euclid_to_centroids(s, d):
    b = Base(s, d)
    return b.gone.select("series_id", "win", F.posexplode(euclid_to("z", b.centroids)).alias("k", "v")).select("series_id", "win", F.col("k").cast("long").alias("cluster"), F.round("v", 4).alias("dist"))


def gap_dtw_to_centroids(s, d):
    b = Base(s, d)
    return b.gone.select("series_id", "win", F.posexplode(distances_to("z", b.centroids)).alias("k", "v")).select("series_id", "win", F.col("k").alias("cluster"), F.round("v", 4).alias("dist"))


def gap_cost_diagonal(s, d):
    """Point costs against the previous window of the series: nothing where either side is a gap."""
    z = wins(s, d)
    prev = z.select("series_id", (F.col("win") + 1).alias("win"), F.col("x").alias("before"))
    cost = F.zip_with("x", "before", lambda a, b: F.when(a.isNull() | b.isNull(), 0.0).otherwise((a - b) * (a - b)))
    return z.join(prev, ["series_id", "win"]).select("series_id", "win", F.round(F.aggregate(cost, F.lit(0.0), lambda t, v: t + v), 4).alias("cost"))


def assign_naive(s, d):
    """Nearest centroid with gaps filled by the window mean, which is 0 after normalisation: no gap handling."""
    b = Base(s, d)
    filled = b.gone.withColumn("z", F.transform("z", lambda v: F.coalesce(v, F.lit(0.0))))
    return cluster.cluster_sequences(filled, b.centroids).select("series_id", "win", F.col("cluster").cast("long").alias("cluster"), F.round("dist", 4).alias("dist"))


def assign_first_choice(s, d):
    return incomplete_assigned(s, d).select("series_id", "win", "cluster", F.round("dist", 4).alias("dist"))


def denormalised(s, d):
    """Normalised and back."""
    return z_wins(s, d).where("n_obs > 0").select("series_id", "win", series.to_text(series.denormalise(F.col("z")), 3).alias("x_text"))


def padded(s, d):
    """Windows that have a reading, the trailing part of the grid kept with gaps."""
    w = series.described(series.to_windows(slots(s, d), W, "pad"), W)
    return w.select("series_id", "win", F.col("n_obs").cast("long").alias("n_obs"), "complete")


def source_formats(s, d):
    """Readings written as CSV, JSON, ORC and Parquet, and read with the declared schema."""
    from ..sources.scratch import scratch_root
    from ..sources.tables import read_slots

    rows, out = materialise(slots(s, d), "slots"), []
    for kind in ("csv", "json", "orc", "parquet"):
        path = f"{scratch_root(s)}/{kind}-{uuid.uuid4().hex[:8]}"
        rows.write.format(kind).save(path)
        out.append(read_slots(s, path, kind).agg(F.lit(kind).alias("format"), F.count("value").alias("n"), F.round(F.sum("value"), 2).alias("total")))
    return reduce(DataFrame.unionByName, out)


def sink_partitioned(s, d):
    """Windows written by completeness and read back, each side from its own partition."""
    from ..sources.scratch import scratch_root
    from ..sources.tables import read_windows, write_windows

    path = f"{scratch_root(s)}/windows-{uuid.uuid4().hex[:8]}"
    write_windows(wins(s, d), path)
    return read_windows(s, path, True).unionByName(read_windows(s, path, False)).groupBy("complete").agg(F.count("*").alias("n"), F.sum("n_obs").alias("observed"))


def embedding_complete(s, d):
    e = series.normalise(series.described(embedding_windows(s, d), 64))
    return e.select("series_id", F.col("n_obs").cast("long").alias("n_obs"), "complete", F.round("mu", 5).alias("mu"), F.round("sd", 5).alias("sd"))


QUERIES = {
    **{f"regularise_{n}": _regular(n) for n in ("supplier_week", "user_halfday", "user_day", "flag_day", "type_hour_value", "type_hour_count", "type_15min", "priority_day", "turn_length")},
    **{f"wl_{n}": _windows(n) for n in ("supplier_week", "user_halfday", "user_day", "flag_day", "type_hour_value", "type_hour_count", "type_15min", "priority_day", "turn_length")},
    "wl_embedding": embedding_complete,
    "split_counts": split_counts,
    "window_spine": window_spine,
    "window_masks": window_masks,
    "zscore_windows": zscore_windows,
    "zscore_series": zscore_series,
    "zscore_inverse": denormalised,
    "windows_tail_pad": padded,
    "source_formats": source_formats,
    "sink_partitioned": sink_partitioned,
    "lloyd_two_steps": lloyd_two_steps,
    "assign_complete": assign_complete,
    "dbi_pairs": dbi_pairs,
    "dbi": dbi,
    "dbi_by_k": dbi_by_k,
    "find_k_bisect": find_k("bisect"),
    "find_k_exhaustive": find_k("exhaustive"),
    "find_k_ternary": find_k("ternary"),
    "minibatch_kmeans": minibatch,
    "gap_cost_diagonal": gap_cost_diagonal,
    "gap_euclid_to_centroids": gap_euclid_to_centroids,
    "gap_dtw_to_centroids": gap_dtw_to_centroids,
    "assign_naive": assign_naive,
    "assign_first_choice": assign_first_choice,
}
_PAIR_GAP = "SELECT x.cluster AS i, y.cluster AS j, sqrt(sum((x.c - y.c) * (x.c - y.c))) AS gap FROM c2 x JOIN c2 y ON x.pos = y.pos GROUP BY 1, 2"
_SIM = f"SELECT a.cluster AS i, b.cluster AS j, (a.s + b.s) / g.gap AS similarity FROM sc a JOIN sc b ON a.cluster <> b.cluster JOIN ({_PAIR_GAP}) g ON g.i = a.cluster AND g.j = b.cluster"
_SCATTER = ", sc AS (SELECT cluster, avg(dist) AS s FROM a2 GROUP BY 1)"
ORACLES = {
    **{f"regularise_{n}": _regular_sql(n) for n in WORKLOADS},
    **{f"wl_{n}": _windows_sql(n) for n in WORKLOADS},
    "wl_embedding": "SELECT CAST(vec_id AS VARCHAR) AS series_id, CAST(64 AS BIGINT) AS n_obs, true AS complete, round(list_avg(embedding::DOUBLE[]), 5) AS mu, round(list_stddev_pop(embedding::DOUBLE[]), 5) AS sd FROM embeddings",
    "split_counts": f"WITH {windows_sql(A)} SELECT n_obs = {W} AS complete, count(*) AS n, CAST(sum(n_obs) AS BIGINT) AS observed FROM wins GROUP BY 1",
    "window_spine": f"WITH {windows_sql(A)} SELECT series_id, win FROM wins",
    "window_masks": f"WITH {windows_sql(A)} SELECT series_id, win, word, round(({W} - n_obs) / {float(W)}, 4) AS missing FROM wins",
    "zscore_windows": f"WITH {Z_SQL} SELECT series_id, win, round(max(mu), 6) AS mu, round(max(sd), 6) AS sd, string_agg(coalesce(CAST(CAST(round(z * 1000) AS BIGINT) AS VARCHAR), '-'), ',' ORDER BY pos) AS z_text FROM zs WHERE n_obs > 0 GROUP BY 1, 2",
    "zscore_series": f"""WITH {windows_sql(A)}, t AS (SELECT series_id, avg(value) AS mu, stddev_pop(value) AS sd FROM grid GROUP BY 1)
        SELECT g.series_id, g.win, round(max(t.mu), 4) AS mu, round(max(t.sd), 4) AS sd, round(sum((g.value - t.mu) / t.sd), 3) AS z_sum FROM grid g JOIN t ON t.series_id = g.series_id GROUP BY 1, 2 HAVING count(g.value) = {W}""",
    "zscore_inverse": f"WITH {Z_SQL} SELECT series_id, win, string_agg(coalesce(CAST(CAST(round(value * 1000) AS BIGINT) AS VARCHAR), '-'), ',' ORDER BY pos) AS x_text FROM zs WHERE n_obs > 0 GROUP BY 1, 2",
    "windows_tail_pad": f"WITH {slots_sql(A)} SELECT series_id, slot // {W} AS win, count(*) AS n_obs, count(*) = {W} AS complete FROM slots GROUP BY 1, 2",
    "source_formats": f"WITH {slots_sql(A)} SELECT format, count(*) AS n, round(sum(value), 2) AS total FROM slots, (VALUES ('csv'), ('json'), ('orc'), ('parquet')) f(format) GROUP BY 1",
    "sink_partitioned": f"WITH {windows_sql(A)} SELECT n_obs = {W} AS complete, count(*) AS n, CAST(sum(n_obs) AS BIGINT) AS observed FROM wins GROUP BY 1",
    "lloyd_two_steps": f"WITH {CLUSTER_SQL} SELECT CAST(cluster AS BIGINT) AS cluster, CAST(pos AS BIGINT) AS pos, round(c, 4) AS c FROM c2",
    "assign_complete": f"WITH {CLUSTER_SQL} SELECT series_id, win, CAST(cluster AS BIGINT) AS cluster, round(dist, 4) AS dist FROM a2",
    "dbi_pairs": f"WITH {CLUSTER_SQL}{_SCATTER} SELECT CAST(i AS BIGINT) AS i, CAST(j AS BIGINT) AS j, round(similarity, 4) AS similarity FROM ({_SIM})",
    "dbi": f"WITH {CLUSTER_SQL}{_SCATTER} SELECT round(avg(worst), 4) AS dbi FROM (SELECT i, max(similarity) AS worst FROM ({_SIM}) GROUP BY 1)",
    "dbi_by_k": f"WITH {CLUSTER_SQL}{''.join(map(_dbi_k_ctes, (2, 3, 4)))} {' UNION ALL '.join(map(_dbi_k_sql, (2, 3, 4)))}",
    "gap_cost_diagonal": f"WITH {windows_sql(A)} SELECT a.series_id, a.win, round(sum(coalesce((a.value - b.value) * (a.value - b.value), 0)), 4) AS cost FROM grid a JOIN grid b ON a.series_id = b.series_id AND a.win = b.win + 1 AND a.pos = b.pos GROUP BY 1, 2",
    "gap_euclid_to_centroids": f"WITH {INC_SQL} SELECT series_id, win, CAST(cluster AS BIGINT) AS cluster, round(dist, 4) AS dist FROM gd",
    "assign_naive": f"""WITH {INC_SQL}, nd AS (SELECT z.series_id, z.win, c.cluster, sqrt(sum((coalesce(z.z, 0) - c.c) * (coalesce(z.z, 0) - c.c))) AS dist FROM zs z JOIN c2 c ON c.pos = z.pos WHERE NOT z.complete AND NOT z.held AND z.n_obs > 0 GROUP BY 1, 2, 3)
        SELECT series_id, win, CAST(cluster AS BIGINT) AS cluster, round(dist, 4) AS dist FROM nd QUALIFY row_number() OVER (PARTITION BY series_id, win ORDER BY dist, cluster) = 1""",
    "assign_first_choice": f"WITH {INC_SQL} SELECT series_id, win, cluster, round(dist, 4) AS dist FROM inc",
}
