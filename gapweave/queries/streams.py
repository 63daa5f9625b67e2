"""Streaming queries, replayed over the events file in append mode: equal to their batch twins."""

from __future__ import annotations

import uuid

from pyspark.sql import functions as F

from ..functions.hashing import unit, unit_sql
from ..learners.core import pack_params
from ..schemas import MODELS
from ..sources.scratch import materialise, scratch_root
from ..streaming import windows as st
from .windows import CLUSTER_SQL, INC_SQL, W, base_centroids, complete_assigned, incomplete_assigned

#: How the replay with late rows arrives: parts by time, some rows some parts later.
PARTS, LATE_SEED, LATE_SHARE = 5, 901, 0.05


def _events(s, d):
    """The events, and then the closing row."""
    return st.event_stream(s, f"{d}/events.parquet*").unionByName(st.closing_stream(s))


def stream_tumbling(s, d):
    out = st.replay(st.tumbling(_events(s, d)), s, "tumbling").where(F.col("user_id") != st.CLOSING)
    return out.select("user_id", F.unix_micros("start").alias("start"), "n", F.col("total").cast("double").alias("total"))


def stream_sliding(s, d):
    out = st.replay(st.sliding(_events(s, d)), s, "sliding").where(F.col("user_id") != st.CLOSING)
    return out.select("user_id", F.unix_micros("start").alias("start"), "n")


def stream_sessions(s, d):
    out = st.replay(st.sessions(_events(s, d)), s, "sessions").where(F.col("user_id") != st.CLOSING)
    return out.select("user_id", F.unix_micros("start").alias("start"), F.unix_micros("stop").alias("stop"), "n")


def stream_dedup(s, d):
    return st.replay(st.deduplicated(st.event_stream(s, f"{d}/events.parquet*")).select("event_id", "user_id"), s, "dedup")


def stream_join(s, d):
    e = lambda: st.event_stream(s, f"{d}/events.parquet*")
    return st.replay(st.joined(e(), e()), s, "join")


def stream_carry(s, d):
    e = _events(s, d).withColumn("value", F.when(F.col("event_id") % 5 != 0, F.col("value")))
    out = st.replay(st.carry_forward(e), s, "carry").where(F.col("user_id") != st.CLOSING)
    return out.select("event_id", "user_id", F.round("value", 6).alias("value"), "filled")


def _arrivals(s, d):
    """Events with the part in which they arrive: by time, a share of them two parts later or more."""
    e = s.read.parquet(f"{d}/events.parquet")
    t = e.agg(F.min(F.unix_micros(F.col("ts").cast("timestamp"))).alias("a"), F.max(F.unix_micros(F.col("ts").cast("timestamp"))).alias("b")).first()
    span = max(1, (t.b or 0) - (t.a or 0) + 1)
    due = F.floor((F.unix_micros(F.col("ts").cast("timestamp")) - F.lit(t.a or 0)) * PARTS / F.lit(span))
    late = F.when(unit(LATE_SEED, "event_id") < LATE_SHARE, 3).otherwise(0)
    return e.withColumn("part", F.least(F.lit(PARTS - 1), due + late).cast("int"))


def stream_late(s, d):
    """By part: rows that arrived, rows that the windows counted, and rows that came too late and were dropped."""
    rows = materialise(_arrivals(s, d), "arrivals")
    stream = st.event_stream(s, st.in_parts(s, rows.unionByName(st.closing_row(s).withColumn("part", F.lit(PARTS))), PARTS + 1))
    kept = st.replay(st.tumbling(stream), s, "late").where(F.col("user_id") != st.CLOSING)
    n = kept.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("kept"), F.count("*").alias("windows"))
    return rows.agg(F.count("*").alias("arrived")).crossJoin(n).select("arrived", "kept", (F.col("arrived") - F.col("kept")).alias("dropped"), "windows")


def _by_arrival(df, s, schema):
    """A stream of windows in three files, by window number."""
    path = st.in_parts(s, materialise(df.withColumn("part", (F.col("win") % 3).cast("int")), "windows"), 3)
    return s.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path)


def stream_online(s, d):
    """Incomplete windows filled as they arrive by the newest version of the model table (slot profiles: the centroids)."""
    c = base_centroids(s, d)
    old = [(k, "profile", pack_params({"profile": row * 0}), 1) for k, row in enumerate(c)]
    models = s.createDataFrame(old + [(k, "profile", pack_params({"profile": row}), 2) for k, row in enumerate(c)], MODELS)
    at = f"{scratch_root(s)}/online-{uuid.uuid4().hex[:8]}"
    windows = _by_arrival(incomplete_assigned(s, d).select("series_id", "win", "cluster", "z"), s, "series_id string, win long, cluster int, z array<double>")
    st.replay_batches(windows, s, "online", st.online_imputer(models, lambda df, i: df.write.parquet(f"{at}/{i:06d}")))
    out = s.read.schema("series_id string, win long, filled array<double>, version long").parquet(f"{at}/*")
    return out.select("series_id", "win", "version", F.posexplode("filled").alias("pos", "v")).select("series_id", "win", F.col("pos").cast("long").alias("pos"), F.round("v", 6).alias("filled"), "version")


def stream_drift(s, d):
    """Index and structure ratio of every arriving part, against the fixed clustering."""
    c = base_centroids(s, d)
    done = complete_assigned(s, d).select("series_id", "win", "cluster", "dist", F.lit(None).cast("array<bigint>").alias("words"), F.lit(W).alias("n_obs"), F.lit(True).alias("complete"))
    gone = incomplete_assigned(s, d).select("series_id", "win", "cluster", "dist", "words", "n_obs", F.lit(False).alias("complete"))
    schema = "series_id string, win long, cluster int, dist double, words array<bigint>, n_obs int, complete boolean"
    at = f"{scratch_root(s)}/drift-{uuid.uuid4().hex[:8]}"

    def check(batch, i):
        batch = materialise(batch, "batch")
        st.drift(batch.where("complete"), batch.where("NOT complete"), c, W).withColumn("part", F.lit(i).cast("long")).coalesce(1).write.parquet(f"{at}/{i:06d}")

    st.replay_batches(_by_arrival(done.unionByName(gone), s, schema), s, "drift", check)
    out = s.read.schema("dbi double, ratio double, kept long, refit boolean, part long").parquet(f"{at}/*")
    return out.select("part", F.round("dbi", 4).alias("dbi"), F.round("ratio", 6).alias("ratio"), "refit")


QUERIES = {
    "stream_tumbling": stream_tumbling,
    "stream_sliding": stream_sliding,
    "stream_sessions": stream_sessions,
    "stream_dedup": stream_dedup,
    "stream_join": stream_join,
    "stream_carry_forward": stream_carry,
    "stream_late_rows": stream_late,
    "stream_online_imputer": stream_online,
    "stream_drift": stream_drift,
}
_US = "CAST(epoch_us({}) AS BIGINT)"
_LATE = f"""WITH b AS (SELECT min(epoch_us(ts)) AS a, max(epoch_us(ts)) - min(epoch_us(ts)) + 1 AS span FROM events),
        e AS (SELECT user_id, epoch_us(ts) AS us, CAST(least({PARTS - 1}, floor((epoch_us(ts) - b.a) * {PARTS} / b.span) + CASE WHEN {unit_sql(LATE_SEED, 'event_id')} < {LATE_SHARE} THEN 3 ELSE 0 END) AS INTEGER) AS part FROM events, b),
        m AS (SELECT part, max(us) AS us FROM e GROUP BY 1),
        k AS (SELECT e.*, floor(e.us / 43200000000) * 43200000000 AS start, (SELECT max(m.us) FROM m WHERE m.part <= e.part - 2) - 3600000000 AS mark FROM e)"""
ORACLES = {
    "stream_tumbling": "SELECT user_id, CAST(floor(epoch_us(ts) / 43200000000) * 43200000000 AS BIGINT) AS start, count(*) AS n, CAST(sum(CAST(value AS DECIMAL(18,2))) AS DOUBLE) AS total FROM events GROUP BY 1, 2",
    "stream_sliding": "SELECT user_id, CAST((floor(epoch_us(ts) / 21600000000) - k) * 21600000000 AS BIGINT) AS start, count(*) AS n FROM events, (VALUES (0), (1)) t(k) GROUP BY 1, 2",
    "stream_sessions": f"WITH o AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 6 HOURS THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), g AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM o) SELECT user_id, {_US.format('min(ts)')} AS start, {_US.format('max(ts) + INTERVAL 6 HOURS')} AS stop, count(*) AS n FROM g GROUP BY user_id, k",
    "stream_dedup": "SELECT DISTINCT event_id, user_id FROM events",
    "stream_join": "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id <> b.event_id AND b.ts <= a.ts AND b.ts >= a.ts - INTERVAL 10 MINUTES",
    "stream_carry_forward": "SELECT event_id, user_id, round(last_value(CASE WHEN event_id % 5 <> 0 THEN value END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 6) AS value, event_id % 5 = 0 OR value IS NULL AS filled FROM events",
    "stream_late_rows": f"{_LATE} SELECT count(*) AS arrived, CAST(sum(CASE WHEN mark IS NULL OR start + 43200000000 > mark THEN 1 ELSE 0 END) AS BIGINT) AS kept, CAST(sum(CASE WHEN start + 43200000000 <= mark THEN 1 ELSE 0 END) AS BIGINT) AS dropped, (SELECT count(*) FROM (SELECT DISTINCT user_id, start FROM k WHERE mark IS NULL OR start + 43200000000 > mark)) AS windows FROM k",
    "stream_online_imputer": f"WITH {INC_SQL} SELECT i.series_id, i.win, CAST(z.pos AS BIGINT) AS pos, round(coalesce(z.z, c.c), 6) AS filled, CAST(2 AS BIGINT) AS version FROM inc i JOIN zs z ON z.series_id = i.series_id AND z.win = i.win JOIN c2 c ON c.cluster = i.cluster AND c.pos = z.pos",
}
