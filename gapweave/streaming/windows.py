"""Structured Streaming forms: windows as readings arrive, late data, stateful carry-forward, online imputation, drift.

Windows are emitted in append mode, once, when the watermark has passed their end; their state goes then. A bounded
replay ends with a closing row far in the future, which moves the watermark past everything that was read.
"""

from __future__ import annotations

import json
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..learners.core import LEARNERS, unpack_params
from ..sources.scratch import scratch_root

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
#: The user of the closing row, who is in no result.
CLOSING = -1


def event_stream(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    """A file stream of events; times become timestamps, which watermarks need."""
    raw = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files).parquet(path)
    return raw.withColumn("at", F.col("ts").cast("timestamp"))


def closing_row(spark: SparkSession) -> DataFrame:
    """One event, a century ahead, of a user that does not exist."""
    return spark.sql(f"SELECT CAST({CLOSING} AS BIGINT) AS event_id, TIMESTAMP_NTZ'2124-01-01 00:00:00' AS ts, CAST({CLOSING} AS BIGINT) AS user_id, '' AS event_type, CAST(0 AS DOUBLE) AS value, '' AS props")


def closing_stream(spark: SparkSession) -> DataFrame:
    """A stream of the closing row alone."""
    path = f"{scratch_root(spark)}/closing-{uuid.uuid4().hex[:12]}"
    closing_row(spark).write.parquet(path)
    return event_stream(spark, path)


def in_parts(spark: SparkSession, events: DataFrame, parts: int) -> str:
    """A folder with one file a ``part`` (0 to parts - 1), in order of time of writing: how a bounded replay arrives."""
    path = f"{scratch_root(spark)}/arrivals-{uuid.uuid4().hex[:12]}"
    for i in range(parts):
        events.where(F.col("part") == i).drop("part").coalesce(1).write.mode("append").parquet(path)
    return path


def tumbling(stream: DataFrame, length: str = "12 hours", delay: str = "1 hour") -> DataFrame:
    """Readings of each user in tumbling windows; rows of windows that the watermark has passed are dropped."""
    g = stream.withWatermark("at", delay).groupBy("user_id", F.window("at", length).alias("w"))
    return g.agg(F.count("*").alias("n"), F.sum(F.col("value").cast("decimal(18,2)")).alias("total")).select("user_id", F.col("w.start").alias("start"), "n", "total")


def sliding(stream: DataFrame, length: str = "12 hours", slide: str = "6 hours", delay: str = "1 hour") -> DataFrame:
    g = stream.withWatermark("at", delay).groupBy("user_id", F.window("at", length, slide).alias("w"))
    return g.agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), "n")


def sessions(stream: DataFrame, gap: str = "6 hours", delay: str = "1 hour") -> DataFrame:
    """Bursts of readings; what lies between two of them is a gap."""
    g = stream.withWatermark("at", delay).groupBy("user_id", F.session_window("at", gap).alias("w"))
    return g.agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("stop"), "n")


def deduplicated(stream: DataFrame, delay: str = "1 hour") -> DataFrame:
    return stream.withWatermark("at", delay).dropDuplicatesWithinWatermark(["event_id"])


def joined(readings: DataFrame, meters: DataFrame, within: str = "10 minutes", delay: str = "1 hour") -> DataFrame:
    """Readings with the events of the same user shortly before them."""
    a = readings.withWatermark("at", delay).select(F.col("event_id").alias("a"), "user_id", F.col("at").alias("ta"))
    b = meters.withWatermark("at", delay).select(F.col("event_id").alias("b"), F.col("user_id").alias("user_b"), F.col("at").alias("tb"))
    return a.join(b, F.expr(f"user_id = user_b AND tb <= ta AND tb >= ta - INTERVAL {within} AND a <> b")).select("a", "b")


def carry_forward(stream: DataFrame, delay: str = "1 hour", idle_ms: int = 30 * 86_400_000) -> DataFrame:
    """Each reading, a null value filled by the one before it of the same user, in order of time.

    Readings wait until the watermark has passed them, so the order of arrival inside ``delay`` does not matter. A
    user's state is the last value and the readings that wait; it goes after ``idle_ms`` of event time without any.
    Timeouts are of event time: a bounded stream ends.
    """
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        last, waiting = state.get if state.exists else (None, "[]")
        rows = json.loads(waiting)
        if not state.hasTimedOut:
            for pdf in batches:
                rows += [[int(a), int(i), None if v is None or np.isnan(v) else float(v)] for a, i, v in zip(pdf["us"], pdf["event_id"], pdf["value"], strict=True)]
        rows.sort(key=lambda r: (r[0], r[1]))
        passed = state.getCurrentWatermarkMs() * 1000
        out = []
        while rows and rows[0][0] < passed:
            _, event_id, value = rows.pop(0)
            last = value if value is not None else last
            out.append((event_id, int(key[0]), last, value is None))
        if state.hasTimedOut and not rows and not out:
            state.remove()
        else:
            state.update((last, json.dumps(rows)))
            state.setTimeoutTimestamp(max(passed // 1000 + 1, rows[0][0] // 1000 + 1 if rows else passed // 1000 + idle_ms))
        yield pd.DataFrame({"event_id": pd.array([o[0] for o in out], "int64"), "user_id": pd.array([o[1] for o in out], "int64"), "value": pd.array([o[2] for o in out], "float64"), "filled": pd.array([o[3] for o in out], "bool")})

    cols = stream.withWatermark("at", delay).select("event_id", "user_id", "at", F.unix_micros("at").alias("us"), "value")
    return cols.groupBy("user_id").applyInPandasWithState(step, "event_id long, user_id long, value double, filled boolean", "last double, waiting string", "append", GroupStateTimeout.EventTimeTimeout)


def online_imputer(models: DataFrame, sink: Callable[[DataFrame, int], None]) -> Callable[[DataFrame, int], None]:
    """A foreachBatch function: the newest version of each cluster's model fills the batch's windows.

    The model table is read anew in every batch, so a refit takes effect with the next one.
    """

    def run(batch: DataFrame, batch_id: int) -> None:
        newest = models.groupBy("cluster").agg(F.max_by(F.struct("kind", "params", "version"), "version").alias("m"))
        table = {r.cluster: (r.m.kind, r.m.params, r.m.version) for r in newest.collect()}  # one row a cluster

        def fill(pdfs: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            ready = {c: (LEARNERS[k], unpack_params(p), v) for c, (k, p, v) in table.items()}
            for pdf in pdfs:
                filled, version = [None] * len(pdf), [0] * len(pdf)
                z = np.array([np.array(v, dtype=float) for v in pdf["z"]])
                for c in set(pdf["cluster"]) & set(ready):
                    at = np.flatnonzero(pdf["cluster"] == c)
                    model, params, v = ready[c]
                    for i, guess in zip(at.tolist(), np.where(np.isnan(z[at]), model.predict(params, z[at]), z[at]), strict=True):
                        filled[i], version[i] = guess.tolist(), v
                yield pd.DataFrame({"series_id": pdf["series_id"], "win": pdf["win"], "filled": filled, "version": version})

        sink(batch.select("series_id", "win", "cluster", "z").mapInPandas(fill, "series_id string, win long, filled array<double>, version long"), batch_id)

    return run


def drift(assigned: DataFrame, incomplete: DataFrame, centroids: np.ndarray, w: int, structure_gate: float = 2 / 3, dbi_limit: float = 2.0) -> DataFrame:
    """One row: the Davies-Bouldin index of complete windows, the structure ratio over all clusters of the incomplete
    ones, and whether clusters should be fitted again (the index above its limit, or no cluster's ratio above the gate).

    ``assigned`` has cluster and dist; ``incomplete`` has cluster, series_id, win, words and n_obs.
    """
    from ..operators.cluster import davies_bouldin
    from ..operators.patterns import compared, structure

    found = structure(compared(incomplete, w), structure_gate)
    ratio = found.agg((F.sum("n_p") / F.sum("n")).alias("ratio"), F.sum(F.col("kept").cast("int")).alias("kept"))
    rows = davies_bouldin(assigned, centroids).crossJoin(ratio)  # one row with one row
    return rows.withColumn("refit", F.coalesce(F.col("dbi") > dbi_limit, F.lit(True)) | (F.coalesce("kept", F.lit(0)) == 0))


def replay(stream: DataFrame, spark: SparkSession, name: str) -> DataFrame:
    """Run a stream over the files that are there, in append mode, and read its result back."""
    at = f"{scratch_root(spark)}/stream-{name}-{uuid.uuid4().hex[:8]}"
    stream.writeStream.format("parquet").option("path", f"{at}/out").option("checkpointLocation", f"{at}/log").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{at}/out")


def replay_batches(stream: DataFrame, spark: SparkSession, name: str, handle: Callable[[DataFrame, int], None]) -> None:
    """Run a stream over the files that are there, each batch by ``handle``."""
    at = f"{scratch_root(spark)}/stream-{name}-{uuid.uuid4().hex[:8]}"
    stream.writeStream.foreachBatch(handle).option("checkpointLocation", f"{at}/log").trigger(availableNow=True).start().awaitTermination()
