"""A planted overlay on the real slots: a deterministic signal and a deterministic gap pattern.

The given tables carry almost no temporal signal, so accuracy claims are made on this overlay and said to be.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import draw
from .workloads import WORKLOADS


def planted(spark: SparkSession, folder: str) -> DataFrame:
    """Windows of supplier weeks (series_id, win, archetype, truth, x): truth is complete, x has the planted gaps."""
    from ..operators.series import slots_of, windows

    spec = WORKLOADS["supplier_week"]
    w = spec.w
    raw = windows(slots_of(spark, folder, spec), w)
    i = F.col("series_id").cast("long") * 44 + F.col("win")
    raw = raw.withColumns({"i": i, "archetype": F.col("series_id").cast("long") % 3})
    filled = raw.withColumn("x0", F.array(*[F.coalesce(F.col("x")[j], 1 + 49 * draw(11, "i", F.lit(j)) / F.lit(float(1 << 32))) for j in range(w)]))
    spread = filled.select(F.explode("x0").alias("v")).agg(F.avg("v").alias("m"), F.stddev_pop("v").alias("s")).first()
    m, s = (spread.m, spread.s) if spread.m is not None else (0.0, 1.0)
    wave = lambda j: F.sin(F.lit(2 * math.pi * j / 8) + F.lit(2 * math.pi / 3) * F.col("archetype"))
    truth = F.array(*[F.lit(0.35) * (F.col("x0")[j] - m) / s + wave(j) + 10.0 for j in range(w)])
    begin = F.element_at(F.array(F.lit(0), F.lit(3), F.lit(5)), (F.col("archetype") + 1).cast("int"))
    run = draw(7, "i") < 0.8 * (1 << 32)
    gap = lambda j: (run & (F.lit(j) >= begin) & (F.lit(j) < begin + 3)) | (draw(13, "i", F.lit(j)) < 0.02 * (1 << 32))
    out = filled.withColumn("truth", truth)
    return out.select("series_id", "win", "archetype", "truth", F.array(*[F.when(~gap(j), F.col("truth")[j]) for j in range(w)]).alias("x"))
