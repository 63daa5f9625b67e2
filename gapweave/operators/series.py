"""From readings to windows: the expected grid, tumbling windows, masks, completeness, normalisation."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import SEEDS, unit
from ..functions.masks import mask_words
from ..sources.workloads import SeriesSpec, readings


class NoCompleteWindows(ValueError):
    """There is no complete window to learn from."""


def regularise(rows: DataFrame, step: int | None, fold: str = "avg", origin: int | None = None) -> DataFrame:
    """(series_id, slot, value) on the expected grid, from (series_id, at, value).

    ``at`` is microseconds where ``step`` (seconds) is given, else a slot number. Readings of one slot are folded;
    nulls and NaN are gaps. Slots count from ``origin``, by default the earliest of the whole collection.
    """
    at = F.floor(F.col("at") / F.lit(step * 1_000_000)).cast("long") if step else F.col("at")
    rows = rows.select("series_id", at.alias("slot"), F.col("value"))
    if origin is None:
        origin = rows.agg(F.min("slot")).first()[0] or 0
    rows = rows.where(F.col("value").isNotNull() & ~F.isnan("value") & F.col("slot").isNotNull())
    return rows.groupBy("series_id", (F.col("slot") - F.lit(origin)).alias("slot")).agg(F.expr(f"{fold}(value)").alias("value"))


def slots_of(spark: SparkSession, folder: str, spec: SeriesSpec) -> DataFrame:
    return regularise(readings(spark, folder, spec), spec.step if spec.time else None, spec.fold)


def to_windows(slots: DataFrame, w: int, tail: str = "floor") -> DataFrame:
    """Tumbling windows of w slots as arrays with gaps. A series' slots and windows share one shuffle.

    ``tail='floor'`` drops the trailing part of the grid that fills no window; ``'pad'`` keeps it with gaps.
    """
    keyed = slots.select("series_id", F.expr(f"slot div {w}").alias("win"), F.expr(f"cast(slot % {w} as int)").alias("pos"), "value")
    if w <= 32:
        cells = [F.max(F.when(F.col("pos") == i, F.col("value"))) for i in range(w)]
        wins = keyed.groupBy("series_id", "win").agg(F.array(*cells).alias("x"))
    else:
        wins = keyed.groupBy("series_id", "win").agg(F.map_from_entries(F.collect_list(F.struct("pos", "value"))).alias("m"))
        wins = wins.select("series_id", "win", F.transform(F.sequence(F.lit(0), F.lit(w - 1)), lambda i: F.try_element_at("m", i)).alias("x"))
    if tail == "pad":
        return wins
    return wins.where(F.col("win") < F.lit(_whole_windows(slots, w)))


def _whole_windows(slots: DataFrame, w: int) -> int:
    last = slots.agg(F.max("slot")).first()[0]
    return 0 if last is None else (last + 1) // w


def spine(slots: DataFrame, w: int) -> DataFrame:
    """(series_id, win) of every whole window that should exist, also those without a reading."""
    n = _whole_windows(slots, w)
    wins = slots.sparkSession.range(n).select(F.col("id").alias("win"))  # as many rows as windows of one series
    return slots.select("series_id").distinct().crossJoin(F.broadcast(wins))


def windows(slots: DataFrame, w: int, with_empty: bool = True, tail: str = "floor") -> DataFrame:
    """(series_id, win, x, n_obs, words, complete): all expected windows."""
    made = to_windows(slots, w, tail)
    if with_empty:
        made = spine(slots, w).join(made, ["series_id", "win"], "left")
        made = made.withColumn("x", F.coalesce("x", F.array(*[F.lit(None).cast("double")] * w)))
    return described(made, w)


def described(made: DataFrame, w: int) -> DataFrame:
    """Windows with their mask words, count of observations and completeness."""
    n = F.size(F.filter("x", lambda v: v.isNotNull()))
    return made.withColumns({"n_obs": n, "words": mask_words("x", w), "complete": n == w})


def split_complete(wins: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Complete and incomplete windows, as filters of one table."""
    return wins.where("complete"), wins.where("NOT complete")


def _moments(x: Column, n: Column) -> tuple[Column, Column]:
    zero = F.lit(0.0)
    mu = F.aggregate(x, zero, lambda a, v: a + F.coalesce(v, zero)) / F.when(n > 0, n)
    ss = F.aggregate(x, zero, lambda a, v: a + F.coalesce((v - mu) * (v - mu), zero))
    return mu, F.sqrt(ss / F.when(n > 0, n))


def normalise(wins: DataFrame, mode: str = "window") -> DataFrame:
    """Adds mu, sd and z: by window, by series, or not at all; constant or single observations give zeros."""
    if mode == "window":
        n = F.col("n_obs")
        mu, _ = _moments(F.col("x"), n)
        wins = wins.withColumn("mu", mu)
        ss = F.aggregate("x", F.lit(0.0), lambda a, v: a + F.coalesce((v - F.col("mu")) * (v - F.col("mu")), F.lit(0.0)))
        wins = wins.withColumn("sd", F.sqrt(ss / F.when(n > 0, n)))
        flat = (n < 2) | (F.col("sd") < 1e-12)
    elif mode == "series":
        flat_values = wins.select("series_id", F.explode("x").alias("v")).groupBy("series_id").agg(F.avg("v").alias("mu"), F.stddev_pop("v").alias("sd"))
        wins = wins.join(flat_values, "series_id")
        flat = F.col("sd") < 1e-12
    elif mode == "none":
        wins = wins.withColumns({"mu": F.lit(0.0), "sd": F.lit(1.0)})
        flat = F.lit(False)
    else:
        raise ValueError("mode is window, series or none")
    z = F.transform("x", lambda v: F.when(v.isNotNull(), F.when(flat, 0.0).otherwise((v - F.col("mu")) / F.when(~flat, F.col("sd")))))
    return wins.withColumn("z", z)


def denormalise(z: str | Column, mu: str | Column = "mu", sd: str | Column = "sd") -> Column:
    """The inverse of ``normalise`` on an array."""
    mu, sd = (F.col(c) if isinstance(c, str) else c for c in (mu, sd))
    return F.transform(z, lambda v: v * sd + mu)


def holdout(series_id: str = "series_id", win: str = "win", share: float = 0.2) -> Column:
    """True for test windows: a fifth, by hash."""
    return unit(SEEDS["hold"], series_id, win) < share


def to_text(x: str | Column, scale: int = 4) -> Column:
    """An array as text, for comparing whole windows between engines."""
    return F.array_join(F.transform(x, lambda v: F.coalesce(F.round(v * 10**scale).cast("long").cast("string"), F.lit("-"))), ",")


def to_readings(imputed: DataFrame, w: int) -> DataFrame:
    """(series_id, slot, value, imputed, source) from windows with x (observed) and filled; observed values never change."""
    rows = imputed.select("series_id", "win", "source", F.posexplode(F.arrays_zip("x", "filled")).alias("pos", "c"))
    return rows.select(
        "series_id",
        (F.col("win") * w + F.col("pos")).alias("slot"),
        F.coalesce(F.col("c.x"), F.col("c.filled")).alias("value"),
        F.col("c.x").isNull().alias("imputed"),
        F.when(F.col("c.x").isNull(), F.col("source")).otherwise("observed").alias("source"),
    )
