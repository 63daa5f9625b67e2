"""Gap generators for controlled experiments, and profiles of the gaps that are there.

Every generator adds hidden, an array of booleans over the slots; ids make the draws reproducible.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import SEEDS, draw, unit

IDS = ("series_id", "win")


def _slots(w: int) -> Column:
    return F.sequence(F.lit(0), F.lit(w - 1))


def mcar(df: DataFrame, w: int, p: float, seed: int = SEEDS["gap"]) -> DataFrame:
    """Completely at random: each slot with chance p."""
    return df.withColumn("hidden", F.transform(_slots(w), lambda i: unit(seed, *IDS, i) < p))


def mcar_exact(df: DataFrame, w: int, p: float, seed: int = SEEDS["gap"]) -> DataFrame:
    """Exactly round(p * w) slots, those with the least draws."""
    drawn = F.array_sort(F.transform(_slots(w), lambda i: F.struct(draw(seed, *IDS, i).alias("h"), i.alias("i"))))
    chosen = F.transform(F.slice(drawn, F.lit(1), F.lit(round(p * w))), lambda s: s["i"])
    return df.withColumn("_chosen", chosen).withColumn("hidden", F.transform(_slots(w), lambda i: F.array_contains("_chosen", i))).drop("_chosen")


def mnar_value(df: DataFrame, w: int, p: float, slope: float = 0.8, x: str = "x", seed: int = SEEDS["value"]) -> DataFrame:
    """High values go more often: the chance falls with the slot's rank by value."""
    ranked = F.array_sort(F.transform(F.col(x), lambda v, i: F.struct((-v).alias("v"), i.alias("i"))))
    chance = lambda r: F.greatest(F.lit(0.0), F.least(F.lit(1.0), F.lit(p) * (1 + slope * (1 - 2.0 * r / (w - 1)))))
    rank = lambda i: F.array_position(F.transform("_ranked", lambda s: s["i"]), i) - 1
    return df.withColumn("_ranked", ranked).withColumn("hidden", F.transform(_slots(w), lambda i: unit(seed, *IDS, i) < chance(rank(i)))).drop("_ranked")


def mnar_burst(df: DataFrame, w: int, p: float, seed: int = SEEDS["burst"]) -> DataFrame:
    """One run of missing slots, or two runs in the two halves above a half."""
    if p <= 0.5:
        n = max(1, min(w // 2, round(p * w)))
        start = draw(seed, *IDS) % (w - n + 1)
        return df.withColumn("hidden", F.transform(_slots(w), lambda i: (i >= start) & (i < start + n)))
    half = w // 2
    n1, n2 = min(half, round(p * w / 2)), min(w - half, round(p * w) - min(half, round(p * w / 2)))
    a = draw(seed, *IDS, F.lit(1)) % (half - n1 + 1)
    b = half + draw(seed, *IDS, F.lit(2)) % (w - half - n2 + 1)
    return df.withColumn("hidden", F.transform(_slots(w), lambda i: ((i >= a) & (i < a + n1)) | ((i >= b) & (i < b + n2))))


def mnar_group(df: DataFrame, w: int, group: str, p: float, seed: int = SEEDS["group"]) -> DataFrame:
    """The same gaps for all series of a group: shared maintenance."""
    return df.withColumn("hidden", F.transform(_slots(w), lambda i: unit(seed, group, "win", i) < p))


GENERATORS = {"mcar": mcar, "mcar_exact": mcar_exact, "mnar_value": mnar_value, "mnar_burst": mnar_burst}


def gap_runs(cells: DataFrame) -> DataFrame:
    """(series_id, start, length) of maximal runs of empty slots; ``cells`` has series_id, slot, value on the whole grid."""
    by = Window.partitionBy("series_id").orderBy("slot")
    empty = cells.withColumn("island", F.col("slot") - F.row_number().over(Window.partitionBy("series_id", F.col("value").isNull()).orderBy("slot")))
    del by
    return empty.where("value IS NULL").groupBy("series_id", "island").agg(F.min("slot").alias("start"), F.count("*").alias("length")).drop("island")


def missing_profile(wins: DataFrame, w: int, by: list[str]) -> DataFrame:
    """Missing share, complete and empty windows for every level of ``by`` (a rollup)."""
    return wins.rollup(*by).agg(
        F.count("*").alias("windows"),
        F.sum(F.lit(w) - F.col("n_obs")).alias("missing"),
        (F.sum(F.lit(w) - F.col("n_obs")) / (F.count("*") * w)).alias("share"),
        F.sum(F.col("complete").cast("int")).alias("complete"),
        F.sum((F.col("n_obs") == 0).cast("int")).alias("empty"),
    )
