"""Mixing sources to target weights by capped water-filling.

Every source gets a share of the budget in proportion to its weight, clamped at a number of epochs over its own
words; what a clamped source cannot take is dealt again to the others by weight, until no source is above its
clamp. A source's rate (target / size) is then met by whole repetitions of all its documents and one fractional
repetition, a seeded sample of whole documents: they are ordered by a hash, and those up to a threshold are
repeated once more. The document in which the target is reached is taken or left by a seeded draw with the chance of
its share, so a source misses its target by less than that document, and on average by nothing. No text is ever cut.

Defined results: a null or blank text has size 0 and takes 0; a null source is a source of its own, the last in
order; repeated rows count as often as they occur, and go together; sources of size 0 have target 0; an empty table gives an
empty result; other columns are ignored, whatever their names.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialise, word_count

#: Sources that the driver may hold (a row of four numbers each) while it fills them.
MAX_SOURCES = 1_000_000
#: The order of documents in a bucket; rows equal in all three are equal in id and text.
KEY = ("_draw", "_tie_id", "_tie_mark")


def water_fill(sizes: Sequence[float], weights: Sequence[float], budget: float, max_epochs: float) -> list[float]:
    """Targets that share ``budget`` by weight, none above ``max_epochs`` times its size.

    Beyond what all sources can give, every target is at its clamp.
    """
    caps = [max_epochs * s for s in sizes]
    targets = [0.0] * len(caps)
    open_ = [i for i, c in enumerate(caps) if c > 0 and weights[i] > 0]
    left = min(float(budget), float(sum(caps[i] for i in open_)))
    while open_:
        level = left / sum(weights[i] for i in open_)
        full = [i for i in open_ if weights[i] * level >= caps[i]]
        if not full:
            for i in open_:
                targets[i] = weights[i] * level
            break
        for i in full:
            targets[i] = caps[i]
            left -= caps[i]
        open_ = [i for i in open_ if targets[i] == 0.0]
    return targets


def _sized(docs: DataFrame, seed: int, buckets: int) -> DataFrame:
    """``docs`` with _source, _size (words), _draw (a seeded hash), _bucket, and _tie_mark and _tie_id to break ties of _draw."""
    rows = docs.withColumns({"_source": F.col("source").cast("string"), "_size": word_count("text"), "_tie_mark": F.xxhash64("text"), "_tie_id": F.coalesce(F.col("doc_id").cast("long"), F.lit(-1).cast("long"))})
    rows = rows.withColumn("_draw", F.xxhash64(F.lit(seed), F.col("doc_id").cast("long"), F.col("_size")))
    return rows.withColumn("_bucket", F.pmod("_draw", F.lit(buckets)).cast("int"))


def source_rates(sized: DataFrame, weights: Sequence[float], budget_share: float, max_epochs: float, seed: int) -> DataFrame:
    """One row per source: its size, target, whole repetitions, and the threshold of its fractional repetition.

    The threshold is a bucket and, inside it, the last document taken (``last``, null if none is).
    """
    spark = sized.sparkSession
    listed = sized.groupBy("_source").agg(F.sum("_size").alias("n")).limit(MAX_SOURCES + 1).collect()
    if len(listed) > MAX_SOURCES:
        raise ValueError(f"more than {MAX_SOURCES} sources: mix groups of sources instead")
    listed.sort(key=lambda r: (r._source is None, (r._source or "").encode()))
    sizes = [int(r.n) for r in listed]
    targets = water_fill(sizes, [float(weights[i % len(weights)]) for i in range(len(listed))], budget_share * sum(sizes), max_epochs)
    plan = [(r._source, n, t, *_whole_and_rest(t, n)) for r, n, t in zip(listed, sizes, targets, strict=True)]
    plan_df = spark.createDataFrame(plan, "source string, source_size long, target double, whole long, rest double")

    # The threshold of the fractional repetition, from a histogram of words by hash bucket.
    filled = sized.groupBy("_source", "_bucket").agg(F.sum("_size").alias("words"))
    steps = filled.groupBy("_source").agg(F.array_sort(F.collect_list(F.struct(F.col("_bucket").alias("bucket"), "words"))).alias("steps"))
    start = F.struct(F.lit(0.0).alias("below"), F.lit(-1).alias("edge"))

    def step(acc, x):  # words below the threshold so far; the bucket in which the rest is reached
        reached = (acc["edge"] < 0) & (acc["below"] + x["words"] > F.col("rest"))
        return F.struct(
            F.when(acc["edge"] < 0, F.when(reached, acc["below"]).otherwise(acc["below"] + x["words"])).otherwise(acc["below"]).alias("below"),
            F.when(reached, x["bucket"]).otherwise(acc["edge"]).alias("edge"),
        )

    rates = (
        plan_df.join(steps, F.col("source").eqNullSafe(F.col("_source")), "left")
        .withColumn("found", F.aggregate(F.coalesce("steps", F.array().cast("array<struct<bucket:int,words:bigint>>")), start, step))
        .select(F.col("source").alias("_of"), "source_size", "target", "whole", "rest", F.col("found.edge").alias("edge"), F.col("found.below").alias("below"))
    )
    rates = materialise(rates.coalesce(1), "rates")

    # Inside that bucket, documents in hash order as long as they fit; the one in which the rest is reached by a draw.
    at_edge = sized.join(rates.select("_of", "edge", "below", "rest"), F.col("_source").eqNullSafe(F.col("_of")) & (F.col("_bucket") == F.col("edge")))
    tied = at_edge.groupBy("_of", *KEY).agg(F.sum("_size").alias("words"), F.first("below").alias("below"), F.first("rest").alias("rest"))
    to_here = F.sum("words").over(Window.partitionBy("_of").orderBy(*KEY).rowsBetween(Window.unboundedPreceding, Window.currentRow))
    room = F.col("rest") - F.col("below") - (to_here - F.col("words"))
    unit = F.pmod(F.xxhash64(F.lit(seed + 1), F.col("_draw")), F.lit(1 << 20)) / F.lit(float(1 << 20))
    fits = (room > 0) & (unit * F.col("words") < room)
    last = tied.withColumn("_fits", fits).where("_fits").groupBy("_of").agg(F.max(F.struct(*KEY)).alias("last"))
    last = last.withColumnRenamed("_of", "_by")
    return materialise(rates.join(last, F.col("_of").eqNullSafe(F.col("_by")), "left").drop("_by", "below").coalesce(1), "thresholds")


def _taken(sized: DataFrame, rates: DataFrame) -> DataFrame:
    """``sized`` with repeats, all of the whole text.

    Rates have one row a source: adaptive execution broadcasts them if they are small, and else splits hot sources in
    a sort-merge join.
    """
    met = sized.join(rates, F.col("_source").eqNullSafe(F.col("_of")))
    past = (F.col("edge") < 0) & (F.col("rest") > 0)  # the whole histogram lies below the threshold
    up_to_last = (F.col("_bucket") == F.col("edge")) & F.coalesce(F.struct(*KEY) <= F.col("last"), F.lit(False))
    once_more = past | (F.col("_bucket") < F.col("edge")) | up_to_last
    return met.withColumn("repeats", (F.col("whole") + F.when(once_more, 1).otherwise(0)).cast("long"))


def mix(docs: DataFrame, weights: Sequence[float] = (3, 1, 2), budget_share: float = 1.5, max_epochs: float = 2.0, seed: int = 17, buckets: int = 4096) -> DataFrame:
    """One row per document: doc_id, source, size, source_size, target, repeats, taken.

    ``weights`` repeat over the sources in code point order, null last. ``taken`` is the number of words that the
    mix takes: ``repeats`` times the whole text.
    """
    sized = _sized(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "source", "text"), seed, buckets)
    sized = materialise(sized.select("doc_id", "_source", "_size", "_bucket", *KEY), "sizes")
    taken = _taken(sized, source_rates(sized, weights, budget_share, max_epochs, seed))
    shown = taken.select("doc_id", F.col("_source").alias("source"), F.col("_size").alias("size"), "source_size", "target", "repeats")
    return shown.withColumn("taken", (F.col("repeats") * F.col("size")).cast("long"))


def mix_rows(docs: DataFrame, weights: Sequence[float] = (3, 1, 2), budget_share: float = 1.5, max_epochs: float = 2.0, seed: int = 17, buckets: int = 4096) -> DataFrame:
    """The mix itself: the rows of ``docs``, all columns, as often as the mix takes them, every one with its whole text.

    Texts stay where they lie: only the rates are joined to them.
    """
    plain = docs.select(F.struct("*").alias("_row"), F.col("doc_id").cast("long").alias("doc_id"), "source", "text")
    keys = ("_source", "_size", "_bucket", *KEY)
    sizes = materialise(_sized(plain, seed, buckets).select(*keys), "sizes")
    taken = _taken(_sized(plain, seed, buckets).select("_row", *keys), source_rates(sizes, weights, budget_share, max_epochs, seed))
    rows = taken.where("repeats > 0").withColumn("_copy", F.explode(F.sequence(F.lit(1).cast("long"), F.col("repeats"))))
    return rows.select("_row.*")


def _whole_and_rest(target: float, size: int) -> tuple[int, float]:
    whole = int(target // size) if size else 0
    return whole, max(0.0, target - whole * size)
