"""Projection of gap patterns: pairing, rivals, the structure test, and the three masked training sets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import SEEDS, draw, unit
from ..functions.masks import n_words, observed, pattern_kl


def _ranked(df: DataFrame, seed: int) -> DataFrame:
    order = Window.partitionBy("cluster").orderBy(draw(seed, "series_id", "win"), "series_id", "win")
    return df.withColumn("rank", F.row_number().over(order))


def pair(incomplete: DataFrame, complete: DataFrame, mode: str = "wrap", home: str = "cluster") -> DataFrame:
    """Each incomplete window with a complete one of its cluster, both in hash order.

    ``wrap`` uses complete windows again when they are short, ``injective`` drops the surplus, ``replacement`` draws.
    Incomplete needs cluster, series_id, win, words; complete cluster, series_id, win, z. ``home`` is the column of the
    incomplete windows that names the cluster to pair from, where several collections share the complete windows.

    Only as many complete windows as a cluster's incomplete ones ask for are ranked: those under a threshold of the hash
    that twice as many and a thousand more are expected to be below.
    """
    spark = complete.sparkSession
    asked = incomplete.groupBy("cluster", F.col(home).alias("home")).agg(F.count("*").alias("n")).groupBy("home").agg(F.max("n").alias("n"))
    asked = {r.home: r.n for r in asked.collect()}  # one row a cluster
    sizes = {r.cluster: r.n for r in complete.groupBy("cluster").agg(F.count("*").alias("n")).collect() if r.cluster in asked}
    share = {c: 1.0 if mode == "replacement" or n <= 4 * asked[c] + 2000 else (2 * asked[c] + 1000) / n for c, n in sizes.items()}
    table = F.broadcast(spark.createDataFrame([(c, n, share[c] * float(1 << 32)) for c, n in sorted(sizes.items())] or [(-1, 0, 0.0)], "cluster int, n_comp long, below double"))
    inc = _ranked(incomplete.select("cluster", F.col(home).alias("home"), "series_id", "win", "words"), SEEDS["inc"])
    chosen = complete.select("cluster", "series_id", "win", "z").join(table, "cluster").where(draw(SEEDS["comp"], "series_id", "win") < F.col("below"))
    comp = _ranked(chosen, SEEDS["comp"]).select(F.col("cluster").alias("home"), F.col("rank").alias("comp_rank"), F.col("series_id").alias("comp_series"), F.col("win").alias("comp_win"), "z")
    inc = inc.join(table.select(F.col("cluster").alias("home"), "n_comp"), "home")
    if mode == "wrap":
        at = (F.col("rank") - 1) % F.col("n_comp") + 1
    elif mode == "injective":
        inc, at = inc.where(F.col("rank") <= F.col("n_comp")), F.col("rank")
    elif mode == "replacement":
        at = F.floor(unit(SEEDS["comp"] + 500, "series_id", "win") * F.col("n_comp")) + 1
    else:
        raise ValueError("mode is wrap, injective or replacement")
    return inc.withColumn("comp_rank", at.cast("int")).join(comp, ["home", "comp_rank"])


def project(words: str | Column, x: str | Column, w: int) -> Column:
    """The values of ``x`` where the mask has a slot, null elsewhere."""
    words, x = (F.col(c) if isinstance(c, str) else c for c in (words, x))
    return F.transform(x, lambda v, i: F.when(F.getbit(F.element_at(words, (i / 64).cast("int") + 1), (i % 64).cast("int")) == 1, v))


def random_pattern(words: str | Column, w: int, *ids: str, seed: int = SEEDS["random"]) -> Column:
    """A mask with as many gaps, on the slots whose draws are the least."""
    gone = F.lit(w) - observed(words, w)
    slots = F.transform(F.sequence(F.lit(0), F.lit(w - 1)), lambda i: F.struct(draw(seed, *ids, i).alias("h"), i.alias("i")))
    hidden = F.transform(F.slice(F.array_sort(slots), F.lit(1), gone), lambda s: s["i"])
    return F.array(*[_without(hidden, k, w) for k in range(n_words(w))])


def _without(hidden: Column, k: int, w: int) -> Column:
    size = min(64, w - 64 * k)
    full = (1 << size) - 1 if size < 64 else -1
    bits = F.aggregate(F.filter(hidden, lambda i: (i >= 64 * k) & (i < 64 * (k + 1))), F.lit(0).cast("long"), lambda a, i: a.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("long"), (i - 64 * k).cast("int"))))
    return F.lit(full).cast("long").bitwiseXOR(bits)


def sampled_rival(incomplete: DataFrame, seed: int = SEEDS["rival"]) -> DataFrame:
    """Adds rival: the mask of the next window of the cluster in hash order, the first for the last, null if alone."""
    by = Window.partitionBy("cluster")
    order = by.orderBy(draw(seed, "series_id", "win"), "series_id", "win")
    follow = F.coalesce(F.lead("words").over(order), F.first("words").over(order.rowsBetween(Window.unboundedPreceding, Window.currentRow)))
    return incomplete.withColumn("rival", F.when(F.count("*").over(by) > 1, follow))


def compared(incomplete: DataFrame, w: int, eps: float = 0.1) -> DataFrame:
    """Adds rival, random, kl_s (to the sampled rival) and kl_r (to the random one)."""
    both = sampled_rival(incomplete).withColumn("random", random_pattern("words", w, "series_id", "win"))
    return both.withColumns({"kl_s": pattern_kl("words", "rival", w, eps), "kl_r": pattern_kl("words", "random", w, eps)})


def structure(with_kl: DataFrame, gate: float = 2 / 3) -> DataFrame:
    """(cluster, n_p, n, ratio, kept): the share of patterns nearer to a real rival than to a random one."""
    closer = F.col("kl_s") < F.col("kl_r") - 1e-9
    g = with_kl.groupBy("cluster").agg(F.sum(closer.cast("int")).alias("n_p"), F.count("*").alias("n"))
    return g.withColumn("ratio", F.col("n_p") / F.col("n")).withColumn("kept", F.coalesce(F.col("ratio") > gate, F.lit(False)))


def select_pattern(kl_s: str = "kl_s", kl_r: str = "kl_r", sampled: str = "rival", random: str = "random") -> Column:
    """The sampled pattern where it is the nearer one, else the random one."""
    return F.when(F.col(kl_s) < F.col(kl_r) - 1e-9, F.col(sampled)).otherwise(F.col(random))


def keep_structured(df: DataFrame, found: DataFrame) -> DataFrame:
    """Only rows of clusters above the gate."""
    return df.join(F.broadcast(found.where("kept").select("cluster")), "cluster", "left_semi")


def artificial_mask(w: int, share: float | Column, *ids: str, seed: int = SEEDS["mask"], run: int = 0, min_positions: int = 1, eligible: Column | None = None) -> Column:
    """Words of the slots that stay visible: each is hidden with chance ``share``, at least ``min_positions`` of the eligible ones."""
    share = share if isinstance(share, Column) else F.lit(float(share))
    able = (lambda i: F.getbit(F.element_at(eligible, (i / 64).cast("int") + 1), (i % 64).cast("int")) == 1) if eligible is not None else (lambda i: F.lit(True))
    slots = F.filter(F.sequence(F.lit(0), F.lit(w - 1)), able)
    drawn = F.array_sort(F.transform(slots, lambda i: F.struct(unit(seed, F.lit(run), *ids, i).alias("u"), i.alias("i"))))
    chosen = F.filter(drawn, lambda s, k: (s["u"] < share) | (k < min_positions))
    hidden = F.transform(chosen, lambda s: s["i"])
    return F.array(*[_without(hidden, k, w) for k in range(n_words(w))])


def words_and(a: Column, b: Column, w: int) -> Column:
    return F.array(*[a[k].bitwiseAND(b[k]) for k in range(n_words(w))])


def masked_sets(pairs: DataFrame, w: int, share: float | Column, run: int = 0, keep: tuple[str, ...] = ()) -> DataFrame:
    """(cluster, role, series_id, win, x_in, y, shown, *keep): projected, masked, and both; y keeps the truth."""
    extra = artificial_mask(w, share, "series_id", "win", run=run)
    p = pairs.withColumn("extra", extra).withColumn("both", words_and(F.col("words"), F.col("extra"), w))
    roles = F.array(*[F.struct(F.lit(r).alias("role"), F.col(c).alias("shown")) for r, c in (("proj", "words"), ("mask", "extra"), ("proj_mask", "both"))])
    rows = p.select("cluster", "series_id", "win", F.col("z").alias("y"), F.explode(roles).alias("r"), *keep)
    return rows.select("cluster", "r.role", "series_id", "win", project(F.col("r.shown"), F.col("y"), w).alias("x_in"), "y", F.col("r.shown").alias("shown"), *keep)
