"""Bound-limited assignment of incomplete windows to clusters.

Every window takes its nearest cluster that is still open; a cluster closes when its windows' observable shares reach
the bound or it is full. All clusters see the windows in one hash order, so the sequential rule equals deferred
acceptance: windows propose in rounds, and a cluster holds the first proposals, in hash order, that it has room for.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.gapdtw import ranked
from ..functions.hashing import SEEDS, draw
from ..sources.scratch import materialise
from .bounds import observable_ratio


def sample_incomplete(wins: DataFrame, clusters: int, need: float, gamma: float, safety: float = 1.5, total: int | None = None) -> DataFrame:
    """Enough incomplete windows, by hash, to fill all clusters: about clusters * safety * need / gamma of them."""
    total = wins.count() if total is None else total
    want = math.ceil(clusters * safety * need / max(gamma, 1e-9))
    if want >= total:
        return wins
    return wins.where(draw(SEEDS["sample"], "series_id", "win") < want / total * float(1 << 32))


def proposals(wins: DataFrame, distances, mask: float, w: int, gamma_rule: str = "product", base=None, keep: tuple[str, ...] = ()) -> DataFrame:
    """(series_id, win, h, gamma, choices, no_evidence, *keep): each window's clusters, nearest first. Map only.

    ``base`` is added to the cluster numbers: several collections over K clusters each are dealt at once with base = i K.
    """
    missing = (F.lit(w) - F.col("n_obs")) / F.lit(float(w))
    choices = ranked(F.transform(distances, lambda d: F.coalesce(d, F.lit(0.0))))
    if base is not None:
        choices = F.transform(choices, lambda c: F.struct(c["dist"].alias("dist"), (c["cluster"] + base).alias("cluster")))
    return wins.select(
        "series_id",
        "win",
        draw(SEEDS["inc"], "series_id", "win").alias("h"),
        observable_ratio(missing, mask, gamma_rule).alias("gamma"),
        choices.alias("choices"),
        (F.col("n_obs") == 0).alias("no_evidence"),
        *keep,
    )


def assign_incomplete(proposed: DataFrame, need: float, max_size: int, overflow: str = "smallest") -> DataFrame:
    """(series_id, win, cluster, dist, choice_rank, gamma, no_evidence, ...) of the windows admitted.

    A round first keeps, by cluster, the ``max_size`` first proposals in hash order (a bounded group, cut before the
    shuffle), and then sums their shares. Each round is written to shared storage, which cuts its lineage. Without any
    bound every window has its first choice, in one map.
    """
    kept = [c for c in proposed.columns if c not in ("h", "choices")]
    of = lambda at, what: F.try_element_at("choices", at)[what]
    columns = ["series_id", "win", "cluster", "dist", "choice_rank", *[c for c in kept if c not in ("series_id", "win")]]
    if math.isinf(need) and max_size >= 1 << 30:
        first = proposed.where(F.size("choices") > 0).withColumns({"cluster": of(F.lit(1), "cluster"), "dist": of(F.lit(1), "dist"), "choice_rank": F.lit(1)})
        return first.select(*columns)
    state = materialise(proposed.withColumn("at", F.lit(1)), "proposals")
    clusters = (state.agg(F.max(F.size("choices"))).first()[0]) or 0
    order = Window.partitionBy("cluster").orderBy("h", "series_id", "win")
    while True:
        state = state.withColumn("cluster", of(F.col("at"), "cluster"))
        asking = state.where(F.col("at") <= clusters).select("series_id", "win", "cluster", "h", "gamma")
        first = asking.withColumn("place", F.row_number().over(order)).where(F.col("place") <= max_size)
        before = F.sum("gamma").over(order.rowsBetween(Window.unboundedPreceding, -1))
        held = first.withColumn("before", F.coalesce(before, F.lit(0.0))).where(F.col("before") < need).select("series_id", "win", "cluster", F.lit(True).alias("held"))
        state_next = state.join(held, ["series_id", "win", "cluster"], "left").withColumn("rejected", F.col("held").isNull() & (F.col("at") <= clusters))
        state_next = materialise(state_next.withColumn("at", F.col("at") + F.col("rejected").cast("int")).drop("held", "cluster"), "round")
        if not state_next.where("rejected").limit(1).count():
            break
        state = state_next.drop("rejected")
    state = state_next.drop("rejected")
    placed = state.where(F.col("at") <= clusters).withColumns({"cluster": of(F.col("at"), "cluster"), "dist": of(F.col("at"), "dist")}).withColumnRenamed("at", "choice_rank").select(*columns)
    if overflow == "drop":
        return placed
    left = state.where(F.col("at") > clusters).drop("at")
    n = left.count()
    if not n:
        return placed
    return placed.unionByName(_seated(left, placed, clusters, n).select(*columns))


def _seated(left: DataFrame, placed: DataFrame, clusters: int, n: int, per_bucket: int = 50_000) -> DataFrame:
    """Leftovers, in hash order, one by one in the smallest cluster of their collection.

    Where the i-th of them goes follows from the sizes alone; i is the count of the hash buckets before its own and its
    place in its bucket, so no task orders more than a bucket.
    """
    spark = left.sparkSession
    buckets = -(-n // per_bucket)
    left = left.withColumns({"collection": F.floor(F.col("choices")[0]["cluster"] / clusters).cast("int"), "bucket": F.floor(F.col("h") * buckets / F.lit(float(1 << 32))).cast("int")})
    sizes = {r.cluster: r.n for r in placed.groupBy("cluster").agg(F.count("*").alias("n")).collect()}
    counts = sorted((r.collection, r.bucket, r.n) for r in left.groupBy("collection", "bucket").agg(F.count("*").alias("n")).collect())
    offsets, run = [], {}
    for g, b, m in counts:
        offsets.append((g, b, run.get(g, 0)))
        run[g] = run.get(g, 0) + m
    table = F.broadcast(spark.createDataFrame(offsets, "collection int, bucket int, ahead long"))  # one row for each 50,000 leftovers
    place = F.row_number().over(Window.partitionBy("collection", "bucket").orderBy("h", "series_id", "win"))
    rows = left.withColumn("place", place).join(table, ["collection", "bucket"]).withColumn("seat", F.col("ahead") + F.col("place") - 1)
    goes = None
    for g in sorted(run):
        for begin, ids in fill_phases({c: sizes.get(c, 0) for c in range(g * clusters, (g + 1) * clusters)}):
            mine = F.element_at(F.array(*[F.lit(i) for i in ids]), ((F.col("seat") - begin) % len(ids) + 1).cast("int"))
            now = (F.col("collection") == g) & (F.col("seat") >= begin)
            goes = F.when(now, mine) if goes is None else F.when(now, mine).otherwise(goes)
    rows = rows.withColumn("cluster", goes)
    return rows.withColumns({"dist": F.expr("filter(choices, c -> c.cluster = cluster)[0].dist"), "choice_rank": F.lit(clusters + 1)})


def fill_phases(sizes: dict[int, int]) -> list[tuple[int, list[int]]]:
    """(first leftover, clusters that take turns from there on) while leftovers go to the smallest, ties to the lowest number."""
    order = sorted(sizes.items(), key=lambda x: (x[1], x[0]))
    phases, begin = [], 0
    for j in range(1, len(order) + 1):
        if j < len(order) and order[j][1] == order[j - 1][1]:
            continue
        phases.append((begin, sorted(c for c, _ in order[:j])))
        if j < len(order):
            begin += j * (order[j][1] - order[j - 1][1])
    return phases


def filled_sizes(sizes: dict[int, int], n: int) -> dict[int, int]:
    """Sizes after n leftovers, in closed form."""
    phases, out = fill_phases(sizes), dict(sizes)
    for i, (begin, ids) in enumerate(phases):
        end = min(n, phases[i + 1][0]) if i + 1 < len(phases) else n
        each, rest = divmod(max(0, end - begin), len(ids))
        for k, c in enumerate(ids):
            out[c] += each + (k < rest)
    return out


def fill_smallest(sizes: dict[int, int], n: int) -> list[int]:
    """The clusters that n leftovers go to, in order."""
    phases, out = fill_phases(sizes), []
    for i, (begin, ids) in enumerate(phases):
        end = min(n, phases[i + 1][0]) if i + 1 < len(phases) else n
        out.extend(ids[k % len(ids)] for k in range(max(0, end - begin)))
    return out


def assign_sequential(rows: list[dict], need: float, max_size: int, clusters: int, overflow: str = "smallest") -> dict:
    """The same by the plain loop, for tests: rows have id, h, gamma, choices (clusters, nearest first)."""
    size, share, out, left = [0] * clusters, [0.0] * clusters, {}, []
    for r in sorted(rows, key=lambda r: (r["h"], r["id"])):
        for rank, c in enumerate(r["choices"], 1):
            if share[c] < need and size[c] < max_size:
                size[c] += 1
                share[c] += r["gamma"]
                out[r["id"]] = (c, rank)
                break
        else:
            left.append(r)
    if overflow == "smallest":
        for r, c in zip(left, fill_smallest(dict(enumerate(size)), len(left)), strict=True):
            out[r["id"]] = (c, clusters + 1)
    return out


def measured_shares(assigned: DataFrame, beta: float) -> dict[int, tuple[int, float]]:
    """cluster -> (windows, mean share that is neither missing nor under the extra mask), from the patterns admitted.

    ``gamma`` is the product rule's share under the same mask, so a window's missing share is 1 - gamma / (1 - beta).
    """
    share = F.greatest(F.lit(0.0), F.col("gamma") / (1 - beta) - beta)
    return {r.cluster: (r.n, r.share) for r in assigned.groupBy("cluster").agg(F.count("*").alias("n"), F.avg(share).alias("share")).collect()}  # one row a cluster


def refine_assignment(assigned: DataFrame, reserve: DataFrame, measured: dict[int, tuple[int, float]], need: float) -> DataFrame:
    """One more admission from the reserve, where a cluster's windows times its measured share fall short of the bound."""
    short = [(c, math.ceil(need / max(g, 1e-9)) - n) for c, (n, g) in measured.items()]
    quota = assigned.sparkSession.createDataFrame([s for s in short if s[1] > 0] or [(-1, 0)], "cluster int, quota int")
    ranked_ = reserve.withColumn("cluster", F.col("choices")[0]["cluster"]).join(F.broadcast(quota), "cluster")
    place = F.row_number().over(Window.partitionBy("cluster").orderBy("h", "series_id", "win"))
    more = ranked_.withColumn("place", place).where(F.col("place") <= F.col("quota"))
    more = more.withColumns({"dist": F.col("choices")[0]["dist"], "choice_rank": F.lit(1)})
    return assigned.unionByName(more.select(*assigned.columns))


def cluster_balance(assigned: DataFrame, need: float, max_size: int, clusters: int) -> DataFrame:
    """Per cluster: size, sum of shares, closed, and how many windows got their first, second ... choice."""
    ranks = [F.sum((F.col("choice_rank") == r).cast("int")).alias(f"choice_{r}") for r in range(1, clusters + 2)]
    g = assigned.groupBy("cluster").agg(F.count("*").alias("size"), F.sum("gamma").alias("share"), *ranks)
    return g.withColumn("closed", (F.col("share") >= need) | (F.col("size") >= max_size))
