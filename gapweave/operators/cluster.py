"""Clustering of complete windows: mini-batch and full k-means, the Davies-Bouldin index, the search for k."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.gapdtw import nearest
from ..functions.hashing import SEEDS, draw, draw_py
from .series import NoCompleteWindows

#: Windows that a clustering sample may hold.
MAX_SAMPLE = 1_000_000


def training_sample(wins: DataFrame, most: int = MAX_SAMPLE) -> DataFrame:
    """At most about ``most`` complete windows (series_id, win, z), drawn by hash in one map-side filter."""
    n = wins.count()
    if n <= most:
        return wins
    return wins.where(draw(SEEDS["sample"], "series_id", "win") < most / n * float(1 << 32))


def _points(wins: DataFrame, n: int, seed: int = SEEDS["init"]) -> np.ndarray:
    """The first n windows in hash order."""
    ordered = wins.select("z", draw(seed, "series_id", "win").alias("h"), "series_id", "win").orderBy("h", "series_id", "win")
    rows = ordered.limit(n).collect()
    if not rows:
        raise NoCompleteWindows("no complete window to start from")
    return np.array([r.z for r in rows], dtype=float)


def _start(points: np.ndarray, k: int, how: str, seed: int = SEEDS["init"]) -> np.ndarray:
    if how == "hash":
        return points[:k]
    chosen = [points[0]]
    for i in range(1, min(k, len(points))):
        d = ((points[:, None, :] - np.array(chosen)[None]) ** 2).sum(axis=2).min(axis=1)
        u = draw_py(seed, "plus", i) / float(1 << 32) * d.sum()
        chosen.append(points[min(int(np.searchsorted(np.cumsum(d), u)), len(points) - 1)])
    return np.array(chosen)


def initial_centroids(wins: DataFrame, k: int, how: str = "hash", seed: int = SEEDS["init"], sample: int = 4096) -> np.ndarray:
    """k starting points: the first in hash order, or spread by squared distance (k-means++) over a bounded sample."""
    return _start(_points(wins, k if how == "hash" else max(k, sample), seed), k, how, seed)


def _partials(batch: DataFrame, centroids: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
    """Sums, counts and inertia by nearest centroid: K rows reach the driver."""
    k, w = centroids.shape

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums, counts, cost = np.zeros((k, w)), np.zeros(k), np.zeros(k)
        for b in batches:
            if not b.num_rows:
                continue
            z = np.array(b.column("z").to_pylist(), dtype=float)
            d = ((z[:, None, :] - centroids[None]) ** 2).sum(axis=2)
            at = d.argmin(axis=1)
            np.add.at(sums, at, z)
            np.add.at(counts, at, 1)
            np.add.at(cost, at, d[np.arange(len(z)), at])
        yield pa.record_batch([pa.array(range(k), pa.int32()), pa.array(sums.tolist(), pa.list_(pa.float64())), pa.array(counts), pa.array(cost)], names=["cluster", "sums", "n", "cost"])

    parts = batch.select("z").mapInArrow(run, "cluster int, sums array<double>, n double, cost double")
    cells = [F.sum(F.col("sums")[j]).alias(f"s{j}") for j in range(w)]
    rows = parts.groupBy("cluster").agg(*cells, F.sum("n").alias("n"), F.sum("cost").alias("cost")).collect()
    sums, counts, cost = np.zeros((k, w)), np.zeros(k), 0.0
    for r in rows:
        sums[r.cluster], counts[r.cluster], cost = [r[f"s{j}"] for j in range(w)], r.n, cost + r.cost
    return sums, counts, cost


def lloyd(wins: DataFrame, k: int, iterations: int = 10, init: str = "hash", tolerance: float = 0.0) -> np.ndarray:
    """Full k-means: every step reads all windows, the centroids stay plain driver arrays. An empty cluster keeps its centroid."""
    centroids = initial_centroids(wins, k, init)
    for _ in range(iterations):
        sums, counts, _ = _partials(wins, centroids)
        new = np.where(counts[:, None] > 0, sums / np.maximum(counts, 1)[:, None], centroids)
        moved = float(np.abs(new - centroids).max())
        centroids = new
        if moved <= tolerance:
            break
    return centroids


def _batches(wins: DataFrame, batch: int, iterations: int, seed: int) -> tuple[list[np.ndarray], bool]:
    """Mini-batches drawn by hash, all in one job, and whether a batch is everything.

    About ``batch * iterations`` windows at most reach the driver, whatever the size of ``wins``.
    """
    total = wins.count()
    if not total:
        raise NoCompleteWindows("no complete window to cluster")
    if batch >= total:
        rows = sorted(wins.select("series_id", "win", "z").collect())
        return [np.array([r.z for r in rows], dtype=float)], True
    tags = [F.when(draw(seed + 1000 * (t + 1), "series_id", "win") < batch / total * float(1 << 32), t) for t in range(iterations)]
    rows = sorted(wins.select(F.explode(F.array_compact(F.array(*tags))).alias("t"), "series_id", "win", "z").collect())
    found = [[r.z for r in rows if r.t == t] for t in range(iterations)]
    return [np.array(f, dtype=float) for f in found if f], False


def _descend(centroids: np.ndarray, batches: list[np.ndarray], whole: bool, iterations: int) -> np.ndarray:
    """A centre moves by its batch mean at the rate 1 / (points it has seen); a batch of everything is a step of Lloyd's."""
    centroids, seen = centroids.copy(), np.zeros(len(centroids))
    for t in range(iterations):
        z = batches[t % len(batches)]
        at = ((z[:, None, :] - centroids[None]) ** 2).sum(axis=2).argmin(axis=1)
        counts = np.bincount(at, minlength=len(centroids)).astype(float)
        sums = np.zeros_like(centroids)
        np.add.at(sums, at, z)
        seen = counts if whole else seen + counts
        hit = counts > 0
        centroids[hit] += (counts[hit] / seen[hit])[:, None] * (sums[hit] / counts[hit][:, None] - centroids[hit])
    return centroids


def minibatch_kmeans(wins: DataFrame, k: int, batch: int = 1024, iterations: int = 20, init: str = "plus", seed: int = SEEDS["batch"]) -> np.ndarray:
    """k-means on hashed batches: a bounded sample is fetched in one job, the steps are the driver's."""
    batches, whole = _batches(wins, batch, iterations, seed)
    return _descend(initial_centroids(wins, k, init), batches, whole, iterations)


def stable_order(centroids: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Cluster numbers by falling size, then by centroid."""
    order = sorted(range(len(centroids)), key=lambda c: (-counts[c], tuple(centroids[c])))
    return centroids[order]


def _stats(wins: DataFrame, sets: list[np.ndarray]) -> list[tuple[np.ndarray, np.ndarray, float]]:
    """(counts, sums of distances, inertia) by nearest centroid, of every set of centroids, in one pass over ``wins``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = [np.zeros((len(c), 3)) for c in sets]
        for b in batches:
            for begin in range(0, b.num_rows, 4096):
                z = np.array(b.column("z").slice(begin, 4096).to_pylist(), dtype=float)
                for c, out in zip(sets, total, strict=True):
                    d = ((z[:, None, :] - c[None]) ** 2).sum(axis=2)
                    at = d.argmin(axis=1)
                    least = d[np.arange(len(z)), at]
                    np.add.at(out, at, np.stack([np.ones(len(z)), np.sqrt(least), least], axis=1))
        rows = [(i, k, *map(float, row)) for i, out in enumerate(total) for k, row in enumerate(out)]
        yield pa.record_batch([pa.array(c, kind) for c, kind in zip(zip(*rows, strict=True), (pa.int32(), pa.int32(), *[pa.float64()] * 3), strict=True)], names=["trial", "cluster", "n", "dist", "cost"])

    rows = wins.select("z").mapInArrow(run, "trial int, cluster int, n double, dist double, cost double").groupBy("trial", "cluster").agg(F.sum("n").alias("n"), F.sum("dist").alias("dist"), F.sum("cost").alias("cost")).collect()
    found = [(np.zeros(len(c)), np.zeros(len(c)), [0.0]) for c in sets]
    for r in rows:  # one row a centroid
        n, dist, cost = found[r.trial]
        n[r.cluster], dist[r.cluster] = r.n, r.dist
        cost[0] += r.cost
    return [(n, dist, cost[0]) for n, dist, cost in found]


def index_of(centroids: np.ndarray, counts: np.ndarray, distances: np.ndarray) -> float | None:
    """The Davies-Bouldin index from each cluster's size and sum of distances; None for one cluster or coincident centroids."""
    used = np.flatnonzero(counts > 0)
    if len(used) < 2:
        return None
    spread = distances[used] / counts[used]
    gap = np.sqrt(((centroids[used][:, None] - centroids[used][None]) ** 2).sum(axis=2))
    np.fill_diagonal(gap, np.inf)
    if not gap.all():
        return None
    return float(((spread[:, None] + spread[None]) / gap).max(axis=1).mean())


class Trials:
    """Restarted mini-batch clusterings of one sample: starting points and batches are fetched once for every k."""

    def __init__(self, wins: DataFrame, restarts: int = 3, batch: int = 4096, iterations: int = 15) -> None:
        self.wins, self.restarts, self.iterations = wins, restarts, iterations
        self.points = _points(wins, 4096)
        self.batches, self.whole = _batches(wins, batch, iterations, SEEDS["batch"])

    def best(self, k: int) -> tuple[np.ndarray, float | None]:
        """The centroids of least inertia, renumbered, and their index; one pass over the sample for all restarts."""
        made = []
        for r in range(self.restarts):
            turned = self.batches[r % len(self.batches) :] + self.batches[: r % len(self.batches)]
            made.append(_descend(_start(self.points, k, "plus" if r else "hash", SEEDS["init"] + 7 * max(0, r - 1)), turned, self.whole, self.iterations))
        found = _stats(self.wins, made)
        at = min(range(len(made)), key=lambda i: (found[i][2], i))
        counts, distances, _ = found[at]
        return stable_order(made[at], counts), index_of(made[at], counts, distances)


def best_of(wins: DataFrame, k: int, restarts: int = 3, batch: int = 4096, iterations: int = 15) -> np.ndarray:
    """The least inertia of several mini-batch runs, renumbered."""
    return Trials(wins, restarts, batch, iterations).best(k)[0]


def plain_distances(z: str, centroids: np.ndarray):
    return plain_distances_of(F.col(z), centroids)


def plain_distances_of(col, centroids: np.ndarray):
    out = []
    for c in centroids:
        diff = F.zip_with(col, F.array(*[F.lit(float(v)) for v in c]), lambda a, b: (a - b) * (a - b))
        out.append(F.sqrt(F.aggregate(diff, F.lit(0.0), lambda s, v: s + v)))
    return F.array(*out)


def cluster_sequences(wins: DataFrame, centroids: np.ndarray) -> DataFrame:
    """``wins`` with cluster and dist; map only, the centroids are literals of the plan (K * w numbers)."""
    near = nearest(plain_distances("z", centroids))
    return wins.withColumn("_near", near).withColumns({"cluster": F.col("_near.cluster"), "dist": F.col("_near.dist")}).drop("_near")


def scatter(assigned: DataFrame) -> DataFrame:
    return assigned.groupBy("cluster").agg(F.avg("dist").alias("scatter"), F.count("*").alias("n"))


def centroid_table(spark, centroids: np.ndarray) -> DataFrame:
    return spark.createDataFrame([(k, [float(v) for v in c]) for k, c in enumerate(centroids)], "cluster int, centroid array<double>")


def dbi_pairs(assigned: DataFrame, centroids: np.ndarray) -> DataFrame:
    """(i, j, similarity) of all cluster pairs: K rows joined with themselves."""
    c = scatter(assigned).join(centroid_table(assigned.sparkSession, centroids), "cluster")
    a, b = c.alias("a"), c.alias("b")
    gap = F.sqrt(F.aggregate(F.zip_with("a.centroid", "b.centroid", lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, v: s + v))
    pairs = a.join(F.broadcast(b), F.col("a.cluster") != F.col("b.cluster"))
    return pairs.select(F.col("a.cluster").alias("i"), F.col("b.cluster").alias("j"), ((F.col("a.scatter") + F.col("b.scatter")) / F.when(gap > 0, gap)).alias("similarity"))


def davies_bouldin(assigned: DataFrame, centroids: np.ndarray) -> DataFrame:
    """One row: dbi. Null for a single cluster or coincident centroids."""
    worst = dbi_pairs(assigned, centroids).groupBy("i").agg(F.max("similarity").alias("worst"), F.sum(F.col("similarity").isNull().cast("int")).alias("bad"))
    return worst.agg(F.when(F.sum("bad") == 0, F.avg("worst")).alias("dbi"))


@dataclass
class KSearch:
    k: int
    trace: dict[int, float] = field(default_factory=dict)
    at_boundary: bool = False


def search_k(score, kmin: int, kmax: int, how: str = "bisect") -> KSearch:
    """The k of the least score among those evaluated. Bisection follows the sign of score(k + 1) - score(k)."""
    trace: dict[int, float] = {}

    def at(k: int) -> float:
        if k not in trace:
            s = score(k)
            trace[k] = float("inf") if s is None else float(s)
        return trace[k]

    if how == "exhaustive":
        for k in range(kmin, kmax + 1):
            at(k)
    elif how == "ternary":
        lo, hi = kmin, kmax
        while hi - lo > 2:
            a, b = lo + (hi - lo) // 3, hi - (hi - lo) // 3
            lo, hi = (lo, b) if at(a) <= at(b) else (a, hi)
        for k in range(lo, hi + 1):
            at(k)
    elif how == "bisect":
        lo, hi = kmin, kmax
        while lo < hi:
            mid = (lo + hi) // 2
            lo, hi = (lo, mid) if at(mid) <= at(mid + 1) else (mid + 1, hi)
        at(lo)
    else:
        raise ValueError("search is bisect, exhaustive or ternary")
    best = min(trace, key=lambda k: (trace[k], k))
    return KSearch(best, dict(sorted(trace.items())), best in (kmin, kmax))


def find_k(wins: DataFrame, kmin: int = 2, kmax: int = 8, how: str = "bisect", restarts: int = 3) -> tuple[KSearch, dict[int, np.ndarray]]:
    """Search k by the Davies-Bouldin index of clusterings of ``wins`` (a written sample): one pass for each k tried."""
    made: dict[int, np.ndarray] = {}
    trials = Trials(wins, restarts)

    def score(k: int) -> float | None:
        made[k], index = trials.best(k)
        return index

    return search_k(score, kmin, kmax, how), made
