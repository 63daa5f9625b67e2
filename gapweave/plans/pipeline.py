"""The framework end to end: prepare (windows, clusters, assignment), train (projection, gate, masks, fits), impute.

Several collections of incomplete windows over the same clusters (the column ``cell``: one gap kind and level each) can
go through the same jobs: cluster c of cell i has the number i K + c.
"""

from __future__ import annotations

import math
import time
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.gapdtw import distances_to, euclid_to, gap_dtw, nearest
from ..functions.hashing import SEEDS, draw, draw_py, unit
from ..learners.core import LEARNERS, Learner, pack_params, unpack_params
from ..learners.keyed import merged_sums
from ..operators import assign, bounds, cluster, minmask, patterns, series
from ..schemas import MODELS
from ..sources.scratch import materialise
from .fitting import Job, fit_everywhere

#: The model that imputes windows without a cluster model.
GLOBAL = -1
#: The extra mask that the bound reckons with before a cluster's own is known, and that the global model trains with.
PLAIN_MASK = 0.1
ROLES = ("proj", "mask", "proj_mask")


@dataclass
class Prepared:
    """What the steps before training hand on."""

    w: int
    windows: DataFrame | None
    centroids: np.ndarray
    complete: DataFrame
    assigned: DataFrame
    need: float


@dataclass
class Trained:
    """Model table (kind is the learner; milliseconds of its fits in ``times``), structure by cluster, masks, pairs."""

    models: DataFrame
    structure: DataFrame
    masks: DataFrame
    pairs: DataFrame
    times: dict[str, float]


def cluster_windows(train: DataFrame, k: int | None = None, kmax: int = 6) -> tuple[np.ndarray, DataFrame]:
    """Centroids from a bounded sample of the complete training windows, and all of them labelled, in one map."""
    sample = materialise(cluster.training_sample(train.select("series_id", "win", "z")), "sample")
    if not sample.limit(1).count():
        raise series.NoCompleteWindows("no complete training window")
    if k is None:
        found, made = cluster.find_k(sample, 2, kmax)
        centroids = made[found.k]
    else:
        centroids = cluster.best_of(sample, k)
    return centroids, materialise(cluster.cluster_sequences(train.select("series_id", "win", "z"), centroids), "complete")


def _distances(how: str, centroids: np.ndarray):
    if how == "dtw":
        return distances_to("z", centroids)
    if how == "diagonal":
        return euclid_to("z", centroids)
    if how == "naive":  # gaps filled by the mean: no gap handling
        return cluster.plain_distances_of(F.transform("z", lambda v: F.coalesce(v, F.lit(0.0))), centroids)
    raise ValueError("distance is dtw, diagonal or naive")


def admit(gone: DataFrame, centroids: np.ndarray, w: int, need: float, mask: float = PLAIN_MASK, max_size: int = 10_000, distance: str = "dtw", overflow: str = "smallest", refine_passes: int = 1, safety: float = 1.5) -> DataFrame:
    """Incomplete windows (series_id, win, z, n_obs, words, and cell where there are several collections) sampled to the
    bound and assigned under it. The patterns admitted then tell what a cluster's windows really show; where that falls
    short of the bound, more are admitted from the next slice of the hash order."""
    gone = gone if "cell" in gone.columns else gone.withColumn("cell", F.lit(0))
    k = len(centroids)
    stats = gone.groupBy("cell").agg(F.count("*").alias("n"), F.avg((F.lit(w) - F.col("n_obs")) / w).alias("missing")).collect()  # one row a cell
    if math.isinf(need):
        share, max_size = {r.cell: 1.0 for r in stats}, 1 << 30
    else:
        share = {r.cell: min(1.0, k * safety * need / max((1 - r.missing) * (1 - mask), 1e-9) / r.n) for r in stats}
    if not share:
        share = {0: 1.0}

    def slice_of(i: int) -> DataFrame:
        low, high = (F.element_at(F.create_map(*[F.lit(x) for c, s in sorted(share.items()) for x in (c, min(1.0, j * s))]), F.col("cell")) for j in (i, i + 1))
        h = unit(SEEDS["sample"], "series_id", "win")
        return assign.proposals(gone.where((h >= low) & (h < high)), _distances(distance, centroids), mask, w, base=F.col("cell") * k, keep=("words",))

    assigned = materialise(assign.assign_incomplete(slice_of(0), need, max_size, overflow), "assigned")
    for i in range(1, refine_passes + 1):
        measured = assign.measured_shares(assigned, mask)
        short = [c for c, (n, g) in measured.items() if n * g < need and i * share[c // k] < 1]
        if math.isinf(need) or not short:
            break
        assigned = materialise(assign.refine_assignment(assigned, slice_of(i), {c: measured[c] for c in short}, need), "assigned")
    return assigned


def prepare(wins: DataFrame, w: int, k: int | None = None, kmax: int = 6, eps: float = 0.03, delta: float = 0.1, mask: float = PLAIN_MASK, max_size: int = 10_000, distance: str = "dtw", overflow: str = "smallest", refine_passes: int = 1) -> Prepared:
    """Cluster the complete training windows, sample the incomplete ones to the bound, and assign them under it."""
    wins = materialise(series.normalise(wins), "windows")
    train_ = wins.where(~series.holdout())
    centroids, labelled = cluster_windows(train_.where("complete"), k, kmax)
    need = bounds.need_value(eps, delta)
    gone = train_.where("NOT complete AND n_obs > 0").select("series_id", "win", "z", "n_obs", "words")
    assigned = admit(gone, centroids, w, need, mask, max_size, distance, overflow, refine_passes)
    return Prepared(w, wins, centroids, labelled, assigned, need)


def fit_clusters(training: DataFrame, learner: str = "gaussian", version: int = 1, max_group: int = minmask.MAX_GROUP) -> DataFrame:
    """A model table, one model a cluster and learner, from (cluster, series_id, win, x_in, y) and, where there are several,
    role and learner; ``training`` is read more than once. ``params`` holds the milliseconds of the fit under ``fit_ms``.

    Up to three times ``max_group`` rows are one group; larger clusters are fitted by sums of all their rows.
    """
    training = training if "learner" in training.columns else training.withColumn("learner", F.lit(learner))
    sizes = training.groupBy("cluster", "learner").agg(F.count("*").alias("n")).where(F.col("n") > 3 * max_group).collect()  # one row a model
    large = {(r.cluster, r.learner): r.n for r in sizes}

    def fit(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["series_id", "win", "role"]) if "role" in pdf else pdf
        to = lambda c: np.array([np.array(v, dtype=float) for v in pdf[c]])
        kind, began = pdf["learner"].iloc[0], time.perf_counter()
        params = LEARNERS[kind].fit(to("x_in"), to("y"), version)
        params = pack_params(params) | {"fit_ms": [(time.perf_counter() - began) * 1000], "fit_ms.shape": [1.0]}
        return pd.DataFrame({"cluster": [int(pdf["cluster"].iloc[0])], "kind": [kind], "params": [params], "version": [version]})

    if not large:
        return training.groupBy("cluster", "learner").applyInPandas(fit, MODELS)
    inside = F.array(*[F.struct(F.lit(c).alias("cluster"), F.lit(m).alias("learner")) for c, m in sorted(large)])
    beyond = F.array_contains(inside, F.struct(F.col("cluster").cast("int").alias("cluster"), F.col("learner").alias("learner")))
    small = training.where(~beyond).groupBy("cluster", "learner").applyInPandas(fit, MODELS)
    return small.unionByName(_fit_by_sums(training.where(beyond), large, version))


def _fit_by_sums(training: DataFrame, sizes: dict[tuple[int, str], int], version: int) -> DataFrame:
    """The models of clusters of any size, from every row: what a learner tunes beforehand comes from some windows by hash."""
    keys = sorted(sizes)
    at = {key: i for i, key in enumerate(keys)}
    array = lambda v: np.array([np.array(a, dtype=float) for a in v])
    columns = ["cluster", "learner", "series_id", "win", *(["role"] if "role" in training.columns else []), "x_in", "y"]
    share = F.element_at(F.create_map(*[F.lit(x) for c in sorted({c for c, _ in keys}) for x in (c, minmask.TUNING / max(n for (k, _), n in sizes.items() if k == c) * float(1 << 32))]), F.col("cluster").cast("int"))
    some = pd.DataFrame([r.asDict() for r in training.select(*columns).where(draw(917, "series_id", "win") < share).collect()])  # about TUNING rows a model
    some = some.sort_values([c for c in columns if c not in ("x_in", "y")])
    prepared = {at[int(c), m]: LEARNERS[m].prepare(array(part["x_in"]), array(part["y"]), version) for (c, m), part in some.groupby(["cluster", "learner"])}

    def sums_of(pdf: pd.DataFrame):
        for (c, m), part in pdf.groupby(["cluster", "learner"]):
            k, names = at[int(c), m], part["role"] if "role" in part else part["learner"]
            seeds = [draw_py(version, *i) for i in zip(part["series_id"], part["win"], names, strict=True)] if m == "linear_diffusion" else []
            yield k, len(part), LEARNERS[m].sums(prepared[k], array(part["x_in"]), array(part["y"]), seeds)

    rows = []
    for k, (sums, _, ms) in sorted(merged_sums(training.select(*columns), sums_of).items()):
        params = pack_params(LEARNERS[keys[k][1]].from_sums(prepared[k], sums)) | {"fit_ms": [ms], "fit_ms.shape": [1.0]}
        rows.append((*keys[k], params, version))
    return training.sparkSession.createDataFrame(rows, MODELS)


def fit_framework(p: Prepared, learners: tuple[str, ...] = ("gaussian",), gate: float = 2 / 3, on_unstructured: str = "drop", roles: tuple[str, ...] = ROLES, schedule: list[float] | None = None, runs: int = 3, with_global: bool = True) -> Trained:
    """Project, test structure, search masks, and fit a model for every kept cluster and learner, and a global one a learner.

    The global model, for windows without a cluster model, comes from sums over all complete training windows.
    """
    w, k = p.w, len(p.centroids)
    inc = p.assigned.select("series_id", "win", "cluster", "words", (F.col("cluster") % k).alias("home"))
    found = materialise(patterns.structure(patterns.compared(inc, w), gate), "structure")
    kept = patterns.keep_structured(inc, found) if on_unstructured == "drop" else inc
    pairs = materialise(patterns.pair(kept, p.complete.select("cluster", "series_id", "win", "z"), home="home"), "pairs")
    masks = materialise(minmask.min_mask_search(pairs, w, learners, schedule, runs)[0], "masks")
    sets = pairs.join(F.broadcast(masks.select("cluster", "learner", "mask")), "cluster")
    sets = patterns.masked_sets(sets, w, F.col("mask"), keep=("learner",)).where(F.col("role").isin(*roles)).select("cluster", "learner", "role", "series_id", "win", "x_in", "y")
    own = materialise(fit_clusters(sets), "models")
    whole = fit_everywhere(p.complete, w, global_jobs(learners) if with_global else {})
    plain = own.sparkSession.createDataFrame([(GLOBAL, learners[i], pack_params(params), 1) for i, (params, _, _) in whole.items()], MODELS)
    times = {r.kind: r.ms for r in own.groupBy("kind").agg(F.sum(F.col("params")["fit_ms"][0]).alias("ms")).collect()}
    return Trained(own.unionByName(plain), found, masks, pairs, {m: times.get(m, 0.0) + sum(ms for i, (_, _, ms) in whole.items() if learners[i] == m) for m in learners})


def global_jobs(learners: tuple[str, ...]) -> dict[int, Job]:
    return {i: Job(m, PLAIN_MASK, 11) for i, m in enumerate(learners)}


def train(p: Prepared, learner: str = "gaussian", gate: float = 2 / 3, **options) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(models, structure, masks) of one learner."""
    t = fit_framework(p, (learner,), gate, **options)
    return t.models, t.structure, t.masks


def route(wins: DataFrame, centroids: np.ndarray, how: str = "dtw") -> DataFrame:
    """Adds cluster: by warping to all centroids, by warping between the two nearest on the diagonal, by the diagonal
    distance in JVM expressions, or without gap handling. A window without any observation has none."""
    if how == "dtw_top2":

        @F.pandas_udf("int")
        def choose(z: pd.Series, order: pd.Series) -> pd.Series:
            x = np.array([np.array(v, dtype=float) for v in z])
            two = np.array([list(o)[:2] for o in order])
            if two.shape[1] < 2:
                return pd.Series(two[:, 0])
            d = gap_dtw(x[:, None, :], centroids[two])
            return pd.Series(two[np.arange(len(two)), np.where(np.isnan(d).any(axis=1), 0, np.argmin(np.nan_to_num(d, nan=np.inf), axis=1))])

        found = choose("z", F.transform(F.array_sort(F.transform(euclid_to("z", centroids), lambda d, k: F.struct(d.alias("d"), k.alias("k")))), lambda s: s["k"]))
    else:
        found = nearest(_distances(how, centroids))["cluster"]
    return wins.withColumn("cluster", F.when(F.exists("z", lambda v: v.isNotNull()), found).cast("int"))


def predict_by_cluster(ready: dict[int, tuple[Learner, dict]], z: np.ndarray, home: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(guesses, whether by the cluster's own model) of windows with gaps; ``home`` is their cluster."""
    guess, use = np.zeros(z.shape), np.array([c if c in ready else GLOBAL for c in home.tolist()], dtype=int)
    for c in np.unique(use):
        at = np.flatnonzero(use == c)
        model, params = ready[c]
        guess[at] = model.predict(params, z[at])
    return guess, use != GLOBAL


def scaled(wins: DataFrame) -> DataFrame:
    """``wins`` where also windows without any observation have mu and sd: their series', or else those of all."""
    full = wins.where("n_obs > 1")
    overall = full.agg(F.avg("mu").alias("mu"), F.avg("sd").alias("sd")).first()
    by = full.groupBy("series_id").agg(F.avg("mu").alias("mu"), F.avg("sd").alias("sd"))
    none = wins.where("n_obs = 0").drop("mu", "sd").join(by, "series_id", "left")
    none = none.withColumns({"mu": F.coalesce("mu", F.lit(overall.mu), F.lit(0.0)), "sd": F.coalesce("sd", F.lit(overall.sd), F.lit(0.0))})
    return wins.where("n_obs > 0").unionByName(none.select(*wins.columns))


def impute(wins: DataFrame, models: DataFrame, w: int) -> DataFrame:
    """Adds filled (original scale) and source, from z, mu, sd, n_obs and cluster; a map but for windows without any
    observation, which meet their series' scale. Models go with the tasks."""
    table = {r.cluster: (r.kind, r.params) for r in models.collect()}  # one row a cluster

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        ready = {c: (LEARNERS[kind], unpack_params(params)) for c, (kind, params) in table.items()}
        for pdf in batches:
            if not len(pdf):
                continue
            z = np.array([np.array(v, dtype=float) for v in pdf["z"]])
            home = pdf["cluster"].fillna(GLOBAL).astype(int).to_numpy()
            guess, own = predict_by_cluster(ready, z, home)
            mu, sd = pdf["mu"].to_numpy(dtype=float), pdf["sd"].to_numpy(dtype=float)
            pdf = pdf.assign(filled=list(guess * sd[:, None] + mu[:, None]), source=np.where(own, "cluster", "global"))
            yield pdf[["series_id", "win", "x", "filled", "source", "cluster"]]

    return scaled(wins).select("series_id", "win", "x", "z", "mu", "sd", "cluster").mapInPandas(run, "series_id string, win long, x array<double>, filled array<double>, source string, cluster int")


def run_framework(wins: DataFrame, w: int, learner: str = "gaussian", k: int | None = None, **options) -> tuple[DataFrame, Prepared, DataFrame]:
    """(readings, prepared, models) of the whole framework over ``wins``, every expected slot; k is searched for if it is not given."""
    p = prepare(wins, w, k)
    models, _, _ = train(p, learner, **options)
    return series.to_readings(impute(route(p.windows, p.centroids), models, w), w), p, models


def register(spark: SparkSession) -> None:
    """Expose the numeric functions to SQL."""
    from pyspark.sql.types import ArrayType, DoubleType

    def dtw(x, y):
        a, b = (np.array([np.nan if v is None else v for v in s], dtype=float) for s in (x, y))
        d = float(gap_dtw(a, b))
        return None if np.isnan(d) else d

    spark.udf.register("gap_dtw", dtw, DoubleType())
    spark.udf.register("mask_schedule", lambda least, growth, steps: minmask.mask_schedule(least, growth, steps), ArrayType(DoubleType()))
    spark.udf.register("sample_need", lambda eps, delta: bounds.need_value(eps, delta), DoubleType())
