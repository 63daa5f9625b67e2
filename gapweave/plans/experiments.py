"""The experiment grids: strategies, learners, gap kinds and levels, scored on every held-out window.

A fifth of the windows is held out by hash. Of the complete training windows a share (the pool) gets the gaps of the cell
under test and stands for the incomplete part of the collection; the others are the clean part, on which everything
trains. For the kind ``natural`` the incomplete part is what is incomplete in the data, and a held-out window gets the
gaps of a held-out incomplete window of its group (the planted archetype, or the whole collection): gaps never
depend on the framework's clusters. All cells of a grid go through the same jobs.

The strategy ``framework`` is that of ``pipeline``: clustering, assignment under the bound by gap-aware warping,
projection, structure gate, mask search, a model a kept cluster, and the global model elsewhere. Its ablations change one
step. Values are scaled by mean and deviation of the clean part; errors are in that scale.
"""

from __future__ import annotations

import math
import pickle
import time
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..baselines.generative import sample_masks, train_generator
from ..baselines.tokens import TokenModel
from ..functions.gapdtw import gap_dtw
from ..functions.hashing import draw, draw_py, unit
from ..functions.masks import mask_words
from ..learners.core import LEARNERS, unpack_params
from ..operators import bounds, gaps, series
from ..operators.cluster import cluster_sequences
from ..sources.scratch import materialise
from . import pipeline
from .fitting import CHUNK, Job, arrays, fit_everywhere, window_draws

#: Strategies that are the framework, with (options of the assignment, options of the training).
FRAMEWORK: dict[str, tuple[dict, dict]] = {
    "framework": ({}, {}),
    "no_gate": ({}, {"gate": -1.0}),
    "one_cluster": ({"k": 1}, {}),
    "one_cluster_no_gate": ({"k": 1}, {"gate": -1.0}),
    "no_cap": ({"need": math.inf}, {}),
    "naive_distance": ({"distance": "naive"}, {}),
    "projection_only": ({}, {"roles": ("proj",)}),
    "mask_only": ({}, {"roles": ("mask",)}),
}
STRATEGIES = ("direct", *FRAMEWORK, "generative", "generative_sample", "token")
POOL_SEED, POOL_SHARE, TEST_SEED = 921, 0.3, 5000
#: Gap patterns that a generator is trained on, by hash.
GENERATOR_PATTERNS = 5000
SCORES = "dataset string, learner string, strategy string, gap_kind string, rate double, mse double, mae double, n long, own long, used long, clean long, total long, prepare_ms double, fit_ms double, infer_ms double"


def _spare_one(hidden, w: int, seed: int):
    """At least one slot of a window stays visible."""
    kept = draw(seed, "series_id", "win") % w
    return F.when(F.forall("hidden", lambda h: h), F.transform("hidden", lambda h, i: i != kept)).otherwise(F.col("hidden"))


def with_gaps(df: DataFrame, w: int, kind: str, rate: float, seed: int) -> DataFrame:
    """Adds hidden to windows (series_id, win, z complete, group)."""
    if kind == "mnar_value":
        out = gaps.mnar_value(df, w, rate, x="z", seed=seed)
    elif kind == "mnar_group":
        out = gaps.mnar_group(df, w, "group", rate, seed=seed)
    else:
        out = {"mcar": gaps.mcar, "mnar_burst": gaps.mnar_burst}[kind](df, w, rate, seed=seed)
    return out.withColumn("hidden", _spare_one("hidden", w, seed + 1))


def with_natural_gaps(df: DataFrame, donors: DataFrame, w: int, rate: float, seed: int) -> DataFrame:
    """Adds hidden: the gaps of a donor (group, series_id, win, words) of the same group, drawn by hash; at random where a
    group has none. Donors are ranked in buckets of some thousands."""
    buckets = donors.count() // 5000 + 1
    own = donors.select("group", (draw(seed, "series_id", "win") % buckets).alias("bucket"), "series_id", "win", "words")
    own = own.withColumn("place", F.row_number().over(Window.partitionBy("group", "bucket").orderBy(draw(seed + 1, "series_id", "win"), "series_id", "win")))
    own = materialise(own.select("group", "bucket", "place", "words"), "donors")
    sizes = own.groupBy("group", "bucket").agg(F.max("place").alias("n"))
    asked = df.withColumn("bucket", draw(seed + 2, "series_id", "win") % buckets).join(sizes, ["group", "bucket"], "left")
    asked = asked.withColumn("place", (draw(seed + 3, "series_id", "win") % F.col("n") + 1).cast("int")).join(own, ["group", "bucket", "place"], "left")
    natural = F.transform(F.sequence(F.lit(0), F.lit(w - 1)), lambda i: F.getbit(F.element_at("words", (i / 64).cast("int") + 1), (i % 64).cast("int")) == 0)
    random = F.transform(F.sequence(F.lit(0), F.lit(w - 1)), lambda i: unit(seed, "series_id", "win", i) < rate)
    out = asked.withColumn("hidden", F.when(F.col("words").isNotNull(), natural).otherwise(random)).drop("bucket", "place", "n", "words")
    return out.withColumn("hidden", _spare_one("hidden", w, seed + 1))


def _masked(df: DataFrame, w: int) -> DataFrame:
    """Windows with hidden as incomplete ones: z with gaps, n_obs, words."""
    df = df.withColumn("z", F.zip_with("z", "hidden", lambda v, h: F.when(~h, v)))
    return df.withColumns({"n_obs": F.size(F.filter("z", lambda v: v.isNotNull())), "words": mask_words("z", w)})


class Setting:
    """One data set prepared for a grid: clean, incomplete (by cell) and test windows (by cell), written."""

    def __init__(self, wins: DataFrame, w: int, kinds: tuple[str, ...], rates: tuple[float, ...]) -> None:
        self.w, self.cells = w, [(i, g, float(r)) for i, (g, r) in enumerate((g, r) for g in kinds for r in rates)]
        wins = wins.withColumn("held", series.holdout())
        pool = F.col("complete") & ~F.col("held") & (unit(POOL_SEED, "series_id", "win") < POOL_SHARE)
        wins = materialise(wins.withColumn("pool", pool).select("series_id", "win", "x", "words", "n_obs", "complete", "group", "held", "pool"), "windows")
        clean = wins.where("complete AND NOT held AND NOT pool")
        s = clean.select(F.explode("x").alias("v")).agg(F.avg("v").alias("mu"), F.stddev_pop("v").alias("sd")).first()
        self.empty = s.mu is None or not s.sd
        mu, sd = (0.0, 1.0) if self.empty else (s.mu, s.sd)
        wins = wins.withColumn("z", F.transform("x", lambda v: (v - mu) / sd)).drop("x")
        self.clean = materialise(wins.where("complete AND NOT held AND NOT pool").select("series_id", "win", "z"), "clean")
        self.total, self.n_clean = wins.where("n_obs > 0").count(), self.clean.count()
        if self.empty:
            return
        gone, tests = [], []
        left, test, natural, donors = wins.where("pool"), wins.where("complete AND held"), wins.where("NOT complete AND n_obs > 1 AND NOT held"), wins.where("NOT complete AND n_obs > 1 AND held")
        for i, kind, rate in self.cells:
            seed = 1000 + 10 * i
            if kind == "natural":
                gone.append(natural.select(F.lit(i).alias("cell"), "series_id", "win", "z", "n_obs", "words"))
                t = with_natural_gaps(test.select("series_id", "win", "z", "group"), donors, w, rate, TEST_SEED + seed)
            else:
                gone.append(_masked(with_gaps(left.select("series_id", "win", "z", "group"), w, kind, rate, seed), w).select(F.lit(i).alias("cell"), "series_id", "win", "z", "n_obs", "words"))
                t = with_gaps(test.select("series_id", "win", "z", "group"), w, kind, rate, TEST_SEED + seed)
            tests.append(t.select(F.lit(i).alias("cell"), "series_id", "win", "z", "hidden"))
        self.incomplete = materialise(reduce(DataFrame.unionByName, gone), "incomplete")
        self.tests = materialise(reduce(DataFrame.unionByName, tests), "tests")


def _generators(s: Setting) -> dict[int, tuple]:
    """A trained mask generator for each cell that has incomplete windows."""
    found = {}
    n = {r.cell: r.n for r in s.incomplete.groupBy("cell").agg(F.count("*").alias("n")).collect()}
    share = F.element_at(F.create_map(*[F.lit(x) for c, m in sorted(n.items()) for x in (c, min(1.0, GENERATOR_PATTERNS / m))]), F.col("cell")) if n else F.lit(0.0)
    rows = s.incomplete.where(unit(923, "series_id", "win") < share).select("cell", "series_id", "win", F.transform("z", lambda v: v.isNull().cast("int")).alias("m"))
    by: dict[int, list] = {}
    for r in sorted(rows.collect()):  # about GENERATOR_PATTERNS rows a cell
        by.setdefault(r.cell, []).append(r.m)
    for c, masks in by.items():
        found[c] = train_generator(np.array(masks), draw_py(31, c) % 10_000)
    return found


def _fit_sampled(pairs: DataFrame, k: int, w: int, generators: dict[int, tuple], learners: tuple[str, ...]) -> dict[tuple[int, str], tuple[dict, int, float]]:
    """One model a cell and learner on the framework's own sample of complete windows, with generated gaps."""

    def fit(pdf: pd.DataFrame) -> pd.DataFrame:
        cell, learner = int(pdf["cell"].iloc[0]), pdf["learner"].iloc[0]
        pdf = pdf.sort_values(["series_id", "win"])
        began, z = time.perf_counter(), arrays(pdf["z"], w)
        u = window_draws(37, pdf["series_id"].tolist(), pdf["win"].tolist(), len(generators[cell][0]) + w)
        hidden = sample_masks(generators[cell], u)
        params = LEARNERS[learner].fit(np.where(hidden, np.nan, z), z, 41)
        return pd.DataFrame([(cell, learner, pickle.dumps(params), int(pdf[["comp_series", "comp_win"]].drop_duplicates().shape[0]), (time.perf_counter() - began) * 1000)], columns=["cell", "learner", "params", "n", "ms"])

    rows = pairs.withColumn("cell", F.floor(F.col("cluster") / k).cast("int")).where(F.col("cell").isin(*generators) if generators else F.lit(False))
    rows = rows.withColumn("learner", F.explode(F.array(*[F.lit(m) for m in learners])))
    out = rows.groupBy("cell", "learner").applyInPandas(fit, "cell int, learner string, params binary, n long, ms double")
    return {(r.cell, r.learner): (pickle.loads(r.params), r.n, r.ms) for r in out.collect()}  # one row a cell and learner


def run_grid(wins: DataFrame, w: int, dataset: str, learners: tuple[str, ...], strategies: tuple[str, ...], kinds: tuple[str, ...] = ("mcar",), rates: tuple[float, ...] = (0.5,), k: int | None = None, token_rows: list | None = None, runs: int = 2) -> DataFrame:
    """SCORES of every cell. ``wins`` has series_id, win, x, words, n_obs, complete and group.

    ``used`` counts the complete windows that the fits of clusters (or the one model) read, ``own`` the test windows filled by
    a cluster's own model. Fit and inference times are milliseconds of the workers, summed; preparation is wall time.
    """
    spark, s = wins.sparkSession, Setting(wins, w, kinds, rates)
    if s.empty:  # cold start: nothing to learn from
        rows = [(dataset, m, t, g, r, None, None, 0, 0, 0, s.n_clean, s.total, 0.0, 0.0, 0.0) for m in learners for t in strategies for _, g, r in s.cells]
        return spark.createDataFrame(rows, SCORES)
    need = bounds.need_value()
    models: dict[tuple, dict[int, tuple[str, dict]]] = {}  # (strategy, learner, cell) -> cluster -> (learner, params)
    routes: dict[str, tuple[np.ndarray, str]] = {}
    used: dict[tuple, int] = {}
    spent: dict[tuple, tuple[float, float]] = {}
    clustered: dict[int | None, tuple] = {}
    admitted: dict[tuple, pipeline.Prepared] = {}

    def prepared(options: dict) -> tuple[pipeline.Prepared, float]:
        began, of = time.perf_counter(), options.get("k", k)
        if of not in clustered:
            if of == 1:
                mean = np.array(s.clean.select(*[F.avg(F.col("z")[j]) for j in range(w)]).first(), dtype=float)[None]
                clustered[of] = mean, materialise(cluster_sequences(s.clean, mean), "complete")
            else:
                clustered[of] = pipeline.cluster_windows(s.clean, of)
        key = tuple(sorted(options.items()))
        if key not in admitted:
            centroids, labelled = clustered[of]
            assigned = pipeline.admit(s.incomplete, centroids, w, options.get("need", need), distance=options.get("distance", "dtw"))
            admitted[key] = pipeline.Prepared(w, None, centroids, labelled, assigned, need)
        return admitted[key], (time.perf_counter() - began) * 1000

    # Strategies that differ in the gate only are fitted in one go under the least gate; a cluster's fit does not depend on it.
    runs_of: dict[tuple, list[str]] = {}
    for strategy in strategies:
        if strategy in FRAMEWORK:
            first, second = FRAMEWORK[strategy]
            runs_of.setdefault((tuple(sorted(first.items())), second.get("roles", pipeline.ROLES)), []).append(strategy)
    for (first, roles), group in runs_of.items():
        p, prepare_ms = prepared(dict(first))
        gate = {t: FRAMEWORK[t][1].get("gate", 2 / 3) for t in group}
        t = pipeline.fit_framework(p, learners, min(gate.values()), roles=roles, runs=runs, with_global=False)
        kk = len(p.centroids)
        table = [(r.cluster, r.kind, unpack_params(r.params)) for r in t.models.collect()]  # cells x clusters x learners
        ratio = {r.cluster: r.ratio for r in t.structure.collect()}
        seen = t.pairs.select("cluster", F.floor(F.col("cluster") / kk).cast("int").alias("cell"), "comp_series", "comp_win")
        for strategy in group:
            routes[strategy] = p.centroids, dict(first).get("distance", "dtw")
            kept = {c for c, x in ratio.items() if x is not None and x > gate[strategy]}
            n = {r.cell: r.n for r in seen.where(F.col("cluster").isin(*kept) if kept else F.lit(False)).groupBy("cell").agg(F.count_distinct("comp_series", "comp_win").alias("n")).collect()}
            for i, _, _ in s.cells:
                for m in learners:
                    models[strategy, m, i] = {c % kk: (kind, params) for c, kind, params in table if kind == m and c // kk == i and c in kept}
                    used[strategy, m, i], spent[strategy, m, i] = n.get(i, 0), (prepare_ms / len(s.cells), t.times[m] / len(s.cells))

    generators = _generators(s) if {"generative", "generative_sample"} & set(strategies) else {}
    jobs, keys = {}, {}
    if routes:
        for j, job in pipeline.global_jobs(learners).items():
            jobs[j], keys[j] = job, ("global", job.learner, -1)
    for strategy in strategies:
        if strategy in ("direct", "generative"):
            for m in learners:
                for i, _, rate in s.cells:
                    if strategy == "direct" or i in generators:
                        keys[len(jobs)] = (strategy, m, i)
                        jobs[len(jobs)] = Job(m, max(rate, 0.05), draw_py(7, dataset, rate) % 10_000, generators[i] if strategy == "generative" else None)
    for j, (params, n, ms) in fit_everywhere(s.clean, w, jobs).items():
        if keys[j][0] == "global":
            for strategy in routes:
                for i, _, _ in s.cells:
                    models[strategy, jobs[j].learner, i][pipeline.GLOBAL] = (jobs[j].learner, params)
                    before = spent[strategy, jobs[j].learner, i]
                    spent[strategy, jobs[j].learner, i] = (before[0], before[1] + ms / len(s.cells))
            continue
        models[keys[j]], used[keys[j]], spent[keys[j]] = {pipeline.GLOBAL: (jobs[j].learner, params)}, n, (0.0, ms)
    if "generative_sample" in strategies:
        p, prepare_ms = prepared({})
        inc = p.assigned.select("series_id", "win", "cluster", "words", (F.col("cluster") % len(p.centroids)).alias("home"))
        pairs = materialise(pipeline.patterns.pair(inc, p.complete.select("cluster", "series_id", "win", "z"), home="home"), "pairs")
        for (i, m), (params, n, ms) in _fit_sampled(pairs, len(p.centroids), w, generators, learners).items():
            key = ("generative_sample", m, i)
            models[key], used[key], spent[key] = {pipeline.GLOBAL: (m, params)}, n, (prepare_ms / len(s.cells), ms)
    token = TokenModel.from_rows(token_rows) if token_rows else TokenModel({"": {32: 1}})
    sent = spark.sparkContext.broadcast((models, routes, token))  # as many models as cells, clusters and learners

    def scored(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        models, routes, token = sent.value
        total: dict[tuple, np.ndarray] = {}
        for pdf in batches:
            for begin in range(0, len(pdf), CHUNK):
                for i, part in pdf.iloc[begin : begin + CHUNK].groupby("cell"):
                    z, h = arrays(part["z"], w), np.array(part["hidden"].tolist(), dtype=bool).reshape(-1, w)
                    x, home = np.where(h, np.nan, z), {}
                    for strategy in strategies:
                        if strategy in routes and (key := strategy) not in home:
                            c, how = routes[strategy]
                            d = ((np.nan_to_num(x)[:, None] - c[None]) ** 2).sum(axis=2) if how == "naive" else gap_dtw(x[:, None], c[None])
                            home[key] = d.argmin(axis=1)
                        for m in learners:
                            began = time.perf_counter()
                            if strategy == "token":
                                guess, own = token.fill(x), np.zeros(len(x), dtype=bool)
                            elif (strategy, m, i) in models:
                                ready = {c: (LEARNERS[kind], params) for c, (kind, params) in models[strategy, m, i].items()}
                                guess, own = pipeline.predict_by_cluster(ready, x, home.get(strategy, np.full(len(x), pipeline.GLOBAL)))
                            else:
                                continue
                            e = (guess - z)[h]
                            ms = (time.perf_counter() - began) * 1000
                            at = (int(i), m, strategy)
                            total[at] = total.get(at, np.zeros(5)) + [(e**2).sum(), np.abs(e).sum(), len(e), own.sum(), ms]
        yield pd.DataFrame([(*k, v[0], v[1], int(v[2]), int(v[3]), v[4]) for k, v in total.items()], columns=["cell", "learner", "strategy", "se", "ae", "n", "own", "ms"])

    sums = s.tests.mapInPandas(scored, "cell int, learner string, strategy string, se double, ae double, n long, own long, ms double")
    sums = {(r.strategy, r.learner, r.cell): r for r in sums.groupBy("cell", "learner", "strategy").agg(*[F.sum(c).alias(c) for c in ("se", "ae", "n", "own", "ms")]).collect()}  # one row a score
    out = []
    for m in learners:
        for t in strategies:
            for i, g, rate in s.cells:
                r, (prepare_ms, fit_ms) = sums.get((t, m, i)), spent.get((t, m, i), (0.0, 0.0))
                ok = r is not None and r.n > 0
                out.append((dataset, m, t, g, rate, r.se / r.n if ok else None, r.ae / r.n if ok else None, r.n if ok else 0, r.own if ok else 0, used.get((t, m, i), 0), s.n_clean, s.total, prepare_ms, fit_ms, r.ms if ok else 0.0))
    return spark.createDataFrame(out, SCORES)


def windows_for(spark: SparkSession, folder: str, name: str) -> tuple[DataFrame, int]:
    """Windows of a workload, of the embeddings, or of the planted overlay, with the group that shares gaps."""
    from ..operators.series import described, slots_of, windows
    from ..sources.planted import planted
    from ..sources.workloads import WORKLOADS, embedding_windows

    if name == "embedding":
        return described(embedding_windows(spark, folder), 64).withColumn("group", F.lit("")), 64
    if name in ("planted", "planted_truth"):
        p = planted(spark, folder)
        x = F.col("x") if name == "planted" else F.col("truth")
        return described(p.select("series_id", "win", F.col("archetype").cast("string").alias("group"), x.alias("x")), 8), 8
    spec = WORKLOADS[name]
    return windows(slots_of(spark, folder, spec), spec.w).withColumn("group", F.lit("")), spec.w
