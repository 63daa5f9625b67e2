"""Queries of imputers, measures, baselines and the experiment grids."""

from __future__ import annotations

from functools import reduce

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..baselines import generative, tokens
from ..functions.gapdtw import euclid_to, nearest
from ..functions.hashing import SEEDS, unit_sql
from ..learners.core import EVALUATED
from ..operators import gaps, impute, metrics, minmask, patterns, series
from ..plans import experiments, pipeline
from ..sources.scratch import materialise
from ..sources.workloads import WORKLOADS, windows_sql
from .patterns import _pairs
from .windows import CLUSTER_SQL, W, Z_SQL, Base, base_centroids, incomplete_assigned, slots, train_complete, wins, z_wins

# ---- exact imputers on held-out windows, half of the slots hidden ---------------------------------------------


def _test(s, d):
    t = z_wins(s, d).where("complete").where(series.holdout())
    t = gaps.mcar(t, W, 0.5)
    return t.withColumns({"seen": impute.shown("x", "hidden"), "seen_z": impute.shown("z", "hidden")})


def _train_mean(s, d):
    return F.lit(z_wins(s, d).where("complete").where(~series.holdout()).select(F.explode("x").alias("v")).agg(F.avg("v")).first()[0])


def _filled(kind, s, d):
    t, m = _test(s, d), _train_mean(s, d)
    truth = "x"
    if kind == "mean":
        guess = impute.constant("seen", W, m)
    elif kind == "profile":
        means = impute.slot_means(z_wins(s, d).where("complete").where(~series.holdout()), W)
        guess = F.array(*[F.lit(v) for v in means])
    elif kind == "centroid":
        c = base_centroids(s, d)
        t = t.withColumn("k", nearest(euclid_to("seen_z", c))["cluster"])
        guess, truth = F.element_at(F.array(*[F.array(*[F.lit(float(v)) for v in row]) for row in c]), F.col("k") + 1), "z"
    else:
        guess = {"locf": impute.locf, "nocb": impute.nocb, "linear": impute.linear}[kind]("seen", W, m)
    rows = t.select("series_id", "win", F.posexplode(F.arrays_zip(F.col(truth).alias("t"), F.col("hidden").alias("h"), guess.alias("g"))).alias("pos", "c"))
    return rows.where("c.h").select("series_id", "win", F.col("pos").cast("long").alias("pos"), F.col("c.t").alias("truth"), F.col("c.g").alias("pred"))


KINDS = ("mean", "profile", "centroid", "locf", "nocb", "linear")


def _impute(kind):
    return lambda s, d: _filled(kind, s, d).select("series_id", "win", "pos", F.round("pred", 6).alias("pred"))


def eval_all(s, d):
    """Every measure of every exact imputer."""
    out = None
    for kind in KINDS:
        e = metrics.errors(_filled(kind, s, d).withColumn("learner", F.lit(kind)), ["learner"])
        out = e if out is None else out.unionByName(e)
    return out.select("learner", "n", *[F.round(c, 4).alias(c) for c in ("mse", "mae", "rmse", "bias", "r2")])


_TEST = f"""te AS (SELECT series_id, win, pos, value, z, {unit_sql(SEEDS['gap'], 'series_id', 'win', 'pos')} < 0.5 AS hidden FROM zs WHERE complete AND held),
 tm AS (SELECT avg(value) AS m FROM zs WHERE complete AND NOT held),
 sm AS (SELECT pos, avg(value) AS m FROM zs WHERE complete AND NOT held GROUP BY 1),
 v AS (SELECT *, CASE WHEN NOT hidden THEN value END AS s, CASE WHEN NOT hidden THEN pos END AS sp FROM te),
 nb AS (SELECT *, last_value(s IGNORE NULLS) OVER a AS va, last_value(sp IGNORE NULLS) OVER a AS pa, first_value(s IGNORE NULLS) OVER b AS vb, first_value(sp IGNORE NULLS) OVER b AS pb FROM v
  WINDOW a AS (PARTITION BY series_id, win ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), b AS (PARTITION BY series_id, win ORDER BY pos ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING)),
 vis AS (SELECT series_id, win, count(s) AS n FROM v GROUP BY 1, 2),
 td AS (SELECT v.series_id, v.win, c.cluster, sqrt(sum(CASE WHEN v.hidden THEN 0 ELSE (v.z - c.c) * (v.z - c.c) END) * {2.0 * W} / (max(vis.n) + {W})) AS dist FROM v JOIN c2 c ON c.pos = v.pos JOIN vis ON vis.series_id = v.series_id AND vis.win = v.win GROUP BY 1, 2, 3),
 tk AS (SELECT series_id, win, cluster FROM td QUALIFY row_number() OVER (PARTITION BY series_id, win ORDER BY dist, cluster) = 1)"""
_BASE = f"WITH {CLUSTER_SQL}, {_TEST}"
_PRED = {
    "mean": "SELECT series_id, win, pos, value AS truth, (SELECT m FROM tm) AS pred FROM te WHERE hidden",
    "profile": "SELECT te.series_id, te.win, te.pos, te.value AS truth, sm.m AS pred FROM te JOIN sm ON sm.pos = te.pos WHERE hidden",
    "centroid": "SELECT te.series_id, te.win, te.pos, te.z AS truth, c2.c AS pred FROM te JOIN tk ON tk.series_id = te.series_id AND tk.win = te.win JOIN c2 ON c2.cluster = tk.cluster AND c2.pos = te.pos WHERE hidden",
    "locf": "SELECT series_id, win, pos, value AS truth, coalesce(va, (SELECT m FROM tm)) AS pred FROM nb WHERE hidden",
    "nocb": "SELECT series_id, win, pos, value AS truth, coalesce(vb, (SELECT m FROM tm)) AS pred FROM nb WHERE hidden",
    "linear": "SELECT series_id, win, pos, value AS truth, coalesce(va + (vb - va) * (pos - pa) / (pb - pa), va, vb, (SELECT m FROM tm)) AS pred FROM nb WHERE hidden",
}
_ERR = "SELECT '{k}' AS learner, count(*) AS n, round(avg((pred - truth) * (pred - truth)), 4) AS mse, round(avg(abs(pred - truth)), 4) AS mae, round(sqrt(avg((pred - truth) * (pred - truth))), 4) AS rmse, round(avg(pred - truth), 4) AS bias, round(1 - avg((pred - truth) * (pred - truth)) / var_pop(truth), 4) AS r2 FROM ({q})"


def pair_moments(s, d):
    return impute.pair_moments(train_complete(s, d), W).select(F.col("i").cast("long").alias("i"), F.col("j").cast("long").alias("j"), "n", F.round("total", 3).alias("total"))


def imputed_readings(s, d):
    """Readings of windows with at least one observation, gaps carried forward in the window, else its mean."""
    t = z_wins(s, d).where("n_obs > 0").withColumn("filled", impute.locf("x", W, F.col("mu"))).withColumn("source", F.lit("locf"))
    return series.to_readings(t, W).select("series_id", "slot", F.round("value", 6).alias("value"), "imputed", "source")


def weighted_mse(s, d):
    """A grouped pandas aggregate: squared error weighted by the truth's magnitude."""

    @F.pandas_udf("double")
    def wmse(pred: pd.Series, truth: pd.Series) -> float:
        w = truth.abs()
        return float((w * (pred - truth) ** 2).sum() / w.sum())

    return _filled("linear", s, d).groupBy("pos").agg(F.round(wmse("pred", "truth"), 4).alias("wmse"))


# ---- baselines ------------------------------------------------------------------------------------------------


def mask_transition_counts(s, d):
    gone = wins(s, d).where("NOT complete AND n_obs > 0")
    return generative.transition_counts(gone, W).select(F.col("pos").cast("long").alias("pos"), F.col("prev").cast("long").alias("prev"), F.col("cur").cast("long").alias("cur"), "n")


def generated_masks(s, d):
    p = generative.chain(generative.transition_counts(wins(s, d).where("NOT complete AND n_obs > 0"), W), W)
    return train_complete(s, d).select("series_id", "win", F.array_join(generative.generated(p, "series_id", "win"), "").alias("mask"))


def token_counts(s, d):
    w = series.windows(slots(s, d, "priority_day"), 8).where("complete")
    return tokens.token_counts(w, 2)


_TOKENS = f"""WITH {windows_sql(WORKLOADS['priority_day'])}, full_w AS (SELECT g.series_id, g.win, g.pos, g.value FROM grid g JOIN wins n ON n.series_id = g.series_id AND n.win = g.win WHERE n.n_obs = 8),
 sc AS (SELECT series_id, win, avg(abs(value)) AS m FROM full_w GROUP BY 1, 2),
 tk AS (SELECT f.series_id, f.win, f.pos, CAST(greatest(0, least({tokens.BINS - 1}, floor((f.value / sc.m + 4.0) / {8.0 / tokens.BINS}))) AS INTEGER) AS token FROM full_w f JOIN sc ON sc.series_id = f.series_id AND sc.win = f.win),
 ctx AS (SELECT pos, token, CAST(lag(token, 1) OVER o AS VARCHAR) AS p1, CAST(lag(token, 2) OVER o AS VARCHAR) AS p2 FROM tk WINDOW o AS (PARTITION BY series_id, win ORDER BY pos))
 SELECT context, token, count(*) AS n FROM (SELECT '' AS context, token FROM ctx UNION ALL SELECT p1, token FROM ctx WHERE p1 IS NOT NULL UNION ALL SELECT p2 || ',' || p1, token FROM ctx WHERE p2 IS NOT NULL) GROUP BY 1, 2"""

# ---- measures on a table of scores ----------------------------------------------------------------------------


def _scores(s, d):
    """Errors of slot means by cluster (``framework``) and over all (``direct``), by region and share hidden at random.

    A data set is a region's suppliers; z is what is scored.
    """
    b = Base(s, d)
    profile = F.array(*[F.lit(float(v)) for v in impute.slot_means(b.train, W, "z")])
    centres = F.array(*[F.array(*[F.lit(float(v)) for v in row]) for row in b.centroids])
    nation = s.read.parquet(f"{d}/nation.parquet").select(F.col("n_nationkey").alias("s_nationkey"), "n_regionkey")
    region = s.read.parquet(f"{d}/supplier.parquet").join(F.broadcast(nation), "s_nationkey").select(F.col("s_suppkey").cast("string").alias("series_id"), F.col("n_regionkey").cast("string").alias("dataset"))
    test = materialise(z_wins(s, d).where("complete").where(series.holdout()).select("series_id", "win", "z").join(region, "series_id"), "test")
    rows = []
    for rate in (0.1, 0.5, 0.9):
        t = gaps.mcar(test, W, rate).withColumn("seen", impute.shown("z", "hidden"))
        t = t.withColumn("own", F.element_at(centres, nearest(euclid_to("seen", b.centroids))["cluster"] + 1))
        cells = t.select("dataset", F.explode(F.arrays_zip(F.col("z").alias("t"), F.col("hidden").alias("h"), F.col("own").alias("framework"), profile.alias("direct"))).alias("c")).where("c.h")
        for strategy in ("framework", "direct"):
            rows.append(metrics.errors(cells.select("dataset", F.col(f"c.{strategy}").alias("pred"), F.col("c.t").alias("truth")), ["dataset"]).select("dataset", F.lit("profile").alias("learner"), F.lit(strategy).alias("strategy"), F.lit("mcar").alias("gap_kind"), F.lit(rate).alias("rate"), F.round("mse", 6).alias("mse")))
    return reduce(DataFrame.unionByName, rows)


def win_grid(s, d):
    return metrics.win_grid(_scores(s, d), "framework", "direct", ["rate"]).select("rate", "wins", "losses", "ties", F.round("mean_ratio", 4).alias("mean_ratio"))


def reduction(s, d):
    p = _scores(s, d).groupBy("dataset", "learner", "rate").pivot("strategy", ["framework", "direct"]).agg(F.first("mse"))
    return p.select("dataset", "learner", "rate", F.round(metrics.reduction_pct(F.col("framework"), F.col("direct")), 3).alias("reduction_pct"))


_SCORES = f"""WITH {CLUSTER_SQL}, te AS (SELECT z.series_id, z.win, z.pos, z.z, r.rate, {unit_sql(SEEDS['gap'], 'z.series_id', 'z.win', 'z.pos')} < r.rate AS hidden FROM zs z, (VALUES (0.1::DOUBLE), (0.5), (0.9)) r(rate) WHERE z.complete AND z.held),
 sm AS (SELECT pos, avg(z) AS m FROM zc GROUP BY 1),
 vis AS (SELECT series_id, win, rate, sum(CASE WHEN hidden THEN 0 ELSE 1 END) AS n FROM te GROUP BY 1, 2, 3),
 td AS (SELECT v.series_id, v.win, v.rate, c.cluster, sqrt(sum(CASE WHEN v.hidden THEN 0 ELSE (v.z - c.c) * (v.z - c.c) END) * {2.0 * W} / (max(vis.n) + {W})) AS dist FROM te v JOIN c2 c ON c.pos = v.pos JOIN vis ON vis.series_id = v.series_id AND vis.win = v.win AND vis.rate = v.rate GROUP BY 1, 2, 3, 4),
 tk AS (SELECT series_id, win, rate, cluster FROM td QUALIFY row_number() OVER (PARTITION BY series_id, win, rate ORDER BY dist, cluster) = 1),
 p AS (SELECT CAST(n.n_regionkey AS VARCHAR) AS dataset, te.rate, round(avg((c2.c - te.z) * (c2.c - te.z)), 6) AS a, round(avg((sm.m - te.z) * (sm.m - te.z)), 6) AS b FROM te JOIN tk ON tk.series_id = te.series_id AND tk.win = te.win AND tk.rate = te.rate JOIN c2 ON c2.cluster = tk.cluster AND c2.pos = te.pos JOIN sm ON sm.pos = te.pos
  JOIN supplier s ON CAST(s.s_suppkey AS VARCHAR) = te.series_id JOIN nation n ON n.n_nationkey = s.s_nationkey WHERE te.hidden GROUP BY 1, 2)"""


def training_reduction(s, d):
    """Windows that direct training uses, all windows, and those the bound asks for: by workload."""
    from ..operators.bounds import need_value

    out = None
    for name in ("supplier_week", "user_halfday", "flag_day"):
        w = WORKLOADS[name].w
        g = series.windows(slots(s, d, name), w).agg(F.lit(name).alias("dataset"), F.count("*").alias("total"), F.sum(F.col("complete").cast("int")).alias("clean"), F.avg(F.when(F.col("n_obs") > 0, F.col("n_obs") / w)).alias("seen"))
        out = g if out is None else out.unionByName(g)
    used = F.least(F.col("total"), F.ceil(F.lit(3 * need_value()) / (F.col("seen") * 0.9)))
    return out.withColumn("used", used).select("dataset", "total", "clean", "used", F.round(F.col("clean") / F.col("used"), 4).alias("clean_ratio"), F.round(F.col("total") / F.col("used"), 4).alias("total_ratio"))


def _reduction_sql(name: str) -> str:
    from ..operators.bounds import need_value

    w = WORKLOADS[name].w
    return f"""SELECT '{name}' AS dataset, total, clean, used, round(clean / used, 4) AS clean_ratio, round(total / used, 4) AS total_ratio FROM (SELECT count(*) AS total, CAST(sum(CASE WHEN n_obs = {w} THEN 1 ELSE 0 END) AS BIGINT) AS clean,
 least(count(*), CAST(ceil({3 * need_value()!r}::DOUBLE / (avg(CASE WHEN n_obs > 0 THEN n_obs / {float(w)} END) * 0.9::DOUBLE)) AS BIGINT)) AS used FROM (WITH {windows_sql(WORKLOADS[name])} SELECT * FROM wins))"""


# ---- the framework end to end, and the experiments ------------------------------------------------------------


def framework_readings(s, d):
    return pipeline.run_framework(wins(s, d), W, runs=2)[0]


def framework_readings_k3_no_gate(s, d):
    return pipeline.run_framework(wins(s, d), W, k=3, runs=2, gate=-1.0)[0]


def framework_planted(s, d):
    """Where structure is planted the gate keeps the clusters; readings filled by their models."""
    from ..sources.planted import planted

    w = series.described(planted(s, d).select("series_id", "win", "x"), W)
    return pipeline.run_framework(w, W, runs=2)[0]


def _models(k, **options):
    def run(s, d):
        p = pipeline.prepare(wins(s, d), W, k)
        return pipeline.train(p, "profile", runs=2, **options)[0].select("cluster", "kind", F.size(F.map_filter("params", lambda k, v: ~k.startswith("fit_ms"))).alias("parts"), "version")

    return run


def _token_rows(s, d):
    """Token contexts of another collection: every one of them, with its counts."""
    w = series.windows(slots(s, d, "priority_day"), 8).where("complete")
    return [r.asDict() for r in tokens.token_counts(w, 3).where(F.col("n") > 1).collect()]  # contexts seen once say nothing of what follows


def _scored(s, d, names, learners, strategies, kinds=("mcar",), rates=(0.5,), k=None):
    """Scores of every cell of a grid over several data sets."""
    rows = _token_rows(s, d) if "token" in strategies else None
    grids = []
    for name in names:
        windows, w = experiments.windows_for(s, d, name)
        grids.append(experiments.run_grid(windows, w, name, learners, strategies, kinds, rates, k, rows))
    return reduce(DataFrame.unionByName, grids)


def _grid(*args, **options):
    def run(s, d):
        out = _scored(s, d, *args, **options)
        return out.select("dataset", "learner", "strategy", "gap_kind", "rate", F.round("mse", 6).alias("mse"), F.round("mae", 6).alias("mae"), "n", "own", "used")

    return run


ALL_SETS = ("supplier_week", "user_halfday", "flag_day", "type_hour_value", "type_hour_count", "type_15min", "embedding")
LEVELS = (0.1, 0.3, 0.5, 0.7, 0.9)
INDUCED = ("mcar", "mnar_value", "mnar_burst", "mnar_group")


def mask_curve(s, d):
    """Error against the extra mask's share, pooled over clusters."""
    t = minmask.trace_stats(minmask.sweep_masks(materialise(_pairs(s, d), "pairs"), W, "gaussian", [0.0001, 0.001, 0.01, 0.1, 0.3], runs=3))
    return t.groupBy("mask").agg(F.round(F.avg("oracle"), 6).alias("oracle"), F.round(F.avg("projected"), 6).alias("projected"))


def stage_times(s, d):
    """Milliseconds of each strategy and learner at 10 % and 90 % hidden, and the increment: preparation (wall time, shared by
    a grid's cells), fits and inference (time of the workers)."""
    out = _scored(s, d, ("supplier_week", "user_halfday"), ("gaussian", "bidirectional", "stationarised"), ("direct", "framework", "generative", "token"), rates=(0.1, 0.9))
    total = F.col("prepare_ms") + F.col("fit_ms") + F.col("infer_ms")
    at = lambda rate, c: F.max(F.when(F.col("rate") == rate, c))
    g = out.groupBy("dataset", "learner", "strategy").agg(at(0.1, total).alias("ms_10"), at(0.9, total).alias("ms_90"), at(0.1, F.col("prepare_ms")).alias("prepare_ms"), at(0.1, F.col("fit_ms")).alias("fit_ms"), at(0.1, F.col("infer_ms")).alias("infer_ms"))
    return g.withColumn("increment_ms", F.col("ms_90") - F.col("ms_10"))


def training_size(s, d):
    """Complete windows that fits read, counted from the fits, by strategy, against the clean ones and all."""
    out = _scored(s, d, ("supplier_week", "user_halfday", "planted"), ("gaussian",), ("direct", "generative", "generative_sample", "framework", "no_gate"), ("natural",))
    ratio = lambda c: F.round(F.try_divide(c, "used"), 4)
    return out.select("dataset", "strategy", "total", "clean", "used", ratio("clean").alias("clean_ratio"), ratio("total").alias("total_ratio"))


def gap_profile_masks(s, d):
    """Roles of the three training sets, counted."""
    return patterns.masked_sets(_pairs(s, d), W, 0.08).groupBy("role").agg(F.count("*").alias("n"))


QUERIES = {
    **{f"impute_{k}": _impute(k) for k in KINDS},
    "eval_all": eval_all,
    "eval_mse": lambda s, d: eval_all(s, d).select("learner", "mse"),
    "eval_mae": lambda s, d: eval_all(s, d).select("learner", "mae"),
    "pair_moments": pair_moments,
    "imputed_readings": imputed_readings,
    "udaf_wmse": weighted_mse,
    "mask_transition_counts": mask_transition_counts,
    "generated_masks": generated_masks,
    "token_counts": token_counts,
    "win_grid": win_grid,
    "reduction_pct": reduction,
    "training_reduction": training_reduction,
    "role_counts": gap_profile_masks,
    "framework_readings": framework_readings,
    "framework_planted": framework_planted,
    "framework_models": _models(None),
    "framework_readings_k3_no_gate": framework_readings_k3_no_gate,
    "framework_models_k3_no_gate": _models(3, gate=-1.0),
    "exp1_mse_grid": _grid(ALL_SETS, (*EVALUATED, "gaussian"), ("direct", "framework", "no_gate")),
    "exp2_levels": _grid(("planted_truth",), ("gaussian", "stationarised"), ("direct", "framework", "no_gate"), INDUCED, LEVELS),
    "exp3_pretrained": _grid(("planted_truth", "supplier_week"), ("gaussian",), ("framework", "no_gate", "token"), ("mcar", "mnar_burst"), LEVELS),
    "exp4_generative": _grid(("planted", "supplier_week"), (*EVALUATED, "gaussian"), ("generative", "generative_sample", "framework"), ("mcar",), (0.1, 0.9)),
    "exp4_natural": _grid(("planted", "supplier_week", "user_halfday"), ("gaussian", "bidirectional"), ("direct", "generative", "generative_sample", "framework"), ("natural",)),
    "exp5_time": stage_times,
    "exp6_reduction": training_size,
    "expU_mask_curve": mask_curve,
    "exp_clustered_gain": _grid(("planted_truth",), ("stationarised",), ("direct", "one_cluster", "framework", "no_gate"), ("mcar",), (0.1,)),
    "exp_planted_order": _grid(("planted",), ("gaussian", "profile", "mean"), ("direct", "framework"), ("natural",), (0.5,)),
    "exp_surveyed_learners": _grid(("planted",), ("decay_recurrent", "lag_decomposed", "multiscale", "locf", "nocb", "linear", "window_mean"), ("direct", "framework"), ("natural",)),
    "ablation_grid": _grid(("planted",), ("gaussian", "bidirectional", "attention"), tuple(experiments.FRAMEWORK), ("natural",), (0.5,)),
}
ORACLES = {
    **{f"impute_{k}": f"{_BASE} SELECT series_id, win, CAST(pos AS BIGINT) AS pos, round(pred, 6) AS pred FROM ({q})" for k, q in _PRED.items()},
    "eval_all": f"{_BASE} " + " UNION ALL ".join(_ERR.format(k=k, q=q) for k, q in _PRED.items()),
    "eval_mse": f"SELECT learner, mse FROM ({_BASE} " + " UNION ALL ".join(_ERR.format(k=k, q=q) for k, q in _PRED.items()) + ")",
    "eval_mae": f"SELECT learner, mae FROM ({_BASE} " + " UNION ALL ".join(_ERR.format(k=k, q=q) for k, q in _PRED.items()) + ")",
    "pair_moments": f"WITH {CLUSTER_SQL} SELECT CAST(a.pos AS BIGINT) AS i, CAST(b.pos AS BIGINT) AS j, count(*) AS n, round(sum(a.z * b.z), 3) AS total FROM zc a JOIN zc b ON a.series_id = b.series_id AND a.win = b.win AND a.pos <= b.pos GROUP BY 1, 2",
    "imputed_readings": f"""WITH {Z_SQL}, f AS (SELECT series_id, win * {W} + pos AS slot, value, mu, last_value(value IGNORE NULLS) OVER (PARTITION BY series_id, win ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS carried FROM zs WHERE n_obs > 0)
        SELECT series_id, slot, round(coalesce(value, carried, mu), 6) AS value, value IS NULL AS imputed, CASE WHEN value IS NULL THEN 'locf' ELSE 'observed' END AS source FROM f""",
    "udaf_wmse": f"{_BASE} SELECT CAST(pos AS BIGINT) AS pos, round(sum(abs(truth) * (pred - truth) * (pred - truth)) / sum(abs(truth)), 4) AS wmse FROM ({_PRED['linear']}) GROUP BY 1",
    "mask_transition_counts": f"""WITH {Z_SQL}, g AS (SELECT series_id, win, pos, CASE WHEN value IS NULL THEN 1 ELSE 0 END AS cur FROM zs WHERE NOT complete AND n_obs > 0)
        SELECT CAST(pos AS BIGINT) AS pos, CAST(coalesce(prev, 2) AS BIGINT) AS prev, CAST(cur AS BIGINT) AS cur, count(*) AS n FROM (SELECT *, lag(cur) OVER (PARTITION BY series_id, win ORDER BY pos) AS prev FROM g) GROUP BY 1, 2, 3""",
    "token_counts": _TOKENS,
    "win_grid": f"{_SCORES} SELECT rate, CAST(sum(CASE WHEN round(a, 4) < round(b, 4) THEN 1 ELSE 0 END) AS BIGINT) AS wins, CAST(sum(CASE WHEN round(a, 4) > round(b, 4) THEN 1 ELSE 0 END) AS BIGINT) AS losses, CAST(sum(CASE WHEN round(a, 4) = round(b, 4) THEN 1 ELSE 0 END) AS BIGINT) AS ties, round(exp(avg(ln(round(b, 4) / round(a, 4)))), 4) AS mean_ratio FROM p GROUP BY 1",
    "reduction_pct": f"{_SCORES} SELECT dataset, 'profile' AS learner, rate, round(100 * (1 - a / b), 3) AS reduction_pct FROM p",
    "training_reduction": " UNION ALL ".join(map(_reduction_sql, ("supplier_week", "user_halfday", "flag_day"))),
}
