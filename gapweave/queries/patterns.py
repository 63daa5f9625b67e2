"""Queries of projection, structure, masks, gap generators, bounds and assignment."""

from __future__ import annotations

import math
from dataclasses import replace

from pyspark.sql import functions as F

from ..functions.hashing import SEEDS, draw_sql, unit_sql
from ..functions.masks import missing_ratio, pattern_kl_sql
from ..operators import assign, bounds, gaps, minmask, patterns, series
from ..sources.planted import planted
from ..sources.scratch import materialise
from ..sources.tables import read_table
from ..sources.workloads import WORKLOADS, windows_sql
from .windows import CLUSTER_SQL, INC_SQL, W, Z_SQL, Base, complete_assigned, incomplete_assigned, slots, wins, z_wins

H = SEEDS
ALL = (1 << W) - 1


def _inc(s, d):
    return incomplete_assigned(s, d).select("series_id", "win", "cluster", "words", "n_obs")


def _pairs(s, d, mode="wrap"):
    b = Base(s, d)
    return patterns.pair(b.incomplete(), b.complete(), mode)


_RANK = f"""ri AS (SELECT *, row_number() OVER (PARTITION BY cluster ORDER BY {draw_sql(H['inc'], 'series_id', 'win')}, series_id, win) AS rank FROM inc),
 rc AS (SELECT cluster, series_id AS comp_series, win AS comp_win, row_number() OVER (PARTITION BY cluster ORDER BY {draw_sql(H['comp'], 'series_id', 'win')}, series_id, win) AS comp_rank, count(*) OVER (PARTITION BY cluster) AS n_comp FROM a2)"""
PAIR_SQL = f"""WITH {INC_SQL}, {_RANK}, pairs AS (SELECT ri.*, rc.comp_series, rc.comp_win FROM ri JOIN rc ON rc.cluster = ri.cluster AND rc.comp_rank = (ri.rank - 1) % rc.n_comp + 1)"""
_BITS = f"(SELECT unnest(range({W})) AS pos)"


def pair_one_to_one(s, d):
    return _pairs(s, d, "injective").select("series_id", "win", "cluster", "comp_series", "comp_win")


def pair_reuse(s, d):
    return _pairs(s, d).select("series_id", "win", "cluster", "comp_series", "comp_win")


def pair_replacement(s, d):
    return _pairs(s, d, "replacement").select("series_id", "win", "cluster", "comp_series", "comp_win")


def project_pairs(s, d):
    shown = patterns.project("words", "z", W)
    return _pairs(s, d).select("series_id", "win", (F.round(F.aggregate(shown, F.lit(0.0), lambda a, v: a + F.coalesce(v, F.lit(0.0))), 4) + 0.0).alias("shown_sum"), F.size(F.filter(shown, lambda v: v.isNotNull())).cast("long").alias("shown"))


def random_rivals(s, d):
    return _inc(s, d).select("series_id", "win", patterns.random_pattern("words", W, "series_id", "win")[0].alias("word"))


def sampled_rivals(s, d):
    return patterns.sampled_rival(_inc(s, d)).select("series_id", "win", "cluster", F.col("rival")[0].alias("rival"))


def kl(s, d):
    return patterns.compared(_inc(s, d), W).select("series_id", "win", "cluster", F.round("kl_s", 6).alias("kl_s"), F.round("kl_r", 6).alias("kl_r"))


def structure_ratio(s, d):
    return patterns.structure(patterns.compared(_inc(s, d), W)).select("cluster", F.col("n_p").cast("long").alias("n_p"), "n", F.round("ratio", 6).alias("ratio"), "kept")


def selected_patterns(s, d):
    return patterns.compared(_inc(s, d), W).select("series_id", "win", patterns.select_pattern()[0].alias("word"))


def structure_null(s, d):
    """The ratio after replacing each pattern by its random rival: what chance alone gives."""
    inc = _inc(s, d).withColumn("words", patterns.random_pattern("words", W, "series_id", "win", seed=H["random"] + 1000))
    return patterns.structure(patterns.compared(inc, W)).select("cluster", "n", F.round("ratio", 6).alias("ratio"), "kept")


def structure_planted(s, d):
    """The same test where structure was planted: by archetype, the clusters must be kept."""
    p = series.described(planted(s, d), W).where("NOT complete AND n_obs > 1").select("series_id", "win", F.col("archetype").cast("int").alias("cluster"), "words", "n_obs")
    return patterns.structure(patterns.compared(p, W)).select("cluster", "n", F.round("ratio", 6).alias("ratio"), "kept")


def kl_features(s, d):
    from ..functions.masks import run_length_features, transition_features

    return _inc(s, d).select("series_id", "win", run_length_features(F.col("words"), W).alias("r"), transition_features(F.col("words"), W).alias("t")).select("series_id", "win", "r.gaps", "r.longest", F.array_join("t", ",").alias("transitions"))


_COMPARED = f"""WITH {INC_SQL},
 rnd AS (SELECT series_id, win, CAST({ALL} - sum(1::BIGINT << pos) AS BIGINT) AS word FROM (SELECT i.series_id, i.win, b.pos, i.n_obs, row_number() OVER (PARTITION BY i.series_id, i.win ORDER BY {draw_sql(H['random'], 'i.series_id', 'i.win', 'b.pos')}, b.pos) AS k FROM inc i CROSS JOIN {_BITS} b) WHERE k <= {W} - n_obs GROUP BY 1, 2),
 riv AS (SELECT series_id, win, cluster, word, CASE WHEN count(*) OVER (PARTITION BY cluster) > 1 THEN coalesce(lead(word) OVER o, first_value(word) OVER o) END AS rival FROM inc WINDOW o AS (PARTITION BY cluster ORDER BY {draw_sql(H['rival'], 'series_id', 'win')}, series_id, win)),
 cmp AS (SELECT v.series_id, v.win, v.cluster, v.word, v.rival, r.word AS random, {pattern_kl_sql('v.word', 'v.rival', W)} AS kl_s, {pattern_kl_sql('v.word', 'r.word', W)} AS kl_r FROM riv v JOIN rnd r ON r.series_id = v.series_id AND r.win = v.win)"""


def artificial_mask(s, d):
    m = patterns.artificial_mask(W, 0.1, "series_id", "win")
    return complete_assigned(s, d).select("series_id", "win", m[0].alias("word"))


_MASK = f"""msk AS (SELECT series_id, win, CAST({ALL} - sum(1::BIGINT << pos) AS BIGINT) AS word FROM (SELECT *, row_number() OVER (PARTITION BY series_id, win ORDER BY u, pos) AS k FROM (SELECT t.series_id, t.win, b.pos, {unit_sql(H['mask'], '0', 't.series_id', 't.win', 'b.pos')} AS u FROM {{src}} t CROSS JOIN {_BITS} b)) WHERE u < 0.1 OR k <= 1 GROUP BY 1, 2)"""


def masked_sets_counts(s, d):
    sets = patterns.masked_sets(_pairs(s, d), W, 0.1)
    return sets.groupBy("cluster", "role").agg(F.count("*").alias("n"), F.sum(F.bit_count(F.col("shown")[0])).alias("shown"), F.round(F.sum(F.aggregate("x_in", F.lit(0.0), lambda a, v: a + F.coalesce(v, F.lit(0.0)))), 3).alias("total"))


def mask_schedule(s, d):
    """The schedule from each discount of the line items as the least share."""
    shares = F.udf(lambda least: minmask.mask_schedule(least), "array<double>")
    least = read_table(s, d, "lineitem").where("l_discount > 0").groupBy(F.col("l_discount").alias("least")).agg(F.count("*").alias("n"))
    return least.select("least", "n", F.posexplode(shares("least")).alias("step", "m")).select("least", "n", F.col("step").cast("long").alias("step"), F.round("m", 6).alias("mask"))


def mask_sweep(s, d):
    return minmask.trace_stats(minmask.sweep_masks(materialise(_pairs(s, d), "pairs"), W, "gaussian", runs=3)).select("cluster", "step", "mask", *[F.round(c, 4).alias(c) for c in ("oracle", "projected", "gap", "limit")])


def mask_search(s, d):
    return minmask.min_mask_search(materialise(_pairs(s, d), "pairs"), W, "gaussian", runs=3)[0]


#: A trace for the rules, in both engines: suppliers as clusters, line numbers as steps; the gap is the distance of the mean
#: discount from the mean tax, in whole percent, the limit twice the discount's standard error. Sums are of whole numbers, so
#: that both engines compare and order the same doubles.
_SUMS = "SELECT CAST(l_suppkey AS INTEGER) AS cluster, CAST(l_linenumber - 1 AS INTEGER) AS step, count(*) AS n, CAST(sum(a) AS BIGINT) AS a, CAST(sum(b) AS BIGINT) AS b, CAST(sum(a * a) AS BIGINT) AS aa FROM (SELECT l_suppkey, l_linenumber, CAST(round(l_discount * 100) AS BIGINT) AS a, CAST(round(l_tax * 100) AS BIGINT) AS b FROM {lineitem}) l GROUP BY 1, 2"
_TRACE = f"SELECT cluster, step, round(0.01 * pow(2.0, step), 6) AS mask, CAST(abs(a - b) AS DOUBLE) / n AS gap, CASE WHEN n > 1 THEN 2 * sqrt(CAST(n * aa - a * a AS DOUBLE) / (CAST(n AS DOUBLE) * n * (n - 1))) END AS lim FROM ({_SUMS}) s"
_TRACE_SQL = f"t AS ({_TRACE.format(lineitem='lineitem')})"


def _rule(rule):
    def run(s, d):
        t = s.sql(_TRACE, lineitem=read_table(s, d, "lineitem")).withColumnRenamed("lim", "limit")
        return minmask.pick_mask(t, rule).select("cluster", "step", "mask", "within")

    return run


def _rule_sql(hit: str) -> str:
    return f"WITH {_TRACE_SQL}, r AS (SELECT *, sum(CASE WHEN gap < lim THEN 0 ELSE 1 END) OVER (PARTITION BY cluster ORDER BY step) AS lost FROM t), g AS (SELECT cluster, {hit} AS hit, arg_min(step, struct_pack(a := gap, b := step)) AS least FROM r GROUP BY 1) SELECT CAST(g.cluster AS INTEGER) AS cluster, CAST(t.step AS INTEGER) AS step, CAST(t.mask AS DOUBLE) AS mask, g.hit IS NOT NULL AS within FROM g JOIN t ON t.cluster = g.cluster AND t.step = coalesce(g.hit, g.least)"


# ---- gap generators -------------------------------------------------------------------------------------------


def _complete(s, d):
    return wins(s, d).where("complete").select("series_id", "win", "x")


def _hidden(df):
    word = F.aggregate(F.transform("hidden", lambda h, i: F.when(h, F.call_function("shiftleft", F.lit(1).cast("long"), i)).otherwise(F.lit(0).cast("long"))), F.lit(0).cast("long"), lambda a, b: a.bitwiseOR(b))
    return df.select("series_id", "win", word.alias("word"))


_COMPLETE = f"WITH {Z_SQL}, whole AS (SELECT series_id, win, pos, value FROM zs WHERE complete)"
_WORD = "CAST(sum(CASE WHEN hidden THEN 1::BIGINT << pos ELSE 0 END) AS BIGINT)"


def _gap_sql(hidden: str, source: str = "whole") -> str:
    return f"{_COMPLETE} SELECT series_id, win, {_WORD} AS word FROM (SELECT series_id, win, pos, {hidden} AS hidden FROM {source}) GROUP BY 1, 2"


def _group(s, d):
    nation = s.read.parquet(f"{d}/supplier.parquet").select(F.col("s_suppkey").cast("string").alias("series_id"), F.col("s_nationkey").alias("nation"))
    return _hidden(gaps.mnar_group(_complete(s, d).join(nation, "series_id"), W, "nation", 0.5))


def _levels(s, d):
    """Share hidden by every generator at every level."""
    out = None
    for kind, make in gaps.GENERATORS.items():
        for p in (0.1, 0.3, 0.5, 0.7, 0.9):
            df = make(_complete(s, d), W, p).select(F.lit(kind).alias("kind"), F.lit(p).alias("p"), F.size(F.filter("hidden", lambda h: h)).alias("n"))
            out = df if out is None else out.unionByName(df)
    return out.groupBy("kind", "p").agg(F.round(F.avg(F.col("n") / W), 4).alias("share"), F.count("*").alias("windows"))


def missing_profile(s, d):
    sup = s.read.parquet(f"{d}/supplier.parquet").select(F.col("s_suppkey").cast("string").alias("series_id"), "s_nationkey")
    nat = s.read.parquet(f"{d}/nation.parquet").select(F.col("n_nationkey").alias("s_nationkey"), F.col("n_name").alias("nation"), "n_regionkey")
    reg = s.read.parquet(f"{d}/region.parquet").select(F.col("r_regionkey").alias("n_regionkey"), F.col("r_name").alias("region"))
    rows = wins(s, d).join(sup, "series_id").join(F.broadcast(nat), "s_nationkey").join(F.broadcast(reg), "n_regionkey")
    return gaps.missing_profile(rows, W, ["region", "nation"]).select("region", "nation", "windows", "missing", F.round("share", 6).alias("share"), "complete", "empty")


def gap_runs(s, d):
    cells = wins(s, d).select("series_id", "win", F.posexplode("x").alias("pos", "value")).select("series_id", (F.col("win") * W + F.col("pos")).alias("slot"), "value")
    return gaps.gap_runs(cells)


def gap_run_lengths(s, d):
    return gap_runs(s, d).groupBy("length").agg(F.count("*").alias("n"))


_CELLS = f"WITH {Z_SQL}, cells AS (SELECT series_id, win * {W} + pos AS slot, value FROM zs), isl AS (SELECT *, slot - row_number() OVER (PARTITION BY series_id, value IS NULL ORDER BY slot) AS island FROM cells), runs AS (SELECT series_id, min(slot) AS start, count(*) AS length FROM isl WHERE value IS NULL GROUP BY series_id, island)"


# ---- bounds and assignment ------------------------------------------------------------------------------------


def sample_need(s, d):
    """The bound at each discount (as the error) and tax (as the risk) of the line items."""
    grid = read_table(s, d, "lineitem").where("l_discount > 0 AND l_tax > 0").groupBy(F.col("l_discount").alias("eps"), F.col("l_tax").alias("delta")).agg(F.count("*").alias("n"))
    need = bounds.sample_need(F.col("eps"), F.col("delta"))
    return grid.select("eps", "delta", "n", F.round(need, 4).alias("need"), F.ceil(need).alias("windows"))


def observable_ratio(s, d):
    return wins(s, d).select("series_id", "win", *[F.round(bounds.observable_ratio(missing_ratio("words", W), 0.1, r), 6).alias(r) for r in ("product", "difference")])


def windows_needed(s, d):
    g = bounds.observable_ratio(missing_ratio("words", W), 0.1)
    return wins(s, d).groupBy("n_obs").agg(F.first(bounds.windows_needed(g)).alias("needed"), F.round(F.first(bounds.max_mask_for(F.lit(600.0), missing_ratio("words", W))), 6).alias("max_mask")).select(F.col("n_obs").cast("long").alias("n_obs"), "needed", "max_mask")


#: A mask a cluster, for the exact twin of the guarantees.
MASKS = [(0, 0.01), (1, 0.08), (2, 0.32)]


def cluster_guarantees(s, d):
    rows = _inc(s, d).withColumn("missing", missing_ratio("words", W))
    g = bounds.cluster_guarantees(rows, s.createDataFrame(MASKS, "cluster int, mask double"))
    return g.select("cluster", "n", "met", "feasible", *[F.round(c, 6).alias(c) for c in ("alpha", "beta", "gamma", "need", "slack")])


def searched_guarantees(s, d):
    """The same with the masks that the search finds: beta is the cluster's own."""
    b = Base(s, d)
    inc = b.incomplete()
    masks = minmask.min_mask_search(materialise(patterns.pair(inc, b.complete()), "pairs"), W, "gaussian", runs=2)[0]
    g = bounds.cluster_guarantees(inc.withColumn("missing", missing_ratio("words", W)), masks)
    return g.select("cluster", "n", "met", "feasible", *[F.round(c, 6).alias(c) for c in ("alpha", "beta", "gamma", "need", "slack")])


def reconstruction(s, d, share=0.1):
    """Centroids as predictions of the projected slots: successes by cluster under three readings of the test, within a
    tenth of the complete windows' deviation."""
    rows = _reconstructed(s, d, share)
    return rows.groupBy("cluster").agg(*[F.round(F.avg(F.col(a).cast("double")), 6).alias(a) for a in ("all", "mean", "slot")], F.count("all").alias("n"))


def _reconstructed(s, d, share):
    from ..operators.cluster import centroid_table

    b = Base(s, d)
    sd = b.train.select(F.explode("z").alias("v")).agg(F.stddev_pop("v")).first()[0]
    p = patterns.pair(b.incomplete(), b.complete()).join(F.broadcast(centroid_table(s, b.centroids)), "cluster")
    p = p.withColumn("hidden", F.transform("z", lambda v, i: F.getbit(F.col("words")[0], i) == 0))
    return p.select("cluster", *[bounds.reconstruction_test("centroid", "z", "hidden", share * sd, a).alias(a) for a in ("all", "mean", "slot")])


def _proposed(s, d):
    from ..functions.gapdtw import euclid_to

    b = Base(s, d)
    return assign.proposals(b.gone, euclid_to("z", b.centroids), 0.1, W)


def assign_bounded(s, d):
    """Under the bound: every window, its cluster, and whether it got its first choice."""
    return assign.assign_incomplete(_proposed(s, d), bounds.need_value(), 2000).select("series_id", "win", "cluster", "choice_rank", F.round("gamma", 6).alias("gamma"))


def assign_drop(s, d):
    return assign.assign_incomplete(_proposed(s, d), bounds.need_value(), 2000, "drop").select("series_id", "win", "cluster", "choice_rank")


def assign_unbounded(s, d):
    return assign.assign_incomplete(_proposed(s, d), math.inf, 1 << 30).select("series_id", "win", "cluster", F.round("dist", 4).alias("dist"))


def assign_dtw(s, d):
    """The same with warping distances."""
    from ..functions.gapdtw import distances_to

    b = Base(s, d)
    return assign.assign_incomplete(assign.proposals(b.gone, distances_to("z", b.centroids), 0.1, W), bounds.need_value(), 2000).select("series_id", "win", "cluster", "choice_rank")


def cluster_balance(s, d):
    a = assign.assign_incomplete(_proposed(s, d), bounds.need_value(), 2000)
    return assign.cluster_balance(a, bounds.need_value(), 2000, 3).select("cluster", "size", F.round("share", 4).alias("share"), "closed", *[f"choice_{r}" for r in range(1, 5)])


def waterfill_sizes(s, d):
    """Sizes after 1000 leftovers went to the smallest clusters, from the natural sizes."""
    sizes = {r.cluster: r.n for r in _inc(s, d).groupBy("cluster").agg(F.count("*").alias("n")).collect()}
    return s.createDataFrame(sorted(assign.filled_sizes(sizes, 1000).items()), "cluster int, size long")


def sample_incomplete(s, d):
    z = z_wins(s, d).where("NOT complete AND n_obs > 0").where(~series.holdout())
    return assign.sample_incomplete(z, 1, 300.0, 0.7, 1.5).select("series_id", "win")


#: Tolerances of the reconstruction test, as shares of the complete windows' deviation.
TOLERANCES = (0.1, 1.0, 2.0, 2.5)
ALPHAS, BETAS, DELTA = (0.1, 0.3, 0.5, 0.7), (0.01, 0.1, 0.2, 0.4), 0.1


def learnability(s, d):
    """Share of windows that the slot profile rebuilds within each tolerance, over a grid of projected and extra shares,
    and whether it reaches 1 - delta."""
    from ..functions.hashing import unit
    from .windows import train_complete

    z = materialise(train_complete(s, d), "complete")
    profile = z.select(*[F.avg(F.col("z")[j]).alias(f"p{j}") for j in range(W)]).first()
    sd = z.select(F.explode("z").alias("v")).agg(F.stddev_pop("v")).first()[0]
    grid = s.createDataFrame([(a, b) for a in ALPHAS for b in BETAS], "alpha double, beta double")
    rows = z.crossJoin(F.broadcast(grid))  # 16 rows a window
    hidden = F.transform(F.sequence(F.lit(0), F.lit(W - 1)), lambda i: (unit(H["gap"], "series_id", "win", i) < F.col("alpha")) | (unit(H["mask"], "series_id", "win", i) < F.col("beta")))
    rows = rows.withColumns({"hidden": hidden, "guess": F.array(*[F.lit(profile[j]) for j in range(W)])})
    tests = F.array(*[F.struct(F.lit(t).alias("tolerance"), bounds.reconstruction_test("guess", "z", "hidden", t * sd, "all").alias("ok")) for t in TOLERANCES])
    rows = rows.select("alpha", "beta", F.explode(tests).alias("t"))
    g = rows.groupBy("t.tolerance", "alpha", "beta").agg(F.round(F.avg(F.col("t.ok").cast("double")), 6).alias("success"), F.count("*").alias("n"))
    return g.withColumn("label", bounds.success_label(F.col("success"), DELTA))


def learnability_boundary(s, d):
    """A line in (alpha, beta) between learnable and not, for each tolerance, and whether it separates the grid."""
    import numpy as np

    by: dict[float, list] = {}
    for r in learnability(s, d).collect():  # 16 rows a tolerance
        by.setdefault(r.tolerance, []).append((r.alpha, r.beta, r.label))
    out = []
    for t, rows in sorted(by.items()):
        theta, split = bounds.fit_boundary(np.array([r[:2] for r in sorted(rows)]), np.array([r[2] for r in sorted(rows)]))
        out.append((t, *[float(v) for v in theta], bool(split), sum(r[2] for r in rows)))
    return s.createDataFrame(out, "tolerance double, theta_alpha double, theta_beta double, constant double, separates boolean, learnable int")


def operation_counts(s, d):
    """What the complexity formulas count, for the sizes of this collection."""
    from ..operators.metrics import operation_counts as counts

    n = {r.complete: r.n for r in wins(s, d).groupBy("complete").agg(F.count("*").alias("n")).collect()}
    return s.createDataFrame(sorted(counts(n.get(True, 0), n.get(False, 0), 3, W, 15, 6, 5).items()), "operation string, n long")


#: Slots of a window of the worked example.
EXAMPLE = 19


def worked_example(s, d):
    """Windows of 19 slots: gaps, observed slots and mask word."""
    m = series.windows(slots(s, d), EXAMPLE)
    return m.select("series_id", "win", F.col("n_obs").cast("long").alias("observed"), (EXAMPLE - F.col("n_obs")).cast("long").alias("gaps"), F.col("words")[0].alias("word"))


QUERIES = {
    "pair_one_to_one": pair_one_to_one,
    "pair_reuse": pair_reuse,
    "pair_replacement": pair_replacement,
    "project_pairs": project_pairs,
    "random_rivals": random_rivals,
    "sampled_rivals": sampled_rivals,
    "pattern_kl": kl,
    "pattern_features": kl_features,
    "structure_ratio": structure_ratio,
    "structure_null": structure_null,
    "structure_planted": structure_planted,
    "selected_patterns": selected_patterns,
    "artificial_mask": artificial_mask,
    "masked_sets_counts": masked_sets_counts,
    "mask_schedule": mask_schedule,
    "mask_sweep": mask_sweep,
    "mask_search": mask_search,
    "mask_search_rule": _rule("first_within"),
    "mask_last_within": _rule("last_within"),
    "mask_argmin": _rule("argmin"),
    **{f"mcar_{round(p * 100)}": (lambda s, d, p=p: _hidden(gaps.mcar(_complete(s, d), W, p))) for p in (0.1, 0.5, 0.9)},
    "mcar_exact_50": lambda s, d: _hidden(gaps.mcar_exact(_complete(s, d), W, 0.5)),
    "mnar_value_50": lambda s, d: _hidden(gaps.mnar_value(_complete(s, d), W, 0.5)),
    "mnar_burst_50": lambda s, d: _hidden(gaps.mnar_burst(_complete(s, d), W, 0.5)),
    "mnar_group_50": _group,
    "missing_levels": _levels,
    "missing_profile": missing_profile,
    "missing_by_region": lambda s, d: missing_profile(s, d).where("region IS NOT NULL AND nation IS NULL").select("region", "windows", "missing", "share"),
    "gap_runs": gap_runs,
    "gap_run_lengths": gap_run_lengths,
    "sample_need": sample_need,
    "observable_ratio": observable_ratio,
    "windows_needed": windows_needed,
    "cluster_guarantees": cluster_guarantees,
    "cluster_guarantees_searched": searched_guarantees,
    "reconstruction_test": reconstruction,
    "reconstruction_wide": lambda s, d: reconstruction(s, d, 1.0),
    "learnability_labels": learnability,
    "learnability_boundary": learnability_boundary,
    "operation_counts": operation_counts,
    "assign_bounded": assign_bounded,
    "assign_drop": assign_drop,
    "assign_unbounded": assign_unbounded,
    "assign_dtw": assign_dtw,
    "cluster_balance": cluster_balance,
    "waterfill_sizes": waterfill_sizes,
    "sample_incomplete": sample_incomplete,
    "worked_example": worked_example,
}
_NEED = bounds.need_value()
_RECONSTRUCTED = f"""{PAIR_SQL}, e AS (SELECT p.cluster, p.series_id, p.win, abs(c2.c - zc.z) AS e FROM pairs p JOIN zc ON zc.series_id = p.comp_series AND zc.win = p.comp_win JOIN c2 ON c2.cluster = p.cluster AND c2.pos = zc.pos WHERE (p.word >> zc.pos) & 1 = 0),
        sg AS (SELECT TOLERANCE * stddev_pop(z) AS tol FROM zc),
        t AS (SELECT cluster, series_id, win, CASE WHEN max(e) <= max(tol) THEN 1.0 ELSE 0.0 END AS a, CASE WHEN avg(e) <= max(tol) THEN 1.0 ELSE 0.0 END AS m, avg(CASE WHEN e <= tol THEN 1.0 ELSE 0.0 END) AS sl FROM e, sg GROUP BY 1, 2, 3)
        SELECT cluster, round(avg(a), 6) AS "all", round(avg(m), 6) AS mean, round(avg(sl), 6) AS slot, count(*) AS n FROM t GROUP BY 1"""
#: Every pattern replaced by its random rival first.
_NULL = _COMPARED.replace("FROM inc", "FROM inc2").replace(
    " rnd AS (",
    f""" inc2 AS (SELECT i.series_id, i.win, i.cluster, i.n_obs, x.word FROM inc i JOIN (SELECT series_id, win, CAST({ALL} - sum(1::BIGINT << pos) AS BIGINT) AS word FROM (SELECT i.series_id, i.win, b.pos, i.n_obs, row_number() OVER (PARTITION BY i.series_id, i.win ORDER BY {draw_sql(H['random'] + 1000, 'i.series_id', 'i.win', 'b.pos')}, b.pos) AS k FROM inc i CROSS JOIN {_BITS} b) WHERE k <= {W} - n_obs GROUP BY 1, 2) x ON x.series_id = i.series_id AND x.win = i.win),
 rnd AS (""",
    1,
)


def _levels_sql():
    """(kind, level, SQL of hidden) of every generator at every level."""
    for p in (0.1, 0.3, 0.5, 0.7, 0.9):
        yield "mcar", p, f"{unit_sql(H['gap'], 'series_id', 'win', 'pos')} < {p}"
        yield "mcar_exact", p, f"row_number() OVER (PARTITION BY series_id, win ORDER BY {draw_sql(H['gap'], 'series_id', 'win', 'pos')}, pos) <= {round(p * W)}"
        yield "mnar_value", p, f"{unit_sql(H['value'], 'series_id', 'win', 'pos')} < greatest(0.0, least(1.0, {p} * (1 + 0.8 * (1 - 2.0 * (row_number() OVER (PARTITION BY series_id, win ORDER BY -value, pos) - 1) / {W - 1}))))"
        start = lambda n, room, *ids: f"({draw_sql(H['burst'], 'series_id', 'win', *ids)} % {room - n + 1})"
        if p <= 0.5:
            n = max(1, min(W // 2, round(p * W)))
            yield "mnar_burst", p, f"pos >= {start(n, W)} AND pos < {start(n, W)} + {n}"
        else:
            half = W // 2
            n1 = min(half, round(p * W / 2))
            n2 = min(W - half, round(p * W) - n1)
            yield "mnar_burst", p, f"(pos >= {start(n1, half, '1')} AND pos < {start(n1, half, '1')} + {n1}) OR (pos >= {half} + {start(n2, W - half, '2')} AND pos < {half} + {start(n2, W - half, '2')} + {n2})"


ORACLES = {
    "pair_one_to_one": f"WITH {INC_SQL}, {_RANK} SELECT ri.series_id, ri.win, ri.cluster, comp_series, comp_win FROM ri JOIN rc ON rc.cluster = ri.cluster AND rc.comp_rank = ri.rank",
    "pair_reuse": f"{PAIR_SQL} SELECT series_id, win, cluster, comp_series, comp_win FROM pairs",
    "project_pairs": f"{PAIR_SQL} SELECT p.series_id, p.win, round(sum(CASE WHEN (p.word >> zc.pos) & 1 = 1 THEN zc.z ELSE 0 END), 4) + 0.0 AS shown_sum, CAST(max(bit_count(p.word)) AS BIGINT) AS shown FROM pairs p JOIN zc ON zc.series_id = p.comp_series AND zc.win = p.comp_win GROUP BY 1, 2",
    "random_rivals": f"{_COMPARED} SELECT series_id, win, word FROM rnd",
    "sampled_rivals": f"{_COMPARED} SELECT series_id, win, cluster, rival FROM riv",
    "pattern_kl": f"{_COMPARED} SELECT series_id, win, cluster, round(kl_s, 6) AS kl_s, round(kl_r, 6) AS kl_r FROM cmp",
    "structure_ratio": f"{_COMPARED} SELECT cluster, CAST(sum(CASE WHEN kl_s < kl_r - 1e-9 THEN 1 ELSE 0 END) AS BIGINT) AS n_p, count(*) AS n, round(sum(CASE WHEN kl_s < kl_r - 1e-9 THEN 1 ELSE 0 END) / count(*), 6) AS ratio, sum(CASE WHEN kl_s < kl_r - 1e-9 THEN 1 ELSE 0 END) / count(*) > 2 / 3.0 AS kept FROM cmp GROUP BY 1",
    "selected_patterns": f"{_COMPARED} SELECT series_id, win, CASE WHEN kl_s < kl_r - 1e-9 THEN rival ELSE random END AS word FROM cmp",
    "artificial_mask": f"WITH {CLUSTER_SQL}, {_MASK.format(src='a2')} SELECT series_id, win, word FROM msk",
    "masked_sets_counts": f"""{PAIR_SQL}, {_MASK.format(src='pairs')},
        roles AS (SELECT p.cluster, r.role, p.comp_series, p.comp_win, CASE r.role WHEN 'proj' THEN p.word WHEN 'mask' THEN m.word ELSE p.word & m.word END AS shown FROM pairs p JOIN msk m ON m.series_id = p.series_id AND m.win = p.win CROSS JOIN (VALUES ('proj'), ('mask'), ('proj_mask')) r(role))
        SELECT r.cluster, r.role, count(*) // {W} AS n, CAST(sum((shown >> zc.pos) & 1) AS BIGINT) AS shown, round(sum(CASE WHEN (shown >> zc.pos) & 1 = 1 THEN zc.z ELSE 0 END), 3) AS total FROM roles r JOIN zc ON zc.series_id = r.comp_series AND zc.win = r.comp_win GROUP BY 1, 2""",
    "mask_schedule": "SELECT least, n, i AS step, round(least * pow(2.0, i), 6) AS mask FROM (SELECT l_discount AS least, count(*) AS n FROM lineitem WHERE l_discount > 0 GROUP BY 1), (SELECT unnest(range(6)) AS i) WHERE least * pow(2.0, i) < 1",
    "mask_search_rule": _rule_sql("min(CASE WHEN gap < lim THEN step END)"),
    "mask_last_within": _rule_sql("max(CASE WHEN gap < lim AND lost = 0 THEN step END)"),
    "mask_argmin": _rule_sql("CAST(NULL AS INTEGER)"),
    **{f"mcar_{round(p * 100)}": _gap_sql(f"{unit_sql(H['gap'], 'series_id', 'win', 'pos')} < {p}") for p in (0.1, 0.5, 0.9)},
    "mcar_exact_50": _gap_sql(f"row_number() OVER (PARTITION BY series_id, win ORDER BY {draw_sql(H['gap'], 'series_id', 'win', 'pos')}, pos) <= {W // 2}"),
    "mnar_value_50": _gap_sql(f"{unit_sql(H['value'], 'series_id', 'win', 'pos')} < greatest(0.0, least(1.0, 0.5 * (1 + 0.8 * (1 - 2.0 * (row_number() OVER (PARTITION BY series_id, win ORDER BY -value, pos) - 1) / {W - 1}))))"),
    "mnar_burst_50": _gap_sql(f"pos >= {draw_sql(H['burst'], 'series_id', 'win')} % {W // 2 + 1} AND pos < {draw_sql(H['burst'], 'series_id', 'win')} % {W // 2 + 1} + {W // 2}"),
    "mnar_group_50": _gap_sql(f"{unit_sql(H['group'], 'nation', 'win', 'pos')} < 0.5", "(SELECT f.*, s.s_nationkey AS nation FROM whole f JOIN supplier s ON CAST(s.s_suppkey AS VARCHAR) = f.series_id)"),
    "missing_profile": f"WITH {Z_SQL} SELECT r_name AS region, n_name AS nation, count(*) AS windows, CAST(sum({W} - n_obs) AS BIGINT) AS missing, round(sum({W} - n_obs) / (count(*) * {W}), 6) AS share, CAST(sum(CASE WHEN n_obs = {W} THEN 1 ELSE 0 END) AS BIGINT) AS complete, CAST(sum(CASE WHEN n_obs = 0 THEN 1 ELSE 0 END) AS BIGINT) AS empty FROM wins JOIN supplier ON CAST(s_suppkey AS VARCHAR) = series_id JOIN nation ON n_nationkey = s_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY ROLLUP (r_name, n_name)",
    "missing_by_region": f"WITH {Z_SQL} SELECT r_name AS region, count(*) AS windows, CAST(sum({W} - n_obs) AS BIGINT) AS missing, round(sum({W} - n_obs) / (count(*) * {W}), 6) AS share FROM wins JOIN supplier ON CAST(s_suppkey AS VARCHAR) = series_id JOIN nation ON n_nationkey = s_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY 1",
    "gap_runs": f"{_CELLS} SELECT series_id, start, length FROM runs",
    "gap_run_lengths": f"{_CELLS} SELECT length, count(*) AS n FROM runs GROUP BY 1",
    "sample_need": "SELECT e AS eps, q AS delta, n, round((3 * ln(1 / e) + ln(1 / q)) / e, 4) AS need, CAST(ceil((3 * ln(1 / e) + ln(1 / q)) / e) AS BIGINT) AS windows FROM (SELECT l_discount AS e, l_tax AS q, count(*) AS n FROM lineitem WHERE l_discount > 0 AND l_tax > 0 GROUP BY 1, 2)",
    "observable_ratio": f"WITH {Z_SQL} SELECT series_id, win, round((1 - ({W} - n_obs) / {float(W)}) * 0.9::DOUBLE, 6) AS product, round(1 - ({W} - n_obs) / {float(W)} - 0.1::DOUBLE, 6) AS difference FROM wins",
    "windows_needed": f"WITH {Z_SQL} SELECT n_obs, CAST(max(CASE WHEN n_obs > 0 THEN ceil({_NEED!r}::DOUBLE / ((1 - ({W} - n_obs) / {float(W)}) * 0.9::DOUBLE)) END) AS BIGINT) AS needed, round(max(CASE WHEN 1 - ({W} - n_obs) / {float(W)} - {_NEED!r}::DOUBLE / 600 >= 0 THEN 1 - ({W} - n_obs) / {float(W)} - {_NEED!r}::DOUBLE / 600 END), 6) AS max_mask FROM wins GROUP BY 1",
    "cluster_guarantees": f"""WITH {INC_SQL}, m(cluster, beta) AS (VALUES {', '.join(f'({c}, {m}::DOUBLE)' for c, m in MASKS)}),
        g AS (SELECT i.cluster, count(*) AS n, avg(({W} - n_obs) / {float(W)}) AS alpha, max(m.beta) AS beta FROM inc i JOIN m ON m.cluster = i.cluster GROUP BY 1),
        h AS (SELECT *, greatest(0.0, 1 - alpha - beta) AS gamma FROM g)
        SELECT cluster, n, n * gamma - {_NEED!r}::DOUBLE >= 0 AS met, gamma >= 0.2 AS feasible, round(alpha, 6) AS alpha, beta, round(gamma, 6) AS gamma, round({_NEED!r}::DOUBLE, 6) AS need, round(n * gamma - {_NEED!r}::DOUBLE, 6) AS slack FROM h""",
    "reconstruction_test": _RECONSTRUCTED.replace("TOLERANCE", "0.1"),
    "reconstruction_wide": _RECONSTRUCTED.replace("TOLERANCE", "1.0"),
    "learnability_labels": f"""WITH {Z_SQL}, pr AS (SELECT pos, avg(z) AS p FROM zc GROUP BY 1), sg AS (SELECT stddev_pop(z) AS sd FROM zc),
        g AS (SELECT * FROM (VALUES {', '.join(f'({x}::DOUBLE)' for x in ALPHAS)}) a(alpha), (VALUES {', '.join(f'({x}::DOUBLE)' for x in BETAS)}) b(beta)),
        e AS (SELECT g.alpha, g.beta, zc.series_id, zc.win, max(CASE WHEN ({unit_sql(H['gap'], 'zc.series_id', 'zc.win', 'zc.pos')} < g.alpha OR {unit_sql(H['mask'], 'zc.series_id', 'zc.win', 'zc.pos')} < g.beta) THEN abs(pr.p - zc.z) END) AS worst FROM zc JOIN pr ON pr.pos = zc.pos CROSS JOIN g GROUP BY 1, 2, 3, 4),
        t AS (SELECT o.tolerance, alpha, beta, round(avg(CASE WHEN worst > o.tolerance * sg.sd THEN 0.0 ELSE 1.0 END), 6) AS success, count(*) AS n FROM e, sg, (VALUES {', '.join(f'({x}::DOUBLE)' for x in TOLERANCES)}) o(tolerance) GROUP BY 1, 2, 3)
        SELECT tolerance, alpha, beta, success, n, CASE WHEN success >= {1 - DELTA} THEN 1 ELSE 0 END AS label FROM t""",
    "operation_counts": f"""WITH {Z_SQL}, n AS (SELECT CAST(sum(CASE WHEN n_obs = {W} THEN 1 ELSE 0 END) AS BIGINT) AS c, CAST(sum(CASE WHEN n_obs = {W} THEN 0 ELSE 1 END) AS BIGINT) AS i FROM wins)
        SELECT 'kmeans_distances' AS operation, 15 * 3 * c AS n FROM n UNION ALL SELECT 'dbi_cells', c * {W} + 9 * {W} FROM n UNION ALL SELECT 'dtw_cells', i * 3 * {W * W} FROM n UNION ALL SELECT 'mask_fits', 108 FROM n""",
    "pair_replacement": f"WITH {INC_SQL}, {_RANK} SELECT ri.series_id, ri.win, ri.cluster, comp_series, comp_win FROM ri JOIN rc ON rc.cluster = ri.cluster AND rc.comp_rank = CAST(floor({unit_sql(H['comp'] + 500, 'ri.series_id', 'ri.win')} * rc.n_comp) AS BIGINT) + 1",
    "sample_incomplete": f"WITH {Z_SQL}, g AS (SELECT DISTINCT series_id, win FROM zs WHERE NOT complete AND NOT held AND n_obs > 0) SELECT series_id, win FROM g WHERE {math.ceil(1.5 * 300.0 / 0.7)} >= (SELECT count(*) FROM g) OR {draw_sql(H['sample'], 'series_id', 'win')} < {math.ceil(1.5 * 300.0 / 0.7)}::DOUBLE / (SELECT count(*) FROM g) * 4294967296.0",
    "role_counts": f"{PAIR_SQL} SELECT role, count(*) AS n FROM pairs CROSS JOIN (VALUES ('proj'), ('mask'), ('proj_mask')) r(role) GROUP BY 1",
    "pattern_features": f"""WITH {INC_SQL}, b AS (SELECT i.series_id, i.win, p.pos, CAST((i.word >> p.pos) & 1 AS INTEGER) AS seen FROM inc i CROSS JOIN {_BITS} p),
        t AS (SELECT *, lag(seen) OVER (PARTITION BY series_id, win ORDER BY pos) AS prev, pos - row_number() OVER (PARTITION BY series_id, win, seen ORDER BY pos) AS island FROM b),
        r AS (SELECT series_id, win, island, count(*) AS length FROM t WHERE seen = 0 GROUP BY 1, 2, 3),
        l AS (SELECT series_id, win, count(*) AS gaps, max(length) AS longest FROM r GROUP BY 1, 2),
        k AS (SELECT series_id, win, sum(CASE WHEN prev = 0 AND seen = 0 THEN 1 ELSE 0 END) AS a, sum(CASE WHEN prev = 0 AND seen = 1 THEN 1 ELSE 0 END) AS b, sum(CASE WHEN prev = 1 AND seen = 0 THEN 1 ELSE 0 END) AS c, sum(CASE WHEN prev = 1 AND seen = 1 THEN 1 ELSE 0 END) AS d FROM t GROUP BY 1, 2)
        SELECT k.series_id, k.win, CAST(l.gaps AS INTEGER) AS gaps, CAST(l.longest AS INTEGER) AS longest, concat_ws(',', CAST(a AS BIGINT), CAST(b AS BIGINT), CAST(c AS BIGINT), CAST(d AS BIGINT)) AS transitions FROM k JOIN l ON l.series_id = k.series_id AND l.win = k.win""",
    "structure_null": _NULL + f" SELECT cluster, count(*) AS n, round(sum(CASE WHEN kl_s < kl_r - 1e-9 THEN 1 ELSE 0 END) / count(*), 6) AS ratio, sum(CASE WHEN kl_s < kl_r - 1e-9 THEN 1 ELSE 0 END) / count(*) > 2 / 3.0 AS kept FROM cmp GROUP BY 1",
    "missing_levels": f"{_COMPLETE} " + " UNION ALL ".join(f"SELECT '{k}' AS kind, {p}::DOUBLE AS p, round(avg(n / {float(W)}), 4) AS share, count(*) AS windows FROM (SELECT series_id, win, sum(CASE WHEN hidden THEN 1 ELSE 0 END) AS n FROM (SELECT series_id, win, {h} AS hidden FROM whole) GROUP BY 1, 2)" for k, p, h in _levels_sql()),
    "assign_unbounded": f"WITH {INC_SQL} SELECT series_id, win, cluster, round(dist, 4) AS dist FROM inc",
    "waterfill_sizes": f"""WITH {INC_SQL}, n AS (SELECT cluster, count(*) AS n FROM inc GROUP BY 1), lv AS (SELECT max(l) AS l FROM (SELECT unnest(range(0, 20000)) AS l) WHERE (SELECT sum(greatest(0, l - n.n)) FROM n) <= 1000),
        b AS (SELECT n.cluster, greatest(n.n, lv.l) AS base, lv.l FROM n, lv), r AS (SELECT *, 1000 - (SELECT sum(b.base) FROM b) + (SELECT sum(n.n) FROM n) AS rest, row_number() OVER (PARTITION BY base = l ORDER BY cluster) AS k FROM b)
        SELECT cluster, CAST(base + CASE WHEN base = l AND k <= rest THEN 1 ELSE 0 END AS BIGINT) AS size FROM r""",
    "worked_example": f"WITH {windows_sql(replace(WORKLOADS['supplier_week'], w=EXAMPLE))} SELECT series_id, win, n_obs AS observed, {EXAMPLE} - n_obs AS gaps, word FROM wins",
}
