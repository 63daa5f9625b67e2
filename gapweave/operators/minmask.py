"""The smallest extra mask that makes projected training as good as training on plain masks."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import SEEDS, draw, draw_py
from ..learners.core import LEARNERS
from ..learners.keyed import merged_sums, uniforms
from ..sources.scratch import materialise

TRACE = "cluster int, learner string, step int, mask double, run int, oracle double, projected double, n int"
#: Windows of one cluster that a fit may hold; groups of applyInPandas do not spill. Larger clusters are fitted by sums.
MAX_GROUP = 100_000
#: Windows, by hash, from which is taken what a learner tunes before sums are added up (a kernel's width, a lag).
TUNING = 2000


def mask_schedule(least: float = 0.01, growth: float = 1.0, steps: int = 6) -> list[float]:
    """Growing shares least * (1 + growth)^i, kept under 1."""
    return [m for m in (least * (1 + growth) ** i for i in range(steps)) if m < 1]


def hide(shape: tuple[int, int], share: float, rng: np.random.Generator, eligible: np.ndarray | None = None) -> np.ndarray:
    """Slots hidden at random, at least one eligible slot a window."""
    u = rng.random(shape)
    u = np.where(eligible, u, 2.0) if eligible is not None else u
    out = u < share
    rows = np.flatnonzero(~out.any(axis=1))
    out[rows, u[rows].argmin(axis=1)] = True
    return out if eligible is None else out & eligible


def _unpack(words: list, w: int) -> np.ndarray:
    """(n, w) booleans, True where present."""
    return np.array([[(int(ws[j // 64]) >> (j % 64)) & 1 for j in range(w)] for ws in words], dtype=bool)


def one_fit(z: np.ndarray, patterns: np.ndarray, learner: str, share: float, seed: int, score: str = "own") -> tuple[float, float, int]:
    """Losses on held-out windows: trained on plain masks (oracle) and on projected plus plain masks.

    ``patterns`` are the projected masks of the windows (True present). A third of the windows validates. ``score`` is
    'own' (each model on the slots it hides) or 'masked' (both on the plainly masked ones).
    """
    rng = np.random.default_rng(seed)
    n = len(z)
    order = rng.permutation(n)
    test, train = order[: max(1, n // 3)], order[max(1, n // 3) :]
    if not len(train):
        return float("nan"), float("nan"), n
    plain = hide(z.shape, share, rng)
    both = ~patterns | hide(z.shape, share, rng, patterns)
    m = LEARNERS[learner]
    oracle = m.fit(np.where(plain, np.nan, z)[train], z[train], seed)
    real = m.fit(np.where(both, np.nan, z)[train], z[train], seed)
    a = m.predict(oracle, np.where(plain, np.nan, z)[test]) - z[test]
    b = m.predict(real, np.where(both, np.nan, z)[test]) - z[test]
    slots = plain[test]
    scored = both[test] if score == "own" else slots & both[test]
    return float((a[slots] ** 2).mean()), float((b[scored] ** 2).mean()) if scored.any() else float("nan"), n


def sweep_masks(pairs: DataFrame, w: int, learner: str | tuple[str, ...] = "gaussian", schedule: list[float] | None = None, runs: int = 5, score: str = "own", max_group: int | None = None, group: int = MAX_GROUP) -> DataFrame:
    """Losses of every (cluster, learner, step, run): ``pairs`` has cluster, z (complete) and words (projected), and is read
    more than once.

    All pairs of a cluster are used. Up to ``group`` of them are one group for each run, which goes through all steps; the
    pairs of larger clusters stay where they are and only sums of them move. With ``max_group`` more pairs are an error.
    """
    schedule, learners = schedule or mask_schedule(), (learner,) if isinstance(learner, str) else tuple(learner)
    rows = pairs.select("cluster", "series_id", "win", "z", "words")
    if max_group is not None:
        place = F.row_number().over(Window.partitionBy("cluster").orderBy("series_id", "win"))
        above = F.raise_error(F.lit(f"a cluster has more than {max_group} pairs: assign under a bound first")).cast("boolean")
        rows = rows.withColumn("_place", place).where(F.when(F.col("_place") <= max_group, F.lit(True)).otherwise(above)).drop("_place")
        large: dict[int, int] = {}
    else:
        large = {r.cluster: r.n for r in pairs.groupBy("cluster").agg(F.count("*").alias("n")).where(F.col("n") > group).collect()}  # one row a cluster

    def cell(pdf: pd.DataFrame) -> pd.DataFrame:
        c, r = int(pdf["cluster"].iloc[0]), int(pdf["run"].iloc[0])
        pdf = pdf.sort_values(["series_id", "win"])
        z, shown = np.array(pdf["z"].tolist(), dtype=float), _unpack(pdf["words"].tolist(), w)
        out = [(c, m, i, float(share), r, *one_fit(z, shown, m, float(share), draw_py(SEEDS["mask"], c, i, r), score)) for m in learners for i, share in enumerate(schedule)]
        return pd.DataFrame(out, columns=["cluster", "learner", "step", "mask", "run", "oracle", "projected", "n"])

    inside = rows.where(~F.col("cluster").isin(*large)) if large else rows
    inside = inside.withColumn("run", F.explode(F.array(*[F.lit(r) for r in range(runs)])))
    small = inside.groupBy("cluster", "run").applyInPandas(cell, TRACE)
    return small.unionByName(_sweep_by_sums(rows.where(F.col("cluster").isin(*large)), large, w, learners, schedule, runs, score)) if large else small


def _masks_of(seed: int, ids: np.ndarray, patterns: np.ndarray, share: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(validates, hidden plainly, hidden by the projected pattern and plainly) of windows, as in ``one_fit`` but by each
    window's own draws."""
    w = patterns.shape[1]
    u = uniforms(seed, ids, 1 + 2 * w)
    plain = u[:, 1 : w + 1] < share
    rows = np.flatnonzero(~plain.any(axis=1))
    plain[rows, u[rows, 1 : w + 1].argmin(axis=1)] = True
    v = np.where(patterns, u[:, w + 1 :], 2.0)
    extra = v < share
    rows = np.flatnonzero(~extra.any(axis=1))
    extra[rows, v[rows].argmin(axis=1)] = True
    return u[:, 0] < 1 / 3, plain, ~patterns | (extra & patterns)


def _sweep_by_sums(pairs: DataFrame, sizes: dict[int, int], w: int, learners: tuple[str, ...], schedule: list[float], runs: int, score: str) -> DataFrame:
    """The losses of clusters of any size, from every pair: one job adds up the fits' sums, another the errors. A window
    validates with a chance of a third, by its own draw."""
    rows = pairs.withColumn("id", F.xxhash64("series_id", "win"))
    cells = [(c, i, r) for c in sorted(sizes) for i in range(len(schedule)) for r in range(runs)]
    seeds = {(c, i, r): draw_py(SEEDS["mask"], c, i, r) for c, i, r in cells}
    jobs = [(*cell, m, real) for cell in cells for m in learners for real in (False, True)]
    at = {job: k for k, job in enumerate(jobs)}

    def parts(pdf: pd.DataFrame):
        """Every cluster's windows of a batch with the masks of every cell."""
        for c, part in pdf.groupby("cluster"):
            z, shown, ids = np.array(part["z"].tolist(), dtype=float), _unpack(part["words"].tolist(), w), part["id"].to_numpy()
            for i, share in enumerate(schedule):
                for r in range(runs):
                    yield (int(c), i, r), z, ids, *_masks_of(seeds[int(c), i, r], ids, shown, float(share))

    below = F.element_at(F.create_map(*[F.lit(x) for c, n in sorted(sizes.items()) for x in (c, TUNING / n * float(1 << 32))]), F.col("cluster"))
    some = pd.DataFrame([r.asDict() for r in sorted(rows.where(draw(917, "series_id", "win") < below).collect())])  # about TUNING rows a cluster
    prepared = {}
    for cell, z, _, test, plain, both in parts(some):
        for m in learners:
            for real, hidden in ((False, plain), (True, both)):
                prepared[at[*cell, m, real]] = LEARNERS[m].prepare(np.where(hidden, np.nan, z)[~test], z[~test], seeds[cell])

    def sums_of(pdf: pd.DataFrame):
        for cell, z, ids, test, plain, both in parts(pdf):
            train = ~test
            own = [int(v) for v in ids[train] & 0x7FFFFFFF] if "linear_diffusion" in learners else []
            for real, hidden in ((False, plain), (True, both)) if train.any() else ():
                x = np.where(hidden, np.nan, z)[train]
                for m in learners:
                    k = at[*cell, m, real]
                    yield k, int(train.sum()), LEARNERS[m].sums(prepared[k], x, z[train], own)

    models = {k: LEARNERS[jobs[k][3]].from_sums(prepared[k], sums) for k, (sums, _, _) in merged_sums(rows, sums_of).items()}
    sent = pairs.sparkSession.sparkContext.broadcast(models)  # two models a cluster, step, run and learner

    def errors_of(pdf: pd.DataFrame):
        for cell, z, _, test, plain, both in parts(pdf):
            if not test.any():
                continue
            for m in learners:
                out = []
                for real, hidden in ((False, plain), (True, both)):
                    e = LEARNERS[m].predict(sent.value[at[*cell, m, real]], np.where(hidden, np.nan, z)[test]) - z[test]
                    scored = hidden[test] & plain[test] if score == "masked" else hidden[test]
                    out += [float((e[scored] ** 2).sum()), float(scored.sum())]
                yield at[*cell, m, False], int(test.sum()), {"e": np.array(out)}

    losses = []
    for k, (sums, _, _) in sorted(merged_sums(rows, errors_of).items()):
        (c, i, r, m, _), (a, n_a, b, n_b) = jobs[k], sums["e"].tolist()
        losses.append((c, m, i, float(schedule[i]), r, a / n_a if n_a else float("nan"), b / n_b if n_b else float("nan"), sizes[c]))
    return pairs.sparkSession.createDataFrame(losses, TRACE)


def trace_stats(losses: DataFrame) -> DataFrame:
    """(cluster, learner, step, mask, oracle, projected, gap, limit): means over runs, their distance, and twice the oracle's spread."""
    g = losses.groupBy("cluster", "learner", "step").agg(F.max("mask").alias("mask"), F.avg("oracle").alias("oracle"), F.avg("projected").alias("projected"), F.stddev_samp("oracle").alias("sd"))
    return g.select("cluster", "learner", "step", "mask", "oracle", "projected", F.abs(F.col("oracle") - F.col("projected")).alias("gap"), (2 * F.col("sd")).alias("limit"))


def pick_mask(trace: DataFrame, rule: str = "first_within") -> DataFrame:
    """(cluster, mask, step, within), and learner where the trace has it: the first step whose gap is under its limit, or
    the last before it leaves the limit, or else the step of the least gap, the lowest on ties."""
    by = [c for c in ("cluster", "learner") if c in trace.columns]
    inside = F.coalesce(F.col("gap") < F.col("limit"), F.lit(False))
    if rule == "first_within":
        chosen = F.min(F.when(inside, F.col("step")))
    elif rule == "last_within":
        run = Window.partitionBy(*by).orderBy("step")
        trace = trace.withColumn("_left", F.sum((~inside).cast("int")).over(run))
        chosen = F.max(F.when(inside & (F.col("_left") == 0), F.col("step")))
    elif rule == "argmin":
        chosen = F.lit(None).cast("int")
    else:
        raise ValueError("rule is first_within, last_within or argmin")
    g = trace.groupBy(*by).agg(chosen.alias("hit"), F.min_by("step", F.struct("gap", "step")).alias("least"))
    g = g.select(*by, F.coalesce("hit", "least").alias("step"), F.col("hit").isNotNull().alias("within"))
    return g.join(trace.select(*by, "step", "mask"), [*by, "step"]).select(*by, "step", "mask", "within")


def min_mask_search(pairs: DataFrame, w: int, learner: str | tuple[str, ...] = "gaussian", schedule: list[float] | None = None, runs: int = 5, rule: str = "first_within") -> tuple[DataFrame, DataFrame]:
    """The chosen mask of every cluster and learner, and the trace."""
    trace = materialise(trace_stats(sweep_masks(pairs, w, learner, schedule, runs)), "trace")
    return pick_mask(trace, rule), trace
