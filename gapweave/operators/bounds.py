"""Sample bounds, observable shares, the reconstruction test and learnability."""

from __future__ import annotations

import math
from itertools import product

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def need_value(eps: float = 0.03, delta: float = 0.1, vc: int = 3) -> float:
    """Observable windows that a cluster needs for error eps with confidence 1 - delta."""
    return (vc * math.log(1 / eps) + math.log(1 / delta)) / eps


def sample_need(eps: Column, delta: Column, vc: int = 3, log_base: float | None = None) -> Column:
    ln = (lambda c: F.ln(c) / math.log(log_base)) if log_base else F.ln
    return (vc * ln(1 / eps) + ln(1 / delta)) / eps


def observable_ratio(missing: Column, mask: Column | float, rule: str = "product") -> Column:
    """What a model still sees: (1 - missing)(1 - mask), or 1 - missing - mask."""
    mask = mask if isinstance(mask, Column) else F.lit(float(mask))
    if rule == "product":
        return (1 - missing) * (1 - mask)
    if rule == "difference":
        return 1 - missing - mask
    raise ValueError("rule is product or difference")


def windows_needed(gamma: Column, eps: float = 0.03, delta: float = 0.1) -> Column:
    """The least number of windows whose observable shares add up to the bound."""
    return F.ceil(F.lit(need_value(eps, delta)) / F.when(gamma > 0, gamma))


def max_mask_for(n: Column, missing: Column, eps: float = 0.03, delta: float = 0.1, rule: str = "difference") -> Column:
    """The largest extra mask under which n windows still meet the bound; null if none does."""
    gamma = F.lit(need_value(eps, delta)) / n
    m = 1 - missing - gamma if rule == "difference" else 1 - gamma / (1 - missing)
    return F.when(m >= 0, m)


def cluster_guarantees(pairs: DataFrame, masks: DataFrame, eps: float = 0.03, delta: float = 0.1, gamma_min: float = 0.2) -> DataFrame:
    """Per cluster: n, alpha (projected share), beta (the mask found for the cluster), gamma, need, slack, met, feasible.

    ``pairs`` has cluster and missing (share); ``masks`` cluster and mask, a row a cluster.
    """
    g = pairs.groupBy("cluster").agg(F.count("*").alias("n"), F.avg("missing").alias("alpha"))
    g = g.join(F.broadcast(masks.select("cluster", F.col("mask").alias("beta"))), "cluster").withColumn("need", F.lit(need_value(eps, delta)))
    g = g.withColumn("gamma", F.greatest(F.lit(0.0), observable_ratio(F.col("alpha"), F.col("beta"), "difference")))
    g = g.withColumn("slack", F.col("n") * F.col("gamma") - F.col("need"))
    return g.withColumns({"met": F.col("slack") >= 0, "feasible": F.col("gamma") >= gamma_min})


def success_label(success: Column, delta: float = 0.1) -> Column:
    """1 where the share of windows that are rebuilt reaches 1 - delta."""
    return (success >= 1 - delta).cast("int")


def reconstruction_test(predicted: str, truth: str, hidden: str, tolerance: Column | float, agg: str = "all") -> Column:
    """True where the hidden slots are rebuilt within tolerance: every one, on average, or (a share) slot by slot."""
    tol = tolerance if isinstance(tolerance, Column) else F.lit(float(tolerance))
    errors = F.transform(F.filter(F.arrays_zip(F.col(predicted).alias("p"), F.col(truth).alias("t"), F.col(hidden).alias("h")), lambda e: e["h"]), lambda e: F.abs(e["p"] - e["t"]))
    if agg == "all":
        return F.forall(errors, lambda e: e <= tol)
    if agg == "mean":
        return F.try_divide(F.aggregate(errors, F.lit(0.0), lambda s, e: s + e), F.size(errors)) <= tol
    if agg == "slot":
        return F.try_divide(F.size(F.filter(errors, lambda e: e <= tol)), F.size(errors))
    raise ValueError("agg is all, mean or slot")


def fit_boundary(points: np.ndarray, labels: np.ndarray, rounds: int = 20000) -> tuple[np.ndarray, bool]:
    """A line theta.(alpha, beta, 1) > 0 by the perceptron rule, and whether it separates the labels."""
    x = np.hstack([points, np.ones((len(points), 1))])
    y = np.where(labels > 0, 1.0, -1.0)
    theta = np.zeros(x.shape[1])
    for _ in range(rounds):
        wrong = np.flatnonzero(y * (x @ theta) <= 0)
        if not len(wrong):
            return theta, True
        theta = theta + y[wrong[0]] * x[wrong[0]]
    return theta, False


def shatters(points: np.ndarray) -> bool:
    """Whether lines can give the points every labelling."""
    return all(fit_boundary(points, np.array(labels), 5000)[1] for labels in product((0, 1), repeat=len(points)))
