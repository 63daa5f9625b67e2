"""Toxicity as ordered severity grades, by cumulative-link (proportional odds) regression on sparse text features.

Grades are 0 (not toxic), 1 (mild) and 2 (severe). One weight vector is shared by all thresholds:
P(grade > k) = sigmoid(w.x - theta_k), with theta_0 < theta_1. Features are words and word beginnings of four and
five letters, valued 1 + ln(count); only those that tell the labelled classes apart are kept, by a cutoff chosen on a
third of the labelled texts that a trial fit leaves out. The labels table is
binary, so labelled toxic texts are graded by their dose: those whose number of indicative features per word is
above the median of the labelled toxic texts are severe.

The model is fitted on a bounded sample of labelled rows (``per_class`` of each class, by hash order) on the
driver; every document is then scored over its whole text in one map-only pass.

Defined results: a null or empty text, or one without letters, has expected severity 0; without labelled rows of
both classes every document has severity 0; repeated rows are scored each; other columns are kept or ignored as
each function says. Repeated labels of one document count as toxic if any of them does.
"""

from __future__ import annotations

import math
import re
import zlib
from array import array
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

_LETTERS = re.compile(r"[^\W\d_]+")
STARTS = (4, 5)


def features(text: str | None) -> Counter[str]:
    """Counts of words and of word beginnings (marked by a trailing hyphen)."""
    words = Counter(_LETTERS.findall((text or "").lower()))
    found = Counter(words)
    for w, n in words.items():
        for k in STARTS:
            if len(w) > k:
                found[w[:k] + "-"] += n
    return found


@dataclass
class OrdinalModel:
    weights: dict[str, float] = field(default_factory=dict)
    thresholds: tuple[float, ...] = (1.0, 2.0)

    def margin(self, text: str | None) -> float | None:
        """w.x, or None where no known feature occurs."""
        get, seen = self.weights.get, {}
        for w, n in Counter(_LETTERS.findall((text or "").lower())).items():
            if w in self.weights:
                seen[w] = seen.get(w, 0) + n
            for k in STARTS:
                if len(w) > k and (s := w[:k] + "-") in self.weights:
                    seen[s] = seen.get(s, 0) + n
        if not seen:
            return None
        return math.fsum(get(f) * (1.0 + math.log(n)) for f, n in seen.items())

    def above(self, text: str | None) -> list[float]:
        """P(grade > k) for every threshold."""
        if not self.weights or not _LETTERS.search(text or ""):
            return [0.0] * len(self.thresholds)
        m = self.margin(text)
        m = 0.0 if m is None else m
        return [1.0 / (1.0 + math.exp(min(700.0, t - m))) for t in self.thresholds]


def _told_apart(parts: list[tuple[Counter[str], Counter[str]]], n1: int, n0: int, least_df: int, least_z: float, most: int) -> dict[str, tuple[float, bool]]:
    """Features whose share differs between the classes: |z| of the difference, and whether it points to toxic texts alone."""
    found = []
    for f in set().union(*(c.keys() for part in parts for c in part)):
        b, a = (sum(part[t][f] for part in parts) for t in (0, 1))
        if a + b < least_df:
            continue
        p = (a + b) / (n1 + n0)
        z = (a / n1 - b / n0) / math.sqrt(max(p * (1 - p), 1e-12) * (1 / n1 + 1 / n0))
        if abs(z) >= least_z:
            found.append((-abs(z), f, z > 0 and a / n1 > 4 * b / n0))
    return {f: (-z, marks) for z, f, marks in sorted(found)[:most]}


def _solve(r: np.ndarray, j: np.ndarray, v: np.ndarray, grade: np.ndarray, m: int, l2: float, steps: int, rate: float) -> tuple[np.ndarray, tuple[float, float]]:
    """Weights of ``m`` features and both thresholds: full-batch Adam on the penalised likelihood of (row, feature, value) entries."""
    n = len(grade)
    w, cut = np.zeros(m), np.array([1.0, 0.0])  # theta_0 and log(theta_1 - theta_0)
    moment, square = [np.zeros(m), np.zeros(2)], [np.zeros(m), np.zeros(2)]
    for step in range(1, steps + 1):
        eta = np.bincount(r, v * w[j], n)
        theta = np.array([cut[0], cut[0] + math.exp(cut[1])])
        s = 1.0 / (1.0 + np.exp(np.clip(theta[:, None] - eta[None, :], -500, 500)))
        upper = np.vstack([np.ones(n), s])[grade, np.arange(n)]  # P(grade > k - 1)
        lower = np.vstack([s, np.zeros(n)])[grade, np.arange(n)]  # P(grade > k)
        p = np.maximum(upper - lower, 1e-9)
        up, down = upper * (1 - upper) / p, lower * (1 - lower) / p
        gw = np.bincount(j, v * (down - up)[r], m) / n + l2 / n * w
        at = [np.where(grade == k + 1, up, 0.0).sum() - np.where(grade == k, down, 0.0).sum() for k in range(2)]
        gc = np.array([at[0] + at[1], at[1] * math.exp(cut[1])]) / n
        for x, g, k in ((w, gw, 0), (cut, gc, 1)):
            moment[k] = 0.9 * moment[k] + 0.1 * g
            square[k] = 0.999 * square[k] + 0.001 * g * g
            x -= rate * (moment[k] / (1 - 0.9**step)) / (np.sqrt(square[k] / (1 - 0.999**step)) + 1e-8)
    return w, (float(cut[0]), float(cut[0] + math.exp(cut[1])))


def fit_ordinal(texts: list[str | None], toxic: list[int], least_df: int = 4, cutoffs: tuple[float, ...] = (2.0, 2.5, 3.0, 3.5, 4.0), most_features: int = 20000, l2: float = 0.5, steps: int = 400, rate: float = 0.1) -> OrdinalModel:
    """Fit on features whose z reaches a cutoff. Without both classes the model is empty.

    The cutoff is chosen inside: a third of the texts, drawn by their digests, is put aside, and that cutoff is taken whose
    fit on the others, features included, gives the third the greatest likelihood of being toxic or not (the higher one on
    ties). Where either part lacks a class the lowest is taken. The model is then fitted on all texts.
    """
    y = np.array(toxic, dtype=int)
    if not y.sum() or y.all():
        return OrdinalModel()
    aside = np.array([zlib.crc32((t or "").encode()) % 3 == 0 for t in texts], dtype=bool)
    counts = {k: (Counter(), Counter()) for k in (False, True)}
    for text, t, k in zip(texts, toxic, aside.tolist(), strict=True):  # features are found again below: holding those of all texts takes much memory
        counts[k][t].update(features(text).keys())
    classes = lambda rows: (int(y[rows].sum()), int((1 - y[rows]).sum()))
    least = min(cutoffs)
    every = np.ones(len(y), dtype=bool)
    whole = _told_apart([counts[False], counts[True]], *classes(every), least_df, least, most_features)
    chooses = len(cutoffs) > 1 and all(n for rows in (aside, ~aside) for n in classes(rows))
    rest = _told_apart([counts[False]], *classes(~aside), least_df, least, most_features) if chooses else {}
    del counts
    if not whole:
        return OrdinalModel()
    column = {f: j for j, f in enumerate(dict.fromkeys([*whole, *rest]))}
    r, j, n, total = array("q"), array("q"), array("q"), np.zeros(len(y))
    for i, text in enumerate(texts):
        found = features(text)
        total[i] = max(1, sum(found.values()))
        for f, k in found.items():
            if f in column:
                r.append(i)
                j.append(column[f])
                n.append(k)
    r, j, n = (np.array(x, dtype=np.int64) for x in (r, j, n))

    def solve(rows: np.ndarray, chosen: dict[str, tuple[float, bool]], cutoff: float) -> tuple[dict[str, float], tuple[float, float], np.ndarray]:
        """Weights by feature, thresholds, and the margins of all texts, from a fit on some rows and the features above a cutoff."""
        kept = [f for f, (z, _) in chosen.items() if z >= cutoff]
        place = np.full(len(column), -1)
        place[[column[f] for f in kept]] = np.arange(len(kept))
        use = place[j] >= 0
        marks = np.array([chosen[f][1] for f in kept], dtype=bool)
        dose = np.bincount(r[use], n[use] * marks[place[j[use]]], len(y)) / total
        severe = dose > np.median(dose[rows & (y == 1)])
        grade = np.where(y == 1, np.where(severe, 2, 1), 0)[rows]
        here = use & rows[r]
        w, theta = _solve((np.cumsum(rows) - 1)[r[here]], place[j[here]], 1.0 + np.log(n[here]), grade, len(kept), l2, steps, rate)
        return dict(zip(kept, map(float, w), strict=True)), theta, np.bincount(r[use], (1.0 + np.log(n[use])) * w[place[j[use]]], len(y))

    best = least
    if chooses:
        gained = []
        for cutoff in cutoffs:
            if not any(z >= cutoff for z, _ in rest.values()) or not any(z >= cutoff for z, _ in whole.values()):
                continue
            _, theta, margin = solve(~aside, rest, cutoff)
            sign = np.where(y[aside] == 1, 1.0, -1.0)
            gained.append((float(-np.logaddexp(0.0, -sign * (margin[aside] - theta[0])).sum()), cutoff))
        best = max(gained, default=(0.0, least))[1]
    weights, theta, _ = solve(every, whole, best)
    return OrdinalModel(weights, theta)


def fit(docs: DataFrame, labels: DataFrame, per_class: int = 3000) -> OrdinalModel:
    """Fit on at most ``per_class`` labelled documents of each class, the first in hash order."""
    known = labels.where("toxic IS NOT NULL AND doc_id IS NOT NULL").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max(F.col("toxic").cast("int")).alias("toxic"))
    order = F.xxhash64(F.lit(6), "doc_id")
    chosen = [r for t in (0, 1) for r in known.where(F.col("toxic") == t).orderBy(order, "doc_id").limit(per_class).collect()]
    if not chosen:
        return OrdinalModel()
    ids = docs.sparkSession.createDataFrame([(r.doc_id, r.toxic) for r in chosen], "doc_id long, toxic int")  # at most 2 * per_class rows
    found = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(F.broadcast(ids), "doc_id").groupBy("doc_id").agg(F.min("text").alias("text"), F.max("toxic").alias("toxic")).orderBy("doc_id").collect()
    return fit_ordinal([r.text for r in found], [r.toxic for r in found])


def above_columns(text: Column, model: OrdinalModel) -> Column:
    """A struct (mild, severe) of P(grade > 0) and P(grade > 1)."""

    @F.pandas_udf("struct<mild:double,severe:double>")
    def grade(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            yield pd.DataFrame([model.above(t) for t in batch], columns=["mild", "severe"])

    return grade(text)


def score(docs: DataFrame, model: OrdinalModel) -> DataFrame:
    """One row per document: doc_id, p_toxic, p_severe, expected_severity (0 to 2), grade (the likeliest), toxic."""
    scored = docs.select(F.col("doc_id").cast("long").alias("doc_id"), above_columns(F.col("text").cast("string"), model).alias("p"))
    mild, severe = F.col("p.mild"), F.col("p.severe")
    zero, one = 1 - mild, mild - severe
    return scored.select(
        "doc_id",
        mild.alias("p_toxic"),
        severe.alias("p_severe"),
        (mild + severe).alias("expected_severity"),
        F.when((zero >= one) & (zero >= severe), 0).when(one >= severe, 1).otherwise(2).alias("grade"),
        (mild >= 0.5).alias("toxic"),
    )


def drop_toxic(docs: DataFrame, model: OrdinalModel) -> DataFrame:
    """``docs``, all columns, without the documents whose probability of any toxic grade is 0.5 or more."""
    return docs.where(above_columns(F.col("text").cast("string"), model)["mild"] < 0.5)
