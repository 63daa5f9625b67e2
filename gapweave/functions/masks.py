"""Observation masks as 64-bit words (bit 1: present), and what is computed on them without unpacking."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F


def n_words(w: int) -> int:
    return -(-w // 64)


def mask_words(x: str | Column, w: int) -> Column:
    """Words of an array with gaps: bit ``pos`` is set where the element is not null."""
    x = F.col(x) if isinstance(x, str) else x
    one = F.lit(1).cast("long")
    words = []
    for k in range(n_words(w)):
        part = F.slice(x, k * 64 + 1, min(64, w - k * 64))
        bits = F.transform(part, lambda v, i: F.when(v.isNotNull(), F.call_function("shiftleft", one, i)).otherwise(F.lit(0).cast("long")))
        words.append(F.aggregate(bits, F.lit(0).cast("long"), lambda a, b: a.bitwiseOR(b)))
    return F.array(*words)


def bit(word: Column, pos: Column | int) -> Column:
    """1 where the slot is present."""
    return F.getbit(word, pos if isinstance(pos, Column) else F.lit(pos)).cast("int")


def count_and(a: str | Column, b: str | Column, w: int) -> Column:
    """Slots present in both masks."""
    a, b = (F.col(c) if isinstance(c, str) else c for c in (a, b))
    return reduce(lambda s, t: s + t, [F.bit_count(a[k].bitwiseAND(b[k])) for k in range(n_words(w))])


def observed(a: str | Column, w: int) -> Column:
    a = F.col(a) if isinstance(a, str) else a
    return reduce(lambda s, t: s + t, [F.bit_count(a[k]) for k in range(n_words(w))])


def missing_ratio(a: str | Column, w: int) -> Column:
    return (F.lit(w) - observed(a, w)) / F.lit(float(w))


def pattern_kl(p: str | Column, q: str | Column, w: int, eps: float = 0.1) -> Column:
    """Divergence of two gap patterns, read as smoothed distributions of missingness over the slots.

    Only the counts of missing slots matter: a in p, b in q, c in both.
    """
    a, b = F.lit(w) - observed(p, w), F.lit(w) - observed(q, w)
    c = F.lit(w) - observed(p, w) - observed(q, w) + count_and(p, q, w)
    p1, p0 = (1 + eps) / (a + w * eps), eps / (a + w * eps)
    q1, q0 = (1 + eps) / (b + w * eps), eps / (b + w * eps)
    return c * p1 * F.ln(p1 / q1) + (a - c) * p1 * F.ln(p1 / q0) + (b - c) * p0 * F.ln(p0 / q1) + (w - a - b + c) * p0 * F.ln(p0 / q0)


def pattern_kl_sql(p: str, q: str, w: int, eps: float = 0.1) -> str:
    """The same for one-word masks in DuckDB."""
    a, b, c = f"({w} - bit_count({p}))", f"({w} - bit_count({q}))", f"({w} - bit_count({p}) - bit_count({q}) + bit_count({p} & {q}))"
    p1, p0 = f"({1 + eps} / ({a} + {w * eps}))", f"({eps} / ({a} + {w * eps}))"
    q1, q0 = f"({1 + eps} / ({b} + {w * eps}))", f"({eps} / ({b} + {w * eps}))"
    return f"({c} * {p1} * ln({p1} / {q1}) + ({a} - {c}) * {p1} * ln({p1} / {q0}) + ({b} - {c}) * {p0} * ln({p0} / {q1}) + ({w} - {a} - {b} + {c}) * {p0} * ln({p0} / {q0}))"


def run_length_features(words: Column, w: int) -> Column:
    """(number of gaps, longest gap) of a mask, an alternative feature of a pattern."""
    start = F.struct(F.lit(0).alias("run"), F.lit(0).alias("gaps"), F.lit(0).alias("longest"))

    def step(acc, pos):
        gone = F.getbit(F.element_at(words, (pos / 64).cast("int") + 1), (pos % 64).cast("int")) == 0
        run = F.when(gone, acc["run"] + 1).otherwise(0)
        return F.struct(run.alias("run"), (acc["gaps"] + F.when(gone & (acc["run"] == 0), 1).otherwise(0)).alias("gaps"), F.greatest(acc["longest"], run).alias("longest"))

    return F.aggregate(F.sequence(F.lit(0), F.lit(w - 1)), start, step, lambda a: F.struct(a["gaps"].alias("gaps"), a["longest"].alias("longest")))


def transition_features(words: Column, w: int) -> Column:
    """Counts of the four slot-to-slot transitions (present or missing to present or missing)."""
    pair = lambda i: F.getbit(F.element_at(words, (i / 64).cast("int") + 1), (i % 64).cast("int")).cast("int")
    kinds = F.transform(F.sequence(F.lit(1), F.lit(w - 1)), lambda i: pair(i - 1) * 2 + pair(i))
    count = lambda t: F.size(F.filter(kinds, lambda k: k == t))
    return F.array(*[count(t) for t in range(4)])
