"""The pre-trained model's stand-in: values as tokens, back-off n-gram counts from other tables, filled left to right."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BINS, LOW, HIGH = 64, -4.0, 4.0


def tokens(x: str | Column) -> Column:
    """Bin numbers of an array scaled by its mean magnitude; a gap is null."""
    x = F.col(x) if isinstance(x, str) else x
    seen = F.filter(x, lambda v: v.isNotNull())
    scale = F.try_divide(F.aggregate(seen, F.lit(0.0), lambda s, v: s + F.abs(v)), F.size(seen))
    width = (HIGH - LOW) / BINS
    return F.transform(x, lambda v: F.greatest(F.lit(0), F.least(F.lit(BINS - 1), F.floor((v / F.when(scale > 0, scale) - LOW) / width).cast("int"))))


def token_counts(wins: DataFrame, order: int = 3) -> DataFrame:
    """(context, token, n) for contexts of 0 to ``order`` tokens, written "a,b,c"."""
    t = wins.select(tokens("x").alias("t")).where(~F.exists("t", lambda v: v.isNull()))
    ends = F.sequence(F.lit(1), F.size("t"))
    cells = F.flatten(F.transform(ends, lambda e: F.transform(F.sequence(F.lit(0), F.least(F.lit(order), e - 1)), lambda k: F.struct(F.array_join(F.slice("t", e - k, k), ",").alias("context"), F.element_at("t", e).alias("token")))))
    return t.select(F.explode(cells).alias("c")).groupBy("c.context", "c.token").agg(F.count("*").alias("n"))


class TokenModel:
    """Expected bin centre under the longest context seen; filled slots feed the next context."""

    def __init__(self, counts: dict[str, dict[int, int]], order: int = 3) -> None:
        self.order = order
        width = (HIGH - LOW) / BINS
        self.expected = {c: sum((LOW + (t + 0.5) * width) * n for t, n in ts.items()) / sum(ts.values()) for c, ts in counts.items()}

    @staticmethod
    def from_rows(rows, order: int = 3) -> TokenModel:
        counts: dict[str, dict[int, int]] = {}
        for r in rows:
            counts.setdefault(r["context"], {})[r["token"]] = r["n"]
        return TokenModel(counts, order)

    def fill(self, x: np.ndarray) -> np.ndarray:
        out = x.copy()
        width = (HIGH - LOW) / BINS
        for row in out:
            seen = ~np.isnan(row)
            scale = float(np.abs(row[seen]).mean()) if seen.any() else 1.0
            scale = scale if scale > 0 else 1.0
            past: list[int] = []
            for j in range(len(row)):
                if np.isnan(row[j]):
                    for k in range(min(self.order, len(past)), -1, -1):
                        key = ",".join(map(str, past[len(past) - k :]))
                        if key in self.expected:
                            row[j] = self.expected[key] * scale
                            break
                    else:
                        row[j] = 0.0
                past.append(int(min(BINS - 1, max(0, np.floor((row[j] / scale - LOW) / width)))))
        return out
