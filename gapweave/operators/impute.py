"""Simple exact imputers as array expressions: map only, no shuffle beyond the windows themselves."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def shown(x: str, hidden: str) -> Column:
    """The array with hidden slots as gaps."""
    return F.zip_with(x, hidden, lambda v, h: F.when(~h, v))


def constant(visible: str, w: int, value: Column) -> Column:
    return F.transform(F.sequence(F.lit(0), F.lit(w - 1)), lambda i: value)


def _before(visible: Column, i: Column) -> Column:
    return F.array_max(F.filter(F.sequence(F.lit(0), i), lambda j: F.element_at(visible, j + 1).isNotNull()))


def _after(visible: Column, i: Column, w: int) -> Column:
    return F.array_min(F.filter(F.sequence(i, F.lit(w - 1)), lambda j: F.element_at(visible, j + 1).isNotNull()))


def locf(visible: str, w: int, default: Column) -> Column:
    """The last value seen in the window, else ``default``."""
    v = F.col(visible)
    return F.transform(F.sequence(F.lit(0), F.lit(w - 1)), lambda i: F.coalesce(F.try_element_at(F.filter(F.slice(v, F.lit(1), i + 1), lambda a: a.isNotNull()), F.lit(-1)), default))


def nocb(visible: str, w: int, default: Column) -> Column:
    """The next value seen in the window, else ``default``."""
    v = F.col(visible)
    return F.transform(F.sequence(F.lit(0), F.lit(w - 1)), lambda i: F.coalesce(F.try_element_at(F.filter(F.slice(v, i + 1, F.lit(w)), lambda a: a.isNotNull()), F.lit(1)), default))


def linear(visible: str, w: int, default: Column) -> Column:
    """Between the neighbours seen, flat at the ends, else ``default``."""
    v = F.col(visible)

    def at(i: Column) -> Column:
        a, b = _before(v, i), _after(v, i, w)
        va, vb = F.try_element_at(v, a + 1), F.try_element_at(v, b + 1)
        inside = va + (vb - va) * F.coalesce(F.try_divide((i - a).cast("double"), (b - a).cast("double")), F.lit(0.0))
        return F.coalesce(inside, va, vb, default)

    return F.transform(F.sequence(F.lit(0), F.lit(w - 1)), at)


def slot_means(df, w: int, x: str = "x") -> list[float]:
    """The mean of each slot: w numbers."""
    row = df.select(*[F.avg(F.col(x)[j]).alias(f"m{j}") for j in range(w)]).first()
    return [row[j] for j in range(w)]


def pair_moments(df, w: int, x: str = "z"):
    """(i, j, n, total): co-observed pairs and their summed products, exact at any size; one partial row a task and cell."""
    cells = F.flatten(F.transform(F.sequence(F.lit(0), F.lit(w - 1)), lambda i: F.transform(F.sequence(i, F.lit(w - 1)), lambda j: F.struct(i.alias("i"), j.alias("j"), (F.element_at(F.col(x), i + 1) * F.element_at(F.col(x), j + 1)).alias("p")))))
    return df.select(F.explode(cells).alias("c")).groupBy("c.i", "c.j").agg(F.count("c.p").alias("n"), F.sum("c.p").alias("total"))
