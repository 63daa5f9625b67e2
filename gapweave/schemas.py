"""Declared schemas of the stage tables."""

from __future__ import annotations

SLOTS = "series_id string, slot bigint, value double"
WINDOWS = "series_id string, win bigint, x array<double>, n_obs int, words array<bigint>, complete boolean"
ASSIGNED = "series_id string, win bigint, cluster int, dist double, choice_rank int, gamma double, no_evidence boolean"
TRAINING = "cluster int, role string, x_in array<double>, y array<double>, score_words array<bigint>"
MODELS = "cluster int, kind string, params map<string,array<double>>, version bigint"
READINGS = "series_id string, slot bigint, value double, imputed boolean, source string"
SCORES = "dataset string, learner string, strategy string, gap_kind string, rate double, mse double, mae double, n bigint"


def require(df, schema: str):
    """``df`` with the columns of ``schema`` in order; a missing column or another type is an error."""
    from pyspark.sql.types import StructType

    want = StructType.fromDDL(schema)
    have = {f.name: f.dataType.simpleString() for f in df.schema}
    wrong = [f"{f.name}: {have.get(f.name, 'missing')}, not {f.dataType.simpleString()}" for f in want if have.get(f.name) != f.dataType.simpleString()]
    if wrong:
        raise TypeError("; ".join(wrong))
    return df.select(*want.fieldNames())
