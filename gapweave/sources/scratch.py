"""Intermediate tables in the folder that all executors share."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_roots: dict[str, str] = {}


def scratch_root(spark: SparkSession) -> str:
    """A folder of this process below spark.checkpoint.dir, which all executors share.

    Only where that setting is absent (tests in one JVM) is a local temporary folder used.
    The folder is removed when the driver's Python ends.
    """
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = _roots.setdefault("", tempfile.mkdtemp(prefix="gapweave-"))
    if base not in _roots:
        _roots[base] = f"{base.rstrip('/')}/gapweave-{uuid.uuid4().hex}"
        atexit.register(_remove, spark, _roots[base])
    return _roots[base]


def _remove(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        where = jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)
    except Exception:  # the session has already ended: nothing more can be removed through it
        return


def materialise(df: DataFrame, name: str, codec: str = "zstd") -> DataFrame:
    """Write ``df`` as Parquet in the shared scratch folder and read it back.

    This cuts the lineage so that a lost executor costs no recomputation beyond the
    current stage, and gives joins a plain scan on that side, which adaptive execution
    can split where a key is hot.
    """
    spark = df.sparkSession
    path = f"{scratch_root(spark)}/{name}-{uuid.uuid4().hex[:12]}"
    df.write.option("compression", codec).parquet(path)
    return spark.read.schema(df.schema).parquet(path)
