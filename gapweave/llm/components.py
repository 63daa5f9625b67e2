"""Connected components of a link table, by label exchange and pointer jumping on DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialise


def connected_components(links: DataFrame) -> DataFrame:
    """(node, component): the smallest node reachable from each node of ``links`` (x, y).

    Labels move along links and then jump to the label's own label, so the number of rounds grows with the
    logarithm of a component's width. Every round is written to the shared scratch folder: lineage stays short, and a
    hot node meets its label in a join of two plain scans, which adaptive execution splits.
    """
    both = links.select(F.col("x").alias("src"), F.col("y").alias("dst")).where("src <> dst")
    both = materialise(both.unionByName(both.select(F.col("dst").alias("src"), F.col("src").alias("dst"))).distinct(), "links")
    # A node starts with its smallest neighbour or itself.
    labels = materialise(both.groupBy(F.col("src").alias("node")).agg(F.min("dst").alias("component")).withColumn("component", F.least("node", "component")), "labels")
    while True:
        told = both.join(labels, both["src"] == labels["node"]).groupBy(F.col("dst").alias("node")).agg(F.min("component").alias("told"))
        heard = materialise(labels.join(told, "node").select("node", F.least("component", "told").alias("component"), (F.col("told") < F.col("component")).alias("moved")), "heard")
        if not heard.where("moved").limit(1).count():
            return labels
        of = heard.select(F.col("node").alias("_at"), F.col("component").alias("_next"))
        labels = materialise(heard.join(of, heard["component"] == of["_at"]).select("node", F.least("component", "_next").alias("component")), "labels")
