"""Connected components of an edge table by shrinking labels."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from motifprune.llm import common


def components(edges: DataFrame) -> DataFrame:
    """(v, comp) of every vertex of edges (a, b): comp is the smallest vertex of its component.

    Each round takes the least label among neighbours and then the label of that label, so the number of
    rounds grows with the logarithm of the longest chain. Every round is a written table.
    """
    arcs = common.written(edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))), "arcs")
    labels = common.written(arcs.groupBy(F.col("a").alias("v")).agg(F.least(F.col("v"), F.min("b")).alias("comp")), "labels")
    while True:
        near = arcs.join(labels, arcs.b == labels.v).groupBy("a").agg(F.min("comp").alias("near"))
        least = labels.join(near, labels.v == near.a).select("v", "comp", F.least("comp", "near").alias("new"))
        up = labels.select(F.col("v").alias("new"), F.col("comp").alias("up"))
        after = common.written(least.join(up, "new", "left").select("v", "comp", F.least("new", F.coalesce("up", "new")).alias("new")), "labels")
        labels = after.select("v", F.col("new").alias("comp"))
        if after.where("new <> comp").isEmpty():
            return labels
