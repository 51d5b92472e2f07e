"""Connected components by least labels with pointer jumping; nothing is collected but a count of changes."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from dupflow.llm.common import materialize


def components(edges: DataFrame) -> DataFrame:
    """(node, comp) for every node of the edges (a, b); comp is the least node that it reaches.

    Each turn takes the least label among the neighbours and then the label of
    that label, so stars settle in two turns and chains in a logarithmic number.
    """
    edges = materialize(edges.select("a", "b").where(F.col("a") != F.col("b")).distinct(), "edges")
    both = edges.unionAll(edges.select("b", "a"))
    labels = materialize(both.groupBy("a").agg(F.min("b").alias("near")).select(F.col("a").alias("node"), F.least("a", "near").alias("comp")), "labels")
    while True:
        near = both.join(labels, both["b"] == labels["node"]).groupBy("a").agg(F.min("comp").alias("near"))
        least = labels.join(near, labels["node"] == near["a"], "left").select("node", F.col("comp").alias("old"), F.least("comp", F.coalesce("near", "comp")).alias("comp"))
        up = labels.select(F.col("node").alias("up"), F.col("comp").alias("top"))
        jumped = least.join(up, least["comp"] == up["up"], "left").select("node", "old", F.least("comp", F.coalesce("top", "comp")).alias("comp"))
        new = materialize(jumped, "labels")
        labels = new.select("node", "comp")
        if new.where(F.col("comp") != F.col("old")).isEmpty():
            return labels
