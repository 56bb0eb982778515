"""Connected components of a large graph by minimum labels and pointer jumping."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def components(edges: DataFrame, max_rounds: int = 200) -> DataFrame:
    """Label (node, comp) every node of edges (a, b) with the smallest node it reaches.

    Each round takes the least label among the neighbours' and then the label of that label, so that long
    chains take a logarithmic number of rounds. Rounds end in a checkpoint.
    """
    both = edges.select("a", "b").unionAll(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a <> b").distinct().checkpoint()
    label = both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("node"), F.least("a", "m").alias("comp")).checkpoint()
    for _ in range(max_rounds):
        near = both.join(label.withColumnRenamed("node", "b"), "b").groupBy("a").agg(F.min("comp").alias("m"))
        lower = label.join(near, label.node == near.a).select("node", F.col("comp").alias("was"), F.least("comp", "m").alias("comp"))
        up = lower.select(F.col("node").alias("comp"), F.col("comp").alias("next"))
        new = lower.join(up, "comp", "left").select("node", "was", F.least("comp", F.coalesce("next", "comp")).alias("comp")).checkpoint()
        label = new.select("node", "comp")
        if new.where("comp <> was").isEmpty():
            return label
    raise RuntimeError("components did not settle")
