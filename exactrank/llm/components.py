"""Connected components of an edge table, by minimum labels with pointer jumping.

Each round every node takes the least label around it and then the label of its label, so
the rounds needed grow with the logarithm of the longest path. Labels and edges stay in
tables of the shared folder; only the number of changed labels comes to the driver.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from exactrank.llm.common import discard, materialise


def contracted(edges: DataFrame) -> DataFrame:
    """Distinct edges (a < b) with the same components, a node's greater neighbours hung on its
    least one: stars that overlap in most of their nodes shrink to about an edge a node."""
    up = edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a <> b").distinct()
    hung = up.withColumn("least", F.min("a").over(Window.partitionBy("b")))
    to = F.when(F.col("a") == F.col("least"), F.col("b")).otherwise(F.col("a"))
    return hung.select(F.col("least").alias("a"), to.alias("b")).distinct()


def components(edges: DataFrame, max_rounds: int = 100) -> DataFrame:
    """(node, component) for every node of ``edges(a, b)``; a component is its least node."""
    edges = materialise(contracted(edges), "edges")
    both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
    labels = materialise(both.groupBy(F.col("a").alias("node")).agg(F.least(F.col("node"), F.min("b")).alias("component")), "labels")
    for _ in range(max_rounds):
        near = (
            both.join(labels.withColumnRenamed("node", "b"), "b").groupBy(F.col("a").alias("node"))
            .agg(F.min("component").alias("near"))
        )
        hooked = labels.join(near, "node").select("node", F.col("component").alias("old"), F.least("component", "near").alias("to"))
        of = labels.select(F.col("node").alias("to"), F.col("component").alias("beyond"))
        moved = materialise(hooked.join(of, "to").select("node", "old", F.least("to", "beyond").alias("component")), "labels")
        changed = moved.where("old <> component").limit(1).count()
        discard(labels)
        labels = moved
        if not changed:
            break
    else:
        raise RuntimeError("components did not settle")
    discard(edges)
    return labels.select("node", "component")
