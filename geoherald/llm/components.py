"""Connected components of an edge table, by rounds of joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from geoherald.llm.scratch import discard, stored


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """``node, component`` for every node of an edge; the component is its smallest node.

    Each round gives a node the least label among its neighbours and itself and then follows that label
    one step further, so a chain of length d takes about log d rounds. Labels are written after each
    round; only a count of changes reaches the driver. An empty edge table gives an empty result.
    """
    spark = edges.sparkSession
    both = edges.select(F.col(a).alias("x"), F.col(b).alias("y")).union(edges.select(F.col(b), F.col(a)))
    both, held = stored(both.distinct(), "edges")
    labels, old = stored(both.groupBy(F.col("x").alias("node")).agg(F.least(F.min("y"), F.first("x")).alias("component")), "labels")
    while True:
        near = both.join(labels, both["y"] == labels["node"]).select(F.col("x").alias("node"), "component")
        least = near.union(labels.select("node", "component")).groupBy("node").agg(F.min("component").alias("component"))
        ahead = labels.select(F.col("node").alias("via"), F.col("component").alias("further"))
        jumped = least.join(ahead, least["component"] == ahead["via"], "left").select("node", F.least("component", F.coalesce("further", "component")).alias("component"))
        before = labels.select(F.col("node").alias("was"), F.col("component").alias("had"))
        jumped = jumped.join(before, jumped["node"] == before["was"]).select("node", "component", (F.col("component") < F.col("had")).alias("changed"))
        following, path = stored(jumped, "labels")
        changed = following.filter("changed").count()
        labels = following.select("node", "component")
        discard(spark, old)
        old = path
        if not changed:
            discard(spark, held)
            return labels
