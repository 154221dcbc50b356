"""Connected components of a graph given as edges."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .storage import discard, materialise


def components(edges: DataFrame) -> DataFrame:
    """(node, component) for the nodes of edges (a, b) BIGINT: component is the smallest node that can be reached.

    A round gives each node, and the node its label names, the smallest label of a label beside it, so that labels jump
    along chains and roots are hooked too, in whatever order the ids lie: chains of 20,000 nodes settle in 16 or 17
    rounds. Rounds go on until nothing changes. Labels are written to the shared folder every round. Nulls are left out.
    """
    both = materialise(edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a IS NOT NULL AND b IS NOT NULL AND a <> b").distinct(), "edges")
    labels = materialise(both.groupBy(F.col("a").alias("node")).agg(F.least("node", F.min("b")).alias("component")), "labels")
    while True:
        tops = labels.join(labels.select(F.col("node").alias("component"), F.col("component").alias("top")), "component")
        near = both.join(tops.select(F.col("node").alias("b"), "top"), "b").groupBy(F.col("a").alias("node")).agg(F.min("top").alias("c"))
        own = F.struct("node", F.least("top", "c").alias("c"), F.col("component").alias("was"))
        root = F.struct(F.col("component").alias("node"), "c", F.lit(None).cast("long").alias("was"))
        least = tops.join(near, "node").select(F.explode(F.array(own, root)).alias("x")).select("x.*")
        after = materialise(least.groupBy("node").agg(F.min("c").alias("component"), F.max("was").alias("was")), "labels")
        changed = after.where("component <> was").limit(1).count()
        discard(labels)
        labels = after
        if not changed:
            discard(both)
            return labels.select("node", "component")
