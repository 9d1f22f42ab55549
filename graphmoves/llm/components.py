"""Connected components of an edge table by shrinking label propagation; state stays in snapshots, never on the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphmoves.llm.common import drop_snapshot, snapshot


def components(edges: DataFrame) -> DataFrame:
    """edges (a, b) -> (id, c): each node that has an edge and the smallest id it can reach.

    Per round every node takes the least label around it, then its label's label, so stars end in
    two rounds and long chains shrink geometrically.
    """
    both = snapshot(edges.select("a", "b").union(edges.select("b", "a")).where("a <> b").distinct())
    labels = snapshot(both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("id"), F.least("a", "m").alias("c")))
    while True:
        near = both.join(labels.withColumnRenamed("id", "b"), "b").groupBy("a").agg(F.min("c").alias("m"))
        low = labels.join(near, labels.id == near.a).select("id", F.least("c", "m").alias("c"), F.col("c").alias("was"))
        up = low.join(labels.select(F.col("id").alias("c"), F.col("c").alias("cc")), "c", "left")
        new = snapshot(up.select("id", F.least("c", F.coalesce("cc", "c")).alias("c"), "was"))
        changed = new.where("c < was").limit(1).count()
        drop_snapshot(labels)
        if not changed:
            return new.select("id", "c")
        labels = new
