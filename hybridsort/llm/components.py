"""Connected components by contraction, in rounds that each cut the lineage with a staged table."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import staged


def components(edges: DataFrame) -> DataFrame:
    """node and component (the smallest node reachable) for each node of edges(a long, b long).

    A round points every node at its smallest neighbour if that is smaller, rewrites the edges to
    these parents and drops those that became loops; paths halve at least, so the rounds are few.
    Hot nodes cost nothing extra: minima are combined before the shuffle. No edges give no rows.
    """
    chain: list[DataFrame] = []
    left = staged(edges.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a < b").distinct(), "edges")
    while left.limit(1).count():
        both = left.union(left.select(F.col("b").alias("a"), F.col("a").alias("b")))
        parent = staged(both.groupBy(F.col("a").alias("node")).agg(F.least("node", F.min("b")).alias("parent")), "parents")
        chain.append(parent)
        at_a = left.join(parent.withColumnsRenamed({"node": "a", "parent": "pa"}), "a")
        at_b = at_a.join(parent.withColumnsRenamed({"node": "b", "parent": "pb"}), "b")
        left = staged(at_b.select(F.least("pa", "pb").alias("a"), F.greatest("pa", "pb").alias("b")).where("a < b").distinct(), "edges")
    if not chain:
        return left.select(F.col("a").alias("node"), F.col("b").alias("component"))
    out = chain[0].withColumnRenamed("parent", "component")
    for parent in chain[1:]:
        step = parent.withColumnsRenamed({"node": "component", "parent": "next"})
        out = out.join(step, "component", "left").select("node", F.coalesce("next", "component").alias("component"))
    return out
