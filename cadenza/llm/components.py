"""Connected components of a distributed graph, by contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cadenza.llm.common import cut


def components(links: DataFrame) -> DataFrame:
    """(node, root) for each node of links (a, b); root is the same for all nodes of a component.

    Each round points a node to its smallest neighbour, if smaller, and contracts the links by these
    pointers. Nodes should be in random order (hashes), so that a round removes a good part of them.
    Neither links nor components come to the driver; a round's tables are kept in the shared folder.
    Links to itself or repeated links do no harm; no links give no rows.
    """
    edges = cut(links.select("a", "b").where("a <> b").union(links.select("b", "a").where("a <> b")).distinct())
    steps: list[DataFrame] = []
    while not edges.isEmpty():
        parents = cut(edges.groupBy("a").agg(F.min("b").alias("low")).select(F.col("a").alias("node"), F.least("a", "low").alias("parent")))
        steps.append(parents)
        to_a = parents.select(F.col("node").alias("a"), F.col("parent").alias("pa"))
        to_b = parents.select(F.col("node").alias("b"), F.col("parent").alias("pb"))
        edges = cut(edges.join(to_a, "a").join(to_b, "b").where("pa <> pb").select(F.col("pa").alias("a"), F.col("pb").alias("b")).distinct())
    if not steps:
        return links.select(F.col("a").alias("node"), F.col("b").alias("root")).limit(0)
    found = steps[0].withColumnRenamed("parent", "root")
    for parents in steps[1:]:
        found = found.join(parents.select(F.col("node").alias("root"), "parent"), "root", "left").select("node", F.coalesce("parent", "root").alias("root"))
    return found
