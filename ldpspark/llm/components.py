"""Connected components of a link table, by contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ldpspark.llm.staging import gathered, stage


def components(links: DataFrame) -> DataFrame:
    """(node, component): the smallest node that can be reached, for each node of ``links(a, b)``.

    Each round lets every node join its neighbour of least hash rank and redraws the links between
    the chosen nodes, so that a star vanishes in one round and a chain loses a constant share of its
    nodes; no node list or link list leaves the cluster. Self-links are allowed (they only name the
    node); null ends are ignored.
    """
    given = stage(links.select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b")).where("a is not null and b is not null"), "links")
    current, steps = given.where("a != b").distinct(), []
    left_over = most = given.count()
    rank = lambda c: F.struct(F.xxhash64(c).alias("h"), F.col(c).alias("v"))
    while left_over:
        both = current.select("a", "b").unionByName(current.select(F.col("b").alias("a"), F.col("a").alias("b")))
        chosen = both.groupBy("a").agg(F.min(rank("b")).alias("best")).select(F.col("a").alias("node"), F.least(rank("node"), F.col("best"))["v"].alias("next"))
        chosen = stage(gathered(chosen, 2 * left_over), "hop")
        steps.append(chosen)
        left = chosen.select(F.col("node").alias("a"), F.col("next").alias("x"))
        right = chosen.select(F.col("node").alias("b"), F.col("next").alias("y"))
        current = current.join(left, "a").join(right, "b").select(F.col("x").alias("a"), F.col("y").alias("b")).where("a != b").distinct()
        current = stage(gathered(current, left_over), "contracted")
        left_over = current.count()
    nodes = given.select(F.col("a").alias("node")).union(given.select("b")).distinct()
    if not steps:
        return nodes.select("node", F.col("node").alias("component"))
    label = steps[0].select("node", F.col("next").alias("root"))
    for step in steps[1:]:
        hop = step.select(F.col("node").alias("root"), "next")
        label = label.join(hop, "root", "left").select("node", F.coalesce("next", "root").alias("root"))
    label = stage(gathered(label, 2 * most), "labels")
    least = label.groupBy("root").agg(F.min("node").alias("component"))
    named = label.join(least, "root").select("node", F.least("component", "node").alias("component"))
    return nodes.join(named, "node", "left").select("node", F.coalesce("component", "node").alias("component"))
