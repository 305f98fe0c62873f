"""Connected components of link tables by contraction, without collecting links or labels."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from raydescent.llm.common import cut, drop_cut


def connected_components(links: DataFrame) -> DataFrame:
    """links (a, b long) to node, component (smallest node reachable), for the nodes that have a link to another one.

    Each round every node points to its smallest neighbour, pointers are doubled until they stand on roots, and links
    are drawn between roots; every tree has two nodes at least, so rounds are at most the logarithm of the node count.
    Minima are pre-aggregated; the joins to the pointers have one row on one side, which adaptive execution splits.
    """
    edges = cut(links.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "links")
    steps: list[DataFrame] = []
    while not edges.isEmpty():
        both = edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        up = cut(both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("m")).select("node", F.least("node", "m").alias("up")), "up")
        while True:
            over = up.select(F.col("node").alias("_n"), F.col("up").alias("_u"))
            jumped = cut(up.join(over, F.col("up") == F.col("_n")).select("node", F.col("_u").alias("up"), (F.col("_u") != F.col("up")).alias("moved")), "up")
            drop_cut(up)
            up = jumped.select("node", "up")
            if jumped.where("moved").isEmpty():
                break
        steps.append(up)
        a, b = up.toDF("a", "ra"), up.toDF("b", "rb")
        rest = edges.join(a, "a").join(b, "b").where("ra <> rb").select(F.greatest("ra", "rb").alias("a"), F.least("ra", "rb").alias("b")).distinct()
        rest = cut(rest, "links")
        drop_cut(edges)
        edges = rest
    if not steps:
        return edges.select(F.col("a").alias("node"), F.col("b").alias("component"))
    labels = steps[0].select("node", F.col("up").alias("component"))
    for later in steps[1:]:
        further = later.select(F.col("node").alias("_n"), F.col("up").alias("_u"))
        labels = labels.join(further, F.col("component") == F.col("_n"), "left").select("node", F.coalesce("_u", "component").alias("component"))
    return labels
