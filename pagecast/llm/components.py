"""Connected components of a graph held as a table of links."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pagecast.cluster import Written


def connected_components(links: DataFrame) -> Written:
    """links(a bigint, b bigint) -> written table (id, component): for every
    node of a link the smallest id that can be reached from it.

    Each round hooks every node to its smallest neighbour, follows the hooks to
    their ends, renames the links' ends and drops the links that have become
    loops; what is left is a smaller graph over the hooks' ends. A node only
    ever meets its neighbours in a minimum, so a hub costs a partial aggregate.
    """
    renamed: list[Written] = []
    edges = Written(links.where("a <> b").select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo")).distinct(), "cc-links")
    while edges.df.limit(1).count():
        both = edges.df.unionByName(edges.df.select(F.col("lo").alias("hi"), F.col("hi").alias("lo")))
        hooks = Written(both.groupBy("hi").agg(F.least(F.min("lo"), F.first("hi")).alias("to")).select(F.col("hi").alias("id"), "to"), "cc-hooks")
        while True:
            jumped = hooks.df.alias("x").join(hooks.df.alias("y"), F.col("x.to") == F.col("y.id"), "left").select("x.id", F.coalesce("y.to", "x.to").alias("to"), (F.coalesce("y.to", "x.to") != F.col("x.to")).alias("moved"))
            step = Written(jumped, "cc-hooks")
            moved = step.df.where("moved").limit(1).count()
            hooks.drop()
            hooks = step
            if not moved:
                break
        renamed.append(hooks)
        to = hooks.df.select("id", "to")
        next_edges = (
            edges.df.join(to.select(F.col("id").alias("hi"), F.col("to").alias("a")), "hi")
            .join(to.select(F.col("id").alias("lo"), F.col("to").alias("b")), "lo")
            .where("a <> b")
            .select(F.greatest("a", "b").alias("hi"), F.least("a", "b").alias("lo"))
            .distinct()
        )
        following = Written(next_edges, "cc-links")
        edges.drop()
        edges = following
    edges.drop()
    if not renamed:
        return Written(links.sparkSession.createDataFrame([], "id bigint, component bigint"), "cc")
    labels = renamed[0].df.select("id", F.col("to").alias("component"))
    for hooks in renamed[1:]:
        labels = labels.join(hooks.df.select(F.col("id").alias("component"), "to"), "component", "left").select("id", F.coalesce("to", "component").alias("component"))
    out = Written(labels, "cc")
    for hooks in renamed:
        hooks.drop()
    return out
