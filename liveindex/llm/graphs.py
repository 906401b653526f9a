"""Connected components of a table of links, by contraction; no link ever leaves the cluster."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from liveindex.llm.common import drop, saved


def _roots(hook: DataFrame) -> DataFrame:
    """hook(node, to) with `to` followed to its end, where a node points to itself; each pass doubles the way gone."""
    last = None
    while True:
        ahead = hook.select(F.col("node").alias("to"), F.col("to").alias("next"))
        gone = saved(hook.join(ahead, "to").select("node", F.col("next").alias("to"), (F.col("next") != F.col("to")).alias("moved")), "hooks")
        if gone.where("moved").isEmpty():
            drop(gone)
            return hook
        if last is not None:
            drop(last)
        hook, last = gone.select("node", "to"), gone


def components(links: DataFrame) -> DataFrame:
    """(node, component) of all nodes of links(a, b): the component is its smallest node.

    Each round, every node points to its smallest neighbour, or every node to its largest, unless it is beyond that
    itself; whole trees of pointers become one node, links join what is left, and the rounds end when no link is.
    No node with links is both below and above all its neighbours, so that the better of the two ways leaves half of
    the nodes at most: rounds grow with the logarithm of the nodes, and so do the passes along a tree.
    """
    live = saved(links.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).where("a < b").distinct(), "links")
    labels = None
    while not live.isEmpty():
        both = live.select("a", "b").union(live.select(F.col("b").alias("a"), F.col("a").alias("b")))
        near = saved(both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("least"), F.max("b").alias("most")), "neighbours")
        down, up = near.agg(F.count_if(F.col("least") < F.col("node")), F.count_if(F.col("most") > F.col("node"))).first()
        hook = _roots(near.select("node", (F.least("node", "least") if down >= up else F.greatest("node", "most")).alias("to")))
        if labels is None:
            labels = hook.select("node", F.col("to").alias("component"))
        else:
            labels = saved(labels.join(hook.withColumnRenamed("node", "component"), "component", "left").select("node", F.coalesce("to", "component").alias("component")), "labels")
        moved = (live.join(hook.select(F.col("node").alias("a"), F.col("to").alias("ta")), "a").join(hook.select(F.col("node").alias("b"), F.col("to").alias("tb")), "b"))
        live = saved(moved.select(F.least("ta", "tb").alias("a"), F.greatest("ta", "tb").alias("b")).where("a < b").distinct(), "links")
    if labels is None:
        return links.sparkSession.createDataFrame([], "node long, component long")
    smallest = labels.groupBy("component").agg(F.min("node").alias("least"))
    return saved(labels.join(smallest, "component").select("node", F.col("least").alias("component")), "labels")
