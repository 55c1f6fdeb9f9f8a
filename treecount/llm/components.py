"""Connected components of a graph of links, as joins and aggregates over tables in the shared folder."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import commit, discard


def components(links: DataFrame) -> DataFrame:
    """(node, component) for each node of the links (a, b): the smallest node reachable.

    Each round takes the smallest label among a node's neighbours and then the label of that
    label, so rounds grow with the logarithm of a chain's length. Nothing but one number a round
    reaches the driver; a hub's links are aggregated before they are dealt out.
    """
    links = links.select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b")).where("a <> b")
    both = commit(links.union(links.select("b", "a")).distinct(), "links")
    state = commit(both.groupBy("a").agg(F.min("b").alias("low")).select(F.col("a").alias("node"), F.least("a", "low").alias("component")), "components")
    while True:
        low = both.join(state.select(F.col("node").alias("b"), "component"), "b").groupBy("a").agg(F.min("component").alias("low"))
        lower = commit(state.join(low, state.node == low.a, "left").select("node", F.col("component").alias("was"), F.least("component", F.coalesce("low", "component")).alias("component")), "components")
        up = lower.select(F.col("node").alias("component"), F.col("component").alias("up"))
        last, state = state, commit(lower.join(up, "component", "left").select("node", "was", F.coalesce("up", "component").alias("component")), "components")
        discard(last, lower)
        if not state.where("was <> component").limit(1).count():
            discard(both)
            return state.select("node", "component")
