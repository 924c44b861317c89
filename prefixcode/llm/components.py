"""Connected components of a table of links, all in tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from prefixcode.llm.common import cut


def components(links: DataFrame, label: str = "components") -> DataFrame:
    """links: a, b (bigint). Gives node, component: the smallest node that links lead to.

    Each round every node takes the smallest label among its neighbours and itself, then the label
    of its label, so paths halve. Rounds are cut at written tables; minima combine before shuffles.
    No links: an empty table.
    """
    one = links.select(F.col("a").alias("node"), F.col("b").alias("neighbour"))
    both = cut(one.unionAll(one.select(F.col("neighbour").alias("node"), F.col("node").alias("neighbour"))).where("node <> neighbour").distinct(), f"{label}-edges")
    state = cut(both.groupBy("node").agg(F.least(F.min("neighbour"), F.col("node")).alias("component")), f"{label}-0")
    k = 0
    while True:
        k += 1
        near = both.join(state.withColumnRenamed("node", "neighbour"), "neighbour").groupBy("node").agg(F.min("component").alias("low"))
        better = state.join(near, "node").select("node", F.col("component").alias("old"), F.least("component", "low").alias("component"))
        over = state.select(F.col("node").alias("component"), F.col("component").alias("top"))
        jumped = better.join(over, "component").select("node", "old", F.least("component", "top").alias("component"))
        moved = cut(jumped, f"{label}-{k}")
        state = moved.select("node", "component")
        if not moved.where("old <> component").limit(1).count():
            return state
