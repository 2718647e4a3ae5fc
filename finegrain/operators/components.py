"""Connected components of an edge table, without bringing edges to the driver."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from finegrain.sources.staging import drop_staged, staged


def connected_components(edges: DataFrame, a: str = "a", b: str = "b", most_rounds: int = 60) -> DataFrame:
    """``(node, component)`` for every node of ``edges``; the component is its least node.

    Every round hooks each component's label to the least label next to it and then halves the label chains; the state is
    staged each round, so a lost executor costs one round, and the round before is deleted. Labels of a round are aggregated before they
    shuffle, so a node with very many neighbours is no hot key.
    """
    both = edges.select(F.col(a).alias("node"), F.col(b).alias("other")).filter("node != other")
    both = staged(both.unionByName(both.select(F.col("other").alias("node"), F.col("node").alias("other"))).distinct(), "edges")
    # the first round needs no join: every node is its own label
    state = staged(both.groupBy("node").agg(F.least(F.min("other"), F.first("node")).alias("component")), "labels")
    for _ in range(most_rounds):
        labels = state.select(F.col("node").alias("other"), F.col("component").alias("seen"))
        near = both.join(labels, "other").groupBy("node").agg(F.min("seen").alias("seen"))
        # a node's neighbours' labels, offered to the node and to the node's own label
        offered = state.join(near, "node").withColumn("least", F.least("component", "seen"))
        hooks = offered.groupBy(F.col("component").alias("node")).agg(F.min("least").alias("hook"))
        hooked = offered.select("node", F.col("component").alias("was"), "least").join(hooks, "node", "left")
        hooked = hooked.select("node", "was", F.least("least", F.coalesce("hook", "least")).alias("label"))
        hooked = staged(hooked, "labels")
        # halve chains: a label's own label
        jump = hooked.select(F.col("node").alias("label"), F.col("label").alias("next"))
        jumped = hooked.join(jump, "label", "left").select("node", "was", F.least("label", F.coalesce("next", "label")).alias("component"))
        fresh = staged(jumped, "labels")
        changed = fresh.filter("component != was").limit(1).count()
        drop_staged(edges.sparkSession, state)
        drop_staged(edges.sparkSession, hooked)
        state = fresh.select("node", "component")
        if not changed:
            return state
    raise RuntimeError("components did not settle")
