"""Trees of medians: the b - 1 pivots of a group from the pivots of its nodes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from finegrain.operators.treemerge import depth


def median_of(values: Column, upper: Column) -> Column:
    """An element of the ascending array: the lower or, where ``upper``, the upper middle."""
    n = F.size(values)
    at = F.when(upper, F.floor(n / 2)).otherwise(F.floor((n - 1) / 2))
    return F.get(values, at.cast("int"))


def votes(local: DataFrame, width: int) -> DataFrame:
    """``(grp, node, pivots)`` as rows ``(grp, j, idx, p)``; idx is the node's place in its group of ``width``, known without its neighbours.
    A node without pivots leaves its place empty."""
    idx = (F.col("node") - F.col("grp") * F.lit(width)).cast("int")
    return local.filter("pivots is not null").select("grp", idx.alias("idx"), F.posexplode("pivots").alias("j", "p"))


def median_level(rows: DataFrame, fan_in: int, level: int, rule: str = "alternating") -> DataFrame:
    """One round of all trees at once. An even number of votes has two middles: ``lower`` takes the first always, ``alternating``
    one and the other in turn by place and level, so that the choice does not add up."""
    parent = F.floor(F.col("idx") / F.lit(fan_in)).cast("int")
    gathered = rows.groupBy("grp", "j", parent.alias("idx")).agg(F.array_sort(F.collect_list("p")).alias("all"))
    upper = F.pmod(F.col("idx") + F.lit(level), F.lit(2)) == 1 if rule == "alternating" else F.lit(False)
    return gathered.select("grp", "j", "idx", median_of(F.col("all"), upper).alias("p"))


def median_tree(local: DataFrame, nodes: int, fan_in: int, rule: str = "alternating", participants: int | None = None, rounds: bool = False) -> DataFrame:
    """``(grp, pivots)`` from ``(grp, node, pivots)`` of groups of up to ``nodes`` nodes.

    ``participants`` lets that many nodes of a group vote at most, spread evenly. ``rounds=True`` returns the rows of every round.
    """
    rows = votes(local, nodes)
    if participants and participants < nodes:
        step = -(-nodes // participants)
        rows = rows.filter(F.pmod("idx", F.lit(step)) == 0).withColumn("idx", F.floor(F.col("idx") / step).cast("int"))
        nodes = -(-nodes // step)
    seen = [rows.withColumn("level", F.lit(0))]
    for level in range(1, max(1, depth(nodes, max(2, fan_in))) + 1):
        rows = median_level(rows, max(2, fan_in), level, rule)
        seen.append(rows.withColumn("level", F.lit(level)))
    if rounds:
        out = seen[0]
        for s in seen[1:]:
            out = out.unionByName(s.select(*out.columns))
        return out
    return rows.groupBy("grp").agg(F.array_sort(F.collect_list("p")).alias("pivots"))


def exact_median(local: DataFrame) -> DataFrame:
    """Baseline: the lower median of all nodes' pivots, each pivot of a group gathered in one place."""
    ordered = votes(local, 0).withColumn("at", F.row_number().over(Window.partitionBy("grp", "j").orderBy("p"))).withColumn("n", F.count("*").over(Window.partitionBy("grp", "j")))
    middle = ordered.filter(F.col("at") == F.floor((F.col("n") + 1) / 2))
    return middle.groupBy("grp").agg(F.array_sort(F.collect_list("p")).alias("pivots"))


def best_fan_in(nodes: int, hop_ns: float, first_ns: float = 8.0, next_ns: float = 6.22, most: int = 64) -> int:
    """The fan-in with the least modelled latency for so many nodes."""
    cost = lambda f: depth(nodes, f) * (hop_ns + first_ns + (min(f, nodes) - 1) * next_ns)
    return min(range(2, max(3, min(most, nodes) + 1)), key=cost)
