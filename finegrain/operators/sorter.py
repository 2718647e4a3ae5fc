"""Recursive bucket sort.

Keys are spread over ``n`` nodes; at each level every node picks pivots from a bounded sample of its keys, trees of medians turn
them into the group's pivots, and every key goes to a random node of its bucket's share of the group's nodes. When
a group is one node it sorts what it has. No data reaches the driver; it only steps through the levels.

Nodes are a column (``virtual``: exact at any number of nodes, whatever the cluster) or partitions (``physical``). ``fused``
takes all levels' pivots from a sample and moves every row once.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from finegrain.functions.hashing import HASHES
from finegrain.functions.keys import KeySpec
from finegrain.functions.pivots import pick_pivots
from finegrain.operators.mediantree import exact_median, median_tree
from finegrain.operators.placement import bucket_of, initial_shuffle, route
from finegrain.sources.staging import staged

#: Pivot tables up to this number of groups are broadcast; beyond it the join shuffles.
MOST_BROADCAST_GROUPS = 100_000
#: Nodes up to this number can be partitions of one exchange.
MOST_PARTITIONS = 4096


@dataclass(frozen=True)
class SortConfig:
    """``nodes`` must be the product of the levels' bucket numbers: ``buckets`` at every level, or ``radices``."""

    nodes: int
    buckets: int = 16
    fan_in: int = 16
    policy: str | tuple[str, tuple[float, float]] = "mixed"
    rule: str = "alternating"
    seed: int = 7
    mode: str = "virtual"
    initial: str = "exact"
    hash_name: str = "portable"
    radices: tuple[int, ...] | None = None
    median: str = "tree"
    participants: int | None = None
    target_rows: int | None = None
    carry: str = "key_origin"

    @property
    def levels(self) -> tuple[int, ...]:
        if self.radices:
            plan = tuple(self.radices)
        else:
            plan, left = (), self.nodes
            while left > 1:
                if left % self.buckets:
                    raise ValueError(f"{self.nodes} nodes are no power of {self.buckets} buckets")
                plan, left = (*plan, self.buckets), left // self.buckets
        if reduce(lambda a, x: a * x, plan, 1) != self.nodes:
            raise ValueError("the levels' bucket numbers do not multiply to the number of nodes")
        return plan

    def width(self, level: int) -> int:
        """Nodes of a group before ``level``."""
        return self.nodes // reduce(lambda a, x: a * x, self.levels[:level], 1)


@dataclass
class Level:
    """What one level left behind: local pivots, the groups' pivots, and the routed keys."""

    level: int
    local: DataFrame
    pivots: DataFrame
    routed: DataFrame
    before: DataFrame


@dataclass
class SortResult:
    """``df``: key columns, record id, ``node`` and ``rank`` (from 0)."""

    df: DataFrame
    placed: DataFrame
    levels: list[Level] = field(default_factory=list)
    config: SortConfig | None = None


def keyed_rows(df: DataFrame, key: KeySpec, keep: Sequence[str] = ()) -> DataFrame:
    """``k`` (order struct), ``_rid`` (text), the record id and the order columns; all else is pruned from the scan."""
    names = dict.fromkeys([*(c.lstrip("-") for c in key.order), *key.rid, *keep])
    return df.select(key.key(df).alias("k"), key.rid_text().alias("_rid"), *names)


def local_sample(df: DataFrame, level: int, cfg: SortConfig, b: int) -> DataFrame:
    """``(grp, node, keys)``: of every node the 2b keys that come first in hash order (all keys for full quantiles)."""
    if cfg.policy == "full_quantile":  # all keys, in any order
        return df.groupBy("grp", "node").agg(F.collect_list("k").alias("keys"))
    h = HASHES[cfg.hash_name](cfg.seed, level, "pick", F.col("_rid"))
    rows = df.select("grp", "node", "k", h.alias("_h"), "_rid")
    first = Window.partitionBy("grp", "node").orderBy("_h", "_rid")
    rows = rows.withColumn("_at", F.row_number().over(first)).filter(F.col("_at") <= 2 * b)
    gathered = rows.groupBy("grp", "node").agg(F.array_sort(F.collect_list(F.struct("_h", "_rid", "k"))).alias("all"))
    return gathered.select("grp", "node", F.transform("all", lambda x: x["k"]).alias("keys"))


def local_pivots(df: DataFrame, level: int, cfg: SortConfig, b: int) -> DataFrame:
    """``(grp, node, pivots)`` of the nodes that have keys."""
    make = HASHES[cfg.hash_name]
    draw = lambda purpose, *more: make(cfg.seed, level, purpose, F.col("node"), *more)
    sample = local_sample(df, level, cfg, b)
    return sample.select("grp", "node", pick_pivots(F.col("keys"), b, draw, cfg.policy).alias("pivots"))


def group_pivots(local: DataFrame, nodes: int, cfg: SortConfig) -> DataFrame:
    if cfg.median == "exact":
        return exact_median(local)
    return median_tree(local, nodes, cfg.fan_in, cfg.rule, cfg.participants)


def attach_pivots(rows: DataFrame, pivots: DataFrame, groups: int) -> DataFrame:
    """Give every row its group's pivots; a broadcast only while the number of groups allows it. (The left join keeps the
    optimizer from working out the bucket once more to filter out nulls.)"""
    return rows.join(F.broadcast(pivots) if groups <= MOST_BROADCAST_GROUPS else pivots, "grp", "left")


def first_pivots(df: DataFrame, key: KeySpec, cfg: SortConfig) -> tuple[DataFrame, DataFrame]:
    """The nodes' own pivots and the group's pivots of the first level, as :func:`recursive_sort` makes them, without moving a key."""
    placed = initial_shuffle(keyed_rows(df, key), cfg.nodes, cfg.seed, cfg.initial, cfg.hash_name)
    local = staged(local_pivots(placed.withColumn("grp", F.lit(0)), 0, cfg, cfg.levels[0]), "local-pivots")
    return local, staged(group_pivots(local, cfg.nodes, cfg), "group-pivots")


def ranks_of(df: DataFrame, key: KeySpec, wanted: DataFrame) -> DataFrame:
    """``(k, rank)`` of the distinct keys ``k`` in ``wanted``: a pass over ``df`` counts between them, and no key moves. For keys of a few nodes' pivots."""
    cuts = staged(wanted.agg(F.sort_array(F.collect_set("k")).alias("pivots"), F.count_distinct("k").alias("_m")), "wanted-keys")
    count = cuts.first()["_m"]
    rows = keyed_rows(df, key).select("k", F.lit(0).alias("grp"))
    counts = attach_pivots(rows, cuts.select(F.lit(0).alias("grp"), "pivots"), 1).groupBy(bucket_of("k", "pivots", count).alias("at")).agg(F.count("*").alias("n"))
    below = F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("rank")
    keys = cuts.select(F.posexplode("pivots").alias("j", "k"))
    return keys.join(F.broadcast(counts), F.col("at") <= F.col("j"), "left").groupBy("j", "k").agg(below).select("k", "rank")


def _one_level(rows: DataFrame, level: int, cfg: SortConfig) -> Level:
    b, width = cfg.levels[level], cfg.width(level)
    grouped = rows.withColumn("grp", F.floor(F.col("node") / F.lit(width)).cast("int"))
    local = local_pivots(grouped, level, cfg, b)
    pivots = staged(group_pivots(local, width, cfg), "group-pivots")
    routed = route(attach_pivots(grouped, pivots, cfg.nodes // width), level, width, b, cfg.seed, cfg.hash_name)
    routed = routed.drop("pivots")
    if cfg.mode == "physical":
        routed = routed.repartitionById(cfg.nodes, F.col("node"))
    return Level(level, local, pivots, staged(routed, "routed"), grouped)


def node_starts(counts: DataFrame, nodes: int) -> DataFrame:
    """``(node, start)``: rows on lower nodes, from ``(node, n)``, by a prefix sum over blocks of nodes."""
    block = max(1, int(nodes**0.5))
    placed = counts.withColumn("_block", F.floor(F.col("node") / F.lit(block)))
    inside = placed.withColumn("_in", F.sum("n").over(Window.partitionBy("_block").orderBy("node")) - F.col("n"))
    per_block = placed.groupBy("_block").agg(F.sum("n").alias("_n"))
    before = per_block.select("_block", (F.sum("_n").over(Window.orderBy("_block")) - F.col("_n")).alias("_before"))
    return inside.join(F.broadcast(before), "_block").select("node", (F.col("_in") + F.col("_before")).alias("start"))


def global_rank(rows: DataFrame, nodes: int, unmoved: DataFrame | None = None) -> DataFrame:
    """Rank inside the node plus the number of rows on lower nodes: no window over all rows.

    ``unmoved``: the same rows before their exchange, to count nodes from without moving them.
    """
    counts = (rows if unmoved is None else unmoved).groupBy("node").agg(F.count("*").alias("n"))
    starts = node_starts(counts, nodes)
    local = rows.withColumn("_local", F.row_number().over(Window.partitionBy("node").orderBy("k")) - 1)
    return local.join(F.broadcast(starts) if nodes <= MOST_BROADCAST_GROUPS else starts, "node", "left").withColumn("rank", (F.col("_local") + F.col("start")).cast("long")).drop("_local", "start")


def recursive_sort(df: DataFrame, key: KeySpec, cfg: SortConfig) -> SortResult:
    """Sort ``df`` by ``key``; see :class:`SortConfig`. Other columns follow where ``carry`` is ``record``."""
    if cfg.mode == "fused":
        return _fused_sort(df, key, cfg)
    keep = df.columns if cfg.carry == "record" else ()
    placed = initial_shuffle(keyed_rows(df, key, keep), cfg.nodes, cfg.seed, "round_robin" if cfg.mode == "physical" and cfg.initial == "round_robin" else cfg.initial, cfg.hash_name)
    if cfg.mode == "physical":
        placed = placed.repartitionById(cfg.nodes, F.col("node"))
    placed = rows = staged(placed, "placed")
    levels, done = [], []
    for level in range(len(cfg.levels)):
        if cfg.target_rows:
            # a group that is small enough goes to its first node and stops there
            width = cfg.width(level)
            grouped = rows.withColumn("_g", F.floor(F.col("node") / F.lit(width)))
            small = grouped.groupBy("_g").agg(F.count("*").alias("_n")).filter(F.col("_n") <= cfg.target_rows).select("_g")
            done.append(grouped.join(small, "_g", "left_semi").withColumn("node", (F.col("_g") * width).cast("int")).drop("_g"))
            rows = staged(grouped.join(small, "_g", "left_anti").drop("_g"), "open-rows")
        made = _one_level(rows, level, cfg)
        levels.append(made)
        rows = made.routed.drop("grp", "bucket", "src")
    for part in done:
        rows = rows.unionByName(part)
    return SortResult(global_rank(rows, cfg.nodes).drop("_rid"), placed, levels, cfg)


def fused_pivots(df: DataFrame, key: KeySpec, cfg: SortConfig) -> DataFrame:
    """All levels' pivots from a hash sample of the keys: ``nodes - 1`` rows ``(j, cut)`` with ascending cut points.

    Every cut is the median over independent samples' quantiles, as a tree of medians would give. The sample is a filter on
    the hash: nothing is sorted and only the sample moves.
    """
    keys = keyed_rows(df, key)
    ways = max(3, min(cfg.fan_in, 15))
    wanted = ways * max(16 * cfg.nodes, 256)
    share = min(1.0, wanted / max(1, df.count()))
    h = HASHES[cfg.hash_name](cfg.seed, 0, "fused", F.col("_rid"))
    sample = keys.select("k", h.alias("_h")).filter(F.col("_h") < int(share * 2**32) + 1)
    way = F.pmod(HASHES[cfg.hash_name](cfg.seed, 1, F.col("_h")), F.lit(ways)).cast("int")
    lists = sample.groupBy(way.alias("way")).agg(F.array_sort(F.collect_list("k")).alias("all"))
    at = lambda j: F.greatest(F.lit(1), F.ceil(j * F.size("all") / F.lit(float(cfg.nodes))).cast("int"))
    picks = lists.select("way", F.posexplode(F.transform(F.sequence(F.lit(1), F.lit(cfg.nodes - 1)), lambda j: F.element_at("all", at(j)))).alias("j", "p"))
    rows = picks.groupBy("j").agg(F.array_sort(F.collect_list("p")).alias("all"))
    return rows.select("j", F.get("all", F.floor((F.size("all") - 1) / 2).cast("int")).alias("cut"))


def _fused_sort(df: DataFrame, key: KeySpec, cfg: SortConfig) -> SortResult:
    # nodes - 1 cuts in one row: bounded by the number of nodes, far below that of rows
    cuts = staged(fused_pivots(df, key, cfg).groupBy(F.lit(0).alias("grp")).agg(F.array_sort(F.collect_list("cut")).alias("pivots")), "cuts")
    rows = keyed_rows(df, key, df.columns if cfg.carry == "record" else ())
    routed = attach_pivots(rows.withColumn("grp", F.lit(0)), cuts, 1).withColumn("node", F.coalesce(bucket_of("k", "pivots", cfg.nodes - 1), F.lit(0))).drop("pivots", "grp", "_rid")
    # the window finds the exchange's partitioning by node and adds none of its own
    moved = routed.repartitionById(cfg.nodes, F.col("node")) if cfg.nodes <= MOST_PARTITIONS else routed
    return SortResult(global_rank(moved, cfg.nodes, routed), rows, [], cfg)


#: Keys of the sample that top-k and selection take their cut points from.
CUT_SAMPLE = 8192


def _cut_points(df: DataFrame, key: KeySpec, rows: int, first: float, last: float, cfg: SortConfig) -> DataFrame:
    """One row ``(low, high)`` of keys that hold the ranks from ``first`` to ``last`` between them, four deviations of the sample's error
    apart; null where the end of the order is nearer."""
    share = min(1.0, CUT_SAMPLE / max(rows, 1))
    h = HASHES[cfg.hash_name](cfg.seed, 0, "cut", F.col("_rid"))
    sample = keyed_rows(df, key).filter(h < int(share * 2**32) + 1).agg(F.array_sort(F.collect_list("k")).alias("all"), F.count("*").alias("m"))

    def at(rank: float, side: int) -> Column:
        q = min(1.0, max(0.0, rank / max(rows, 1)))
        place = F.lit(q) * F.col("m") + F.lit(float(side)) * (F.sqrt(F.lit(q * (1 - q)) * F.col("m")) * 4 + 4)
        return F.when((place >= 0) & (place < F.col("m")), F.get("all", F.floor(place).cast("int")))

    return sample.select(at(first, -1).alias("low"), at(last, 1).alias("high"))


def _between(df: DataFrame, key: KeySpec, first: int, last: int, cfg: SortConfig) -> tuple[DataFrame, int]:
    """The keyed rows that can have the ranks ``first`` to ``last``, and how many come before them: nothing else is ever moved."""
    keys = keyed_rows(df, key)
    cuts = staged(_cut_points(df, key, df.count(), first, last, cfg), "cut-points")
    marked = keys.crossJoin(F.broadcast(cuts))  # one row
    below, inside = F.coalesce(F.col("k") < F.col("low"), F.lit(False)), F.coalesce(F.col("k") <= F.col("high"), F.lit(True))
    counts = marked.agg(F.count_if(below).alias("before"), F.count_if(~below & inside).alias("kept")).first()
    if counts["before"] > first or counts["before"] + counts["kept"] <= last:
        return keys, 0  # the sample was off, or the table ends before: all rows
    return marked.filter(~below & inside).drop("low", "high"), counts["before"]


def top_k(df: DataFrame, key: KeySpec, k: int, cfg: SortConfig) -> DataFrame:
    """The k least rows with ``rank``: a cut point from a sample leaves few rows to sort, and of those only the buckets that can hold them are
    carried on at each level."""
    kept, _ = _between(df, key, 0, max(0, k - 1), cfg)
    rows = staged(initial_shuffle(kept, cfg.nodes, cfg.seed, "hash", cfg.hash_name), "placed")
    for level in range(len(cfg.levels)):
        made = _one_level(rows, level, cfg)
        counts = made.routed.groupBy("grp", "bucket").agg(F.count("*").alias("n"))
        before = F.sum("n").over(Window.orderBy("grp", "bucket")) - F.col("n")  # as many rows as open buckets
        open_buckets = counts.withColumn("_before", before).filter(F.col("_before") < k).select("grp", "bucket")
        rows = made.routed.join(F.broadcast(open_buckets), ["grp", "bucket"], "left_semi").drop("grp", "bucket", "src")
    return global_rank(rows, cfg.nodes).filter(F.col("rank") < k).drop("_rid")


def select_rank(df: DataFrame, key: KeySpec, rank: int, cfg: SortConfig) -> DataFrame:
    """The row of one rank (from 0): two cut points leave the rows around it, and each level keeps the one bucket that holds it."""
    kept, before_all = _between(df, key, rank, rank, cfg)
    rows = staged(initial_shuffle(kept, cfg.nodes, cfg.seed, "hash", cfg.hash_name), "placed")
    left = rank - before_all
    for level in range(len(cfg.levels)):
        made = _one_level(rows, level, cfg)
        counts = made.routed.groupBy("grp", "bucket").agg(F.count("*").alias("n"))
        before = F.sum("n").over(Window.orderBy("grp", "bucket")) - F.col("n")
        hit = counts.withColumn("_before", before).filter((F.col("_before") <= left) & (F.col("_before") + F.col("n") > left)).first()
        if hit is None:
            return global_rank(rows, cfg.nodes).filter(F.lit(False)).drop("_rid")
        left -= hit["_before"]
        rows = made.routed.filter((F.col("grp") == hit["grp"]) & (F.col("bucket") == hit["bucket"])).drop("grp", "bucket", "src")
    out = global_rank(rows, cfg.nodes).filter(F.col("rank") == left)
    return out.withColumn("rank", F.lit(rank).cast("long")).drop("_rid")


def plan_levels(rows: int, row_bytes: int, partition_bytes: int = 256 << 20, most_blocks: int = 10**8) -> tuple[int, ...]:
    """Bucket numbers by level for a physical run: one level while mappers times reducers stays below ``most_blocks``, else two."""
    parts = max(1, -(-rows * row_bytes // partition_bytes))
    if parts * parts <= most_blocks:
        return (parts,)
    first = int(parts**0.5) + 1
    return (first, -(-parts // first))
