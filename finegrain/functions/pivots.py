"""Pivot picks: from a node's sample of keys to its ``b - 1`` ascending pivots, as array expressions."""

from __future__ import annotations

import json
import math
from collections.abc import Callable, Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F

from finegrain.functions.hashing import fraction

#: Shares of the three ways to leave one of b keys out: any key, the last, the first.
POLICIES: dict[str, tuple[float, float, float]] = {
    "naive": (1.0, 0.0, 0.0),
    "shifted": (0.0, 0.5, 0.5),
    "mixed": (0.25, 0.375, 0.375),
}

Draw = Callable[..., Column]


def leave_one_out(keys: Column, b: int, draw: Draw, policy: str = "mixed") -> Column:
    """From b ascending keys b - 1 pivots."""
    any_share, low_share, _ = POLICIES[policy]
    u = fraction(draw("case"))
    dropped = F.pmod(draw("drop"), F.lit(b)).cast("int")
    naive = F.filter(keys, lambda x, i: i != dropped)
    return F.when(u < any_share, naive).when(u < any_share + low_share, F.slice(keys, 1, b - 1)).otherwise(F.slice(keys, 2, b - 1))


def case_equal(sample: Column, b: int, draw: Draw, policy: str = "mixed") -> Column:
    """As many keys as buckets."""
    return leave_one_out(F.array_sort(sample), b, draw, policy)


def case_short(sample: Column, b: int, draw: Draw, policy: str = "mixed") -> Column:
    """Fewer keys than buckets: random own keys are doubled up to b."""
    n = F.size(sample)
    again = F.transform(F.sequence(F.lit(1), F.greatest(F.lit(1), F.lit(b) - n)), lambda j: F.element_at(sample, (F.pmod(draw("again", j), n) + 1).cast("int")))
    return leave_one_out(F.array_sort(F.concat(sample, again)), b, draw, policy)


def case_between(sample: Column, b: int, draw: Draw, policy: str = "mixed") -> Column:
    """More than b and fewer than 2b keys: the b that come first in hash order."""
    return leave_one_out(F.array_sort(F.slice(sample, 1, b)), b, draw, policy)


def case_double(sample: Column, b: int, draw: Draw, policy: str = "mixed") -> Column:
    """2b keys: every second one, from the second or from the third."""
    ordered = F.array_sort(sample)
    shift = F.when(fraction(draw("set")) < 0.5, 0).otherwise(1)
    return F.transform(F.sequence(F.lit(1), F.lit(b - 1)), lambda j: F.element_at(ordered, (j * 2 + shift).cast("int")))


def full_quantiles(keys: Column, b: int, draw: Draw) -> Column:
    """All keys of a node as votes: pivot j at rank ``j (n + 1) / b``, rounded up with the probability of its fraction."""
    n = F.size(keys)

    def at(ordered: Column, j: Column) -> Column:
        rank = j * (n + 1).cast("long") / F.lit(float(b))
        low = F.floor(rank)
        up = F.when(fraction(draw("vote", j)) < rank - low, 1).otherwise(0)
        return F.element_at(ordered, F.least(n, F.greatest(F.lit(1), (low + up).cast("int"))).cast("int"))

    # bound by a lambda of its own: named outside, the sort would run again for every pivot
    picked = F.transform(F.array(F.sort_array(keys)), lambda ordered: F.transform(F.sequence(F.lit(1), F.lit(b - 1)), lambda j: at(ordered, j)))
    return F.array_sort(F.get(picked, F.lit(0)))


def weighted_ranks(keys: Column, b: int, draw: Draw, weights: Sequence[Sequence[tuple[int, float]]]) -> Column:
    """Pivot j is the key at one of the ranks that ``weights[j - 1]`` lists with their probabilities."""
    ordered = F.array_sort(keys)
    out = []
    for j, options in enumerate(weights, 1):
        u, left, pick = fraction(draw("mix", F.lit(j))), 0.0, None
        for rank, share in options:
            left += share
            value = F.element_at(ordered, rank)
            pick = F.when(u < left, value) if pick is None else pick.when(u < left, value)
        out.append(pick.otherwise(F.element_at(ordered, options[-1][0])))
    return F.array_sort(F.array(*out))


def weight_table(b: int, policy: str | tuple[str, tuple[float, float]]) -> list[list[list[tuple[int, float]]]]:
    """For samples of b to 2b keys and each pivot, two neighbouring ranks with their probabilities.

    ``calibrated`` puts every pivot's median at its quantile. ``("mix", (w, v))`` takes the nearer of the two ranks from its own end of the
    order with probability ``w`` and the next one inwards with ``v``.
    """
    if policy == "calibrated":
        return [calibrated_weights(n, b) for n in range(b, 2 * b + 1)]
    name, (near, far) = policy
    if name != "mix" or abs(near + far - 1) > 1e-9 or min(near, far) < 0:
        raise ValueError(f"no pivot policy {policy!r}")
    table = []
    for n in range(b, 2 * b + 1):
        low = [max(1, j * n // b) for j in range(1, b)]
        ends = [(i, near) if 2 * j <= b else (n - low[b - j - 1], far) for j, i in enumerate(low, 1)]
        table.append([[(min(i, n - 1), w), (min(i, n - 1) + 1, 1 - w)] for i, w in ends])
    return table


def pick_pivots(sample: Column, b: int, draw: Draw, policy: str | tuple[str, tuple[float, float]] = "mixed") -> Column:
    """Dispatch by the number of keys in the sample, of which a node keeps 2b at most.

    ``sample`` is in hash order; ``draw(purpose, ...)`` gives the node's 32-bit random numbers. A node without keys has none. Policies
    by weights (see :func:`weight_table`) double the keys of a node with fewer than b, as the others do.
    """
    if policy == "full_quantile":
        return F.when(F.size(sample) > 0, full_quantiles(sample, b, draw))
    n = F.size(sample)
    if policy == "calibrated" or isinstance(policy, tuple):
        table = [[{"i": i, "w": w} for (i, w), _ in row] for row in weight_table(b, policy)]
        weights = F.from_json(F.lit(json.dumps(table)), "array<array<struct<i: int, w: double>>>")
        ordered = F.array_sort(sample)

        def ranked(j: Column) -> Column:
            options = F.get(F.get(weights, n - b), j - 1)
            return F.element_at(ordered, options["i"] + F.when(fraction(draw("mix", j)) < options["w"], 0).otherwise(1))

        wide = F.array_sort(F.transform(F.sequence(F.lit(1), F.lit(b - 1)), ranked))
        return F.when(n == 0, F.lit(None)).when(n < b, case_short(sample, b, draw, "mixed")).otherwise(wide)
    return (
        F.when(n == 0, F.lit(None))
        .when(n < b, case_short(sample, b, draw, policy))
        .when(n == b, case_equal(sample, b, draw, policy))
        .when(n < 2 * b, case_between(sample, b, draw, policy))
        .otherwise(case_double(F.slice(sample, 1, 2 * b), b, draw, policy))
    )


# ------------------------------------------------------------- quantile laws


def _rank_cdf(n: int, i: int, q: float) -> float:
    """P(i-th least of n uniform keys <= q)."""
    return sum(math.comb(n, k) * q**k * (1 - q) ** (n - k) for k in range(i, n + 1))


def median_quantile(n: int, mixture: Sequence[tuple[int, float]]) -> float:
    """Quantile that the median over many nodes tends to, when each picks rank i of n keys with the given probability."""
    lo, hi = 0.0, 1.0
    for _ in range(60):
        mid = (lo + hi) / 2
        if sum(w * _rank_cdf(n, i, mid) for i, w in mixture) < 0.5:
            lo = mid
        else:
            hi = mid
    return (lo + hi) / 2


def policy_mixture(policy: str, b: int, j: int) -> list[tuple[int, float]]:
    """Ranks (of b keys) that pivot j takes under a policy, with probabilities."""
    any_share, low, high = POLICIES[policy]
    stay = any_share * (b - j) / b + low  # a later key was left out
    return [(j, stay), (j + 1, any_share * j / b + high)]


def expected_buckets(policy: str, b: int) -> list[float]:
    """Expected bucket sizes times b, in the limit of many nodes of b keys."""
    cuts = [0.0, *(median_quantile(b, policy_mixture(policy, b, j)) for j in range(1, b)), 1.0]
    return [(y - x) * b for x, y in zip(cuts, cuts[1:], strict=False)]


def calibrated_weights(n: int, b: int) -> list[list[tuple[int, float]]]:
    """For each pivot j two neighbouring ranks of n keys, weighted so that the median lies at j / b exactly."""
    out = []
    for j in range(1, b):
        q = j / b
        i = max(1, min(n - 1, next((k for k in range(1, n + 1) if _rank_cdf(n, k, q) < 0.5), n) - 1))
        f, g = _rank_cdf(n, i, q), _rank_cdf(n, i + 1, q)
        w = 1.0 if f == g else min(1.0, max(0.0, (0.5 - g) / (f - g)))
        out.append([(i, w), (i + 1, 1 - w)])
    return out
