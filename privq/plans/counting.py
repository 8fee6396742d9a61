"""Continual counting: correlated noise for a vector of ranks, and running counters.

Position i of the vector is the sum of the first i leaves. A tree node of level l covers k**l leaves and has one noise
value; a prefix is a signed sum of nodes. With balanced digits (odd k) level l takes the nodes between the prefix
rounded to whole nodes of level l + 1 and to those of level l, at most (k - 1) / 2 of them. A shift of all positions
after t by one is one more unit in one leaf, which at most one node a level covers, so node noise of scale
levels / eps hides it at cost eps.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from privq.functions import prf


def levels(m: int, arity: int) -> int:
    if arity == 2:
        return max(1, m.bit_length())
    if arity < 3 or arity % 2 == 0:
        raise ValueError("arity must be 2 or odd")
    depth = 1
    while (arity**depth - 1) // 2 < m:
        depth += 1
    return depth


def rounded(i: int, arity: int, level: int) -> int:
    """Prefix i in whole nodes of a level: rounded for balanced digits, cut off for binary ones."""
    width = arity**level
    return i // width if arity == 2 else (i + (width - 1) // 2) // width


def nodes(i: int, m: int, arity: int) -> Iterator[tuple[int, int, int]]:
    """Sign, level and number of the nodes whose signed sum is the prefix i."""
    for level in range(levels(m, arity)):
        a, b = arity * rounded(i, arity, level + 1), rounded(i, arity, level)
        sign = 1 if b > a else -1
        for t in range(min(a, b), max(a, b)):
            yield sign, level, t


def most_nodes(m: int, arity: int) -> int:
    """The largest number of nodes in any prefix up to m."""
    return max(sum(1 for _ in nodes(i, m, arity)) for i in range(1, m + 1))


def node_scale(m: int, eps: float, arity: int) -> float:
    return levels(m, arity) / eps


def prefix_noise(m: int, eps: float, arity: int, key: str, law: str = "geometric") -> list[int]:
    """Noise for positions 1..m. law: geometric, or laplace with the sum rounded afterwards."""
    scale = node_scale(m, eps, arity)
    draw: Callable[..., float] = prf.two_sided_geometric_of if law == "geometric" else prf.laplace_of
    return [round(sum(s * draw(key, scale, "cc", level, t) for s, level, t in nodes(i, m, arity))) for i in range(1, m + 1)]


def independent_noise(m: int, eps: float, key: str) -> list[int]:
    """Uncorrelated noise at eps / m each: what it costs not to correlate."""
    return [prf.two_sided_geometric_of(key, m / eps, "ind", i) for i in range(1, m + 1)]


def rank_noise(ranks: list[int], eps: float, arity: int | str, key: str, law: str = "geometric") -> list[int]:
    m = len(ranks)
    noise = independent_noise(m, eps, key) if arity == "independent" else prefix_noise(m, eps, int(arity), key, law)
    return [r + z for r, z in zip(ranks, noise, strict=True)]


def prefix_noise_frame(spark: SparkSession, m: int, eps: float, arity: int, key: str, trials: DataFrame | None = None) -> DataFrame:
    """(trial,) i, noise: the same draws as columns, for many trials at once. Trials use the key ``key/trial``."""
    depth, scale = levels(m, arity), node_scale(m, eps, arity)
    half = "0" if arity == 2 else f"(CAST(pow({arity}, l) AS BIGINT) - 1) DIV 2"
    upper = "0" if arity == 2 else f"(CAST(pow({arity}, l + 1) AS BIGINT) - 1) DIV 2"
    at = spark.range(1, m + 1).toDF("i").selectExpr("i", f"explode(sequence(0, {depth - 1})) AS l")
    at = at.selectExpr("i", "l", f"{arity} * ((i + {upper}) DIV CAST(pow({arity}, l + 1) AS BIGINT)) AS a", f"(i + {half}) DIV CAST(pow({arity}, l) AS BIGINT) AS b").where("a <> b")
    each = at.selectExpr("i", "l", "IF(b > a, 1, -1) AS sign", "explode(sequence(least(a, b), greatest(a, b) - 1)) AS t")
    if trials is None:
        noise = each.select("i", (F.col("sign") * prf.two_sided_geometric(key, scale, "cc", F.col("l"), F.col("t"))).alias("z"))
        return noise.groupBy("i").agg(F.sum("z").alias("noise"))
    noise = each.crossJoin(F.broadcast(trials)).select("trial", "i", (F.col("sign") * prf.two_sided_geometric(key, scale, F.col("trial"), "cc", F.col("l"), F.col("t"))).alias("z"))
    return noise.groupBy("trial", "i").agg(F.sum("z").alias("noise"))


class RunningCounter:
    """Private running count over time: the binary tree, one node of each level open at a time."""

    def __init__(self, horizon: int, eps: float, key: str):
        self.horizon, self.eps, self.key = horizon, eps, key
        self.scale, self.step, self.total = node_scale(horizon, eps, 2), 0, 0

    def add(self, count: int) -> int:
        """True count so far plus the noise of the prefix's nodes."""
        self.step += 1
        if self.step > self.horizon:
            raise ValueError("past the horizon the counter was made for")
        self.total += count
        return self.total + sum(s * prf.two_sided_geometric_of(self.key, self.scale, "cc", level, t) for s, level, t in nodes(self.step, self.horizon, 2))


def sup_norm(noise: list[int]) -> int:
    return max((abs(z) for z in noise), default=0)


def best_arity(m: int, bound: Callable[[int], float], most: int = 51) -> int:
    """The odd arity (or 2) of the smallest noise bound."""
    return min([2, *range(3, min(most, 2 * m + 3) + 1, 2)], key=lambda k: (bound(k), k))


def mgf_terms(m: int, arity: int) -> tuple[int, int]:
    """Levels and most nodes of a prefix, which the tail bound needs."""
    return levels(m, arity), most_nodes(m, arity)


def log2_levels(m: int) -> int:
    return max(1, math.ceil(math.log2(max(1, m))) + 1)
