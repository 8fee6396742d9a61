"""Rivals over the whole column: recursive bisection and independent selections, on one stored rank index.

A row of the index stands for the interval from its value to the next; ``upto`` points lie below the interval. A node
(quantile number, bounds, target rank) weighs the intervals clipped to its bounds. The index comes in parts of known
bounds and ranks, so a node is joined by part with those parts only that could hold its pick: a noisy score has a
greatest and a least value, as keyed uniforms do. So a level reads the neighbourhoods of its targets, not the column.
Each level broadcasts nodes by part and returns as many estimates as it has nodes.

The number of rows counts as public here, as in the published comparisons of these rivals.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from privq.functions import prf
from privq.functions.domain import Domain
from privq.functions.local import halves
from privq.operators import locate
from privq.operators.slices import result_frame
from privq.plans import accountant, ranks

#: Bounds of a keyed Gumbel draw, from the least and the greatest uniform.
GUMBEL_LEAST, GUMBEL_MOST = -4.0, 146.0


@dataclass(frozen=True)
class Parts:
    """Bounds of the parts of an index: first value, end of the last interval, ranks below and upto, longest interval."""

    rows: list[tuple[int, float, float, int, int, float]]

    @classmethod
    def of(cls, index: DataFrame) -> Parts:
        found = index.groupBy("part").agg(F.min("value").alias("lo"), F.max("next").alias("hi"), F.min("upto").alias("first"), F.max("upto").alias("last"), F.max(F.col("next") - F.col("value")).alias("longest")).collect()
        return cls([tuple(r) for r in sorted(found, key=lambda r: r["part"])])

    @property
    def n(self) -> int:
        return max((r[4] for r in self.rows), default=0)

    def for_node(self, lo: float, hi: float, target: int, eps: float) -> list[int]:
        """Parts whose best possible score reaches what some part inside the bounds has at least."""
        near = [r for r in self.rows if r[1] < hi and r[2] > lo]
        least = max((math.log(r[5]) - eps / 2 * max(abs(r[3] - target), abs(r[4] - target)) + GUMBEL_LEAST for r in near if r[1] >= lo and r[2] <= hi and r[5] > 0), default=-math.inf)
        most = lambda r: math.log(hi - lo) - eps / 2 * max(0, r[3] - target, target - r[4]) + GUMBEL_MOST
        return [r[0] for r in near if most(r) >= least]


def select_over_index(index: DataFrame, parts: Parts, nodes: list[tuple[int, float, float, int]], eps: float, key: str) -> DataFrame:
    """i, z for nodes (i, lo, hi, target rank)."""
    placed = [(p, *node) for node in nodes if node[1] < node[2] for p in parts.for_node(node[1], node[2], node[3], eps)]
    frame = index.sparkSession.createDataFrame(placed, "part int, i int, lo double, hi double, r bigint")
    met = index.join(F.broadcast(frame), "part").where("value < hi and next > lo")
    left, right = F.greatest("value", "lo"), F.least("next", "hi")
    cut = met.select("i", F.col("upto").alias("j"), left.alias("left"), (right - left).alias("len"), "r").where("len > 0")
    score = F.log("len") - F.lit(eps / 2) * F.abs(F.col("j") - F.col("r")) + prf.gumbel(key, "bis", F.col("i"), F.col("j"))
    best = cut.groupBy("i").agg(F.max_by(F.struct("left", "len"), F.struct(score, F.col("j"))).alias("b"))
    return best.select("i", (F.col("b.left") + F.col("b.len") * prf.uniform(key, "pos", F.col("i"))).alias("z"))


def bisection(values: DataFrame, qs: list[float], level_eps: float, domain: Domain, key: str, index: DataFrame | None = None) -> DataFrame:
    """i, q, z by the middle quantile first, then both halves within its estimate."""
    index = locate.build_index(values, domain) if index is None else index
    parts, m = Parts.of(index), len(qs)
    target, z = ranks.target_ranks(qs, parts.n), [0.0] * m
    bounds = {(0, m - 1): (float(domain.lo), float(domain.hi))}
    for level in halves(m):
        nodes = [(mid + 1, *bounds[a, b], target[mid]) for mid, a, b in level]
        found = {r["i"]: r["z"] for r in select_over_index(index, parts, nodes, level_eps, key).collect()}
        for mid, a, b in level:
            lo, hi = bounds.pop((a, b))
            z[mid] = found.get(mid + 1, lo)  # bounds that met have no interval left
            bounds[a, mid - 1], bounds[mid + 1, b] = (lo, z[mid]), (z[mid], hi)
    return result_frame(index.sparkSession, qs, z)


def independent(values: DataFrame, qs: list[float], each_eps: float, domain: Domain, key: str, index: DataFrame | None = None) -> DataFrame:
    """i, q, z by m selections over all data."""
    index = locate.build_index(values, domain) if index is None else index
    parts = Parts.of(index)
    nodes = [(i, float(domain.lo), float(domain.hi), r) for i, r in enumerate(ranks.target_ranks(qs, parts.n), 1)]
    found = {r["i"]: r["z"] for r in select_over_index(index, parts, nodes, each_eps, key).collect()}
    return result_frame(index.sparkSession, qs, [found[i] for i in range(1, len(qs) + 1)])


def release_bisection(values: DataFrame, qs: list[float], eps: float, delta: float, composition: str, adjacency: str, domain: Domain, key: str, index: DataFrame | None = None) -> DataFrame:
    return bisection(values, qs, accountant.bisection_level_eps(len(qs), eps, delta, composition, adjacency), domain, key, index)
