"""Quantiles, target ranks, the feasible set, and merging of close quantiles. Public, on the driver, no Spark job."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from privq.functions import prf


class GapTooSmall(ValueError):
    """The queried quantiles don't leave the room that the mechanism needs; no data was read."""


def check_quantiles(qs: list[float]) -> list[float]:
    qs = [float(q) for q in qs]
    if not qs or any(not 0 <= q <= 1 for q in qs) or any(a >= b for a, b in zip(qs, qs[1:], strict=False)):
        raise ValueError("quantiles must be strictly increasing within [0, 1]")
    return qs


def target_ranks(qs: list[float], n: int) -> list[int]:
    """floor(q n); the product is nudged so that decimal quantiles of round n don't fall one short."""
    return [math.floor(q * n + 1e-9) for q in check_quantiles(qs)]


def target_ranks_frame(spark: SparkSession, qs: list[float], n: int) -> DataFrame:
    """i, q, r as a DataFrame."""
    rows = spark.createDataFrame([(check_quantiles(qs),)], "qs array<double>").select(F.posexplode("qs").alias("i", "q"))
    return rows.select((F.col("i") + 1).alias("i"), "q", F.floor(F.col("q") * n + F.lit(1e-9)).cast("bigint").alias("r"))


def even_quantiles(m: int) -> list[float]:
    return [i / (m + 1) for i in range(1, m + 1)]


def grid_sample(m: int, key: str, trial: int = 0, grid: int = 251) -> list[float]:
    """m of the points i / grid, in the order of a keyed hash."""
    order = sorted(range(1, grid), key=lambda i: (prf.uniform_of(key, "grid", trial, i), i))
    return [i / grid for i in sorted(order[:m])]


def is_feasible(ranks: list[int], n: int, margin: int) -> bool:
    """Both end windows lie within 1..n and neighbours are more than two margins apart."""
    if not ranks:
        return True
    apart = all(b - a > 2 * margin for a, b in zip(ranks, ranks[1:], strict=False))
    return ranks[0] - margin >= 1 and ranks[-1] <= n - margin and apart


def has_room(ranks: list[int], n: int, margin: int) -> bool:
    """Feasible with gaps larger by one: a shift map may lead to a set whose gaps are smaller by one."""
    return is_feasible(ranks, n, margin) and all(b - a > 2 * margin + 1 for a, b in zip(ranks, ranks[1:], strict=False))


def precheck(ranks: list[int], n: int, w: int, h: int) -> None:
    """Refuse target ranks without room; ``n`` is public or noisy."""
    if not has_room(ranks, n, w + h):
        gaps = [b - a for a, b in zip(ranks, ranks[1:], strict=False)]
        raise GapTooSmall(f"ranks need gaps above {2 * (w + h) + 1} and ends {w + h} from both sides; least gap {min(gaps, default=n)}, first {ranks[0] if ranks else None}, last {ranks[-1] if ranks else None} of {n}")


def merge_close(qs: list[float], n: int, w: int, h: int) -> tuple[list[float], list[int]]:
    """Representatives and, for each quantile, the number of its representative.

    Greedy from below: a quantile is kept when its rank is far enough from the last kept one. Targets too near an end
    move to the nearest rank that has room. A member is within one gap of its representative.
    """
    margin = w + h
    least, most = margin + 1, n - margin
    if least > most:
        raise GapTooSmall(f"{n} rows leave no room for a single quantile with margin {margin}")
    ranks, reps, of = target_ranks(qs, n), [], []
    for r in ranks:
        moved = min(max(r, least), most)
        if not reps or moved - reps[-1] > 2 * margin + 1:
            reps.append(moved)
        of.append(len(reps) - 1)
    return [(r + 0.25) / n for r in reps], of
