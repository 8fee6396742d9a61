"""Single-quantile selection by the exponential mechanism over intervals.

Sorted points cut [lo, hi] into intervals; interval j has j points below it and log-weight
``ln(length) - eps / 2 * |j - target|``. The arg max of weight plus keyed Gumbel noise has the mechanism's law, and
does not depend on the order of summation. The estimate is uniform inside the interval, again by a keyed hash.
"""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from privq.functions import prf
from privq.functions.domain import Domain


def intervals(slices: DataFrame, lo: Column, hi: Column, h: int) -> DataFrame:
    """i, j, left, right, len of the 2h+2 intervals of each slice (i, pos, x); points are clamped to lo..hi.

    The window is over one slice of 2h+1 rows. ``lo`` and ``hi`` may be columns of ``slices`` that are equal within i.
    """
    x = F.greatest(lo, F.least(hi, F.col("x")))
    by = Window.partitionBy("i").orderBy("pos")
    cut = slices.withColumn("__x", x).withColumn("__before", F.lag("__x").over(by)).withColumn("__lo", lo).withColumn("__hi", hi)
    own = F.struct((F.col("pos") - 1).alias("j"), F.coalesce("__before", "__lo").alias("left"), F.col("__x").alias("right"))
    last = F.struct(F.lit(2 * h + 1).cast("bigint").alias("j"), F.col("__x").alias("left"), F.col("__hi").alias("right"))
    both = F.when(F.col("pos") == 2 * h + 1, F.array(own, last)).otherwise(F.array(own))
    return cut.select("i", F.explode(both).alias("v")).select("i", "v.*", (F.col("v.right") - F.col("v.left")).alias("len"))


def scores(cuts: DataFrame, eps: float, target: Column | float, key: str | Column, at: str = "i") -> DataFrame:
    """Log-weight and noisy score of every interval of positive length."""
    weight = F.log("len") - F.lit(eps / 2) * F.abs(F.col("j") - target)
    noisy = cuts.where("len > 0").withColumn("log_weight", weight)
    return noisy.withColumn("score", F.col("log_weight") + prf.gumbel(key, "sel", F.col(at), F.col("j")))


def select_interval(slices: DataFrame, eps: float, domain: Domain, h: int, key: str, target: float | None = None, bounds: DataFrame | None = None, grid: bool = False, names: DataFrame | None = None) -> DataFrame:
    """i, z: one estimate per slice. ``bounds`` (i, lo, hi), one row a slice, narrows the domain of each.

    A slice whose clamped intervals all have length zero gives its lower bound. ``names`` (i, own, at), one row a slice,
    gives slices keys and numbers of their own for the noise: those of a group stay the same whatever the other groups.
    """
    lo, hi = F.lit(float(domain.lo)), F.lit(float(domain.hi))
    if bounds is not None:
        slices = slices.join(F.broadcast(bounds), "i")
        lo, hi = F.col("lo"), F.col("hi")
    cuts, target = intervals(slices, lo, hi, h), h + 0.5 if target is None else target
    if names is None:
        scored, own, at = scores(cuts, eps, target, key), key, "i"
    else:
        scored, own, at = scores(cuts.join(F.broadcast(names), "i"), eps, target, F.col("own"), "at"), F.col("own"), "at"
    best = scored.groupBy("i").agg(F.max_by(F.struct("left", "len"), F.struct("score", "j")).alias("b"))
    best = best if names is None else best.join(F.broadcast(names), "i")
    z = F.col("b.left") + F.col("b.len") * prf.uniform(own, "pos", F.col(at))
    if bounds is not None:
        best = bounds.join(best, "i", "left")
        z = F.coalesce(z, F.col("lo"))
    return best.select("i", (F.floor(z + 0.5).cast("double") if grid else z).alias("z"))


def select_with(slices: DataFrame, selector: Callable[[list[float]], float]) -> DataFrame:
    """i, z from any single-quantile routine that maps the sorted points of a slice to an estimate."""

    def run(part: pd.DataFrame) -> pd.DataFrame:
        points = part.sort_values("pos")["x"].tolist()
        return pd.DataFrame({"i": [int(part["i"].iloc[0])], "z": [float(selector(points))]})

    return slices.groupBy("i").applyInPandas(run, "i int, z double")


def select_interval_array(points: Column, eps: float, domain: Domain, key: str, i: Column) -> Column:
    """The same selection as one expression over a sorted array of points."""
    lo, hi = F.lit(float(domain.lo)), F.lit(float(domain.hi))
    clamped = F.transform(points, lambda x: F.greatest(lo, F.least(hi, x)))
    left, right = F.concat(F.array(lo), clamped), F.concat(clamped, F.array(hi))
    target = F.size(points) / 2.0
    pairs = F.transform(F.arrays_zip(left.alias("a"), right.alias("b")), lambda p, j: F.struct(p["a"].alias("left"), (p["b"] - p["a"]).alias("len"), j.cast("bigint").alias("j")))
    scored = F.transform(F.filter(pairs, lambda p: p["len"] > 0), lambda p: F.struct((F.log(p["len"]) - F.lit(eps / 2) * F.abs(p["j"] - target) + prf.gumbel(key, "sel", i, p["j"])).alias("score"), p["left"].alias("left"), p["len"].alias("len")))
    best = F.array_max(scored)
    return F.coalesce(best["left"] + best["len"] * prf.uniform(key, "pos", i), lo)
