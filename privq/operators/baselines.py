"""Baselines by noisy counts over public bins, and sketches for context."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from privq.functions import prf
from privq.functions.domain import Domain
from privq.functions.local import invert_histogram
from privq.operators.locate import bucket
from privq.operators.slices import result_frame
from privq.plans import counting


def bin_counts(values: DataFrame, domain: Domain, bins: int) -> DataFrame:
    """b, rows for every bin, empty ones too (they get noise like all others)."""
    counted = values.groupBy(bucket(F.col("value"), domain, bins).cast("bigint").alias("b")).agg(F.count(F.lit(1)).alias("rows"))
    return values.sparkSession.range(bins).toDF("b").join(counted, "b", "left").select("b", F.coalesce("rows", F.lit(0)).alias("rows"))


def noisy_bins(values: DataFrame, domain: Domain, bins: int, eps: float, key: str, adjacency: str = "add_remove", law: str = "geometric") -> DataFrame:
    scale = (1 if adjacency == "add_remove" else 2) / eps
    draw = prf.two_sided_geometric if law == "geometric" else prf.laplace
    return bin_counts(values, domain, bins).select("b", (F.col("rows") + draw(key, scale, "bin", F.col("b"))).alias("rows"))


def histogram_quantiles(values: DataFrame, qs: list[float], eps: float, domain: Domain, key: str, bins: int = 256, adjacency: str = "add_remove", law: str = "geometric") -> DataFrame:
    """i, q, z by linear interpolation of noisy, clipped, cumulated bins (``bins`` rows reach the driver)."""
    rows = sorted((r["b"], r["rows"]) for r in noisy_bins(values, domain, bins, eps, key, adjacency, law).collect())
    return result_frame(values.sparkSession, qs, invert_histogram(np.array([c for _, c in rows], float), qs, domain.lo, domain.hi).tolist())


def tree_cdf(values: DataFrame, domain: Domain, bins: int, eps: float, key: str, arity: int = 15, adjacency: str = "add_remove") -> DataFrame:
    """b, upto: noisy numbers of points in the first b bins, by the correlated noise of a prefix sum."""
    spark = values.sparkSession
    share = eps if adjacency == "add_remove" else eps / 2
    upto = Window.orderBy("b").rowsBetween(Window.unboundedPreceding, 0)  # as many rows as bins
    true = bin_counts(values, domain, bins).select((F.col("b") + 1).alias("b"), F.sum("rows").over(upto).alias("rows"))
    noise = counting.prefix_noise_frame(spark, bins, share, arity, key)
    return true.join(noise.withColumnRenamed("i", "b"), "b").select("b", (F.col("rows") + F.col("noise")).alias("upto"))


def tree_quantiles(values: DataFrame, qs: list[float], eps: float, domain: Domain, key: str, bins: int = 1024, arity: int = 15, adjacency: str = "add_remove") -> DataFrame:
    """i, q, z: the noisy counts made monotone and inverted. Stands in for threshold queries, whose route isn't given."""
    upto = np.array([c for _, c in sorted((r["b"], r["upto"]) for r in tree_cdf(values, domain, bins, eps, key, arity, adjacency).collect())], float)
    rising = np.maximum.accumulate(np.maximum(0, upto))
    return result_frame(values.sparkSession, qs, invert_histogram(np.diff(np.concatenate([[0.0], rising])), qs, domain.lo, domain.hi).tolist())


def sketch_quantiles(values: DataFrame, qs: list[float], accuracy: int = 10_000) -> DataFrame:
    """i, q, z by Spark's approximate percentiles. Not private; for context only."""
    at = F.percentile_approx("value", [float(q) for q in qs], accuracy)
    found = values.agg(at.alias("zs")).select(F.posexplode("zs").alias("i", "z"))
    return found.select((F.col("i") + 1).alias("i"), F.element_at(F.array(*[F.lit(float(q)) for q in qs]), F.col("i") + 1).alias("q"), "z")


def kll_quantiles(values: DataFrame, qs: list[float], k: int = 400) -> DataFrame:
    """i, q, z by a KLL sketch. Not private."""
    sketch = values.agg(F.call_function("kll_sketch_agg_double", F.col("value"), F.lit(k)).alias("s"))
    rows = sketch.select(*[F.call_function("kll_sketch_get_quantile_double", F.col("s"), F.lit(float(q))).alias(f"z{i}") for i, q in enumerate(qs)]).first()
    return result_frame(values.sparkSession, qs, list(rows))
