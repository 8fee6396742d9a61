"""Accuracy and cost measures of releases."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from privq.functions import prf


def rank_of(values: DataFrame, zs: list[float], ties: str = "lt") -> DataFrame:
    """i, z, below (and upto for ties="interval"): one pass, one partial sum for each estimate.

    ties: lt counts points below z, le up to z, interval gives both.
    """
    x = F.col("value")
    sums = []
    for k, z in enumerate(zs):
        if ties in ("lt", "interval"):
            sums.append(F.sum((x < z).cast("bigint")).alias(f"lt{k}"))
        if ties in ("le", "interval"):
            sums.append(F.sum((x <= z).cast("bigint")).alias(f"le{k}"))
    names = ["below"] if ties == "lt" else ["upto"] if ties == "le" else ["below", "upto"]
    prefix = {"below": "lt", "upto": "le"}
    rows = F.array(*[F.struct(F.lit(k + 1).alias("i"), F.lit(float(z)).alias("z"), *[F.coalesce(F.col(f"{prefix[n]}{k}"), F.lit(0)).alias(n) for n in names]) for k, z in enumerate(zs)])
    return values.agg(*sums).select(F.explode(rows).alias("r")).select("r.*")


def rank_of_index(index: DataFrame, zs: DataFrame) -> DataFrame:
    """``zs`` (z and any keys) with below, by the rank index: z falls into one interval of it, so an equi-join on a
    coarse bucket isn't needed; at most as many rows as estimates are broadcast."""
    met = index.join(F.broadcast(zs), (F.col("value") < F.col("z")) & (F.col("next") >= F.col("z")), "inner")
    return met.select(*zs.columns, F.col("upto").alias("below"))


def rank_errors(values: DataFrame, released: DataFrame) -> DataFrame:
    """i, q, z, r, below, error, share for one release."""
    rows = sorted(released.select("i", "q", "z").collect(), key=lambda r: r["i"])
    n = values.count()
    ranked = rank_of(values, [r["z"] for r in rows])
    qs = values.sparkSession.createDataFrame([(r["i"], r["q"]) for r in rows], "i int, q double")
    target = F.floor(F.col("q") * n + F.lit(1e-9)).cast("bigint")
    out = qs.join(ranked, "i").withColumn("r", target).withColumn("error", F.abs(F.col("below") - F.col("r")))
    return out.select("i", "q", "z", "r", "below", "error", (F.col("error") / n).alias("share"))


def max_rank_error(errors: DataFrame, *keys: str) -> DataFrame:
    out = (F.max("error").alias("max_error"), F.avg("error").alias("mean_error"))
    return errors.groupBy(*keys).agg(*out) if keys else errors.agg(*out)


def trial_mean(trials: DataFrame, *keys: str) -> DataFrame:
    """Average of the trials' maximum errors, by configuration."""
    return trials.groupBy(*keys).agg(F.avg("max_error").alias("mean_max_error"), F.count(F.lit(1)).alias("trials"))


def bootstrap_ci(trials: DataFrame, keys: list[str], reps: int = 1000, key: str = "7", level: float = 0.95) -> DataFrame:
    """Percentile interval of the mean over trials, resampled by keyed hashes. Trials of a configuration are few."""
    by = Window.partitionBy(*keys)
    numbered = trials.withColumn("__k", F.row_number().over(by.orderBy("trial")) - 1).withColumn("__n", F.count(F.lit(1)).over(by))
    resampled = numbered.select(*keys, "__n").distinct().withColumn("rep", F.explode(F.sequence(F.lit(0), F.lit(reps - 1)))).withColumn("d", F.explode(F.expr("sequence(0, __n - 1)")))
    draws = resampled.withColumn("__k", F.floor(prf.uniform(key, "boot", F.col("rep"), F.col("d")) * F.col("__n")).cast("int"))
    means = draws.join(numbered.select(*keys, "__k", "max_error"), [*keys, "__k"]).groupBy(*keys, "rep").agg(F.avg("max_error").alias("mean"))
    tail = (1 - level) / 2
    return means.groupBy(*keys).agg(F.percentile("mean", tail).alias("ci_low"), F.percentile("mean", 1 - tail).alias("ci_high"))


def improvement(means: DataFrame, ours: str, rival: str, keys: list[str]) -> DataFrame:
    """How many times the rival's error is ours."""
    a = means.where(F.col("method") == ours).select(*keys, F.col("mean_max_error").alias("ours"))
    b = means.where(F.col("method") == rival).select(*keys, F.col("mean_max_error").alias("rival"))
    return a.join(b, keys).withColumn("factor", F.col("rival") / F.col("ours"))


def failure_rate(trials: DataFrame, *keys: str) -> DataFrame:
    return trials.groupBy(*keys).agg(F.avg(F.col("failed").cast("int")).alias("failure_rate"))


def noise_sup(noise: DataFrame) -> DataFrame:
    """Largest stray of the rank noise of each trial."""
    return noise.groupBy("trial").agg(F.max(F.abs("noise")).alias("sup_norm"))


def value_errors(released: DataFrame, exact: DataFrame) -> DataFrame:
    """|z - order statistic|, the other notion of error."""
    return released.select("i", "q", "z").join(exact.select("i", "x"), "i").withColumn("error", F.abs(F.col("z") - F.col("x")))


def engine_cost(df: DataFrame, action: Callable[[DataFrame], object] = lambda d: d.count()) -> dict[str, float]:
    """Seconds, jobs and stages of an action, and exchanges in its plan."""
    spark, group = df.sparkSession, f"cost-{time.time_ns()}"
    spark.sparkContext.setJobGroup(group, "engine cost")
    began = time.time()
    action(df)
    seconds = time.time() - began
    tracker = spark.sparkContext.statusTracker()
    jobs = [j for j in (tracker.getJobInfo(i) for i in tracker.getJobIdsForGroup(group)) if j]
    plan = df._jdf.queryExecution().executedPlan().toString()
    return {"seconds": seconds, "jobs": len(jobs), "stages": sum(len(j.stageIds) for j in jobs), "exchanges": plan.count("Exchange "), "single_partition": plan.count("SinglePartition")}


def histogram(x: Column, lo: float, hi: float, bins: int) -> Column:
    """Bin of a value for distribution plots."""
    return F.greatest(F.lit(0), F.least(F.lit(bins - 1), F.floor((x - lo) * (bins / (hi - lo))).cast("int")))
