"""Releases by group, and caps on what one privacy unit contributes."""

from __future__ import annotations

import bisect

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from privq.functions import prf
from privq.functions.domain import Domain
from privq.functions.local import noisy_count, random_values
from privq.operators import locate
from privq.operators.select import select_interval
from privq.operators.slices import COUNT_SHARE, random_release, release_counted
from privq.plans import accountant, counting, ranks
from privq.sources.scratch import materialize

#: Equal-width buckets of the domain by which a group's ranks are located.
GROUP_BUCKETS = 1024


def bound_contributions(df: DataFrame, unit: str, cap: int, key: str, row_key: str) -> DataFrame:
    """At most ``cap`` rows of each unit, by keyed order; a release then costs ``cap`` times as much for a unit.

    The window keeps a unit's first ``cap`` rows; Spark limits each partition's rows before the shuffle, so a unit
    with a third of all rows sends ``cap`` rows a task.
    """
    order = Window.partitionBy(unit).orderBy(prf.uniform(key, "cap", F.col(row_key)), row_key)
    return df.withColumn("__k", F.row_number().over(order)).where(F.col("__k") <= cap).drop("__k")


def grouped_quantiles(values: DataFrame, by: str, groups: list[str], qs: list[float], plan: accountant.Plan, domain: Domain, key: str, sizes: dict[str, int] | None = None, count_eps: float | None = None) -> DataFrame:
    """group, i, q, z for every one of a public list of groups, in one pass over the data; groups are disjoint, so they
    compose in parallel (a substitution that moves a row between groups touches two).

    Runs (group, value) are counted before the shuffle. For a few groups whose values crowd into single buckets use
    ``grouped_release``, which cuts crowded cells again.
    """
    listed = values.where(F.col(by).isin(groups))
    counted = materialize(listed.groupBy(by, "value").agg(F.count(F.lit(1)).alias("rows")), "grouped-runs")
    return release_runs(counted, by, groups, qs, plan, domain, key, sizes, count_eps)


def release_runs(counted: DataFrame, by: str, groups: list[str], qs: list[float], plan: accountant.Plan, domain: Domain, key: str, sizes: dict[str, int] | None = None, count_eps: float | None = None, buckets: int = GROUP_BUCKETS) -> DataFrame:
    """The same from stored runs (group, value, rows).

    A count by group and bucket comes first (its rows, groups x ``buckets`` at most, reach the driver); only buckets that
    hold wanted ranks are numbered, each in a window of its own.

    Numbers of rows are public (``sizes``) or noisy at a cost of ``count_eps``; one of both must be given. A group
    without room, empty ones included, and one whose noisy ranks overlap gives random values, like any failed release.
    """
    if (sizes is None) == (count_eps is None):
        raise ValueError("give public sizes of the groups, or count_eps for noisy ones")
    spark, h, m, hi = counted.sparkSession, plan.h, len(qs), float(domain.hi)
    counted = counted.withColumn("bucket", locate.bucket(F.col("value"), domain, buckets))
    ends: dict[str, list[tuple[int, int]]] = {}  # bucket and rows up to its end
    for r in sorted(counted.groupBy(by, "bucket").agg(F.sum("rows").alias("n")).collect(), key=lambda r: r["bucket"]):
        own = ends.setdefault(r[by], [])
        own.append((r["bucket"], r["n"] + (own[-1][1] if own else 0)))
    windows, beyond, failed, params = [], [], [], []
    for at, g in enumerate(groups):
        own, exact = f"{key}/{g}", ends[g][-1][1] if g in ends else 0
        n = sizes.get(g, 0) if count_eps is None else noisy_count(exact, count_eps, own)
        target = ranks.target_ranks(qs, n)
        noisy = counting.rank_noise(target, plan.eps1, plan.arity, own)
        names = [at * m + i for i in range(1, m + 1)]
        if not ranks.has_room(target, n, plan.margin) or not ranks.is_feasible(noisy, n, h) or prf.uniform_of(own, "coin") < plan.gamma:
            failed += [(g, i, float(q), z) for i, (q, z) in enumerate(zip(qs, random_values(m, float(domain.lo), hi, own, plan.grid), strict=True), 1)]
            continue
        params += [(k, g, i, float(q)) for i, (k, q) in enumerate(zip(names, qs, strict=True), 1)]
        for k, r in zip(names, noisy, strict=True):
            upto = [e for _, e in ends.get(g, [])]
            for b in range(bisect.bisect_left(upto, r - h), min(len(upto), bisect.bisect_left(upto, r + h) + 1)):
                windows.append((k, g, ends[g][b][0], upto[b - 1] if b else 0, r - h, r + h, r))
        beyond += [(k, x - r + h + 1, hi) for k, r in zip(names, noisy, strict=True) for x in range(max(exact + 1, r - h), r + h + 1)]
    out = spark.createDataFrame(failed, f"{by} string, i int, q double, z double")
    if not params:
        return out
    frame = spark.createDataFrame(windows, f"i int, {by} string, bucket int, before bigint, lo bigint, hi bigint, r bigint")
    cells = frame.select(by, "bucket", "before").distinct()
    upto = Window.partitionBy(by, "bucket").orderBy("value").rowsBetween(Window.unboundedPreceding, 0)
    placed = counted.join(F.broadcast(cells), [by, "bucket"]).withColumn("last", F.col("before") + F.sum("rows").over(upto)).withColumn("first", F.col("last") - F.col("rows") + 1)
    met = placed.drop("before").join(F.broadcast(frame.drop("before")), [by, "bucket"]).where("first <= hi and last >= lo")
    cut = met.select("i", F.col("value").alias("x"), F.explode(F.sequence(F.greatest("first", "lo"), F.least("last", "hi"))).alias("rank"), "r")
    slices = cut.select("i", (F.col("rank") - F.col("r") + h + 1).alias("pos"), "x")
    if beyond:
        slices = slices.unionByName(spark.createDataFrame(beyond, "i int, pos bigint, x double"))
    keys = spark.createDataFrame([(k, f"{key}/{g}", i) for k, g, i, _ in params], "i int, own string, at int")
    z = select_interval(slices, plan.eps2, domain, h, key, grid=plan.grid, names=keys)
    names = spark.createDataFrame(params, f"k int, {by} string, i int, q double")
    return names.join(z.withColumnRenamed("i", "k"), "k").select(by, "i", "q", "z").unionByName(out)


def grouped_release(values: DataFrame, by: str, groups: list[str], qs: list[float], eps: float, delta: float, domain: Domain, key: str) -> DataFrame:
    """One located release, with its own noisy number of rows, for each of a few large groups; all groups give rows."""
    out = None
    for g in groups:
        own = values.where(F.col(by) == g).select("value")
        try:
            made = release_counted(own, qs, eps, delta, domain, f"{key}/{g}", clip="none")
        except ranks.GapTooSmall:  # decided on the noisy number
            made = random_release(values.sparkSession, qs, domain, f"{key}/{g}")
        part = made.select(F.lit(g).alias(by), "i", "q", "z")
        out = part if out is None else out.unionByName(part)
    return out


def rollup_releases(df: DataFrame, levels: list[tuple[list[str], list[str]]], value: str, qs: list[float], eps: float, delta: float, domain: Domain, key: str, count_share: float = COUNT_SHARE) -> DataFrame:
    """level, grp, i, q, z for a hierarchy of groupings, each given as (columns, public groups); a group is its column
    values joined by ``|``, and ``all`` without columns. Every level spends its own share of the budget."""
    share, parts = (eps / len(levels), delta / len(levels)), None
    plan = accountant.plan(len(qs), 0, domain.psi, share[0] * (1 - count_share), share[1])
    for k, (names, groups) in enumerate(levels):
        tagged = df.select(F.concat_ws("|", *names) if names else F.lit("all"), F.col(value)).toDF("grp", "value")
        made = grouped_quantiles(tagged, "grp", groups, qs, plan, domain, f"{key}/{k}", count_eps=share[0] * count_share)
        made = made.select(F.lit(k).alias("level"), "grp", "i", "q", "z")
        parts = made if parts is None else parts.unionByName(made)
    return parts


def noisy_counts(df: DataFrame, by: str, groups: list[str], eps: float, key: str) -> DataFrame:
    """group, rows: a noisy number of rows for each of a public list of groups, empty ones too."""
    listed = df.sparkSession.createDataFrame([(k, g) for k, g in enumerate(groups)], f"k int, {by} string")
    counted = df.groupBy(by).agg(F.count(F.lit(1)).alias("rows"))
    joined = listed.join(counted, by, "left")
    return joined.select(by, (F.coalesce("rows", F.lit(0)) + prf.two_sided_geometric(key, 1 / eps, "cnt", F.col("k"))).alias("rows"))
