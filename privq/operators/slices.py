"""The release: correlated rank noise, short disjoint slices around the noisy ranks, one selection in each.

The number of rows is public under substitute adjacency. Under add/remove it is private: ``release`` asks for a public
number then and refuses before anything is read; ``release_counted`` spends a share of the budget on a noisy one. With a
public number nothing is read before the precheck has passed. The rank noise is drawn once, on the driver; all other
noise is a hash of the release key. Exact counts and ranges stay on the driver and are no part of a result.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from privq.functions import prf
from privq.functions.domain import Domain
from privq.functions.local import adaptive_keyed, halves, noisy_count, random_values
from privq.operators import locate
from privq.operators.select import select_interval
from privq.plans import accountant, counting, ranks
from privq.sources.scratch import materialize

RESULT = "i int, q double, z double"
#: Rows of slices that may come to the driver.
MOST_LOCAL = 1_000_000
#: Share of the budget that a noisy number of rows gets.
COUNT_SHARE = 0.05


def result_frame(spark: SparkSession, qs: list[float], zs: list[float]) -> DataFrame:
    return spark.createDataFrame([(i, float(q), float(z)) for i, (q, z) in enumerate(zip(qs, zs, strict=True), 1)], RESULT)


def random_release(spark: SparkSession, qs: list[float], domain: Domain, key: str, grid: bool = False) -> DataFrame:
    """Uniform values on the domain (on its grid for pure privacy): what a failed or mixed-in release looks like."""
    return result_frame(spark, qs, random_values(len(qs), float(domain.lo), float(domain.hi), key, grid))


def adaptive(slices: DataFrame, m: int, plan: accountant.Plan, domain: Domain, key: str, most_local: int = MOST_LOCAL) -> list[float]:
    """Middle quantile on the whole domain, then both halves bounded by what was released, level by level.

    The slices are m (2h + 1) rows. Up to ``most_local`` of them come to the driver once and the levels run there;
    beyond it they are stored, and each level broadcasts at most m bounds and returns as many estimates.
    """
    spark, lo, hi = slices.sparkSession, float(domain.lo), float(domain.hi)
    if m * (2 * plan.h + 1) <= most_local:
        points: dict[int, list[float]] = {}
        for r in slices.select("i", "pos", "x").sort("i", "pos").toArrow().to_pylist():
            points.setdefault(r["i"], []).append(r["x"])
        return adaptive_keyed(points.__getitem__, m, plan.eps2, lo, hi, plan.h, key)
    z, bounds, slices = [0.0] * m, {(0, m - 1): (lo, hi)}, materialize(slices, "slices")
    for level in halves(m):
        frame = spark.createDataFrame([(mid + 1, *bounds[a, b]) for mid, a, b in level], "i int, lo double, hi double")
        for r in select_interval(slices, plan.eps2, domain, plan.h, key, bounds=frame).collect():
            z[r["i"] - 1] = r["z"]
        for mid, a, b in level:
            left, right = bounds.pop((a, b))
            bounds[a, mid - 1], bounds[mid + 1, b] = (left, z[mid]), (z[mid], right)
    return z


def release(values: DataFrame, qs: list[float], plan: accountant.Plan, domain: Domain, key: str, n_public: int | None = None, clip: str = "adaptive", noise: str = "correlated", monotone: bool = False, index: locate.Index | None = None) -> DataFrame:
    """i, q, z for ``values`` (one double column inside the domain) under a finished plan.

    ``n_public`` is a public or noisy number of rows; it may be left out under substitute adjacency only. Ranks beyond
    the last row read the upper bound. noise: correlated, or none for the fixed slices of the naive composition.
    ``monotone`` sorts the estimates, which costs nothing.
    """
    spark, m = values.sparkSession, len(qs)
    if n_public is None and plan.adjacency != "substitute":
        raise ValueError("under add/remove the number of rows is private: give n_public, or use release_counted")
    if n_public is not None:
        ranks.precheck(ranks.target_ranks(qs, n_public), n_public, plan.w, plan.h)
    index = locate.Index(values, domain) if index is None else index
    n = index.n if n_public is None else n_public
    target = ranks.target_ranks(qs, n)
    ranks.precheck(target, n, plan.w, plan.h)
    noisy = target if noise == "none" else counting.rank_noise(target, plan.eps1, plan.arity, key)
    if prf.uniform_of(key, "coin") < plan.gamma or not ranks.is_feasible(noisy, n, plan.h):
        return random_release(spark, qs, domain, key, plan.grid)
    found = locate.slices(index, noisy, plan.h).select("i", "pos", "x")
    beyond = [(i, r - t + plan.h + 1, float(domain.hi)) for i, t in enumerate(noisy, 1) for r in range(max(index.n + 1, t - plan.h), t + plan.h + 1)]
    if beyond:
        found = found.unionByName(spark.createDataFrame(beyond, "i int, pos bigint, x double"))
    if clip == "adaptive":
        zs = adaptive(found, m, plan, domain, key)
        zs = [float(math.floor(z + 0.5)) if plan.grid else z for z in zs]
        return result_frame(spark, qs, sorted(zs) if monotone else zs)
    picked = select_interval(found, plan.eps2, domain, plan.h, key, grid=plan.grid)
    params = spark.createDataFrame([(i, float(q)) for i, q in enumerate(qs, 1)], "i int, q double")
    out = params.join(picked, "i")
    if monotone:
        return result_frame(spark, qs, sorted(r["z"] for r in out.collect()))
    return out


def release_counted(values: DataFrame, qs: list[float], eps: float, delta: float, domain: Domain, key: str, count_share: float = COUNT_SHARE, clip: str = "adaptive", monotone: bool = False, **options) -> DataFrame:
    """A release under add/remove adjacency that nobody knows the number of rows for.

    ``count_share`` of the budget pays for a noisy number; what is left plans the release. ``options`` go to the plan.
    """
    plan = accountant.plan(len(qs), 0, domain.psi, eps * (1 - count_share), delta, "add_remove", **options)
    index = locate.Index(values, domain)
    return release(values, qs, plan, domain, key, noisy_count(index.n, eps * count_share, key), clip, monotone=monotone, index=index)


def release_doubling(values: DataFrame, qs: list[float], eps: float, delta: float, domain: Domain, key: str, n_public: int, clip: str = "adaptive", split: float = 0.5) -> DataFrame:
    """Slices under the earlier accounting, whose map is two-to-one: of eps only eps - ln 2 is left for noise.

    It can't be run at all for eps up to ln 2. Add/remove adjacency.
    """
    plan = accountant.plan_doubling(len(qs), domain.psi, eps, delta, split)
    return release(values, qs, plan, domain, key, n_public, clip)


def fixed_slices(values: DataFrame, qs: list[float], plan: accountant.Plan, domain: Domain, key: str, n_public: int | None = None, index: locate.Index | None = None) -> DataFrame:
    """Slices around the exact ranks, composed over all m of them: the naive use of slices."""
    share = accountant.Plan(**{**plan.__dict__, "eps2": plan.eps / plan.m, "w": 0})
    return release(values, qs, share, domain, key, n_public, clip="none", noise="none", index=index)


def cdf_lookup(released: DataFrame, points: DataFrame, domain: Domain) -> DataFrame:
    """x, cdf: the released quantiles read as a distribution function, linear in between. ``released`` is m rows."""
    rows = sorted((r["z"], r["q"]) for r in released.select("z", "q").collect())
    knots = [(float(domain.lo), 0.0), *rows, (float(domain.hi), 1.0)]
    knots = [(z, max(q for _, q in knots[: k + 1])) for k, (z, _) in enumerate(knots)]
    table = F.array(*[F.struct(F.lit(z).alias("z"), F.lit(q).alias("q")) for z, q in knots])
    x = F.greatest(F.lit(float(domain.lo)), F.least(F.lit(float(domain.hi)), F.col("x")))
    below, above = F.filter(table, lambda k: k["z"] <= x), F.filter(table, lambda k: k["z"] > x)
    a, b = F.element_at(below, -1), F.try_element_at(above, F.lit(1))
    return points.select("x", F.when(b.isNull(), 1.0).otherwise(a["q"] + (b["q"] - a["q"]) * (x - a["z"]) / (b["z"] - a["z"])).alias("cdf"))
