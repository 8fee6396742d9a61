"""Budgets, parameters and bounds: everything here is public and computed on the driver.

Adjacency: ``add_remove`` or ``substitute`` of one privacy unit (a row, or a user whose rows are capped).
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from privq.functions import prf
from privq.plans import ranks as rank_plans
from privq.plans import tails

ADJACENCIES = ("add_remove", "substitute")


def _check(adjacency: str) -> None:
    if adjacency not in ADJACENCIES:
        raise ValueError(f"adjacency must be one of {ADJACENCIES}")


@dataclass(frozen=True)
class Plan:
    """Parameters of one release with correlated slices."""

    eps: float
    delta: float
    adjacency: str
    m: int
    eps1: float
    eps2: float
    delta_cc: float
    w: int
    h: int
    arity: int
    gamma: float = 0.0
    grid: bool = False

    @property
    def margin(self) -> int:
        return self.w + self.h

    @property
    def rank_gap(self) -> int:
        """Least difference of neighbouring target ranks."""
        return 2 * self.margin + 2

    def explain(self) -> str:
        """Public parameters only."""
        return f"eps={self.eps} delta={self.delta} {self.adjacency} m={self.m}: eps1={self.eps1:.6g} eps2={self.eps2:.6g} w={self.w} h={self.h} arity={self.arity} gamma={self.gamma}"


def compose(eps1: float, eps2: float, delta: float, adjacency: str) -> tuple[float, float]:
    """Total epsilon and delta of a release."""
    _check(adjacency)
    if adjacency == "add_remove":
        return eps1 + 2 * eps2, delta
    return 2 * eps1 + 3 * eps2, delta * (1 + math.exp(eps1 + 2 * eps2))


def one_sided(eps1: float, eps2: float) -> dict[str, float]:
    """Cost of adding and of removing a point; their sum is the cost of a substitution."""
    return {"add": eps1 + eps2, "remove": eps1 + 2 * eps2}


def doubling_accountant(eps1: float, eps2: float) -> float:
    """Earlier analysis of slices, whose map sends two noisy vectors to one: never below ln 2."""
    return math.log(2) + eps1 + eps2


def to_substitute(eps: float, delta: float) -> tuple[float, float]:
    """Any add/remove guarantee under substitution: one step each way."""
    return 2 * eps, delta * (1 + math.exp(eps))


def split_budget(eps: float, delta: float, adjacency: str, split: float = 0.5) -> tuple[float, float, float]:
    """eps1, eps2 and the counting delta; ``split`` is the counting noise's share of the composed epsilon."""
    _check(adjacency)
    if not 0 < split < 1 or eps <= 0:
        raise ValueError("eps must be positive and split within (0, 1)")
    if adjacency == "add_remove":
        return split * eps, (1 - split) * eps / 2, delta
    eps1, eps2 = split * eps / 2, (1 - split) * eps / 3
    return eps1, eps2, delta / (1 + math.exp(eps1 + 2 * eps2))


def half_width(ell: int) -> int:
    return math.ceil((ell - 1) / 2)


def half_width_for(m: int, psi: float, beta: float, eps2: float) -> int:
    """h for which every one of m selections stays inside its slice with probability 1 - beta."""
    return math.ceil(2 * math.log(2 * m * psi / beta) / eps2)


def contract(beta: float, psi: float, eps2: float) -> tuple[int, int]:
    """(alpha, ell) of the interval selector: with ell points the median's rank error is at most alpha."""
    h = half_width_for(1, psi, beta, eps2)
    return h, 2 * h + 1


def log_delta_for_gamma(gamma: float, m: int, outcomes: float, eps: float) -> float:
    """ln of the delta that mixing with probability gamma absorbs, with outcomes**m results."""
    return math.log(gamma) + math.log(math.expm1(eps)) - m * math.log(outcomes)


def mixing_probability(log_delta: float, m: int, outcomes: float, eps: float) -> float:
    """gamma that turns an (eps, delta) mechanism with outcomes**m results into a pure one."""
    log_gamma = log_delta + m * math.log(outcomes) - math.log(math.expm1(eps))
    if log_gamma > 0:
        raise ValueError("delta is too large: no mixing probability up to 1 covers it")
    return math.exp(log_gamma)


def plan(m: int, n: int, psi: float, eps: float, delta: float = 0.0, adjacency: str = "add_remove", split: float = 0.5, beta: float = 0.05, gamma: float = 0.0, grid_size: int | None = None, arity: int | str = "auto", w_rule: str = "chernoff") -> Plan:
    """All parameters of a release. ``gamma`` > 0 with ``delta`` = 0 gives pure privacy on a grid of ``grid_size``."""
    pure = gamma > 0
    if pure == (delta > 0):
        raise ValueError("give delta > 0 for approximate privacy, or gamma > 0 and delta = 0 for pure privacy")
    if pure:
        if grid_size is None:
            raise ValueError("pure privacy needs the number of grid values")
        eps1, eps2, _ = split_budget(eps, 0.0, adjacency, split)
        log_delta = log_delta_for_gamma(gamma, m, grid_size, eps)
        log_delta -= math.log(1 + math.exp(eps1 + 2 * eps2)) if adjacency == "substitute" else 0.0
    else:
        eps1, eps2, delta_cc = split_budget(eps, delta, adjacency, split)
        log_delta = math.log(delta_cc)
    if log_delta < math.log(prf.LEAST):
        raise ValueError(f"the plan needs noise of probability {math.exp(log_delta):.3g}; draws resolve {prf.LEAST:.3g}")
    if w_rule == "closed":
        w, k = math.ceil(3 * max(1.0, math.log(m)) * (math.log(2 * m) - log_delta) / eps1), 3 if arity == "auto" else int(arity)
    elif arity == "auto":
        w, k = tails.w_best(m, eps1, log_delta)
    else:
        w, k = tails.w_chernoff(m, eps1, log_delta, int(arity)), int(arity)
    return Plan(eps, delta, adjacency, m, eps1, eps2, math.exp(log_delta), w, half_width_for(m, psi, beta, eps2), k, gamma, pure)


def plan_doubling(m: int, psi: float, eps: float, delta: float, split: float = 0.5, beta: float = 0.05) -> Plan:
    """Parameters under ``doubling_accountant`` (add/remove): ln 2 of eps is spent on the two-to-one map."""
    left = eps - math.log(2)
    if left <= 0:
        raise ValueError("the earlier accounting needs eps above ln 2")
    eps1, eps2 = split * left, (1 - split) * left
    w, k = tails.w_best(m, eps1, math.log(delta))
    return Plan(eps, delta, "add_remove", m, eps1, eps2, delta, w, half_width_for(m, psi, beta, eps2), k)


def lower_bound(b: float, delta: float) -> float:
    """Least order of rank error that any private median needs: log b under pure privacy, its iterated logarithm else."""
    return math.log(b) if delta == 0 else float(log_star(b))


def min_gap(m: int, n: int, b: float, eps1: float, eps2: float, delta: float, beta: float) -> float:
    """Closed-form quantile gap for approximate privacy."""
    return 6 * math.log(m) * math.log(2 * m / delta) / (eps1 * n) + 4 * math.log(2 * b * m / beta) / (eps2 * n)


def min_gap_pure(m: int, n: int, b: float, eps1: float, eps: float, gamma: float, constant: float = 6.0) -> float:
    """Closed-form quantile gap for pure privacy; the second term's constant is not stated."""
    return 6 * m * math.log(b) * math.log(m) / (eps1 * n) + constant * math.log(m) * math.log(m * math.expm1(eps) / gamma) / (eps * n)


def fits(m: int, n: int, psi: float, **options) -> bool:
    p = plan(m, n, psi, **options)
    return rank_plans.has_room(rank_plans.target_ranks(rank_plans.even_quantiles(m), n), n, p.margin)


def max_quantiles(n: int, psi: float, most: int = 4096, **options) -> int:
    """Largest m of evenly spaced quantiles that n rows can answer."""
    lo, hi = 0, 1
    while hi <= most and fits(hi, n, psi, **options):
        lo, hi = hi, hi * 2
    while hi - lo > 1:
        mid = (lo + hi) // 2
        lo, hi = (mid, hi) if fits(mid, n, psi, **options) else (lo, mid)
    return lo


def min_rows(m: int, psi_per_row: float, **options) -> int:
    """Least n for m evenly spaced quantiles; psi is ``psi_per_row * n``."""
    lo, hi = 1, 2
    while not fits(m, hi, psi_per_row * hi, **options):
        lo, hi = hi, hi * 2
    while hi - lo > 1:
        mid = (lo + hi) // 2
        lo, hi = (lo, mid) if fits(m, mid, psi_per_row * mid, **options) else (mid, hi)
    return hi


def log_star(x: float, base: float = 2.0) -> int:
    k = 0
    while x > 1:
        x, k = math.log(x) / math.log(base), k + 1
    return k


def error_bound(m: int, b: float, eps: float, beta: float, alpha: float | None = None) -> float:
    """Shape of this mechanism's rank error, constants left out."""
    first = math.log(b) / eps if alpha is None else alpha
    return first + math.log(m) * math.log(m / beta) / eps


def rival_bounds(m: int, b: float, eps: float, delta: float, beta: float) -> dict[str, float]:
    """Shapes of the rivals' errors."""
    star, lm = log_star(b), math.log(max(m, 2))
    return {
        "bisection": lm**2 * (math.log(b) + lm) / eps,
        "bisection_even": lm * (math.log(b) + lm) / eps,
        "threshold": threshold_bound(b, eps, delta, beta),
        "slices_merged": (math.log(b) + lm * math.log(m / delta)) / eps,
        "lower_pure": lower_bound(b, 0.0),
        "lower_approx": lower_bound(b, delta),
    }


def threshold_bound(b: float, eps: float, delta: float, beta: float, constant: float = 1.0) -> float:
    """Iterated-log route through threshold queries; its constant is not known to be below 1000."""
    star = log_star(b)
    return constant * star * math.log(star / (beta * delta)) ** 2 / eps


def advantage(m: int, b: float, delta: float) -> dict[str, float | bool]:
    """Improvement over pure bisection, and whether the threshold route is worse."""
    return {"factor": min(math.log(b), math.log(m) ** 2), "beats_threshold": math.log(b) < math.log(1 / delta) ** 2 * log_star(b)}


def bisection_level_eps(m: int, eps: float, delta: float, composition: str, adjacency: str = "add_remove") -> float:
    """Budget of one level of the recursion; a substituted point can touch two subsets of a level."""
    _check(adjacency)
    depth = int(math.floor(math.log2(m))) + 1
    if composition == "pure":
        level = eps / depth
    elif composition == "zcdp":
        root = math.sqrt(math.log(1 / delta) + eps) - math.sqrt(math.log(1 / delta))
        level = math.sqrt(8 * root * root / depth)
    else:
        raise ValueError("composition must be pure or zcdp")
    return level / 2 if adjacency == "substitute" else level


def independent_eps(m: int, eps: float, delta: float, composition: str = "pure", adjacency: str = "add_remove") -> float:
    """Budget of one of m selections over all data."""
    if composition == "zcdp":
        root = math.sqrt(math.log(1 / delta) + eps) - math.sqrt(math.log(1 / delta))
        each = math.sqrt(8 * root * root / m)
    else:
        each = eps / m
    return each / 2 if adjacency == "substitute" else each


class OverBudget(ValueError):
    pass


@dataclass
class Ledger:
    """Spends from one budget: releases add up, disjoint groups or windows of one release count once."""

    eps: float
    delta: float = 0.0
    entries: list[tuple[str, float, float]] = field(default_factory=list)

    @property
    def spent(self) -> tuple[float, float]:
        return math.fsum(e for _, e, _ in self.entries), math.fsum(d for _, _, d in self.entries)

    def spend(self, what: str, eps: float, delta: float = 0.0, parallel: list[tuple[float, float]] | None = None) -> None:
        """One release; with ``parallel`` its parts see disjoint data and the largest of them counts."""
        if parallel:
            eps, delta = max(e for e, _ in parallel), max(d for _, d in parallel)
        e, d = self.spent
        if e + eps > self.eps * (1 + 1e-12) or d + delta > self.delta * (1 + 1e-12):
            raise OverBudget(f"{what} needs ({eps}, {delta}); left: ({self.eps - e}, {self.delta - d})")
        self.entries.append((what, eps, delta))


def zcdp_to_approx(rho: float, delta: float) -> float:
    return rho + 2 * math.sqrt(rho * math.log(1 / delta))


def approx_to_zcdp(eps: float, delta: float) -> float:
    """Largest rho whose conversion gives eps."""
    return (math.sqrt(math.log(1 / delta) + eps) - math.sqrt(math.log(1 / delta))) ** 2


def w_closed_column(m: Column, eps1: Column, delta: Column) -> Column:
    return 3 * F.greatest(F.lit(1.0), F.log(m)) * F.log(2 * m / delta) / eps1


def sweep(df: DataFrame) -> DataFrame:
    """Score a frame of configurations (m, n, b, eps, delta, beta) by the closed forms, under both adjacencies."""
    m, n, b, eps, delta, beta = (F.col(c).cast("double") for c in ("m", "n", "b", "eps", "delta", "beta"))
    modes = F.explode(F.array(F.lit("add_remove"), F.lit("substitute")))
    df = df.select("*", modes.alias("adjacency"))
    sub = F.col("adjacency") == "substitute"
    eps1, eps2 = F.when(sub, eps / 4).otherwise(eps / 2), F.when(sub, eps / 6).otherwise(eps / 4)
    delta_cc = F.when(sub, delta / (1 + F.exp(eps1 + 2 * eps2))).otherwise(delta)
    df = df.withColumn("eps1", eps1).withColumn("eps2", eps2).withColumn("delta_cc", delta_cc)
    w = F.ceil(w_closed_column(m, F.col("eps1"), F.col("delta_cc"))).cast("bigint")
    h = F.ceil(2 * F.log(2 * m * b / beta) / F.col("eps2")).cast("bigint")
    df = df.withColumn("w", w).withColumn("h", h)
    return df.withColumn("min_gap", (2 * (F.col("w") + F.col("h")) + 2) / n)
