"""How far the correlated rank noise strays: closed forms and a numeric Chernoff bound."""

from __future__ import annotations

import functools
import math

from privq.plans import counting


#: Steps of the exponent between none and the least that a node's moments don't have.
EXPONENTS = 1000


def w_closed(m: int, eps1: float, delta: float, base: float = math.e) -> float:
    """3 log(m) log(2m / delta) / eps1, at least with the factor of one level."""
    log = lambda x: math.log(x) / math.log(base)
    return 3 * max(1.0, log(m)) * log(2 * m / delta) / eps1


def w_pure(m: int, b: float, gamma: float, eps1: float, eps2: float, adjacency: str = "add_remove", base: float = math.e, mode: str = "lemma") -> float:
    """The closed form at the delta that mixing with probability gamma pays for.

    mode "printed" takes the exponents as they stand in the statement; "lemma" takes the total epsilon, b + 1 grid
    values, and the exact factor of the substitute theorem.
    """
    log = lambda x: math.log(x) / math.log(base)
    log_exp = lambda x: x / math.log(base)
    if mode == "printed":
        inner = m * log(b) + log(2 * m * math.expm1(eps2 if adjacency == "add_remove" else eps1) / gamma)
        inner += 0 if adjacency == "add_remove" else log_exp(eps1 + 2 * eps2)
    else:
        total = eps1 + 2 * eps2 if adjacency == "add_remove" else 2 * eps1 + 3 * eps2
        inner = m * log(b + 1) - log(gamma * math.expm1(total)) + log(2 * m)
        inner += 0 if adjacency == "add_remove" else log(1 + math.exp(eps1 + 2 * eps2))
    return 3 * max(1.0, log(m)) * inner / eps1


def log_mgf(lam: float, eps: float) -> float:
    """Logarithm of the moment generating function of a two-sided geometric draw of scale 1 / eps."""
    a = math.exp(-eps)
    return 2 * math.log1p(-a) - math.log1p(-a * math.exp(lam)) - math.log1p(-a * math.exp(-lam))


@functools.lru_cache(maxsize=4096)
def w_chernoff(m: int, eps1: float, log_delta: float, arity: int) -> int:
    """Whole w with P(any of m sums of nodes strays by w or more) <= delta; every exponent gives a bound, and the best of
    ``EXPONENTS`` evenly spaced ones is taken."""
    depth, most = counting.mgf_terms(m, arity)
    eps = eps1 / depth
    need = math.log(2 * m) - log_delta
    return math.ceil(min((most * log_mgf(k / EXPONENTS * eps, eps) + need) / (k / EXPONENTS * eps) for k in range(1, EXPONENTS)))


def w_best(m: int, eps1: float, log_delta: float) -> tuple[int, int]:
    """The smallest Chernoff w and its arity."""
    arity = counting.best_arity(m, lambda k: w_chernoff(m, eps1, log_delta, k))
    return w_chernoff(m, eps1, log_delta, arity), arity
