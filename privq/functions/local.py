"""The mechanisms on one sorted numpy array.

``release_keyed`` is the release itself for small groups, windows and streams: its draws are the keyed hashes of the
distributed release, so both give the same values. The functions that take ``rng``, a numpy generator, are for experiment
trials and laws in tests; they are no releases, as such a generator doesn't reach the tails of the noise.
"""

from __future__ import annotations

import functools
import math
from collections.abc import Callable

import numpy as np

from privq.functions import prf
from privq.plans import accountant, counting, ranks


def geometric(rng: np.random.Generator, scale: float, size: int) -> np.ndarray:
    p = -math.expm1(-1 / scale)
    return rng.geometric(p, size) - rng.geometric(p, size)


class Points:
    """Sorted values by rank, as one window or several: rank 0 reads ``lo``, ranks after the last ``hi``.

    Windows are (first rank, values), in order and without overlap; one window from rank 1 on is the whole column.
    """

    def __init__(self, windows: list[tuple[int, np.ndarray]], n: int, lo: float, hi: float):
        self.n, self.lo, self.hi = n, float(lo), float(hi)
        parts = [[first, np.asarray(x, float)] for first, x in windows] or [[1, np.zeros(0)]]
        if parts[0][0] == 1:
            parts[0] = [0, np.concatenate([[self.lo], parts[0][1]])]
        if parts[-1][0] + len(parts[-1][1]) == n + 1:
            parts[-1][1] = np.concatenate([parts[-1][1], [self.hi]])
        self.starts = np.array([first for first, _ in parts], np.int64)
        self.offsets = np.cumsum([0, *(len(x) for _, x in parts)])
        self.x = np.concatenate([x for _, x in parts])

    @classmethod
    def whole(cls, x: np.ndarray, lo: float, hi: float) -> Points:
        return cls([(1, x)], len(x), lo, hi)

    def around(self, ranks: np.ndarray, before: int, after: int) -> np.ndarray:
        """Row k: the values of ranks ``ranks[k] - before`` to ``ranks[k] + after``."""
        wanted = np.clip(ranks[:, None] + np.arange(-before, after + 1), 0, self.n + 1)
        part = np.clip(np.searchsorted(self.starts, ranks, "right") - 1, 0, len(self.starts) - 1)
        at = wanted - self.starts[part][:, None] + self.offsets[part][:, None]
        if (at < self.offsets[part][:, None]).any() or (at >= self.offsets[part + 1][:, None]).any():
            raise IndexError("a rank lies outside the windows that were read")
        return self.x[at]

    def below(self, z: np.ndarray) -> np.ndarray:
        """Points below each z; between two windows, the points before the later one."""
        at = np.searchsorted(self.x, z, "left")
        part = np.clip(np.searchsorted(self.offsets, at, "right") - 1, 0, len(self.starts) - 1)
        rank = at - self.offsets[part] + self.starts[part]
        return np.clip(rank - 1, 0, self.n)

    def misses(self, z: np.ndarray) -> np.ndarray:
        """Where the windows don't tell how many points are below z: before the first, between two or after the last."""
        at = np.searchsorted(self.x, z, "left")
        first, last = self.starts[0] == 0, self.starts[-1] + len(self.x) - self.offsets[-2] == self.n + 2
        return (np.isin(at, self.offsets[1:-1])) | ((at == 0) & (not first)) | ((at == len(self.x)) & (not last))


@functools.lru_cache(maxsize=512)
def _node_signs(m: int, arity: int) -> np.ndarray:
    """Row i: the signs of the nodes of prefix i + 1."""
    known: dict[tuple[int, int], int] = {}
    rows = [[(s, known.setdefault((level, t), len(known))) for s, level, t in counting.nodes(i, m, arity)] for i in range(1, m + 1)]
    out = np.zeros((m, len(known)), np.int64)
    for i, row in enumerate(rows):
        for s, k in row:
            out[i, k] = s
    return out


def prefix_noise(rng: np.random.Generator, m: int, eps: float, arity: int) -> np.ndarray:
    """Correlated noise for positions 1..m; each node is drawn once."""
    signs = _node_signs(m, arity)
    return signs @ geometric(rng, counting.node_scale(m, eps, arity), signs.shape[1])


def pick_rows(rng: np.random.Generator, edges: np.ndarray, weights: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """One estimate a row: an interval between neighbouring edges with odds length x weight, then a uniform place in it;
    also each row's total mass. A row without any length gives its first edge."""
    lengths = np.diff(edges, axis=1)
    upto = np.cumsum(lengths * weights, axis=1)
    mass, rows = upto[:, -1], np.arange(len(edges))
    j = np.minimum((upto <= (rng.random(len(edges)) * mass)[:, None]).sum(axis=1), lengths.shape[1] - 1)
    return edges[rows, j] + rng.random(len(edges)) * np.where(mass > 0, lengths[rows, j], 0.0), mass


def pick(rng: np.random.Generator, points: np.ndarray, eps: float, lo: float, hi: float, target: float) -> float:
    """Exponential mechanism over the intervals that sorted points cut [lo, hi] into."""
    edges = np.concatenate([[lo], np.clip(points, lo, hi), [hi]])[None, :]
    return float(pick_rows(rng, edges, np.exp(-eps / 2 * np.abs(np.arange(edges.shape[1] - 1) - target)))[0][0])


def halves(m: int) -> list[list[tuple[int, int, int]]]:
    """Levels of the recursion over 0..m-1: (middle, first, last) of each node."""
    out, now = [], [(0, m - 1)] if m else []
    while now:
        level = [((a + b) // 2, a, b) for a, b in now]
        out.append(level)
        now = [p for mid, a, b in level for p in ((a, mid - 1), (mid + 1, b)) if p[0] <= p[1]]
    return out


def release_slices(rng: np.random.Generator, x: np.ndarray | Points, qs: list[float], plan: accountant.Plan, lo: float, hi: float, clip: bool = True, correlated: bool = True) -> tuple[np.ndarray, bool]:
    """Estimates and whether the release failed; ``x`` is sorted."""
    points = x if isinstance(x, Points) else Points.whole(x, lo, hi)
    n, m, h = points.n, len(qs), plan.h
    target = ranks.target_ranks(qs, n)
    ranks.precheck(target, n, plan.w, h)
    noisy = np.array(target) + (prefix_noise(rng, m, plan.eps1, plan.arity) if correlated else geometric(rng, m / plan.eps1, m))
    if rng.random() < plan.gamma or not ranks.is_feasible(noisy.tolist(), n, h):
        u = rng.random(m)
        return (lo + np.floor(u * (int(hi - lo) + 1)) if plan.grid else lo + (hi - lo) * u), True
    weights = np.exp(-plan.eps2 / 2 * np.abs(np.arange(2 * h + 2) - (h + 0.5)))
    cut, z, bounds = points.around(noisy, h, h), np.empty(m), {(0, m - 1): (lo, hi)}
    for level in halves(m):
        at = np.array([mid for mid, _, _ in level])
        left, right = (np.array(side) for side in zip(*(bounds.pop((a, b)) if clip else (lo, hi) for _, a, b in level), strict=True))
        edges = np.concatenate([left[:, None], np.clip(cut[at], left[:, None], right[:, None]), right[:, None]], axis=1)
        z[at] = pick_rows(rng, edges, weights)[0]
        for k, (mid, a, b) in enumerate(level):
            bounds[a, mid - 1], bounds[mid + 1, b] = (left[k], z[mid]), (z[mid], right[k])
    return (np.floor(z + 0.5) if plan.grid else z), False


#: Odds with which a selection over all data may lie outside the ranks that are looked at, as a natural logarithm.
BEYOND = -28.0


def pick_near(rng: np.random.Generator, points: Points, eps: float, left: np.ndarray, right: np.ndarray, target: np.ndarray) -> np.ndarray:
    """Selections over the whole column within bounds, one a row.

    Only ranks within ``reach`` of the target are read; all intervals beyond hold at most (right - left) exp(-eps reach
    / 2) of mass, and the reach grows until that share is below exp(``BEYOND``).
    """
    out, todo = left.astype(float).copy(), np.flatnonzero(right > left)
    reach = math.ceil(2 / eps * (2 - BEYOND + math.log(max(2, points.n))))
    while len(todo):
        weights = np.exp(-eps / 2 * np.abs(np.arange(-reach, reach)))
        open_ = []
        for lo in range(0, len(todo), max(1, 2_000_000 // (2 * reach + 1))):
            part = todo[lo : lo + max(1, 2_000_000 // (2 * reach + 1))]
            edges = np.clip(points.around(target[part], reach, reach), left[part][:, None], right[part][:, None])
            z, mass = pick_rows(rng, edges, weights)
            with np.errstate(divide="ignore"):
                sure = np.log(right[part] - left[part]) - eps / 2 * reach - np.log(mass) < BEYOND
            sure |= (target[part] - reach <= 0) & (target[part] + reach > points.n)
            out[part[sure]] = z[sure]
            open_.append(part[~sure])
        todo, reach = np.concatenate(open_), 2 * reach
    return out


def release_bisection(rng: np.random.Generator, x: np.ndarray | Points, qs: list[float], level_eps: float, lo: float, hi: float) -> np.ndarray:
    points = x if isinstance(x, Points) else Points.whole(x, lo, hi)
    m = len(qs)
    target, z, bounds = np.array(ranks.target_ranks(qs, points.n)), np.empty(m), {(0, m - 1): (lo, hi)}
    for level in halves(m):
        at = np.array([mid for mid, _, _ in level])
        left, right = (np.array(side, float) for side in zip(*(bounds.pop((a, b)) for _, a, b in level), strict=True))
        z[at] = pick_near(rng, points, level_eps, left, right, target[at])
        for k, (mid, a, b) in enumerate(level):
            bounds[a, mid - 1], bounds[mid + 1, b] = (left[k], z[mid]), (z[mid], right[k])
    return z


def release_independent(rng: np.random.Generator, x: np.ndarray | Points, qs: list[float], each_eps: float, lo: float, hi: float) -> np.ndarray:
    points = x if isinstance(x, Points) else Points.whole(x, lo, hi)
    target = np.array(ranks.target_ranks(qs, points.n))
    return pick_near(rng, points, each_eps, np.full(len(qs), float(lo)), np.full(len(qs), float(hi)), target)


def invert_histogram(counts: np.ndarray, qs: list[float], lo: float, hi: float) -> np.ndarray:
    """Quantiles by linear interpolation of clipped, cumulated bin counts."""
    upto = np.concatenate([[0.0], np.cumsum(np.maximum(0, counts))])
    if upto[-1] <= 0:
        return np.array([lo + q * (hi - lo) for q in qs])
    return np.interp(np.array(qs) * upto[-1], upto, np.linspace(lo, hi, len(counts) + 1))


def release_histogram(rng: np.random.Generator, x: np.ndarray, qs: list[float], eps: float, lo: float, hi: float, bins: int, adjacency: str = "add_remove") -> np.ndarray:
    return release_binned(rng, np.histogram(x, bins=bins, range=(lo, hi))[0], qs, eps, lo, hi, adjacency)


def release_binned(rng: np.random.Generator, counts: np.ndarray, qs: list[float], eps: float, lo: float, hi: float, adjacency: str = "add_remove") -> np.ndarray:
    """The same from counted bins."""
    return invert_histogram(counts + geometric(rng, (1 if adjacency == "add_remove" else 2) / eps, len(counts)), qs, lo, hi)


def rank_errors(x: np.ndarray | Points, qs: list[float], z: np.ndarray) -> np.ndarray:
    """|points below z - target rank|; ``x`` is sorted."""
    if isinstance(x, Points):
        return np.abs(x.below(z) - np.array(ranks.target_ranks(qs, x.n)))
    return np.abs(np.searchsorted(x, z, "left") - np.array(ranks.target_ranks(qs, len(x))))


def random_values(m: int, lo: float, hi: float, key: str, grid: bool = False) -> list[float]:
    """Uniform values on the domain (on its grid for pure privacy): what a failed or mixed-in release looks like."""
    us = [prf.uniform_of(key, "rnd", i) for i in range(1, m + 1)]
    if grid:
        count = int(hi - lo) + 1
        return [lo + min(count - 1, math.floor(u * count)) for u in us]
    return [lo + u * (hi - lo) for u in us]


def pick_keyed(points: list[float], eps: float, lo: float, hi: float, target: float, key: str, *name: str | int) -> float:
    """The interval selector on sorted points, by the draws of ``select_interval``."""
    edges = [lo, *(max(lo, min(hi, x)) for x in points), hi]
    best = None
    for j, (left, right) in enumerate(zip(edges, edges[1:], strict=False)):
        if right > left:
            score = math.log(right - left) - eps / 2 * abs(j - target) + prf.gumbel_of(key, "sel", *name, j)
            if best is None or (score, j) > best[:2]:
                best = (score, j, left, right - left)
    return lo if best is None else best[2] + best[3] * prf.uniform_of(key, "pos", *name)


def adaptive_keyed(points: Callable[[int], list[float]], m: int, eps: float, lo: float, hi: float, h: int, key: str) -> list[float]:
    """Middle quantile on the whole domain, then both halves within its estimate; ``points`` gives a slice (1..m)."""
    z, bounds = [0.0] * m, {(0, m - 1): (lo, hi)}
    for level in halves(m):
        for mid, a, b in level:
            left, right = bounds.pop((a, b))
            z[mid] = pick_keyed(points(mid + 1), eps, left, right, h + 0.5, key, mid + 1)
            bounds[a, mid - 1], bounds[mid + 1, b] = (left, z[mid]), (z[mid], right)
    return z


def release_keyed(x: np.ndarray, qs: list[float], plan: accountant.Plan, lo: float, hi: float, key: str, n: int, clip: bool = True) -> tuple[list[float], bool]:
    """Estimates and whether they are random, from sorted values and a public or noisy number of rows.

    Ranks beyond the last row read the upper bound. Without room, or when the noisy ranks overlap, values are random.
    """
    m, h, target = len(qs), plan.h, ranks.target_ranks(qs, n)
    noisy = counting.rank_noise(target, plan.eps1, plan.arity, key)
    if not ranks.has_room(target, n, plan.margin) or prf.uniform_of(key, "coin") < plan.gamma or not ranks.is_feasible(noisy, n, h):
        return random_values(m, lo, hi, key, plan.grid), True
    at = lambda i: [float(x[r - 1]) if r <= len(x) else hi for r in range(noisy[i - 1] - h, noisy[i - 1] + h + 1)]
    z = adaptive_keyed(at, m, plan.eps2, lo, hi, h, key) if clip else [pick_keyed(at(i), plan.eps2, lo, hi, h + 0.5, key, i) for i in range(1, m + 1)]
    return [float(math.floor(v + 0.5)) for v in z] if plan.grid else z, False


def noisy_count(n: int, eps: float, key: str) -> int:
    """Rows under add/remove adjacency, where their number is private."""
    return max(0, n + prf.two_sided_geometric_of(key, 1 / eps, "n"))
