import itertools
import math

import numpy as np
import pytest

from privq.functions import local, prf
from privq.plans import accountant, counting, ranks, tails


@pytest.mark.parametrize("m,arity", list(itertools.product([1, 2, 3, 7, 9, 30, 100], [2, 3, 5, 9, 21])))
def test_prefixes_are_signed_sums_of_nodes(m, arity):
    depth = counting.levels(m, arity)
    for i in range(1, m + 1):
        cover = np.zeros(4 * m + arity**depth + 4, int)
        for sign, level, t in counting.nodes(i, m, arity):
            assert 0 <= level < depth
            cover[t * arity**level : (t + 1) * arity**level] += sign
        assert (cover[:i] == 1).all() and (cover[i:] == 0).all()


def _pmf(scale, reach):
    a = math.exp(-1 / scale)
    x = np.arange(-reach, reach + 1)
    return (1 - a) / (1 + a) * a ** np.abs(x)


def test_two_sided_geometric_law():
    draws = np.array([prf.two_sided_geometric_of("k", 3.0, "t", i) for i in range(20000)])
    p = _pmf(3.0, 60)
    for x in range(-6, 7):
        assert abs((draws == x).mean() - p[60 + x]) < 4 * math.sqrt(p[60 + x] / len(draws))


@pytest.mark.parametrize("m,arity", [(3, 2), (4, 3), (5, 3), (7, 5)])
def test_shift_costs_one_node_a_level(m, arity):
    """One unit more in a leaf is in at most one node of each level, so node scale levels / eps hides it at cost eps."""
    for leaf in range(m):
        touched = set()
        for i in range(1, m + 1):
            for _, level, t in counting.nodes(i, m, arity):
                if t * arity**level <= leaf < (t + 1) * arity**level:
                    touched.add((level, t))
        assert len(touched) == len({level for level, _ in touched})


def test_shift_inequality_by_convolution():
    """m = 2, binary tree, all outcomes in a box: P(noise = v) <= e^eps P(noise = v + e) for contiguous shifts."""
    eps, m, reach = 1.0, 2, 40
    p = _pmf(counting.node_scale(m, eps, 2), reach)
    joint = {(a, b): p[a + reach] * p[b + reach] for a in range(-15, 16) for b in range(-15, 16)}  # prefix 1 and 2 are single nodes
    for e in [(0, 1), (1, 1), (0, -1), (-1, -1)]:
        for (a, b), q in joint.items():
            other = joint.get((a + e[0], b + e[1]))
            assert other is None or q <= math.exp(eps) * other * (1 + 1e-9)


def test_tail_bounds_hold():
    rng = np.random.default_rng(1)
    w = tails.w_chernoff(20, 1.0, math.log(0.05), 5)
    sup = [np.abs(local.prefix_noise(rng, 20, 1.0, 5)).max() for _ in range(400)]
    assert np.mean(np.array(sup) >= w) <= 0.05
    assert w < tails.w_closed(20, 1.0, 0.05)


def test_published_parameters():
    p = accountant.plan(200, 500_000, 100 * 500_000, 1.0, 1e-16, "substitute")
    assert (p.w, p.h, p.arity) == (642, 321, 21) and 2 * p.margin / 500_000 < 0.005
    p = accountant.plan(200, 500_000, 100 * 500_000, 1.0, 1e-16, "add_remove")
    assert (p.w, p.h) == (316, 214)
    assert tails.w_pure(100, 2**32, 1.0, 1, 1, base=2, mode="printed") == pytest.approx(65_000, rel=0.03)
    assert accountant.bisection_level_eps(200, 1, 0, "pure") == 0.125
    assert accountant.bisection_level_eps(200, 1, 1e-16, "zcdp") == pytest.approx(0.0818, abs=1e-4)


@pytest.mark.parametrize("adjacency", accountant.ADJACENCIES)
def test_budget_split_composes_back(adjacency):
    eps1, eps2, delta = accountant.split_budget(1.3, 1e-9, adjacency)
    assert accountant.compose(eps1, eps2, delta, adjacency) == pytest.approx((1.3, 1e-9))
    costs = accountant.one_sided(eps1, eps2)
    assert costs["add"] + costs["remove"] == pytest.approx(accountant.compose(eps1, eps2, 0, "substitute")[0])


def test_pure_conversion_round_trip():
    log_delta = accountant.log_delta_for_gamma(0.01, 9, 2**17 + 1, 1.0)
    assert accountant.mixing_probability(log_delta, 9, 2**17 + 1, 1.0) == pytest.approx(0.01)
    with pytest.raises(ValueError):
        accountant.mixing_probability(math.log(0.5), 9, 100, 1.0)


def test_zcdp_round_trip_and_doubling():
    assert accountant.zcdp_to_approx(accountant.approx_to_zcdp(1.0, 1e-16), 1e-16) == pytest.approx(1.0)
    assert accountant.doubling_accountant(0.1, 0.1) > math.log(2)
    assert accountant.log_star(2**32) == 5 and accountant.log_star(16) == 3
    assert accountant.to_substitute(1.0, 0.0) == (2.0, 0.0)


def test_ledger():
    book = accountant.Ledger(1.0, 1e-6)
    book.spend("a", 0.5)
    book.spend("groups", 0, parallel=[(0.25, 1e-7), (0.5, 0.0)])
    with pytest.raises(accountant.OverBudget):
        book.spend("c", 0.01)
    assert book.spent == (1.0, 1e-7)


def test_feasibility():
    assert ranks.is_feasible([5], 9, 4) and not ranks.is_feasible([5], 9, 5)
    assert not ranks.is_feasible([10, 10, 10], 100, 2)  # equal noisy ranks: every slice could change
    assert ranks.is_feasible([3, 8], 10, 2) and not ranks.is_feasible([3, 7], 10, 2)
    with pytest.raises(ranks.GapTooSmall):
        ranks.precheck([10, 12], 100, 1, 1)
    with pytest.raises(ValueError):
        ranks.check_quantiles([0.2, 0.2])
    assert ranks.target_ranks([0.1, 0.7], 10) == [1, 7]


def test_merging_keeps_members_close():
    qs = ranks.even_quantiles(400)
    reps, of = ranks.merge_close(qs, 150_000, 294, 202)
    got = ranks.target_ranks(reps, 150_000)
    assert ranks.is_feasible(got, 150_000, 496)
    for r, k in zip(ranks.target_ranks(qs, 150_000), of, strict=True):
        assert abs(r - got[k]) <= 2 * 496 + 1


def test_largest_m_and_least_n():
    m = accountant.max_quantiles(6000, 131072, eps=1.0, delta=1e-16)
    assert accountant.fits(m, 6000, 131072, eps=1.0, delta=1e-16) and not accountant.fits(m + 1, 6000, 131072, eps=1.0, delta=1e-16)
    n = accountant.min_rows(9, 100, eps=1.0, delta=1e-16)
    assert accountant.fits(9, n, 100 * n, eps=1.0, delta=1e-16)


# The maps of the privacy proof on order statistics 1..n; positions 0 and n + 1 stand for the domain's ends.
def _slices(x, r, h):
    return [tuple(x.get(k) for k in range(c - h, c + h + 1)) for c in r]


def _positions(values):
    return {k + 1: v for k, v in enumerate(values)} | {0: -1, len(values) + 1: 10**6}


def _contiguous(change):
    return all(c in (0, change[-1]) for c in change) and list(change) == sorted(change, key=abs)


@pytest.mark.parametrize("n,m,h", [(n, m, h) for n in range(3, 13) for m in (1, 2, 3) for h in (1, 2)])
def test_shift_maps_are_injective_and_cheap(n, m, h):
    vectors = [r for r in itertools.combinations(range(1, n + 1), m) if ranks.is_feasible(list(r), n, h)]
    x = list(range(10, 10 + 2 * n, 2))
    for s in range(1, n + 2):  # a point is added at sorted position s
        grown = x[: s - 1] + [x[s - 2] + 1 if s > 1 else 9] + x[s - 1 :]
        images = set()
        for r in vectors:
            image = tuple(c + (c - h >= s) for c in r)
            assert ranks.is_feasible(list(image), n + 1, h) and _contiguous([u - c for u, c in zip(image, r, strict=True)])
            a, b = _slices(_positions(x), r, h), _slices(_positions(grown), image, h)
            assert sum(len(set(p) - set(q)) for p, q in zip(a, b, strict=True)) <= 1
            images.add(image)
        assert len(images) == len(vectors)
    for s in range(1, n + 1):  # the point at position s is removed
        less = x[: s - 1] + x[s:]
        images = set()
        for r in vectors:
            left = [k for k, c in enumerate(r) if c + h < s]
            p = left[-1] if left else 0
            image = tuple(c - (k >= p) for k, c in enumerate(r))
            assert ranks.is_feasible(list(image), n, h - 1) and _contiguous([u - c for u, c in zip(image, r, strict=True)])
            a, b = _slices(_positions(x), r, h), _slices(_positions(less), image, h)
            assert sum(len(set(u) - set(v)) for u, v in zip(a, b, strict=True)) <= 2
            images.add(image)
        assert len(images) == len(vectors)


# The whole mechanism on a tiny domain: m = 2 ranks, slices of three points, values 0..3, all noise up to a reach.
RANKS, ROWS, H, TOP, REACH = [8, 17], 24, 1, 3, 40


def _density(points, eps):
    """Odds of each unit cell of 0..TOP under the interval selector."""
    law, edges, out = _selection_law(points, eps, 0, TOP, H + 0.5), [0, *points, TOP], np.zeros(TOP)
    for p, (a, b) in zip(law, itertools.pairwise(edges), strict=True):
        for cell in range(a, b):
            out[cell] += p / (b - a)
    return out


def _grid_law(points, eps):
    """Odds of each grid value after rounding: half of a cell goes to either side."""
    cells = _density(points, eps) / 2
    return np.concatenate([cells, [0]]) + np.concatenate([[0], cells])


class _Audit:
    """Exact law of a release of multisets with counts of 0..TOP, and the delta of its parameters."""

    def __init__(self, eps1, eps2, gamma=0.0):
        assert {(level, t) for i in (1, 2) for _, level, t in counting.nodes(i, 2, 2)} == {(0, 0), (1, 0)}  # one node a prefix
        noise = _pmf(counting.node_scale(2, eps1, 2), REACH)
        self.gamma, span = gamma, range(-REACH, REACH + 1)
        self.fits = np.array([[noise[a + REACH] * noise[b + REACH] * ranks.is_feasible([RANKS[0] + a, RANKS[1] + b], ROWS, H) for b in span] for a in span])
        w = max(k for k in range(ROWS) if ranks.has_room(RANKS, ROWS, k + H))
        inside = noise[REACH - w + 1 : REACH + w].sum()
        self.delta = 1 - inside**2  # some noise strays by w or more
        law = _grid_law if gamma else _density
        self.cells = {p: law(p, eps2) for p in itertools.combinations_with_replacement(range(TOP + 1), 3)}
        self.known = {}

    def law(self, counts):
        if counts not in self.known:
            x = [v for v, c in enumerate(counts) for _ in range(c)]
            at = lambda r: x[r - 1] if 1 <= r <= len(x) else (0 if r < 1 else TOP)
            one, two = (np.array([self.cells[tuple(at(r + k + j) for j in (-1, 0, 1))] for k in range(-REACH, REACH + 1)]) for r in RANKS)
            k = one.shape[1]
            self.known[counts] = (1 - self.gamma) * (one.T @ self.fits @ two + (1 - self.fits.sum()) / k**2) + self.gamma / k**2
        return self.known[counts]


def _multisets(n):
    for cut in itertools.combinations(range(n + TOP), TOP):
        ends = [-1, *cut, n + TOP]
        yield tuple(b - a - 1 for a, b in itertools.pairwise(ends))


def _beyond(p, q, eps):
    return np.maximum(0, p - math.exp(eps) * q).sum()


@pytest.mark.parametrize("eps1,eps2", [(2.0, 0.3), (3.0, 0.5), (5.0, 1.0)])
def test_release_privacy_by_enumeration(eps1, eps2):
    audit = _Audit(eps1, eps2)
    add, remove = accountant.one_sided(eps1, eps2)["add"], accountant.one_sided(eps1, eps2)["remove"]
    total, delta_sub = accountant.compose(eps1, eps2, audit.delta, "substitute")
    assert audit.delta < 0.5
    for counts in _multisets(ROWS):
        grown = [tuple(c + (k == v) for k, c in enumerate(counts)) for v in range(TOP + 1)]
        for g in grown:
            assert _beyond(audit.law(counts), audit.law(g), add) <= audit.delta + 1e-9  # g has one point more
            assert _beyond(audit.law(g), audit.law(counts), remove) <= audit.delta + 1e-9
        for a, b in itertools.permutations(grown, 2):
            assert _beyond(audit.law(a), audit.law(b), total) <= delta_sub + 1e-9


def test_pure_release_by_enumeration():
    eps1, eps2 = 5.0, 1.0
    eps = accountant.compose(eps1, eps2, 0, "add_remove")[0]
    plain = _Audit(eps1, eps2, 1e-9)
    gamma = accountant.mixing_probability(math.log(plain.delta), 2, TOP + 1, eps)
    audit = _Audit(eps1, eps2, gamma)
    for counts in _multisets(ROWS):
        for v in range(TOP + 1):
            p, q = audit.law(counts), audit.law(tuple(c + (k == v) for k, c in enumerate(counts)))
            assert (p <= math.exp(eps) * q * (1 + 1e-9)).all() and (q <= math.exp(eps) * p * (1 + 1e-9)).all()


@pytest.mark.parametrize("gamma", [0.0, 0.2])
def test_release_has_the_enumerated_law(gamma):
    """The release itself, over many keys, against the law that the audits use."""
    eps1, eps2, counts, draws = 2.0, 0.7, (9, 5, 4, 6), 4000
    law = _Audit(eps1, eps2, gamma).law(counts)
    x = np.repeat(np.arange(TOP + 1.0), counts)
    qs = [(r + 0.5) / ROWS for r in RANKS]
    p = accountant.Plan(eps1 + 2 * eps2, 0.1, "add_remove", 2, eps1, eps2, 0.1, 1, H, 2, gamma, gamma > 0)
    found = np.zeros_like(law)
    for k in range(draws):
        z, _ = local.release_keyed(x, qs, p, 0.0, float(TOP), f"audit{k}", ROWS, clip=False)
        found[tuple(min(int(v), law.shape[0] - 1) for v in z)] += 1 / draws
    assert np.abs(found - law).max() < 4.5 * math.sqrt(0.25 / draws) and abs(found.sum() - 1) < 1e-9


def test_noise_reaches_the_tails_that_plans_need():
    pure = accountant.plan(9, 0, 131072, 1.0, gamma=0.01, grid_size=131073)
    assert prf.from_blocks([0.0, 0.0, 0.0, 0.0]) < 2.0**-208 < prf.LEAST < pure.delta_cc < 1e-47
    assert prf.from_blocks([2.0**52 - 1] * 4) < 1
    assert prf.from_blocks([0.0, 3.0, 1.0, 0.0]) == pytest.approx(3 / 2.0**104, rel=1e-12)
    with pytest.raises(ValueError, match="probability"):
        accountant.plan(20, 0, 131072, 1.0, gamma=0.01, grid_size=131073)
    scale = counting.node_scale(9, pure.eps1, pure.arity)
    assert -math.log(prf.LEAST) * scale > pure.w / tails.counting.most_nodes(9, pure.arity)  # a draw can be as large as its share of w


def _selection_law(points, eps, lo, hi, target):
    edges = [lo, *points, hi]
    weights = [(b - a) * math.exp(-eps / 2 * abs(j - target)) for j, (a, b) in enumerate(itertools.pairwise(edges))]
    return np.array(weights) / sum(weights)


def test_selector_law():
    rng, points = np.random.default_rng(2), np.array([1.0, 1.0, 2.5, 4.0, 9.0])
    law = _selection_law(points.tolist(), 1.0, 0.0, 10.0, 2.5)
    draws = [local.pick(rng, points, 1.0, 0.0, 10.0, 2.5) for _ in range(8000)]
    found = np.histogram(draws, bins=[0, 1, 2.5, 4, 9, 10])[0] / 8000
    expected = np.array([law[0], law[2], law[3], law[4], law[5]])
    assert np.abs(found - expected).max() < 0.02
    assert local.pick(rng, np.array([3.0, 3.0]), 1.0, 3.0, 3.0, 1.0) == 3.0


def test_selector_privacy_by_enumeration():
    """A substituted point changes interval densities by at most e^eps, on a unit grid of outcomes."""
    eps = 0.8
    grid = np.arange(0.5, 8)
    density = lambda pts: np.array([_selection_law(pts, eps, 0, 8, len(pts) / 2)[j] / (([0, *pts, 8][j + 1]) - [0, *pts, 8][j]) for z in grid for j in [sum(p < z for p in pts)]])
    for a in itertools.combinations_with_replacement(range(1, 8), 3):
        for k, v in itertools.product(range(3), range(1, 8)):
            b = sorted([*a[:k], v, *a[k + 1 :]])
            assert (density(list(a)) <= math.exp(eps) * density(b) * (1 + 1e-9)).all()


def test_methods_order_at_many_quantiles():
    """With many quantiles the slices win under both adjacencies, and tiny delta hurts the approximate rival."""
    rng, n, m = np.random.default_rng(3), 500_000, 150
    x = np.sort(np.clip(np.round(rng.normal(40, 12, n)) + rng.normal(0, 0.1, n), 0, 100))
    points = local.Points.whole(x, 0, 100)
    for adjacency in accountant.ADJACENCIES:
        errors = {"slices": [], "pure": [], "zcdp": []}
        for t in range(3):
            qs = ranks.grid_sample(m, "7", t)
            p = accountant.plan(m, n, 100 * n, 1.0, 1e-16, adjacency)
            z, failed = local.release_slices(rng, points, qs, p, 0, 100)
            assert not failed
            errors["slices"].append(local.rank_errors(points, qs, z).max())
            for c in ("pure", "zcdp"):
                z = local.release_bisection(rng, points, qs, accountant.bisection_level_eps(m, 1.0, 1e-16, c, adjacency), 0, 100)
                errors[c].append(local.rank_errors(x, qs, z).max())
        means = {k: np.mean(v) for k, v in errors.items()}
        assert means["slices"] < means["pure"] < means["zcdp"]
