"""Experiment workloads: trials of several mechanisms over one column, in parallel over trials.

Quantiles of a trial are drawn from a public grid, so every mechanism reads order statistics near grid ranks only. Up to
``MOST_ROWS`` rows a column is read as a whole; beyond it, windows of ``REACH`` ranks to both sides of each grid rank are
located exactly (``locate``), so what is broadcast doesn't grow with the data. Bins of the histogram are then counted over
the whole column, and estimates that lie outside the windows get their exact ranks by one more look at it
(``points_below``). Smaller columns are repeated in whole copies until they have ``LEAST_ROWS``, as the experiments scale
theirs.

A trial whose quantiles are too close for the plan is recorded as refused, without an error. Means compare methods over
the trials that none of them refused.
"""

from __future__ import annotations

import bisect
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from privq.functions import local, prf
from privq.functions.domain import Domain, separate, to_domain
from privq.operators import locate, measures
from privq.plans import accountant, ranks
from privq.sources.io import table
from privq.sources.scratch import materialize

MOST_ROWS = 4_000_000
LEAST_ROWS = 500_000
REACH = 8192
GRID = 251
ESTIMATES = "job bigint, z array<double>, failed boolean"
TRIALS = "method string, adjacency string, eps double, delta double, m int, split double, bins int, trial int, max_error bigint, mean_error double, failed boolean, refused boolean"


@dataclass(frozen=True)
class Setting:
    """One configuration of the sweep."""

    method: str
    adjacency: str
    m: int
    eps: float = 1.0
    delta: float = 1e-16
    split: float = 0.5
    clip: bool = True
    bins: int = 256
    correlated: bool = True
    arity: int | str = "auto"


def column(spark: SparkSession, sf_dir: str, name: str, seed: str = "7") -> tuple[DataFrame, Domain]:
    """Columns of the workloads: value, and its public domain."""
    if name in ("age", "hours"):
        source, scale = {"age": ("l_quantity", 1.9), "hours": ("l_discount", 900.0)}[name]
        domain = Domain(0.0, 100.0)
        df = table(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", source).withColumn("value", F.col(source) * scale + 2.0)
        return to_domain(separate(df, "gaussian", seed, 0.1, ["l_orderkey", "l_linenumber"]), "value", domain, "lo"), domain
    source, relation, lo, hi = {"money": ("l_extendedprice", "lineitem", 0.0, 131072.0), "total": ("o_totalprice", "orders", 0.0, 524288.0), "skewed": ("value", "events", 0.0, 1024.0)}[name]
    domain = Domain(lo, hi)
    return to_domain(table(spark, sf_dir, relation, source), source, domain, "lo"), domain


def replicate(values: DataFrame, times: int) -> DataFrame:
    """Every row ``times`` times: the scaling of the experiments' data."""
    return values.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(times - 1))))


def grid_windows(n: int, reach: int, grid: int = GRID) -> list[tuple[int, int]]:
    """Ranks within ``reach`` of a grid rank, as merged ranges."""
    out: list[list[int]] = []
    for r in ranks.target_ranks([k / grid for k in range(1, grid)], n):
        lo, hi = max(1, r - reach), min(n, r + reach)
        if out and lo <= out[-1][1] + 1:
            out[-1][1] = hi
        else:
            out.append([lo, hi])
    return [(lo, hi) for lo, hi in out]


@dataclass(frozen=True)
class Column:
    """What trials need of a column: windows (first rank, values with how often each occurs), rows, domain; where the
    windows are not the whole column, also its counts by number of bins."""

    windows: list[tuple[int, np.ndarray, np.ndarray]]
    n: int
    lo: float
    hi: float
    counts: dict[int, np.ndarray] = field(default_factory=dict)

    def points(self, spaced: bool) -> local.Points:
        """Values by rank; ``spaced`` adds i / n to the i-th, which is preprocessing of the experiments, not private."""
        parts = []
        for first, value, rows in self.windows:
            x = np.repeat(value, rows)
            parts.append((first, np.clip(x + (first - 1 + np.arange(len(x))) / self.n, self.lo, self.hi) if spaced else x))
        return local.Points(parts, self.n, self.lo, self.hi)


def points_below(index: locate.Index, edges: list[float], spaced: bool) -> list[int]:
    """For each edge of the domain, how many points are below it, exactly; ``spaced`` as in ``Column.points``.

    Points rise with their rank, so an edge parts at most one cell of the index. Only such cells are read, as runs; a run
    of one value that an edge parts (by the spacing) is halved on the driver.
    """
    n = max(1, index.n)
    place = lambda x, rank: x + (rank - 1) / n if spaced else x
    found: dict[float, int] = {}

    def part(cells: list[locate.Cell]) -> list[tuple[int, float]]:
        """Cells (by number) with the edges inside; edges before, between or after cells are found at once."""
        ends, out = [place(c.hi, c.before + c.rows) for c in cells], []
        for e in sorted(set(edges) - set(found)):
            k = bisect.bisect_left(ends, e)  # the first cell with a point not below the edge
            if k == len(cells):
                found[e] = cells[-1].before + cells[-1].rows if cells else 0
            elif place(cells[k].lo, cells[k].before + 1) >= e:
                found[e] = cells[k].before
            else:
                out.append((k, float(e)))
        return out

    inside = part(index.cells)
    if inside:
        met = [index.cells[k] for k in sorted({k for k, _ in inside})]
        runs, cells = index.runs([(c.before + 1, c.before + c.rows) for c in met])
        frame = index.spark.createDataFrame(part(cells), "cell int, edge double")
        shift = lambda rank: F.col("value") + (F.col(rank) - 1) / F.lit(float(n)) if spaced else F.col("value")
        placed = runs.join(F.broadcast(frame), "cell").withColumns({"least": shift("first"), "most": shift("last")}).where("least < edge")
        whole = F.max(F.when(F.col("most") < F.col("edge"), F.col("last"))).alias("upto")
        cut = F.max(F.when(F.col("most") >= F.col("edge"), F.struct("value", "first", "last"))).alias("cut")
        for r in placed.groupBy("edge").agg(whole, cut).toLocalIterator():
            count = r["upto"]
            if r["cut"] is not None:  # its first point is below the edge and its last one is not
                lo, hi = r["cut"]["first"], r["cut"]["last"]
                while lo + 1 < hi:
                    mid = (lo + hi) // 2
                    lo, hi = (mid, hi) if place(r["cut"]["value"], mid) < r["edge"] else (lo, mid)
                count = lo
            found[r["edge"]] = count
    return [found[e] for e in edges]


def _windowed(index: locate.Index, most: int) -> bool:
    return index.n > most


def read_column(values: DataFrame, domain: Domain, least: int = LEAST_ROWS, most: int = MOST_ROWS, reach: int = REACH, bins: list[int] | None = None, spaced: bool = True, index: locate.Index | None = None) -> Column:
    """``bins``: numbers of bins that are counted if the column is read by windows."""
    index = index or locate.Index(values, domain)
    if not index.n:
        return Column([], 0, domain.lo, domain.hi)
    if not _windowed(index, most):
        counted = values.groupBy("value").agg(F.count(F.lit(1)).alias("rows")).toArrow().sort_by("value")
        copies = -(-least // index.n)
        return Column([(1, counted.column("value").to_numpy(), counted.column("rows").to_numpy() * copies)], index.n * copies, domain.lo, domain.hi)
    wanted = grid_windows(index.n, reach)
    found = index.order_statistics([(k, lo, hi) for k, (lo, hi) in enumerate(wanted)]).toArrow().sort_by("rank")
    rank, x = found.column("rank").to_numpy(), found.column("x").to_numpy()
    cuts = [np.searchsorted(rank, [lo, hi + 1]) for lo, hi in wanted]
    edges = {b: np.linspace(domain.lo, domain.hi, b + 1)[1:-1].tolist() for b in bins or []}
    flat = sorted({e for some in edges.values() for e in some})
    below = dict(zip(flat, points_below(index, flat, spaced) if flat else [], strict=True))
    counts = {b: np.diff([0, *(below[e] for e in some), index.n]) for b, some in edges.items()}
    return Column([(lo, x[a:b], np.ones(b - a, np.int64)) for (lo, _), (a, b) in zip(wanted, cuts, strict=True)], index.n, domain.lo, domain.hi, counts)


def one_trial(rng: np.random.Generator, x: local.Points, qs: list[float], s: Setting, domain: Domain, counts: dict[int, np.ndarray] | None = None) -> tuple[np.ndarray, bool]:
    """Estimates and whether the release failed; ``counts``: bins of a column of which ``x`` has windows only."""
    n, lo, hi = x.n, domain.lo, domain.hi
    if s.method == "slices":
        p = accountant.plan(s.m, n, (hi - lo) * n, s.eps, s.delta, s.adjacency, s.split, arity=s.arity)
        return local.release_slices(rng, x, qs, p, lo, hi, s.clip, s.correlated)
    if s.method.startswith("bisection_"):
        level = accountant.bisection_level_eps(s.m, s.eps, s.delta, s.method.split("_")[1], s.adjacency)
        return local.release_bisection(rng, x, qs, level, lo, hi), False
    if s.method == "independent":
        return local.release_independent(rng, x, qs, accountant.independent_eps(s.m, s.eps, s.delta, "pure", s.adjacency), lo, hi), False
    if s.method == "histogram":
        if counts and s.bins in counts:
            return local.release_binned(rng, counts[s.bins], qs, s.eps, lo, hi, s.adjacency), False
        if len(x.x) != n + 2:
            raise ValueError("the histogram needs the whole column or its bins")
        return local.release_histogram(rng, x.x[1:-1], qs, s.eps, lo, hi, s.bins, s.adjacency), False
    raise ValueError(f"unknown method {s.method}")


def run(spark: SparkSession, values: DataFrame, domain: Domain, settings: list[Setting], trials: int, seed: str = "7", spaced: bool = True, least: int = LEAST_ROWS, most: int = MOST_ROWS, reach: int = REACH) -> DataFrame:
    """One row per setting and trial. Fresh quantiles for each trial, the same for all methods of an m."""
    values = materialize(values.select("value"), "column")  # read several times, drawn once
    index = locate.Index(values, domain)
    column = read_column(values, domain, least, most, reach, sorted({s.bins for s in settings if s.method == "histogram"}), spaced, index)
    held = spark.sparkContext.broadcast(column)
    jobs = spark.range(len(settings) * trials).repartition(max(1, min(len(settings) * trials, 4 * spark.sparkContext.defaultParallelism)), "id")
    quantiles = lambda s, trial: ranks.grid_sample(s.m, seed, trial * 1000 + s.m, GRID) if s.m < GRID else ranks.even_quantiles(s.m)

    def estimates(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        x = held.value.points(spaced)
        for batch in batches:
            out = []
            for job in batch["id"].tolist():
                s, trial = settings[job // trials], job % trials
                rng = np.random.default_rng(int(prf.uniform_of(seed, "trial", job) * (1 << 52)))
                try:
                    z, failed = one_trial(rng, x, quantiles(s, trial), s, domain, held.value.counts)
                    out.append((job, z, failed))
                except ranks.GapTooSmall:
                    out.append((job, None, None))
            yield pd.DataFrame(out, columns=["job", "z", "failed"]).astype({"failed": "boolean"})

    def measured(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        x, (at, below) = held.value.points(spaced), strays.value
        for batch in batches:
            out = []
            for job, z, failed in zip(batch["job"].tolist(), batch["z"], batch["failed"], strict=True):
                s, trial = settings[job // trials], job % trials
                name = f"{s.method}{'' if s.clip else '_unclipped'}{'' if s.correlated else '_uncorrelated'}"
                row = (name, s.adjacency, s.eps, s.delta, s.m, s.split, s.bins, trial)
                if z is None:
                    out.append((*row, None, None, None, True))
                    continue
                z, qs = np.asarray(z), quantiles(s, trial)
                errors, missed = local.rank_errors(x, qs, z), x.misses(z)
                if missed.any():
                    errors[missed] = np.abs(below[np.searchsorted(at, z[missed])] - np.array(ranks.target_ranks(qs, x.n))[missed])
                out.append((*row, int(errors.max()), float(errors.mean()), failed, False))
            made = pd.DataFrame(out, columns=[f.split()[0] for f in TRIALS.split(", ")])
            yield made.astype({"max_error": "Int64", "failed": "boolean"})

    if not _windowed(index, most):
        strays = spark.sparkContext.broadcast((np.zeros(0), np.zeros(0, np.int64)))
        return jobs.mapInPandas(lambda batches: measured(estimates(batches)), TRIALS)

    def outside(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        x = held.value.points(spaced)
        for batch in batches:
            z = np.concatenate([np.zeros(0), *(np.asarray(z) for z in batch["z"] if z is not None)])
            yield pd.DataFrame({"z": np.unique(z[x.misses(z)])})

    made = materialize(jobs.mapInPandas(estimates, ESTIMATES), "estimates")
    at = np.unique(made.mapInPandas(outside, "z double").toArrow().column("z").to_numpy())
    strays = spark.sparkContext.broadcast((at, np.array(points_below(index, at.tolist(), spaced), np.int64)))
    return made.mapInPandas(measured, TRIALS)


#: What makes trials comparable: all methods see the same quantiles.
SAME = ("adjacency", "eps", "delta", "m", "trial")


def summary(made: DataFrame, reps: int = 200, key: str = "7") -> DataFrame:
    """By configuration: mean of the maximum errors over common trials, its bootstrap interval, trials and refusals."""
    keys = ["method", "adjacency", "eps", "delta", "m", "split", "bins"]
    refused = made.where("refused").select(*SAME).distinct()
    common = made.join(refused, list(SAME), "left_anti")
    means = measures.trial_mean(common, *keys).join(measures.bootstrap_ci(common, keys, reps, key), keys)
    counts = made.groupBy(*keys).agg(F.sum(F.col("refused").cast("bigint")).alias("refused"), F.avg(F.col("failed").cast("int")).alias("failure_rate"))
    return counts.join(means, keys, "left")


METHODS = ("slices", "bisection_pure", "bisection_zcdp")


def sweep_m(adjacency: str, ms: list[int], methods: tuple[str, ...] = METHODS, **options) -> list[Setting]:
    """The curves over m of one adjacency."""
    return [Setting(method, adjacency, m, **options) for m in ms for method in methods]


def sweep_budget(m: int, adjacency: str, budgets: list[float], deltas: list[float]) -> list[Setting]:
    return [Setting(method, adjacency, m, e, d) for e in budgets for d in deltas for method in METHODS]


def sweep_split(m: int, adjacency: str, splits: list[float]) -> list[Setting]:
    return [Setting("slices", adjacency, m, split=s) for s in splits]


def ablations(m: int, adjacency: str) -> list[Setting]:
    """Clipping off, and rank noise without correlation."""
    return [Setting("slices", adjacency, m), Setting("slices", adjacency, m, clip=False), Setting("slices", adjacency, m, correlated=False)]
