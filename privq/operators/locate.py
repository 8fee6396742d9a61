"""Exact order statistics around many ranks without a global sort.

The domain is public, so equal-width buckets need no look at the data. Pass 1 counts them (partial aggregates, at most
``BUCKETS`` rows reach the driver) and finds the bucket of every wanted rank. Wanted cells that hold more rows than
``cap`` and more than one value are cut again within their own least and greatest value, up to ``ROUNDS`` times, so that
skewed values don't end in one task. The last pass reads only values of wanted cells, as runs (value, count), so a value
that a third of all rows share is one row; runs are numbered inside a cell by a window and shifted by the cell's offset;
copies are only made inside the wanted windows.
"""

from __future__ import annotations

import bisect
import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from privq.functions.domain import Domain
from privq.sources.scratch import materialize

BUCKETS = 1 << 14
SUB_BUCKETS = 1 << 10
CAP = 1 << 16
ROUNDS = 3
#: Distinct values that one part of a rank index should hold, and the most parts.
PART_VALUES, MOST_PARTS = 1 << 14, 1 << 16


def bucket(x: Column, domain: Domain, buckets: int = BUCKETS) -> Column:
    """Bucket 0..buckets-1 of a value inside the domain; the upper end belongs to the last one."""
    at = F.floor((x - domain.lo) * (buckets / (domain.hi - domain.lo))).cast("int")
    return F.greatest(F.lit(0), F.least(F.lit(buckets - 1), at))


@dataclass(frozen=True)
class Cell:
    """Values lo..hi of a bucket: ``before`` rows are smaller, ``rows`` are inside."""

    bucket: int
    lo: float
    hi: float
    before: int
    rows: int


def _histogram(values: DataFrame, domain: Domain, buckets: int) -> list:
    cut = values.select(bucket(F.col("value"), domain, buckets).alias("bucket"), "value")
    return cut.groupBy("bucket").agg(F.count(F.lit(1)).alias("rows"), F.min("value").alias("lo"), F.max("value").alias("hi")).collect()


def _touched(cells: list[Cell], windows: list[tuple[int, int]]) -> list[Cell]:
    """Cells that some window of ranks (1-based, inclusive) meets; cells are in order."""
    ends, out = [c.before + c.rows for c in cells], set()
    for lo, hi in windows:
        k = bisect.bisect_left(ends, lo)
        while k < len(cells) and cells[k].before < hi:
            out.add(k)
            k += 1
    return [cells[k] for k in sorted(out)]


class Index:
    """Where the ranks of one column are; the counts stay on the driver and are never part of a release."""

    def __init__(self, values: DataFrame, domain: Domain, buckets: int = BUCKETS, cap: int = CAP):
        self.values, self.domain, self.buckets, self.cap = values, domain, buckets, cap
        self.spark: SparkSession = values.sparkSession
        self.cells, total = [], 0
        for r in sorted(_histogram(values, domain, buckets), key=lambda r: r["bucket"]):
            self.cells.append(Cell(r["bucket"], r["lo"], r["hi"], total, r["rows"]))
            total += r["rows"]
        self.n = total

    def wanted(self, windows: list[tuple[int, int]]) -> list[Cell]:
        """Cells that the windows meet, none with more than ``cap`` rows unless that is one value or rounds are over."""
        found = _touched(self.cells, windows)
        for _ in range(ROUNDS):
            large = [c for c in found if c.rows > self.cap and c.lo < c.hi]
            if not large:
                break
            frame = self.spark.createDataFrame([(k, c.bucket, c.lo, c.hi) for k, c in enumerate(large)], "cell int, bucket int, lo double, hi double")
            inside = self._inside(frame)
            at = F.floor((F.col("value") - F.col("lo")) * (SUB_BUCKETS / (F.col("hi") - F.col("lo")))).cast("int")
            sub = F.greatest(F.lit(0), F.least(F.lit(SUB_BUCKETS - 1), at)).alias("sub")
            parts = inside.groupBy("cell", sub).agg(F.count(F.lit(1)).alias("rows"), F.min("value").alias("least"), F.max("value").alias("most")).collect()
            cut: list[Cell] = [c for c in found if not (c.rows > self.cap and c.lo < c.hi)]
            totals = [c.before for c in large]
            for r in sorted(parts, key=lambda r: (r["cell"], r["sub"])):
                cut.append(Cell(large[r["cell"]].bucket, r["least"], r["most"], totals[r["cell"]], r["rows"]))
                totals[r["cell"]] += r["rows"]
            found = _touched(sorted(cut, key=lambda c: c.before), windows)
        return found

    def _inside(self, cells: DataFrame) -> DataFrame:
        """Values with the cell (bucket, lo, hi, ...) that they lie in; cells are no more than the windows meet."""
        placed = self.values.select(bucket(F.col("value"), self.domain, self.buckets).alias("bucket"), "value")
        return placed.join(F.broadcast(cells), "bucket").where("value >= lo and value <= hi")

    def runs(self, windows: list[tuple[int, int]]) -> tuple[DataFrame, list[Cell]]:
        """cell, value, first, last: runs of equal values with their ranks, for all cells the windows meet; the cells."""
        cells = self.wanted(windows)
        frame = self.spark.createDataFrame([(k, c.bucket, c.lo, c.hi, c.before) for k, c in enumerate(cells)], "cell int, bucket int, lo double, hi double, before bigint")
        counted = self._inside(frame).groupBy("cell", "before", "value").agg(F.count(F.lit(1)).alias("rows"))
        upto = Window.partitionBy("cell").orderBy("value").rowsBetween(Window.unboundedPreceding, 0)
        counted = counted.withColumn("last", F.col("before") + F.sum("rows").over(upto))
        return counted.select("cell", "value", (F.col("last") - F.col("rows") + 1).alias("first"), "last"), cells

    def order_statistics(self, windows: list[tuple[int, int, int]]) -> DataFrame:
        """i, rank, x for windows (i, first rank, last rank); ranks outside 1..n are left out."""
        windows = [(i, max(1, lo), min(hi, self.n)) for i, lo, hi in windows]
        windows = [w for w in windows if w[1] <= w[2]]
        if not windows or not self.n:
            return self.spark.createDataFrame([], "i int, rank bigint, x double")
        runs, cells = self.runs([(lo, hi) for _, lo, hi in windows])
        ends, placed = [c.before + c.rows for c in cells], []
        for i, lo, hi in windows:
            k = bisect.bisect_left(ends, lo)
            while k < len(cells) and cells[k].before < hi:
                placed.append((k, i, lo, hi))
                k += 1
        frame = self.spark.createDataFrame(placed, "cell int, i int, lo bigint, hi bigint")
        met = runs.join(F.broadcast(frame), "cell").where("first <= hi and last >= lo")
        return met.select("i", F.explode(F.sequence(F.greatest("first", "lo"), F.least("last", "hi"))).alias("rank"), F.col("value").alias("x"))


def slices(index: Index, ranks: list[int], h: int) -> DataFrame:
    """i (1-based), pos (1..2h+1), rank, x: the 2h+1 order statistics around each rank."""
    windows = [(i, r - h, r + h) for i, r in enumerate(ranks, 1)]
    found = index.order_statistics(windows)
    if not ranks:
        return found.withColumn("pos", F.lit(0).cast("bigint"))
    first = F.element_at(F.array(*[F.lit(int(r)).cast("bigint") for r in ranks]), F.col("i"))
    return found.select("i", (F.col("rank") - first + h + 1).alias("pos"), "rank", "x")


def exact_quantiles(values: DataFrame, domain: Domain, qs: list[float]) -> DataFrame:
    """i, q, r, x: the order statistic of rank floor(q n), at least 1. Not private."""
    from privq.plans.ranks import target_ranks

    index = Index(values, domain)
    ranks = [max(1, r) for r in target_ranks(qs, index.n)] if index.n else []
    params = index.spark.createDataFrame([(i, float(q), r) for i, (q, r) in enumerate(zip(qs, ranks, strict=False), 1)], "i int, q double, r bigint")
    return params.join(slices(index, ranks, 0).select("i", "x"), "i")


def build_index(values: DataFrame, domain: Domain, name: str = "rank-index") -> DataFrame:
    """All runs of a column, stored: part, value, rows, upto (points up to the value), next (following value or hi).

    One sort by range of the distinct values, in parts of about ``PART_VALUES``; used where a release reads the whole
    column several times. A first row at the lower bound (rows 0, or its own count) opens the first interval.
    """
    spark = values.sparkSession
    start = spark.createDataFrame([(float(domain.lo), 0)], "value double, rows bigint")
    counted = materialize(values.groupBy("value").agg(F.count(F.lit(1)).alias("rows")).unionByName(start).groupBy("value").agg(F.sum("rows").alias("rows")), f"{name}-runs")
    count = min(MOST_PARTS, math.ceil(counted.count() / PART_VALUES))
    placed = materialize(counted.repartitionByRange(count, "value").withColumn("part", F.spark_partition_id()), f"{name}-parts")
    totals = placed.groupBy("part").agg(F.sum("rows").alias("total"), F.min("value").alias("least"))  # at most MOST_PARTS rows
    by = Window.orderBy("part")
    offsets = totals.select("part", F.coalesce(F.sum("total").over(by.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"), F.coalesce(F.lead("least").over(by), F.lit(float(domain.hi))).alias("beyond"))
    inner = Window.partitionBy("part").orderBy("value")
    joined = placed.join(F.broadcast(offsets), "part")
    indexed = joined.select("part", "value", "rows", (F.col("before") + F.sum("rows").over(inner.rowsBetween(Window.unboundedPreceding, 0))).alias("upto"), F.coalesce(F.lead("value").over(inner), F.col("beyond")).alias("next"))
    return materialize(indexed, name)
