"""Releases over windows of a stream.

A closed window is released once. Noise is keyed by the window, so a batch that is replayed after a failure gives the
same output and the same charge. An event in one window (tumbling) composes in parallel; in size / slide windows
(sliding) each window gets that part of the budget. Late rows beyond the watermark are dropped by Spark and a closed
window is never released again.
"""

from __future__ import annotations

import datetime as dt
import math
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import DataStreamWriter, StatefulProcessor, StatefulProcessorHandle

from privq.functions.domain import Domain
from privq.operators.grouped import release_runs
from privq.operators.slices import COUNT_SHARE
from privq.plans import accountant, counting
from privq.sources.scratch import materialize


def _seconds(text: str) -> float:
    units = {"second": 1, "minute": 60, "hour": 3600, "day": 86400}
    number, unit = text.split()
    return float(number) * units[unit.rstrip("s")]


def windows_of_event(size: str, slide: str | None) -> int:
    """How many windows hold one event."""
    return 1 if slide is None else math.ceil(_seconds(size) / _seconds(slide))


def windowed_runs(events: DataFrame, time: str, value: str, size: str, slide: str | None = None, by: tuple[str, ...] = ()) -> DataFrame:
    """start, (by,) value, rows: what a window release needs; counts are combined before the shuffle."""
    at = F.window(time, size, slide) if slide else F.window(time, size)
    return events.groupBy(at.alias("w"), *by, F.col(value).alias("value")).agg(F.count(F.lit(1)).alias("rows")).select(F.col("w.start").alias("start"), *by, "value", "rows")


def calendar(first: dt.datetime, last: dt.datetime, size: str, slide: str | None = None) -> list[int]:
    """Starts, in microseconds, of the windows of a public calendar that lie within ``first`` to ``last`` (exclusive)."""
    step, length = (int(_seconds(x) * 1_000_000) for x in (slide or size, size))
    lo, hi = (int(t.replace(tzinfo=dt.UTC).timestamp() * 1_000_000) for t in (first, last))
    return list(range(-(-lo // step) * step, hi - length + 1, step))


def window_quantiles(runs: DataFrame, starts: list[int] | None, qs: list[float], eps: float, delta: float, domain: Domain, key: str, share: int = 1, adjacency: str = "add_remove") -> DataFrame:
    """start, i, q, z for every window of a public list of starts (microseconds), empty ones included.

    ``starts`` None takes the windows that hold events, which shows which of them do. The number of events of a window
    is noisy; a window without room gives random values. Each window gets its part of the budget.
    """
    each = eps / share
    plan = accountant.plan(len(qs), 0, domain.psi, each * (1 - COUNT_SHARE), delta / share, adjacency)
    named = materialize(runs.select(F.unix_micros(F.col("start").cast("timestamp")).cast("string").alias("w"), F.col("value").cast("double").alias("value"), "rows"), "window-runs")
    if starts is None:
        starts = sorted(int(r["w"]) for r in named.select("w").distinct().collect())
    made = release_runs(named.where(F.col("w").isin([str(s) for s in starts])), "w", [str(s) for s in starts], qs, plan, domain, key, count_eps=each * COUNT_SHARE)
    return made.select(F.timestamp_micros(F.col("w").cast("bigint")).alias("start"), "i", "q", "z")


def release_closed_windows(events: DataFrame, time: str, value: str, size: str, lateness: str, sink: Callable[[DataFrame, int], None], qs: list[float], eps: float, delta: float, domain: Domain, key: str, slide: str | None = None) -> DataStreamWriter:
    """Streaming writer: windows that the watermark closed are released in ``foreachBatch``, exactly once each.

    A window without any event isn't emitted; whether a window is empty counts as public here.
    """
    runs = windowed_runs(events.withWatermark(time, lateness), time, value, size, slide)
    share = windows_of_event(size, slide)

    def batch(closed: DataFrame, batch_id: int) -> None:
        sink(window_quantiles(closed, None, qs, eps, delta, domain, key, share), batch_id)

    return runs.writeStream.outputMode("append").foreachBatch(batch)


def session_lengths(events: DataFrame, time: str, user: str, gap: str) -> DataFrame:
    """user, start, events, value: seconds of each session."""
    made = events.groupBy(F.session_window(time, gap).alias("s"), user).agg(F.count(F.lit(1)).alias("events"), F.max(time).alias("last"))
    return made.select(user, F.col("s.start").alias("start"), "events", (F.unix_micros(F.col("last").cast("timestamp")) - F.unix_micros(F.col("s.start").cast("timestamp"))).cast("double").alias("micros"))


def running_counts(df: DataFrame, step: str, horizon: int, eps: float, key: str) -> DataFrame:
    """step, rows, noisy: private running count over ``horizon`` public time steps 0..horizon-1, in batch.

    The window runs over one row a step.
    """
    from pyspark.sql import Window

    spark = df.sparkSession
    counted = df.groupBy(F.col(step).cast("bigint").alias("step")).agg(F.count(F.lit(1)).alias("c"))
    upto = Window.orderBy("step").rowsBetween(Window.unboundedPreceding, 0)
    total = spark.range(horizon).toDF("step").join(counted, "step", "left").select("step", F.sum(F.coalesce("c", F.lit(0))).over(upto).alias("rows"))
    noise = counting.prefix_noise_frame(spark, horizon, eps, 2, key).select((F.col("i") - 1).alias("step"), "noise")
    return total.join(noise, "step").select("step", "rows", (F.col("rows") + F.col("noise")).alias("noisy"))


class CounterProcessor(StatefulProcessor):
    """Running count of one stream key with open-node state: steps seen and true total."""

    def __init__(self, horizon: int, eps: float, key: str):
        self.horizon, self.eps, self.key = horizon, eps, key

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("counter", "step int, total bigint")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        step, total = self.state.get() if self.state.exists() else (0, 0)
        counter = counting.RunningCounter(self.horizon, self.eps, f"{self.key}/{key[0]}")
        counter.step, counter.total = step, total
        noisy = counter.add(sum(len(r) for r in rows))
        self.state.update((counter.step, counter.total))
        yield pd.DataFrame({"stream": [str(key[0])], "step": [counter.step], "noisy": [noisy]})

    def close(self) -> None:
        pass


def streaming_counter(events: DataFrame, stream: str, horizon: int, eps: float, key: str) -> DataFrame:
    """stream, step, noisy: one noisy total per micro-batch in which the key occurs."""
    return events.groupBy(stream).transformWithStateInPandas(CounterProcessor(horizon, eps, key), "stream string, step int, noisy bigint", "append", "none")


def deduplicated(events: DataFrame, time: str, lateness: str, ids: list[str]) -> DataFrame:
    """Streaming rows once each, within the watermark."""
    return events.withWatermark(time, lateness).dropDuplicatesWithinWatermark(ids)


def with_reference(events: DataFrame, reference: DataFrame, on: str) -> DataFrame:
    """A stream joined with a static table, whose rows for a key are unique; events without one keep null columns.

    The static side is read anew in each batch and broadcast by Spark where its size allows.
    """
    return events.join(reference, on, "left")
