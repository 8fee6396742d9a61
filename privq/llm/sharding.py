"""Reproducible shuffle by a Feistel permutation of global row numbers.

Every row gets a number from 0 to n-1 that depends on its contents only, not on files, partitions or the cluster: rows
are counted by a hash bucket of their keys, buckets are laid end to end, and a bucket numbers its distinct keys in
order. Rows that agree in all keys are counted before anything is shuffled and share a run of numbers; which of them
gets which is of no consequence, as they are equal.

The permutation works on the grid a x b with a = ceil(sqrt n) and b = ceil(n / a): each round adds a keyed hash of one
coordinate to the other, modulo its side. A number that leaves 0..n-1 is sent through again until it is back (cycle
walking); fewer than a of the a*b cells lie outside. Shard and slot are the remainder and the quotient of the permuted
number, so shard sizes differ by one row at most, slots have no gap, and ``place`` computes both for any row number
without looking at data.

Null text has no bytes; null ids are keys like others; an empty table gives no rows.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from privq.llm.common import table, text_or_empty
from privq.sources.scratch import materialize

#: Least and most buckets, and distinct rows that one should hold.
BUCKETS, MOST_BUCKETS, BUCKET_ROWS = 4096, 1 << 17, 100_000
#: Numbers of equal rows that are made at a time.
RUN_ROWS = 100_000
ROUNDS = 4
#: Steps of the cycle walk. A cell outside has odds below 2 / sqrt(n), and for n <= 4096 no walk can be longer.
WALK = 64
_M31 = (1 << 31) - 1


def grid(n: int) -> tuple[int, int]:
    a = max(1, math.isqrt(max(0, n - 1)) + 1)
    return a, max(1, -(-n // a))


def round_value(x: int, seed: int, k: int) -> int:
    """Keyed round function; multiplication and shifts within 63 bits, the same here and as a column."""
    z = (x * 48271 + seed * 40692 + k * 7919 + 12345) % _M31
    for c in (16807, 69621, 630360016 % _M31):
        z = ((z ^ (z >> 15)) % _M31 * c + k) % _M31
    return z


def place(row: int, n: int, shards: int, seed: int) -> tuple[int, int]:
    """Shard and slot of a row number, on the driver."""
    a, b = grid(n)
    while True:
        left, right = row // b, row % b
        for k in range(ROUNDS):
            if k % 2 == 0:
                left = (left + round_value(right, seed, k)) % a
            else:
                right = (right + round_value(left, seed, k)) % b
        row = left * b + right
        if row < n:
            return row % shards, row // shards


def _round_column(x: Column, seed: int, k: int) -> Column:
    z = (x * 48271 + F.lit(seed * 40692 + k * 7919 + 12345)) % _M31
    for c in (16807, 69621, 630360016 % _M31):
        z = (z.bitwiseXOR(F.shiftright(z, 15)) % _M31 * F.lit(c) + k) % _M31
    return z


def _quotient(x: Column, by: int) -> Column:
    """Whole quotient; exact below 2**53, as the division leaves no fraction."""
    return ((x - x % by) / by).cast("long")


def _once(row: Column, a: int, b: int, seed: int) -> Column:
    """One pass through all rounds."""
    state = F.struct(_quotient(row, b).alias("x"), (row % b).cast("long").alias("y"))
    rounds = F.array(*[F.lit(k) for k in range(ROUNDS)])

    def step(s: Column, k: Column) -> Column:
        left, right = s["x"], s["y"]
        for_even = F.struct(((left + _pick(right, seed, k)) % a).alias("x"), right.alias("y"))
        for_odd = F.struct(left.alias("x"), ((right + _pick(left, seed, k)) % b).alias("y"))
        return F.when(k % 2 == 0, for_even).otherwise(for_odd)

    return F.aggregate(rounds, state, step, lambda s: s["x"] * b + s["y"])


def _pick(x: Column, seed: int, k: Column) -> Column:
    out = _round_column(x, seed, ROUNDS - 1)
    for j in range(ROUNDS - 2, -1, -1):
        out = F.when(k == j, _round_column(x, seed, j)).otherwise(out)
    return out


def permute(row: Column, n: int, seed: int) -> Column:
    """Permuted row number as a column of built-in functions."""
    a, b = grid(n)
    walked = F.aggregate(F.array_repeat(F.lit(0), WALK), _once(row, a, b, seed), lambda v, _: F.when(v < n, v).otherwise(_once(v, a, b, seed)))
    return F.when(walked < n, walked).otherwise(F.raise_error(F.lit("cycle walk did not end")).cast("long"))


def number_rows(df: DataFrame, keys: list[str]) -> tuple[DataFrame, int]:
    """Rows of ``keys`` with ``row_number`` from 0, and how many there are."""
    counted = materialize(df.select(*keys).groupBy(*keys).agg(F.count(F.lit(1)).alias("__copies")), "row-numbers")
    buckets = max(BUCKETS, min(MOST_BUCKETS, counted.count() // BUCKET_ROWS))
    counted = counted.withColumn("__bucket", F.pmod(F.xxhash64(*keys), F.lit(buckets)).cast("int"))
    sizes = counted.groupBy("__bucket").agg(F.sum("__copies").alias("__rows"))  # at most MOST_BUCKETS rows
    n = sizes.agg(F.coalesce(F.sum("__rows"), F.lit(0))).first()[0]
    before = Window.orderBy("__bucket").rowsBetween(Window.unboundedPreceding, -1)
    starts = sizes.select("__bucket", F.coalesce(F.sum("__rows").over(before), F.lit(0)).alias("__start"))
    within = Window.partitionBy("__bucket").orderBy(*[F.col(k).asc_nulls_last() for k in keys]).rowsBetween(Window.unboundedPreceding, -1)
    first = counted.join(F.broadcast(starts), "__bucket").withColumn("__first", F.col("__start") + F.coalesce(F.sum("__copies").over(within), F.lit(0)))
    first = first.select(*keys, "__first", (F.col("__first") + F.col("__copies") - 1).alias("__last"))
    rows = lambda runs: runs.select(*keys, F.explode(F.sequence("__first", "__last")).alias("row_number"))
    long = (F.col("__last") - F.col("__first")) >= RUN_ROWS
    if counted.where(F.col("__copies") > RUN_ROWS).isEmpty():
        return rows(first), n
    at = F.explode(F.sequence(F.col("__first"), F.col("__last"), F.lit(RUN_ROWS))).alias("__from")
    cut = first.where(long).select(*keys, "__last", at).repartition(*keys, "__from")  # long runs of copies go to many tasks
    pieces = cut.select(*keys, F.col("__from").alias("__first"), F.least("__last", F.col("__from") + RUN_ROWS - 1).alias("__last"))
    return rows(first.where(~long)).unionByName(rows(pieces)), n


def feistel_shards(df: DataFrame, keys: list[str], shards: int = 16, seed: int = 20) -> DataFrame:
    """``keys`` with shard and slot, one row per input row."""
    numbered, n = number_rows(df, keys)
    at = permute(F.col("row_number"), max(n, 1), seed)
    return numbered.withColumn("__at", at).select(*keys, (F.col("__at") % shards).cast("int").alias("shard"), _quotient(F.col("__at"), shards).alias("slot"))


def op3_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whole ``documents`` in 16 shards whose row counts differ by one at most."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    keyed = docs.select("doc_id", (F.octet_length(text_or_empty()) + 1).cast("long").alias("size"), F.crc32(text_or_empty().cast("binary")).alias("text_crc32"))
    placed = feistel_shards(keyed, ["doc_id", "size", "text_crc32"])
    return placed.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
