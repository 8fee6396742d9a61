"""Mixing sources to target weights with a multivariate-hypergeometric splitting tree.

Targets: weights share a total of words; a target stops at twice its source, and what is over goes to the others by
weight until none is above (water filling, solved exactly from the sorted ratios). A source is cut into hash blocks. A
target of k whole sources plus a rest takes every block k times, then blocks in permuted order until the rest is used
up; of the last block those documents are taken, in permuted order, that still fit, and what is left over is carried on
to documents of the following blocks, until none fits. So a source misses its target by less than the smallest document
with words that the rest left out. Carried documents belong to the draw of the last block.

Every taking of a block is a draw. The tree starts with each source's number of draws, splits the output shards in two
and draws, from the multivariate hypergeometric law, how many draws of each source go left; it goes on to single
shards. Its leaves are exact quotas. A source's draws, already in permuted order, are dealt to the shards by these
quotas, so the blocks of the shards are disjoint, and each shard is shuffled by a keyed hash.

Sizes are words; null text has none. Null sources form one source, the last. Repeated rows are documents of their own
as to size, and fall into the same block. What reaches the driver is one row a source (at most ``MOST_SOURCES``).
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from privq.llm.common import WORD, table, text_or_empty
from privq.sources.scratch import Scratch, materialize

MOST_SOURCES = 1_000_000
MOST_BLOCKS = 65_536


def fill_targets(sizes: list[int], weights: list[float], total: float, most: float = 2.0) -> list[float]:
    """Share ``total`` by weight, no share above ``most`` times its size."""
    caps = [most * s for s in sizes]
    order = sorted(range(len(sizes)), key=lambda k: caps[k] / weights[k])
    left, weight, out = total, float(sum(weights)), [0.0] * len(sizes)
    for k in order:
        share = left * weights[k] / weight if weight > 0 else 0.0
        out[k] = min(caps[k], share)
        left -= out[k]
        weight -= weights[k]
    return out


def split_quotas(draws: list[int], shards: int, seed: int) -> np.ndarray:
    """Draws of each source for each shard (shards x sources); columns add up to ``draws``, rows are even to one."""
    rng = np.random.Generator(np.random.PCG64(seed))
    out = np.zeros((shards, len(draws)), dtype=np.int64)

    def part(lo: int, hi: int, have: np.ndarray) -> None:
        if hi - lo == 1:
            out[lo] = have
            return
        mid = (lo + hi) // 2
        goes = rng.multivariate_hypergeometric(have, int(have.sum()) * (mid - lo) // (hi - lo), method="marginals")
        part(lo, mid, goes)
        part(mid, hi, have - goes)

    if len(draws):
        part(0, shards, np.array(draws, dtype=np.int64))
    return out


def _plan(totals: list, weights: tuple[float, ...], share: float, block_words: int) -> list[dict]:
    """Target, whole passes, rest and number of blocks of each source, by code point, null last."""
    rows = sorted(totals, key=lambda r: (r["source"] is None, r["source"] or ""))
    sizes = [r["words"] for r in rows]
    own = [weights[k % len(weights)] for k in range(len(rows))]
    plan = []
    for r, target in zip(rows, fill_targets(sizes, own, share * sum(sizes)), strict=True):
        whole = int(target // r["words"]) if r["words"] else 0
        plan.append({"source": r["source"], "words": r["words"], "target": target, "whole": whole, "rest": target - whole * r["words"], "blocks": max(1, min(MOST_BLOCKS, -(-r["words"] // block_words)))})
    return plan


_PARAMS = T.StructType([T.StructField("source", T.StringType()), T.StructField("source_size", T.LongType()), T.StructField("target", T.DoubleType()), T.StructField("whole", T.IntegerType()), T.StructField("rest", T.DoubleType()), T.StructField("blocks", T.LongType())])


def _fill_room(edge: DataFrame, keys: list[str], passes: int = 4) -> DataFrame:
    """``more`` = 1 for documents, in permuted order, that fit into their block's room; later passes use up what the
    first document that didn't fit left over."""
    block = Window.partitionBy("source", "block")
    upto = block.orderBy("order", *keys).rowsBetween(Window.unboundedPreceding, 0)
    edge = edge.withColumn("more", F.lit(0))
    for _ in range(passes):
        edge = edge.withColumn("__left", F.col("room") - F.sum(F.col("more") * F.col("size")).over(block))
        fits = (F.col("more") == 0) & (F.col("size") <= F.col("__left"))
        edge = edge.withColumn("__until", F.sum(F.when(fits, F.col("size")).otherwise(0)).over(upto))
        edge = edge.withColumn("more", F.when(fits & (F.col("__until") <= F.col("__left")), 1).otherwise(F.col("more")))
    return edge.drop("__left", "__until")


def _carry(edge: DataFrame, later: DataFrame, keys: list[str]) -> DataFrame:
    """``edge`` and ``later`` with ``more`` = 1 too for documents that use up what the edge blocks left over.

    A round takes, by block, all that fits what is left of the source, and fills the block in which that runs out. A
    round takes a document at least, and the last one finds that none fits.
    """
    spark, given = edge.sparkSession, edge.columns
    edge = materialize(edge, "mix-edge")
    left = {r["source"]: r["left"] for r in edge.groupBy("source").agg((F.max("room") - F.sum(F.col("more") * F.col("size"))).alias("left")).collect()}
    if not left:
        return edge.unionByName(later)

    def with_left(rows: DataFrame) -> DataFrame:
        known = spark.createDataFrame(list(left.items()), "l_source string, left double")
        return rows.join(F.broadcast(known), F.col("source").eqNullSafe(F.col("l_source")), "left").drop("l_source").withColumn("left", F.coalesce("left", F.lit(0.0)))

    able = (F.col("more") == 0) & (F.col("size") > 0) & (F.col("size") <= F.col("left"))
    every = with_left(edge.unionByName(later))
    others, open_ = every.where(~able).select(*given), materialize(every.where(able).select(*given), "mix-open")
    upto = Window.partitionBy("source").orderBy("ordinal").rowsBetween(Window.unboundedPreceding, 0)
    while True:
        now = with_left(open_)
        blocks = now.where(able).groupBy("source", "ordinal", "left").agg(F.sum("size").alias("fits"))
        if blocks.isEmpty():
            return others.unionByName(open_)
        blocks = blocks.select(F.col("source").alias("b_source"), F.col("ordinal").alias("b_ordinal"), "fits", (F.col("left") - F.sum("fits").over(upto) + F.col("fits")).alias("b_room"))
        met = now.where(able).drop("room").join(blocks, F.col("source").eqNullSafe(F.col("b_source")) & (F.col("ordinal") == F.col("b_ordinal"))).withColumnRenamed("b_room", "room")
        cut = (F.col("room") > 0) & (F.col("room") < F.col("fits"))
        taken = _fill_room(met.where(cut), keys).select(*given).unionByName(met.where(~cut).withColumn("more", (F.col("room") > 0).cast("int")).select(*given))
        taken = materialize(taken, "mix-open")
        for r in taken.groupBy("source").agg(F.sum(F.col("more") * F.col("size")).alias("words")).collect():
            left[r["source"]] -= r["words"]
        open_ = now.where(~able).select(*given).unionByName(taken)


def plan_mix(docs: DataFrame, keys: list[str], weights: tuple[float, ...] = (5.0, 2.0, 1.0), share: float = 1.5, shards: int = 16, seed: int = 20, block_words: int = 50_000) -> DataFrame:
    """``docs`` (keys, source, size) with source_size, target, times and the shard of each taking.

    ``docs`` is read several times and should be narrow and stored. One document is taken at most twice.
    """
    spark = docs.sparkSession
    totals = docs.groupBy("source").agg(F.sum("size").alias("words")).limit(MOST_SOURCES + 1).collect()
    if len(totals) > MOST_SOURCES:
        raise ValueError(f"more than {MOST_SOURCES} sources")
    plan = _plan(totals, weights, share, block_words)
    params = spark.createDataFrame([(p["source"], p["words"], p["target"], p["whole"], p["rest"], p["blocks"]) for p in plan], _PARAMS)
    hashed = F.xxhash64(*keys, F.lit(seed))
    blocked = docs.join(F.broadcast(params), docs["source"].eqNullSafe(params["source"])).drop(params["source"]).withColumn("block", F.pmod(hashed, F.col("blocks"))).withColumn("order", F.xxhash64(*keys, F.lit(seed + 1)))
    by_order = Window.partitionBy("source").orderBy(F.xxhash64("block", F.lit(seed)), "block")
    blocks = blocked.groupBy("source", "block", "rest").agg(F.sum("size").alias("block_words"))
    placed = blocks.select("source", "block", "rest", (F.row_number().over(by_order) - 1).cast("long").alias("ordinal"), F.sum("block_words").over(by_order.rowsBetween(Window.unboundedPreceding, 0)).alias("until"), "block_words")
    placed = materialize(placed.select("source", "block", "ordinal", (F.col("rest") - (F.col("until") - F.col("block_words"))).alias("room"), "block_words"), "mix-blocks")

    counts = {r["source"]: (r["n"], r["used"]) for r in placed.groupBy("source").agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("room") > 0).cast("long")).alias("used")).collect()}
    draws = [p["whole"] * counts.get(p["source"], (0, 0))[0] + counts.get(p["source"], (0, 0))[1] for p in plan]
    ends = split_quotas(draws, shards, seed).cumsum(axis=0)
    dealt = spark.createDataFrame([(p["source"], counts.get(p["source"], (0, 0))[0], counts.get(p["source"], (0, 0))[1], [int(x) for x in ends[:, k]]) for k, p in enumerate(plan)], "d_source string, n_blocks long, used long, ends array<long>")

    located = blocked.join(placed.withColumnRenamed("source", "p_source").withColumnRenamed("block", "p_block"), F.col("source").eqNullSafe(F.col("p_source")) & (F.col("block") == F.col("p_block"))).drop("p_source", "p_block")
    last = (F.col("room") > 0) & (F.col("room") < F.col("block_words"))
    rest = located.where(~last).withColumn("more", (F.col("room") > 0).cast("int"))
    carried = _carry(_fill_room(located.where(last), keys), rest.where("more = 0"), keys)
    taken = rest.where("more = 1").unionByName(carried).join(F.broadcast(dealt), F.col("source").eqNullSafe(F.col("d_source"))).drop("d_source")
    times = F.col("whole") + F.col("more")
    numbers = F.transform(F.sequence(F.lit(0), times - 1), lambda k: k * F.col("n_blocks") + F.when(k == F.col("whole"), F.least("ordinal", F.col("used") - 1)).otherwise(F.col("ordinal")))
    in_shards = F.transform(numbers, lambda d: F.size(F.filter("ends", lambda e: e <= d)))
    return taken.select(*docs.columns, "source_size", "target", times.alias("times"), F.when(times > 0, in_shards).otherwise(F.array().cast("array<int>")).alias("shards"))


def draws(planned: DataFrame, keys: list[str], seed: int = 20) -> DataFrame:
    """One row per taking of a planned document, with its shard and shuffle key."""
    drawn = planned.where("times > 0").select(*[c for c in planned.columns if c != "shards"], F.posexplode("shards").alias("pass", "shard"))
    return drawn.withColumn("shuffle_key", F.xxhash64(*keys, "pass", "shard", F.lit(seed)))


def write_mix(mixed: DataFrame, path: str, parts: int = 64) -> None:
    """Shuffled shards as files: rows go to a part of their shard by shuffle key and are sorted there."""
    part = F.pmod(F.col("shuffle_key"), F.lit(parts)).cast("int")
    mixed.withColumn("part", part).repartition("shard", "part").sortWithinPartitions("shard", "part", "shuffle_key").write.partitionBy("shard").parquet(path)


def mix_documents(docs: DataFrame, id_column: str = "doc_id", text: str = "text", source: str = "source", parts: int = 64, **options) -> DataFrame:
    """Rows of ``docs`` as often as the mix takes them, shard after shard, shuffled within each.

    The plan is made on a stored narrow frame without texts; rows that agree in id, source and text are one unit there,
    taken or left together. Texts are shuffled twice: to the plan's rows, and to their place in the shards.
    """
    names = {"__mix_id": docs[id_column], "__mix_source": docs[source].cast("string"), "__mix_digest": F.xxhash64(docs[text])}
    words = F.regexp_count(text_or_empty(text), F.lit(WORD)).cast("long")
    steps = Scratch(docs.sparkSession)
    narrow = docs.select(*[c.alias(n) for n, c in names.items()], words.alias("size")).withColumnRenamed("__mix_source", "source")
    units = steps.store(narrow.groupBy("__mix_id", "source", "__mix_digest").agg(F.sum("size").alias("size")), "mix-units")
    keys = ["__mix_id", "__mix_digest"]
    drawn = steps.store(draws(plan_mix(units, keys, **options), keys).select(*keys, F.col("source").alias("__mix_source"), F.col("shard").alias("__mix_shard"), "shuffle_key").withColumnRenamed("shuffle_key", "__mix_order"), "mix-draws")
    met = [c.eqNullSafe(drawn[n]) for n, c in names.items()]
    placed = docs.join(drawn, met[0] & met[1] & met[2])
    return placed.repartition("__mix_shard", F.pmod("__mix_order", F.lit(parts))).sortWithinPartitions("__mix_shard", "__mix_order").select(*[docs[c] for c in docs.columns])


def sizes_of(docs: DataFrame) -> DataFrame:
    return docs.select("doc_id", F.col("source").cast("string").alias("source"), F.regexp_count(text_or_empty(), F.lit(WORD)).cast("long").alias("size"))


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whole ``documents`` mixed to weights 5, 2, 1 and 150% of all words."""
    docs = materialize(sizes_of(table(spark, sf_dir, "documents").select("doc_id", "source", "text")), "mix-sizes")
    planned = plan_mix(docs, ["doc_id", "size"])
    return planned.select("doc_id", "size", "source_size", "target", (F.col("times") * F.col("size")).cast("long").alias("taken"), "source", "times", "shards")
