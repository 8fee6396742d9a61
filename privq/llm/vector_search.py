"""Nearest neighbours by a block matrix join with int8 tiles and error bounds.

Queries and candidates are dealt into blocks; a tile is one block of each. In a tile, unit vectors are rounded to int8
with one scale each and multiplied as integers (held in float32, where sums below 2**24 are exact). The rounding
errors' norms bound how far each product is from the true cosine, so a pair whose upper bound is below the k-th lower
bound of its query can't be among the k nearest and is dropped; nothing else is. Surviving pairs are computed again
from the original vectors in double precision, a heap keeps the k best of a tile, and the tiles' heaps are merged. The
result is exact, ties included (to the smaller id).

Vectors that are null, zero or hold a null or non-finite component take no part, nor do null ids. Rows with the
query's own id are no candidates for it. Vectors of different length never meet. Equal vectors of a tile are multiplied
once and keep their k + 1 smallest ids, so a vector that a third of all rows share costs no more than another.
"""

from __future__ import annotations

import heapq

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from privq.llm.common import table

QUERY_BLOCK = 2048
DATA_BLOCK = 8192
HITS = "query_id bigint, vec_id bigint, score double"


def quantise(unit: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Integer rows (as float32), their scales, and the norm of what rounding took away."""
    scale = np.abs(unit).max(axis=1) / 127.0
    scale[scale == 0] = 1.0
    whole = np.rint(unit / scale[:, None])
    return whole.astype(np.float32), scale, np.linalg.norm(unit - whole * scale[:, None], axis=1)


def cosine(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return (a * b).sum(axis=1) / (np.sqrt((a * a).sum(axis=1)) * np.sqrt((b * b).sum(axis=1)))


def search_tile(query_ids: np.ndarray, queries: np.ndarray, ids: np.ndarray, vectors: np.ndarray, k: int) -> list[tuple[int, int, float]]:
    """The k nearest (query, id, cosine) within a tile, for every query."""
    order = np.argsort(ids, kind="stable")
    ids, vectors = ids[order], vectors[order]
    _, first, group = np.unique(vectors.view(np.dtype((np.void, vectors.dtype.itemsize * vectors.shape[1]))).ravel(), return_index=True, return_inverse=True)
    distinct = vectors[first]
    members: list[list[int]] = [[] for _ in first]
    for i, g in zip(ids.tolist(), group.tolist(), strict=True):
        own = members[g]
        if len(own) <= k and (not own or own[-1] != i):
            own.append(i)
    uq, uv = (x / np.linalg.norm(x, axis=1)[:, None] for x in (queries, distinct))
    (iq, sq, eq), (iv, sv, ev) = quantise(uq), quantise(uv)
    near_sum = iq.shape[1] * 127 * 127 < 1 << 24
    out = []
    for lo in range(0, len(queries), 256):
        part = slice(lo, lo + 256)
        product = iq[part] @ iv.T if near_sum else iq[part].astype(np.float64) @ iv.T.astype(np.float64)
        about = product * sq[part, None] * sv[None, :]
        slack = eq[part, None] + ev[None, :] * (1 + eq[part, None]) + 1e-6
        keep = min(k + 1, about.shape[1])  # one more: the query itself may be among them
        bar = np.partition(about - slack, about.shape[1] - keep, axis=1)[:, about.shape[1] - keep]
        rows, columns = np.nonzero(about + slack >= bar[:, None])
        exact = cosine(queries[lo + rows], distinct[columns])
        at = 0
        for r, n in enumerate(np.bincount(rows, minlength=about.shape[0]).tolist()):
            own = int(query_ids[lo + r])
            pairs = ((-s, i) for s, c in zip(exact[at : at + n].tolist(), columns[at : at + n].tolist(), strict=True) for i in members[c] if i != own)
            out += [(own, i, -s) for s, i in heapq.nsmallest(k, pairs)]
            at += n
    return out


def _tile(k: int):
    def run(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        if left.empty or right.empty:
            return pd.DataFrame({"query_id": [], "vec_id": [], "score": []})
        both = [np.array(x["vector"].tolist(), dtype=np.float64) for x in (left, right)]
        hits = search_tile(left["vec_id"].to_numpy(), both[0], right["vec_id"].to_numpy(), both[1], k)
        return pd.DataFrame(hits, columns=["query_id", "vec_id", "score"])

    return run


def usable(df: DataFrame, id_column: str, vector_column: str) -> DataFrame:
    vector = F.col(vector_column)
    finite = F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf")))
    return df.select(df[id_column].cast("long").alias("vec_id"), vector.alias("vector"), F.size(vector).alias("dim")).where(F.col("vec_id").isNotNull() & vector.isNotNull() & finite & F.exists(vector, lambda x: x != 0))


def nearest(vectors: DataFrame, queries: DataFrame, k: int = 5) -> DataFrame:
    """Both frames as ``usable`` gives them. Distinct query ids are expected; a repeated one counts as the first found."""
    queries = queries.dropDuplicates(["vec_id"])
    n_queries, n = queries.count(), vectors.count()
    q_blocks, d_blocks = max(1, -(-n_queries // QUERY_BLOCK)), max(1, -(-n // DATA_BLOCK))
    left = queries.withColumn("qb", F.pmod(F.xxhash64("vec_id"), F.lit(q_blocks)).cast("int")).withColumn("db", F.explode(F.sequence(F.lit(0), F.lit(d_blocks - 1))))
    right = vectors.withColumn("db", F.pmod(F.monotonically_increasing_id(), F.lit(d_blocks)).cast("int")).withColumn("qb", F.explode(F.sequence(F.lit(0), F.lit(q_blocks - 1))))
    tile = ["qb", "db", "dim"]
    hits = left.groupBy(*tile).cogroup(right.groupBy(*tile)).applyInPandas(_tile(k), HITS)
    best = Window.partitionBy("query_id").orderBy(F.col("score").desc(), "vec_id")
    once = hits.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    return once.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def op9_vector_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The 5 nearest of each row whose id is divisible by 50, among all ``embeddings``."""
    vectors = usable(table(spark, sf_dir, "embeddings").select("vec_id", "embedding"), "vec_id", "embedding")
    return nearest(vectors, vectors.where(F.col("vec_id") % 50 == 0), 5)
