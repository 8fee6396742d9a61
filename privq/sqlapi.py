"""SQL entry points: table functions, SQL functions for keyed noise, temporary views."""

from __future__ import annotations

import math
from array import array
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf
from pyspark.sql.types import Row

from privq.functions import local
from privq.functions.domain import Domain
from privq.operators.slices import COUNT_SHARE
from privq.plans import accountant, counting, ranks

#: Rows that a table function holds of one partition.
MOST_ROWS = 100_000_000


@udtf(returnType="i int, q double, r bigint, rt bigint, lo bigint, hi bigint")
class RankWindows:
    """rank_windows(n, qs, psi, eps, delta, adjacency, key): target ranks, noisy ranks and the windows to read."""

    def eval(self, n: int, qs: list, psi: float, eps: float, delta: float, adjacency: str, key: str) -> Iterator[tuple]:
        p = accountant.plan(len(qs), n, float(psi), float(eps), float(delta), adjacency)
        target = ranks.target_ranks(qs, n)
        ranks.precheck(target, n, p.w, p.h)
        noisy = counting.rank_noise(target, p.eps1, p.arity, key)
        for i, (q, r, t) in enumerate(zip(qs, target, noisy, strict=True), 1):
            yield i, float(q), r, t, t - p.h, t + p.h


@udtf(returnType="grp string, i int, q double, z double")
class PrivateQuantiles:
    """private_quantiles(TABLE(t) PARTITION BY (grp), qs, lo, hi, eps, delta, key): one release a partition.

    The table has columns grp and value. A partition is held in one task as numbers of 8 bytes, at most ``MOST_ROWS`` of
    them: beyond it the function refuses (use ``grouped_release``). The number of rows is noisy, at a share of eps. A
    group without room gives random values.
    """

    def __init__(self) -> None:
        self.values = array("d")
        self.options: tuple | None = None
        self.group: str | None = None

    def eval(self, row: Row, qs: list, lo: float, hi: float, eps: float, delta: float, key: str) -> None:
        self.group, self.options = row["grp"], (qs, float(lo), float(hi), float(eps), float(delta), key)
        if row["value"] is not None:
            if len(self.values) >= MOST_ROWS:
                raise ValueError(f"a group has more than {MOST_ROWS} rows")
            self.values.append(min(float(hi), max(float(lo), float(row["value"]))))

    def terminate(self) -> Iterator[tuple]:
        if self.options is None:
            return
        qs, lo, hi, eps, delta, key = self.options
        own = f"{key}/{self.group}"
        p = accountant.plan(len(qs), 0, hi - lo, eps * (1 - COUNT_SHARE), delta)
        n = local.noisy_count(len(self.values), eps * COUNT_SHARE, own)
        z, _ = local.release_keyed(np.sort(np.array(self.values)), qs, p, lo, hi, own, n)
        for i, (q, v) in enumerate(zip(qs, z, strict=True), 1):
            yield self.group, i, float(q), float(v)


def private_quantile(q: float, eps: float, domain: Domain, key: str):
    """Aggregate (value, group name) for small groups: the interval selector over a whole group, at cost eps.

    The name, one a group, goes into the key of the noise.
    """

    def pick(values: pd.Series, names: pd.Series) -> float:
        x = np.sort(np.clip(values.dropna().to_numpy(float), domain.lo, domain.hi))
        return local.pick_keyed(x.tolist(), eps, domain.lo, domain.hi, math.floor(q * len(x)), key, str(names.iloc[0]))

    pick.__annotations__ = {"values": pd.Series, "names": pd.Series, "return": float}
    return F.pandas_udf(pick, "double")


_TWO52 = "4503599627370496D"


def _digit_block(k: int) -> str:
    return f"CAST(conv(substr(d, {13 * k + 1}, 13), 16, 10) AS DOUBLE)"


def _sized(k: int) -> str:
    return f"({_digit_block(k)} + ({_digit_block(k + 1)} + 0.5D) / {_TWO52}) / {' / '.join([_TWO52] * (k + 1))}"


#: Parameters, result and body of each SQL function.
FUNCTIONS = {
    "digest_uniform": ("d STRING", "DOUBLE", f"least(CASE WHEN {_digit_block(0)} > 0 THEN {_sized(0)} WHEN {_digit_block(1)} > 0 THEN {_sized(1)} ELSE {_sized(2)} END, {1 - 2.0**-53!r}D)"),
    "prf_uniform": ("k STRING, tag STRING, i BIGINT", "DOUBLE", "digest_uniform(sha2(concat(k, ':', tag, ':', CAST(i AS STRING)), 256))"),
    "gumbel": ("k STRING, tag STRING, i BIGINT", "DOUBLE", "-ln(CASE WHEN prf_uniform(k, tag, i) < 1e-5D THEN prf_uniform(k, tag, i) * (1 + prf_uniform(k, tag, i) * (0.5D + prf_uniform(k, tag, i) / 3)) ELSE -ln(1 - prf_uniform(k, tag, i)) END)"),
    "two_sided_geometric": ("k STRING, tag STRING, i BIGINT, scale DOUBLE", "BIGINT", "CAST(floor(ln(prf_uniform(k, concat(tag, ':', CAST(i AS STRING)), 0)) / (-1D / scale)) - floor(ln(prf_uniform(k, concat(tag, ':', CAST(i AS STRING)), 1)) / (-1D / scale)) AS BIGINT)"),
    "laplace": ("k STRING, tag STRING, i BIGINT, scale DOUBLE", "DOUBLE", "IF(prf_uniform(k, concat(tag, ':', CAST(i AS STRING)), 1) < 0.5D, 1D, -1D) * scale * ln(prf_uniform(k, concat(tag, ':', CAST(i AS STRING)), 0))"),
    "clamp_to": ("x DOUBLE, lo DOUBLE, hi DOUBLE", "DOUBLE", "greatest(lo, least(hi, x))"),
    "target_rank": ("q DOUBLE, n BIGINT", "BIGINT", "CAST(floor(q * n + 1e-9D) AS BIGINT)"),
    "half_width": ("m INT, psi DOUBLE, beta DOUBLE, eps2 DOUBLE", "BIGINT", "CAST(ceil(2 * ln(2 * m * psi / beta) / eps2) AS BIGINT)"),
    "rank_error": ("below BIGINT, q DOUBLE, n BIGINT", "BIGINT", "abs(below - CAST(floor(q * n + 1e-9D) AS BIGINT))"),
}


def register(spark: SparkSession, views: dict | None = None) -> None:
    """Make the functions, the table functions and the given frames known to SQL in this session."""
    for name, (parameters, returns, body) in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({parameters}) RETURNS {returns} RETURN {body}")
    spark.udtf.register("rank_windows", RankWindows)
    spark.udtf.register("private_quantiles", PrivateQuantiles)
    for name, df in (views or {}).items():
        df.createOrReplaceTempView(name)


def release_map(q: Column, z: Column) -> Column:
    """Aggregate of a release into a map from quantile to estimate."""
    return F.map_from_entries(F.collect_list(F.struct(q, z)))
