"""Queries over the given tables, one for each method, variant, baseline, measure and workload, and their SQL."""

from __future__ import annotations

import datetime as dt
import functools
from collections.abc import Callable
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from privq import oracle as sql
from privq.functions import prf
from privq.functions.domain import Domain, separate, to_domain, to_unit
from privq.operators import baselines, bisection, experiments, grouped, locate, measures, select, slices
from privq.plans import accountant, counting, ranks, tails
from privq.relational import PAIRS
from privq.sources import io
from privq.sources.scratch import materialize
from privq.streaming import windows

KEY = sql.KEY
Query = Callable[[SparkSession, str], DataFrame]
DECILES = ranks.even_quantiles(9)
QUARTILES = ranks.even_quantiles(3)

PRICE = ("lineitem", "l_extendedprice", Domain(0.0, 131072.0))
QUANTITY = ("lineitem", "l_quantity", Domain(0.0, 64.0))
TOTAL = ("orders", "o_totalprice", Domain(0.0, 524288.0))
SHIP_DAY = ("lineitem", "datediff(l_shipdate, DATE'1970-01-01')", Domain(9131.0, 11688.0))
EVENT = ("events", "value", Domain(0.0, 1024.0))
CHARS = ("documents", "n_chars", Domain(0.0, 262144.0))
BALANCE = ("customer", "c_acctbal", Domain(-1024.0, 16384.0))
HTML = ("pages", "length(html)", Domain(0.0, 262144.0))
COORDINATE = ("embeddings", "element_at(embedding, 1)", Domain(-1.0, 1.0, 1e-4))
PROPS = ("events", "CAST(get_json_object(props, '$.k') AS DOUBLE)", Domain(0.0, 128.0))
SIZE = ("part", "p_size", Domain(0.0, 64.0))
#: The sweep of the experiments, and their runs a point.
SWEEP, RUNS = list(range(10, 201, 10)), 200
#: Expressions that DuckDB writes in another way.
IN_DUCKDB = {
    SHIP_DAY[1]: "date_diff('day', DATE '1970-01-01', CAST(l_shipdate AS DATE))",
    COORDINATE[1]: "embedding[1]",
    PROPS[1]: "CAST(json_extract_string(props, '$.k') AS DOUBLE)",
    "datediff(o_orderdate, DATE'1970-01-01')": "date_diff('day', DATE '1970-01-01', CAST(o_orderdate AS DATE))",
    "unix_micros(CAST(ts AS TIMESTAMP)) / 1e6 - 1704067200": "epoch_us(ts) / 1e6 - 1704067200",
}


@dataclass
class Release:
    """A query that releases quantiles of one column, and its SQL."""

    source: tuple[str, str, Domain]
    qs: list[float] = field(default_factory=lambda: list(DECILES))
    eps: float = 1.0
    delta: float = 1e-16
    adjacency: str = "add_remove"
    gamma: float = 0.0
    clip: str = "none"
    fixed: bool = False
    monotone: bool = False

    @property
    def count_eps(self) -> float | None:
        """What a noisy number of rows costs; under substitute adjacency the number is public."""
        return self.eps * slices.COUNT_SHARE if self.adjacency == "add_remove" else None

    @property
    def plan(self) -> accountant.Plan:
        d = self.source[2]
        pure = {"gamma": self.gamma, "grid_size": int(d.hi - d.lo) + 1} if self.gamma else {}
        left = self.eps * (1 - slices.COUNT_SHARE) if self.count_eps else self.eps
        return accountant.plan(len(self.qs), 0, d.psi, left, 0.0 if self.gamma else self.delta, self.adjacency, **pure)

    def run(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        _, _, d = self.source
        values = column(spark, sf_dir, self.source)
        index = locate.Index(values, d)
        n = slices.noisy_count(index.n, self.count_eps, KEY) if self.count_eps else None
        if self.fixed:
            out = slices.fixed_slices(values, self.qs, self.plan, d, KEY, n, index)
        else:
            out = slices.release(values, self.qs, self.plan, d, KEY, n, self.clip, monotone=self.monotone, index=index)
        return out.select("i", "q", F.round("z", 6).alias("z"))

    @property
    def sql(self) -> str:
        relation, expr, d = self.source
        p = replace(self.plan, eps2=self.plan.eps / len(self.qs)) if self.fixed else self.plan
        text = sql.release(relation, IN_DUCKDB.get(expr, expr), d, self.qs, p, not self.fixed, 6, self.count_eps, self.clip == "adaptive")
        if not self.monotone:
            return text
        return f"SELECT a.i, a.q, b.z FROM (SELECT *, row_number() OVER (ORDER BY i) AS k FROM ({text})) a JOIN (SELECT z, row_number() OVER (ORDER BY z) AS k FROM ({text})) b USING (k)"


def column(spark: SparkSession, sf_dir: str, source: tuple[str, str, Domain]) -> DataFrame:
    relation, expr, d = source
    return to_domain(io.table(spark, sf_dir, relation).select(F.expr(expr).alias("x")), "x", d)


def _cte(source: tuple[str, str, Domain]) -> str:
    return sql.values_cte(source[0], IN_DUCKDB.get(source[1], source[1]), source[2])


RELEASES = {
    "private_deciles_price_addremove": Release(PRICE),
    "private_deciles_price_substitute": Release(PRICE, adjacency="substitute"),
    "private_quartiles_pure": Release(QUANTITY, QUARTILES, gamma=0.01),
    "private_deciles_price_pure": Release(PRICE, gamma=0.01),
    "private_median_shipdate": Release(SHIP_DAY, [0.5]),
    "private_deciles_quantity_ties": Release(QUANTITY),
    "private_quantiles_events": Release(EVENT, ranks.even_quantiles(4)),
    "private_quantiles_totalprice": Release(TOTAL),
    "private_quantiles_nchars": Release(CHARS, [0.5], delta=1e-6, eps=2.0),
    "private_quantiles_acctbal": Release(BALANCE, [0.5]),
    "private_html_length": Release(HTML, [0.5], delta=1e-6, eps=4.0),
    "private_embedding_coordinate": Release(COORDINATE, [0.5], delta=1e-6, eps=4.0),
    "private_json_property": Release(PROPS, QUARTILES),
    "private_part_size": Release(SIZE, [0.5], delta=1e-6),
    "fixed_slices_price": Release(PRICE, fixed=True),
    "private_deciles_adaptive": Release(PRICE, clip="adaptive"),
    "private_deciles_adaptive_substitute": Release(PRICE, adjacency="substitute", clip="adaptive"),
    "private_deciles_monotone": Release(QUANTITY, eps=0.5, delta=1e-6, monotone=True),
    "private_quartiles_discount": Release(("lineitem", "l_discount", Domain(0.0, 0.125, 1e-4)), QUARTILES),
    "private_quartiles_tax": Release(("lineitem", "l_tax", Domain(0.0, 0.125, 1e-4)), QUARTILES),
    "private_median_orderdate": Release(("orders", "datediff(o_orderdate, DATE'1970-01-01')", Domain(9131.0, 11688.0)), [0.5]),
    "private_median_retailprice": Release(("part", "p_retailprice", Domain(512.0, 1024.0, 0.01)), [0.5], delta=1e-6),
    "private_median_turn_length": Release(("conversations", "length(text)", Domain(0.0, 65536.0)), [0.5], delta=1e-6, eps=4.0),
    "private_quartiles_event_time": Release(("events", "unix_micros(CAST(ts AS TIMESTAMP)) / 1e6 - 1704067200", Domain(0.0, 2678400.0)), QUARTILES),
}


def target_ranks_deciles(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ranks.target_ranks_frame(spark, DECILES, io.table(spark, sf_dir, "lineitem").count())


def feasible_gap_check(spark: SparkSession, sf_dir: str, margin: int = 150) -> DataFrame:
    n = io.table(spark, sf_dir, "orders").count()
    rows = spark.range(1, 31).toDF("m").select("m", F.explode(F.sequence(F.lit(1), F.col("m"))).alias("i"))
    rows = rows.withColumn("r", F.floor(F.col("i") / (F.col("m") + 1) * n + F.lit(1e-9)))
    rows = rows.withColumn("step", F.col("r") - F.lag("r").over(Window.partitionBy("m").orderBy("i")))
    fits = F.bool_and((F.coalesce("step", F.lit(1 << 60)) > 2 * margin) & (F.col("r") - margin >= 1) & (F.col("r") <= n - margin))
    return rows.groupBy("m").agg(fits.alias("feasible"))


FEASIBLE_SQL = """WITH n AS (SELECT count(*) AS n FROM orders), r AS (
    SELECT m, i, CAST(floor(i / CAST(m + 1 AS DOUBLE) * n + 1e-9) AS BIGINT) AS r FROM range(1, 31) AS a(m), range(1, 31) AS b(i), n WHERE i <= m),
  s AS (SELECT m, r, r - lag(r) OVER (PARTITION BY m ORDER BY i) AS step FROM r)
  SELECT m, bool_and(coalesce(step, 1152921504606846976) > 300 AND r - 150 >= 1 AND r <= n - 150) AS feasible FROM s, n GROUP BY m"""


def merge_close_quantiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    """400 even quantiles of orders, merged to what the plan can answer."""
    qs = ranks.even_quantiles(400)
    n = io.table(spark, sf_dir, "orders").count()
    p = accountant.plan(9, n, TOTAL[2].psi, 1.0, 1e-16)
    reps, of = ranks.merge_close(qs, n, p.w, p.h)
    return spark.createDataFrame([(i + 1, float(q), k + 1, float(reps[k])) for i, (q, k) in enumerate(zip(qs, of, strict=True))], "i int, q double, representative int, rep_q double")


def _merge_sql() -> str:
    p = accountant.plan(9, 0, TOTAL[2].psi, 1.0, 1e-16)
    return f"""WITH RECURSIVE n AS (SELECT count(*) AS n FROM orders),
    t AS (SELECT i, i / 401.0::DOUBLE AS q, least(greatest(CAST(floor(i / 401.0::DOUBLE * n + 1e-9) AS BIGINT), {p.margin + 1}), n - {p.margin}) AS moved, n FROM range(1, 401) AS x(i), n),
    g(i, kept, k) AS (SELECT i, moved, 1 FROM t WHERE i = 1 UNION ALL
      SELECT t.i, CASE WHEN t.moved - g.kept > {2 * p.margin + 1} THEN t.moved ELSE g.kept END, g.k + CAST(t.moved - g.kept > {2 * p.margin + 1} AS INTEGER) FROM g JOIN t ON t.i = g.i + 1)
    SELECT CAST(t.i AS INTEGER) AS i, t.q AS q, g.k AS representative, (g.kept + 0.25::DOUBLE) / t.n AS rep_q FROM g JOIN t ON t.i = g.i"""


#: Quantiles that the merged release plans for; n rows leave room for fewer representatives.
MERGED_FOR = 32


def merged_release(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A grid finer than the gap: representatives are released and copied to the members."""
    index = locate.Index(column(spark, sf_dir, TOTAL), TOTAL[2])
    n = slices.noisy_count(index.n, slices.COUNT_SHARE, KEY)
    p = accountant.plan(MERGED_FOR, 0, TOTAL[2].psi, 1.0 - slices.COUNT_SHARE, 1e-16)
    qs, of = ranks.merge_close(ranks.even_quantiles(400), n, p.w, p.h)
    while len(qs) > p.m:  # a plan for more quantiles needs wider gaps
        p = accountant.plan(len(qs), 0, TOTAL[2].psi, 1.0 - slices.COUNT_SHARE, 1e-16)
        qs, of = ranks.merge_close(ranks.even_quantiles(400), n, p.w, p.h)
    z = slices.release(index.values, qs, p, TOTAL[2], KEY, n, "none", index=index)
    members = spark.createDataFrame([(i + 1, k + 1) for i, k in enumerate(of)], "member int, i int")
    return members.join(z, "i").select(F.col("member").alias("i"), F.round("z", 6).alias("z"))


def trial_quantile_sample(spark: SparkSession, sf_dir: str, trials: int = 5, m: int = 20) -> DataFrame:
    rows = spark.range(trials).toDF("trial").crossJoin(spark.range(1, 251).toDF("g"))
    order = Window.partitionBy("trial").orderBy(prf.uniform(KEY, "grid", F.col("trial"), F.col("g")), "g")
    return rows.withColumn("k", F.row_number().over(order)).where(F.col("k") <= m).select("trial", "g", (F.col("g") / 251.0).alias("q"))


SAMPLE_SQL = f"SELECT trial, g, g / 251.0::DOUBLE AS q FROM (SELECT trial, g, row_number() OVER (PARTITION BY trial ORDER BY {sql.uniform(chr(39) + 'grid' + chr(39), 'trial', 'g')}, g) AS k FROM range(5) AS a(trial), range(1, 251) AS b(g)) WHERE k <= 20"


def geometric_noise(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.range(5000).select("id", prf.two_sided_geometric(KEY, 20.0, "tsg", F.col("id")).alias("z"))


def rank_noise(arity: int, m: int = 60, eps: float = 0.5) -> Query:
    return lambda spark, sf_dir: counting.prefix_noise_frame(spark, m, eps, arity, KEY).select("i", "noise")


def rank_noise_sql(arity: int, m: int = 60, eps: float = 0.5) -> str:
    return f"SELECT CAST(i AS BIGINT) AS i, noise FROM ({sql.prefix_noise(m, eps, arity)})"


def rank_noise_binary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Noisy running counts of the orders over 60 parts of the table, by the binary tree."""
    parts = io.table(spark, sf_dir, "orders", "o_orderkey").groupBy((F.pmod("o_orderkey", F.lit(60)) + 1).alias("i")).agg(F.count("o_orderkey").alias("n"))
    upto = parts.select("i", F.sum("n").over(Window.orderBy("i").rowsBetween(Window.unboundedPreceding, 0)).alias("rows"))  # 60 rows
    return rank_noise(2)(spark, sf_dir).join(upto, "i").select("i", "rows", "noise", (F.col("rows") + F.col("noise")).alias("noisy"))


def rank_noise_laplace(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = [(i, s, level, t) for i in range(1, 31) for s, level, t in counting.nodes(i, 30, 3)]
    nodes = spark.createDataFrame(rows, "i int, s int, l int, t int")
    z = prf.laplace(KEY, counting.node_scale(30, 0.5, 3), "cc", F.col("l"), F.col("t"))
    return nodes.groupBy("i").agg(F.round(F.sum(F.col("s") * z)).cast("bigint").alias("noise"))


def rank_noise_independent(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.range(1, 61).toDF("i").select("i", prf.two_sided_geometric(KEY, 120.0, "ind", F.col("i")).alias("noise"))


def noise_sup_norm(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Largest stray of the noisy ranks in each of 20 parts of the orders; ranks stay within the part's rows."""
    parts = io.table(spark, sf_dir, "orders", "o_orderkey").groupBy(F.pmod("o_orderkey", F.lit(20)).alias("trial")).agg(F.count("o_orderkey").alias("n"))
    noise = counting.prefix_noise_frame(spark, 30, 1.0, 5, KEY, spark.range(20).toDF("trial")).join(F.broadcast(parts), "trial")
    r = F.floor(F.col("i") / 31 * F.col("n") + F.lit(1e-9))
    return measures.noise_sup(noise.withColumn("noise", F.greatest(F.lit(1), F.least("n", r + F.col("noise"))) - r))


NOISE_SUP_SQL = f"""WITH z AS (SELECT trial, i, CAST(sum(s * {sql.geometric(counting.node_scale(30, 1.0, 5), 'trial', chr(39) + 'cc' + chr(39), 'l', 't')}) AS BIGINT) AS noise FROM {sql.node_rows(30, 5)}, range(20) AS x(trial) GROUP BY trial, i),
  r AS (SELECT trial, noise, n, CAST(floor(i / 31.0::DOUBLE * n + 1e-9) AS BIGINT) AS r FROM z JOIN (SELECT o_orderkey % 20 AS trial, count(*) AS n FROM orders GROUP BY 1) USING (trial))
  SELECT trial, max(abs(greatest(1, least(n, r + noise)) - r)) AS sup_norm FROM r GROUP BY trial"""


def plain_slices(source: tuple[str, str, Domain], h: int) -> tuple[Query, str]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        index = locate.Index(column(spark, sf_dir, source), source[2], cap=1000)
        return locate.slices(index, ranks.target_ranks(DECILES, index.n), h).select("i", "pos", "x")

    text = f"""WITH {_cte(source)}, r AS (SELECT i, CAST(floor(q * n + 1e-9) AS BIGINT) AS r FROM {sql.quantile_rows(DECILES)}, n)
      SELECT CAST(i AS INTEGER) AS i, CAST(rn - r + {h + 1} AS BIGINT) AS pos, value AS x FROM o JOIN r ON rn BETWEEN r - {h} AND r + {h}"""
    return run, text


def exact_quantiles_totalprice(spark: SparkSession, sf_dir: str) -> DataFrame:
    return locate.exact_quantiles(column(spark, sf_dir, TOTAL), TOTAL[2], ranks.even_quantiles(99))


EXACT_SQL = f"""WITH {_cte(TOTAL)} SELECT CAST(i AS INTEGER) AS i, q, greatest(1, CAST(floor(q * n + 1e-9) AS BIGINT)) AS r, value AS x
  FROM {sql.quantile_rows(ranks.even_quantiles(99))}, n, o WHERE rn = greatest(1, CAST(floor(q * n + 1e-9) AS BIGINT))"""

_H = 40


def _price_slices(spark: SparkSession, sf_dir: str) -> DataFrame:
    index = locate.Index(column(spark, sf_dir, PRICE), PRICE[2])
    return locate.slices(index, ranks.target_ranks(QUARTILES, index.n), _H)


_SLICE_SQL = f"WITH {_cte(PRICE)}, r AS (SELECT i, CAST(floor(q * n + 1e-9) AS BIGINT) AS r FROM {sql.quantile_rows(QUARTILES)}, n), s AS (SELECT i, rn - r + {_H + 1} AS pos, value AS x FROM o JOIN r ON rn BETWEEN r - {_H} AND r + {_H})"


def interval_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = PRICE[2]
    cuts = select.intervals(_price_slices(spark, sf_dir), F.lit(d.lo), F.lit(d.hi), _H)
    return select.scores(cuts, 0.25, _H + 0.5, KEY).select("i", "j", F.round("log_weight", 6).alias("log_weight"), F.round("score", 6).alias("score"))


def select_interval_query(target: float | None = None, grid: bool = False) -> tuple[Query, str]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return select.select_interval(_price_slices(spark, sf_dir), 0.25, PRICE[2], _H, KEY, target, grid=grid).select("i", F.round("z", 6).alias("z"))

    return run, f"{_SLICE_SQL}, {sql.select_sql('s', 0.25, PRICE[2], _H, target, grid)} SELECT CAST(i AS INTEGER) AS i, round(z, 6) AS z FROM picked"


def select_interval_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    arrays = _price_slices(spark, sf_dir).groupBy("i").agg(F.array_sort(F.collect_list("x")).alias("points"))
    return arrays.select("i", F.round(select.select_interval_array(F.col("points"), 0.25, PRICE[2], KEY, F.col("i")), 6).alias("z"))


def select_pluggable(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Any routine per slice; here the plain median."""
    return select.select_with(_price_slices(spark, sf_dir), lambda points: points[len(points) // 2])


PLUGGABLE_SQL = f"{_SLICE_SQL} SELECT CAST(i AS INTEGER) AS i, x AS z FROM s WHERE pos = {_H + 1}"


def random_release(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What a failed release of the prices looks like: values without a look at the data, and how many prices are below."""
    made = slices.random_release(spark, DECILES, PRICE[2], KEY).select("i", "q", F.round("z", 6).alias("z"))
    ranked = measures.rank_of(column(spark, sf_dir, PRICE), [r["z"] for r in made.orderBy("i").collect()])
    return made.join(ranked.select("i", "below"), "i")


RANDOM_SQL = f"WITH {_cte(PRICE)}, z AS (SELECT CAST(i AS INTEGER) AS i, q, round({sql.uniform(chr(39) + 'rnd' + chr(39), 'i')} * 131072.0, 6) AS z FROM {sql.quantile_rows(DECILES)}) SELECT i, q, z, (SELECT count(*) FROM v WHERE value < z.z) AS below FROM z"


def bisection_query(composition: str, adjacency: str = "add_remove", qs: list[float] = DECILES) -> tuple[Query, str]:
    level = accountant.bisection_level_eps(len(qs), 1.0, 1e-16, composition, adjacency)

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return bisection.bisection(column(spark, sf_dir, TOTAL), qs, level, TOTAL[2], KEY).select("i", "q", F.round("z", 6).alias("z"))

    return run, sql.bisection(*TOTAL, qs, level)


def independent_query(composition: str = "pure") -> tuple[Query, str]:
    each = accountant.independent_eps(len(DECILES), 1.0, 1e-16, composition)

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return bisection.independent(column(spark, sf_dir, TOTAL), DECILES, each, TOTAL[2], KEY).select("i", "q", F.round("z", 6).alias("z"))

    return run, sql.independent(*TOTAL, DECILES, each)


def histogram_query(bins: int) -> tuple[Query, str]:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return baselines.histogram_quantiles(column(spark, sf_dir, TOTAL), DECILES, 1.0, TOTAL[2], KEY, bins).select("i", "q", F.round("z", 6).alias("z"))

    return run, sql.histogram(*TOTAL, DECILES, 1.0, bins)


def tree_cdf(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.tree_cdf(column(spark, sf_dir, TOTAL), TOTAL[2], 64, 1.0, KEY, 5)


TREE_SQL = f"WITH {_cte(TOTAL)}, h AS ({sql.bins_sql(*TOTAL, 64)}) SELECT c.b AS b, CAST(c.k + z.noise AS BIGINT) AS upto FROM (SELECT b + 1 AS b, sum(rows) OVER (ORDER BY b) AS k FROM h) c JOIN ({sql.prefix_noise(64, 1.0, 5)}) z ON z.i = c.b"

FIXED_Z = [0.1 * 131072 * k for k in range(1, 10)]
#: Estimates at uneven distances, one of them out of order.
UNEVEN_Z = [4000.5, 9500.25, 21000.0, 20500.0, 33000.75, 47000.0, 60500.5, 80000.0, 101000.0]


def rank_error_by_quantile(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = slices.result_frame(spark, DECILES, FIXED_Z)
    return measures.rank_errors(column(spark, sf_dir, PRICE), made).select("i", "q", "r", "below", "error", F.round("share", 9).alias("share"))


_ERRORS = f"""WITH {_cte(PRICE)}, e AS (SELECT i, q, CAST(floor(q * n + 1e-9) AS BIGINT) AS r, (SELECT count(*) FROM v WHERE value < 13107.2 * 0 + z) AS below, n FROM
  (VALUES {', '.join(f'({i}, CAST({q!r} AS DOUBLE), CAST({z!r} AS DOUBLE))' for i, (q, z) in enumerate(zip(DECILES, FIXED_Z, strict=True), 1))}) AS t(i, q, z), n)"""


def max_rank_error(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.max_rank_error(rank_error_by_quantile(spark, sf_dir)).select("max_error", F.round("mean_error", 6).alias("mean_error"))


#: Trials of the rank noise alone: 30 even quantiles of 6,000 rows at eps 1, by two trees; a trial fails when slices of
#: half-width 60 around the noisy ranks would meet.
TRIAL_TREES, TRIAL_M, TRIAL_ROWS, TRIAL_H, TRIALS = {"kary": 5, "binary": 2}, 30, 6000, 60, 40


def _trials(spark: SparkSession) -> DataFrame:
    parts = []
    for name, arity in TRIAL_TREES.items():
        noise = counting.prefix_noise_frame(spark, TRIAL_M, 1.0, arity, KEY, spark.range(TRIALS).toDF("trial"))
        at = noise.withColumn("rt", F.floor(F.col("i") / (TRIAL_M + 1) * TRIAL_ROWS + F.lit(1e-9)) + F.col("noise"))
        step = F.col("rt") - F.lag("rt").over(Window.partitionBy("trial").orderBy("i"))
        fits = (F.coalesce(step, F.lit(1 << 60)) > 2 * TRIAL_H) & (F.col("rt") - TRIAL_H >= 1) & (F.col("rt") <= TRIAL_ROWS - TRIAL_H)
        parts.append(at.withColumn("fits", fits).groupBy("trial").agg(F.max(F.abs("noise")).alias("max_error"), (~F.bool_and("fits")).alias("failed")).select(F.lit(name).alias("method"), "trial", "max_error", "failed"))
    return functools.reduce(DataFrame.unionByName, parts)


def _trials_sql() -> str:
    parts = []
    for name, arity in TRIAL_TREES.items():
        z = sql.geometric(counting.node_scale(TRIAL_M, 1.0, arity), "trial", "'cc'", "l", "t")
        noise = f"SELECT trial, i, CAST(sum(s * {z}) AS BIGINT) AS noise FROM {sql.node_rows(TRIAL_M, arity)}, range({TRIALS}) AS x(trial) GROUP BY trial, i"
        at = f"SELECT trial, i, noise, CAST(floor(i / CAST({TRIAL_M + 1} AS DOUBLE) * {TRIAL_ROWS} + 1e-9) AS BIGINT) + noise AS rt FROM ({noise})"
        steps = f"SELECT *, rt - lag(rt) OVER (PARTITION BY trial ORDER BY i) AS step FROM ({at})"
        parts.append(f"SELECT '{name}' AS method, trial, max(abs(noise)) AS max_error, NOT bool_and(coalesce(step, {1 << 60}) > {2 * TRIAL_H} AND rt - {TRIAL_H} >= 1 AND rt <= {TRIAL_ROWS - TRIAL_H}) AS failed FROM ({steps}) GROUP BY trial")
    return f"({' UNION ALL '.join(parts)})"


_TRIALS_SQL = _trials_sql()


#: What splits the orders into the trials' tables.
PART_KEY = "o_orderkey"


def _table_trials(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same trials over the orders: each takes the prices of its own part of the table. The error of a rank is that of
    the order statistic at the noisy rank, so equal prices count; noisy ranks beyond the part read its first or last row."""
    orders = io.table(spark, sf_dir, "orders", PART_KEY, "o_totalprice").where("o_totalprice IS NOT NULL")
    prices = orders.select(F.pmod(PART_KEY, F.lit(TRIALS)).alias("trial"), "o_totalprice")
    by = Window.partitionBy("trial").orderBy("o_totalprice")
    ranked = prices.select("trial", F.row_number().over(by).cast("bigint").alias("rn"), (F.rank().over(by) - 1).alias("below"))
    sizes = prices.groupBy("trial").agg(F.count(F.lit(1)).alias("n"))
    parts = []
    for name, arity in TRIAL_TREES.items():
        noise = counting.prefix_noise_frame(spark, TRIAL_M, 1.0, arity, KEY, spark.range(TRIALS).toDF("trial"))
        at = noise.join(F.broadcast(sizes), "trial").withColumn("r", F.floor(F.col("i") / (TRIAL_M + 1) * F.col("n") + F.lit(1e-9)))
        at = at.withColumn("rt", F.col("r") + F.col("noise")).withColumn("rn", F.greatest(F.lit(1), F.least("n", "rt")))
        step = F.col("rt") - F.lag("rt").over(Window.partitionBy("trial").orderBy("i"))
        fits = (F.coalesce(step, F.lit(1 << 60)) > 2 * TRIAL_H) & (F.col("rt") - TRIAL_H >= 1) & (F.col("rt") <= F.col("n") - TRIAL_H)
        parts.append(at.withColumn("fits", fits).select(F.lit(name).alias("method"), "trial", "r", "rn", "fits"))
    wanted = functools.reduce(DataFrame.unionByName, parts)
    found = ranked.join(F.broadcast(wanted), ["trial", "rn"])
    return found.groupBy("method", "trial").agg(F.max(F.abs(F.col("below") - F.col("r"))).alias("max_error"), (~F.bool_and("fits")).alias("failed"))


def _table_trials_sql() -> str:
    parts = []
    for name, arity in TRIAL_TREES.items():
        z = sql.geometric(counting.node_scale(TRIAL_M, 1.0, arity), "trial", "'cc'", "l", "t")
        noise = f"SELECT trial, i, CAST(sum(s * {z}) AS BIGINT) AS noise FROM {sql.node_rows(TRIAL_M, arity)}, range({TRIALS}) AS x(trial) GROUP BY trial, i"
        at = f"SELECT trial, i, n, CAST(floor(i / CAST({TRIAL_M + 1} AS DOUBLE) * n + 1e-9) AS BIGINT) AS r, noise FROM ({noise}) JOIN (SELECT trial, count(*) AS n FROM o GROUP BY trial) USING (trial)"
        steps = f"SELECT *, r + noise AS rt, r + noise - lag(r + noise) OVER (PARTITION BY trial ORDER BY i) AS step FROM ({at})"
        met = f"SELECT s.trial, abs(o.below - s.r) AS error, coalesce(step, {1 << 60}) > {2 * TRIAL_H} AND rt - {TRIAL_H} >= 1 AND rt <= n - {TRIAL_H} AS fits FROM ({steps}) s JOIN o ON o.trial = s.trial AND o.rn = greatest(1, least(n, rt))"
        parts.append(f"SELECT '{name}' AS method, trial, max(error) AS max_error, NOT bool_and(fits) AS failed FROM ({met}) GROUP BY trial")
    rows = f"SELECT {PART_KEY} % {TRIALS} AS trial, row_number() OVER w AS rn, rank() OVER w - 1 AS below FROM orders WHERE o_totalprice IS NOT NULL WINDOW w AS (PARTITION BY {PART_KEY} % {TRIALS} ORDER BY o_totalprice)"
    return f"(WITH o AS ({rows}) {' UNION ALL '.join(parts)})"


_TABLE_TRIALS_SQL = _table_trials_sql()


def trial_errors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _trials(spark)


def trial_means(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.trial_mean(_trials(spark), "method").select("method", F.round("mean_max_error", 6).alias("mean_max_error"), "trials")


def bootstrap_ci(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.bootstrap_ci(_table_trials(spark, sf_dir), ["method"], 200, KEY).select("method", F.round("ci_low", 6).alias("ci_low"), F.round("ci_high", 6).alias("ci_high"))


BOOTSTRAP_SQL = f"""WITH d AS (SELECT t.method, r.rep, CAST(floor({sql.uniform(chr(39) + 'boot' + chr(39), 'r.rep', 'd.d')} * 40) AS BIGINT) AS k FROM (SELECT DISTINCT method FROM {_TABLE_TRIALS_SQL}) t, range(200) AS r(rep), range(40) AS d(d)),
  m AS (SELECT d.method, d.rep, avg(t.max_error) AS mean FROM d JOIN {_TABLE_TRIALS_SQL} t ON t.method = d.method AND t.trial = d.k GROUP BY 1, 2)
  SELECT method, round(quantile_cont(mean, 0.025), 6) AS ci_low, round(quantile_cont(mean, 0.975), 6) AS ci_high FROM m GROUP BY method"""


def improvement_ratio(spark: SparkSession, sf_dir: str) -> DataFrame:
    means = measures.trial_mean(_table_trials(spark, sf_dir).withColumn("m", F.lit(9)), "method", "m")
    return measures.improvement(means, "kary", "binary", ["m"]).select("m", F.round("factor", 6).alias("factor"))


def failure_rate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return measures.failure_rate(_table_trials(spark, sf_dir), "method")


def value_errors(spark: SparkSession, sf_dir: str) -> DataFrame:
    values = column(spark, sf_dir, PRICE)
    made = slices.result_frame(spark, DECILES, FIXED_Z)
    return measures.value_errors(made, locate.exact_quantiles(values, PRICE[2], DECILES)).select("i", F.round("error", 6).alias("error"))


VALUE_ERRORS_SQL = f"WITH {_cte(PRICE)} SELECT CAST(i AS INTEGER) AS i, round(abs(z - value), 6) AS error FROM (VALUES {', '.join(f'({i}, CAST({q!r} AS DOUBLE), CAST({z!r} AS DOUBLE))' for i, (q, z) in enumerate(zip(DECILES, FIXED_Z, strict=True), 1))}) AS t(i, q, z), n, o WHERE rn = CAST(floor(q * n + 1e-9) AS BIGINT)"


def _configurations(spark: SparkSession) -> DataFrame:
    ms = spark.range(10, 201, 10).select(F.col("id").cast("int").alias("m"))
    rest = spark.createDataFrame([(500_000, 100.0 * 500_000, e, d, 0.05) for e in (0.25, 0.5, 1.0, 2.0, 4.0) for d in (1e-6, 1e-10, 1e-16)], "n long, b double, eps double, delta double, beta double")
    return ms.crossJoin(F.broadcast(rest))


def w_closed_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    return accountant.sweep(_configurations(spark)).select("m", "eps", "delta", "adjacency", "w", "h", F.round("min_gap", 9).alias("min_gap"))


SWEEP_SQL = """WITH c AS (SELECT CAST(m AS INTEGER) AS m, 500000 AS n, 50000000.0::DOUBLE AS b, e::DOUBLE AS eps, d::DOUBLE AS delta, 0.05::DOUBLE AS beta, a AS adjacency
    FROM range(10, 201, 10) AS x(m), (VALUES (0.25), (0.5), (1.0), (2.0), (4.0)) AS y(e), (VALUES (1e-6), (1e-10), (1e-16)) AS z(d), (VALUES ('add_remove'), ('substitute')) AS w(a)),
  s AS (SELECT *, CASE WHEN adjacency = 'substitute' THEN eps / 4 ELSE eps / 2 END AS e1, CASE WHEN adjacency = 'substitute' THEN eps / 6 ELSE eps / 4 END AS e2 FROM c),
  t AS (SELECT *, CASE WHEN adjacency = 'substitute' THEN delta / (1 + exp(e1 + 2 * e2)) ELSE delta END AS dc FROM s),
  u AS (SELECT *, CAST(ceil(3 * greatest(1.0, ln(m)) * ln(2 * m / dc) / e1) AS BIGINT) AS w, CAST(ceil(2 * ln(2 * m * b / beta) / e2) AS BIGINT) AS h FROM t)
  SELECT m, eps, delta, adjacency, w, h, round((2 * (w + h) + 2) / n::DOUBLE, 9) AS min_gap FROM u"""


_CHERNOFF = [(a, m, k) for a in accountant.ADJACENCIES for m in (10, 50, 100, 200) for k in (2, 3, 5, 9, 15, 21)]


def w_chernoff_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Numeric bound over m, arity and adjacency, with the gap it asks of 500,000 rows."""
    rows = []
    for adjacency, m, arity in _CHERNOFF:
        p = accountant.plan(m, 500_000, 100.0 * 500_000, 1.0, 1e-16, adjacency, arity=arity)
        rows.append((adjacency, m, arity, p.w, p.h, round(p.rank_gap / 500_000, 9)))
    return spark.createDataFrame(rows, "adjacency string, m int, arity int, w int, h int, gap double")


def _chernoff_sql() -> str:
    listed = ", ".join(f"('{a}', {m}, {k}, {counting.levels(m, k)}, {counting.most_nodes(m, k)})" for a, m, k in _CHERNOFF)
    return f"""WITH c AS (SELECT *, CASE WHEN adjacency = 'substitute' THEN 0.25::DOUBLE ELSE 0.5::DOUBLE END AS e1, CASE WHEN adjacency = 'substitute' THEN 1 / 6.0::DOUBLE * 0.5 * 2 ELSE 0.25::DOUBLE END AS e2
      FROM (VALUES {listed}) AS t(adjacency, m, arity, depth, most)),
    d AS (SELECT *, e1 / depth AS e, CASE WHEN adjacency = 'substitute' THEN 1e-16::DOUBLE / (1 + exp(e1 + 2 * e2)) ELSE 1e-16::DOUBLE END AS dc FROM c),
    l AS (SELECT *, k / {tails.EXPONENTS}.0::DOUBLE * e AS x, exp(-e) AS a FROM d, range(1, {tails.EXPONENTS}) AS r(k)),
    w AS (SELECT adjacency, m, arity, any_value(e2) AS e2, CAST(ceil(min((most * (2 * ln(1 - a) - ln(1 - a * exp(x)) - ln(1 - a * exp(-x))) + ln(2 * m) - ln(dc)) / x)) AS INTEGER) AS w FROM l GROUP BY adjacency, m, arity)
    SELECT adjacency, m, arity, w, CAST(ceil(2 * ln(2 * m * 50000000.0::DOUBLE / 0.05::DOUBLE) / e2) AS INTEGER) AS h, round((2 * (w + CAST(ceil(2 * ln(2 * m * 50000000.0::DOUBLE / 0.05::DOUBLE) / e2) AS INTEGER)) + 2) / 500000.0::DOUBLE, 9) AS gap FROM w"""


#: Domain length for each row, as in the published gap figures.
PSI_PER_ROW = 100.0


def _priced_orders(spark: SparkSession, sf_dir: str) -> int:
    return io.table(spark, sf_dir, "orders", "o_totalprice").agg(F.count("o_totalprice")).first()[0]


def gap_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The gap that m even quantiles of the priced orders need at the best arity, and whether they have it."""
    rows, n = [], _priced_orders(spark, sf_dir)
    for adjacency in accountant.ADJACENCIES:
        for m in SWEEP:
            p = accountant.plan(m, n, PSI_PER_ROW * n, 1.0, 1e-16, adjacency)
            rows.append((adjacency, m, p.w, p.h, round(p.rank_gap / n, 9), n // (m + 1) >= p.rank_gap))
    return spark.createDataFrame(rows, "adjacency string, m int, w int, h int, gap double, fits boolean")


def _gap_sql() -> str:
    listed = ", ".join(f"('{a}', {m}, {counting.levels(m, k)}, {counting.most_nodes(m, k)})" for a in accountant.ADJACENCIES for m in SWEEP for k in [2, *range(3, min(51, 2 * m + 3) + 1, 2)])
    return f"""WITH c AS (SELECT *, CASE WHEN adjacency = 'substitute' THEN 0.25::DOUBLE ELSE 0.5::DOUBLE END AS e1, CASE WHEN adjacency = 'substitute' THEN 1 / 6.0::DOUBLE ELSE 0.25::DOUBLE END AS e2 FROM (VALUES {listed}) AS t(adjacency, m, depth, most)),
    d AS (SELECT *, e1 / depth AS e, CASE WHEN adjacency = 'substitute' THEN 1e-16::DOUBLE / (1 + exp(e1 + 2 * e2)) ELSE 1e-16::DOUBLE END AS dc FROM c),
    l AS (SELECT *, k / {tails.EXPONENTS}.0::DOUBLE * e AS x, exp(-e) AS a FROM d, range(1, {tails.EXPONENTS}) AS r(k)),
    w AS (SELECT adjacency, m, any_value(e2) AS e2, CAST(ceil(min((most * (2 * ln(1 - a) - ln(1 - a * exp(x)) - ln(1 - a * exp(-x))) + ln(2 * m) - ln(dc)) / x)) AS INTEGER) AS w FROM l GROUP BY adjacency, m),
    h AS (SELECT *, CAST(ceil(2 * ln(2 * m * ({PSI_PER_ROW!r}::DOUBLE * n) / 0.05::DOUBLE) / e2) AS INTEGER) AS h FROM w, (SELECT count(o_totalprice) AS n FROM orders))
    SELECT adjacency, m, w, h, round((2 * (w + h) + 2) / CAST(n AS DOUBLE), 9) AS gap, n // (m + 1) >= 2 * (w + h) + 2 AS fits FROM h"""


def bounds_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Shapes of this mechanism's and the rivals' errors, lower bounds and the threshold regime, over m and delta, for
    the priced orders."""
    rows, b = [], PSI_PER_ROW * _priced_orders(spark, sf_dir)
    for m in (10, 50, 100, 200):
        for delta in (1e-6, 1e-10, 1e-16):
            found = accountant.rival_bounds(m, b, 1.0, delta, 0.05)
            more = accountant.advantage(m, b, delta)
            values = (accountant.error_bound(m, b, 1.0, 0.05), found["bisection"], found["bisection_even"], found["threshold"], found["slices_merged"], found["lower_pure"], found["lower_approx"], float(more["factor"]))
            rows.append((m, delta, *(round(v, 6) for v in values), bool(more["beats_threshold"])))
    return spark.createDataFrame(rows, "m int, delta double, slices double, bisection double, bisection_even double, threshold double, merged double, lower_pure double, lower_approx double, factor double, beats_threshold boolean")


BOUNDS_SQL = f"""WITH RECURSIVE b AS (SELECT {PSI_PER_ROW!r}::DOUBLE * count(o_totalprice) AS b FROM orders), i(x, k) AS (SELECT b, 0 FROM b UNION ALL SELECT log2(x), k + 1 FROM i WHERE x > 1),
  s AS (SELECT CAST(max(k) AS DOUBLE) AS star, (SELECT ln(b) FROM b) AS lb FROM i),
  c AS (SELECT m, d::DOUBLE AS delta, ln(m) AS lm, lb, star FROM (VALUES (10), (50), (100), (200)) AS a(m), (VALUES (1e-6), (1e-10), (1e-16)) AS b(d), s)
  SELECT m, delta, round(lb + lm * ln(m / 0.05::DOUBLE), 6) AS slices, round(lm * lm * (lb + lm), 6) AS bisection, round(lm * (lb + lm), 6) AS bisection_even,
    round(star * power(ln(star / (0.05::DOUBLE * delta)), 2), 6) AS threshold, round(lb + lm * ln(m / delta), 6) AS merged, round(lb, 6) AS lower_pure, star AS lower_approx,
    round(least(lb, lm * lm), 6) AS factor, lb < power(ln(1 / delta), 2) * star AS beats_threshold FROM c"""


def pure_worked_example(spark: SparkSession, sf_dir: str) -> DataFrame:
    """eps1 = eps2 = 1, b = 2**32, m = 100 with base-2 logarithms, as printed; and whether the priced orders are
    as many rows as it needs."""
    rows, found = [], _priced_orders(spark, sf_dir)
    for m in (10, 50, 100):
        w = tails.w_pure(m, 2.0**32, 1.0, 1.0, 1.0, base=2, mode="printed")
        rows.append((m, round(w, 3), round(2 * w, 3), round(2 * w * m, 3), found, found >= 2 * w * m))
    return spark.createDataFrame(rows, "m int, w double, gap double, n double, rows long, fits boolean")


PURE_EXAMPLE_SQL = "SELECT m, round(w, 3) AS w, round(2 * w, 3) AS gap, round(2 * w * m, 3) AS n, rows, rows >= 2 * w * m AS fits FROM (SELECT CAST(m AS INTEGER) AS m, 3 * log2(m) * (m * 32 + log2(2 * m * (exp(1.0::DOUBLE) - 1))) AS w FROM (VALUES (10), (50), (100)) AS t(m)), (SELECT count(o_totalprice) AS rows FROM orders)"


def replicate_x12(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = experiments.replicate(column(spark, sf_dir, QUANTITY), 12)
    return made.groupBy("value").agg(F.count(F.lit(1)).alias("rows"))


def jitter_row_key(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = io.table(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_quantity").withColumn("value", F.col("l_quantity"))
    made = separate(df, "row_key", KEY, 0.5, ["l_orderkey", "l_linenumber"])
    return made.select("l_orderkey", "l_linenumber", F.round("value", 9).alias("value"))


_PLACE = "CAST('0x' || substr(md5(l_orderkey || '|' || l_linenumber), 1, 13) AS BIGINT)"
JITTER_SQL = f"SELECT l_orderkey, l_linenumber, round(l_quantity + 0.5 * {sql.uniform(chr(39) + 'jitter' + chr(39), _PLACE)}, 9) AS value FROM lineitem"


def gaussian_jitter(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = io.table(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_quantity").withColumn("value", F.col("l_quantity"))
    made = separate(df, "gaussian", KEY, 0.1, ["l_orderkey", "l_linenumber"])
    return made.select("l_orderkey", "l_linenumber", F.round("value", 6).alias("value"))


GAUSSIAN_SQL = f"SELECT l_orderkey, l_linenumber, round(l_quantity + 0.1 * sqrt(-2 * ln({sql.uniform(chr(39) + 'jitter' + chr(39), _PLACE, 0)})) * cos(2 * pi() * {sql.uniform(chr(39) + 'jitter' + chr(39), _PLACE, 1)}), 6) AS value FROM lineitem"


def sorted_index_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    index = locate.Index(column(spark, sf_dir, QUANTITY), QUANTITY[2])
    found = locate.slices(index, ranks.target_ranks(QUARTILES, index.n), 3)
    return locate_spread(found, index.n)


def locate_spread(found: DataFrame, n: int) -> DataFrame:
    from privq.functions.domain import spread_slices

    return spread_slices(found, 1.0 / n).select("i", "pos", F.round("x", 9).alias("x"))


SPREAD_SQL = f"WITH {_cte(QUANTITY)}, r AS (SELECT i, CAST(floor(q * n + 1e-9) AS BIGINT) AS r FROM {sql.quantile_rows(QUARTILES)}, n) SELECT CAST(i AS INTEGER) AS i, CAST(rn - r + 4 AS BIGINT) AS pos, round(value + (1.0::DOUBLE / n) * rn, 9) AS x FROM o JOIN r ON rn BETWEEN r - 3 AND r + 3, n"


def value_distribution(spark: SparkSession, sf_dir: str) -> DataFrame:
    at = measures.histogram(F.col("value"), 0.0, 524288.0, 64)
    return column(spark, sf_dir, TOTAL).groupBy(at.cast("bigint").alias("b")).agg(F.count(F.lit(1)).alias("rows"))


DISTRIBUTION_SQL = f"WITH {_cte(TOTAL)} SELECT greatest(0, least(63, CAST(floor(value * {64 / 524288!r}) AS BIGINT))) AS b, count(*) AS rows FROM v GROUP BY 1"


def unit_interval(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = Domain(-1024.0, 16384.0, 0.01)
    return io.table(spark, sf_dir, "customer", "c_custkey", "c_acctbal").select("c_custkey", F.round(to_unit(F.greatest(F.lit(d.lo), F.least(F.lit(d.hi), "c_acctbal")), d), 6).alias("u"))


def null_policy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Missing values to the lower bound: the number of rows stays."""
    df = io.table(spark, sf_dir, "events", "event_id", "value").withColumn("value", F.when(F.col("event_id") % 10 == 0, None).otherwise(F.col("value")))
    made = to_domain(df, "value", Domain(0.0, 100.0), "lo")
    return made.agg(F.count(F.lit(1)).alias("rows"), F.sum((F.col("value") == 0).cast("bigint")).alias("at_lo"), F.sum((F.col("value") == 100).cast("bigint")).alias("at_hi"))


NULL_SQL = "SELECT count(*) AS rows, CAST(sum(CASE WHEN x = 0 THEN 1 ELSE 0 END) AS BIGINT) AS at_lo, CAST(sum(CASE WHEN x = 100 THEN 1 ELSE 0 END) AS BIGINT) AS at_hi FROM (SELECT CASE WHEN event_id % 10 = 0 OR value IS NULL THEN 0.0 ELSE greatest(0.0, least(100.0, value)) END AS x FROM events)"

#: Public groups; the last one has no rows.
_GROUPS = ["AF", "AO", "NF", "NO", "RF", "RO", "XX"]


def grouped_deciles_returnflag(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = Release(PRICE).plan
    df = io.table(spark, sf_dir, "lineitem", "l_returnflag", "l_linestatus", "l_extendedprice")
    values = to_domain(df.withColumn("grp", F.concat("l_returnflag", "l_linestatus")), "l_extendedprice", PRICE[2], keep=("grp",))
    return grouped.grouped_quantiles(values, "grp", _GROUPS, DECILES, p, PRICE[2], KEY, count_eps=slices.COUNT_SHARE).select("grp", "i", "q", F.round("z", 6).alias("z"))


def _grouped_sql() -> str:
    rows = f"SELECT l_returnflag || l_linestatus AS g, {sql.clamp('l_extendedprice', PRICE[2])} AS value FROM lineitem WHERE l_extendedprice IS NOT NULL"
    return f"SELECT g AS grp, CAST(i AS INTEGER) AS i, q, round(z, 6) AS z FROM ({sql.grouped(rows, _GROUPS, DECILES, Release(PRICE).plan, PRICE[2], slices.COUNT_SHARE)})"


def by_group(relation: str, column_sql: str, value: str, groups: list[str], qs: list[float], eps: float, delta: float, domain: Domain) -> tuple[Query, str]:
    """Quantiles of one column by public groups of another, with a noisy number of rows a group."""
    plan = accountant.plan(len(qs), 0, domain.psi, eps * (1 - slices.COUNT_SHARE), delta)

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        df = io.table(spark, sf_dir, relation).select(F.expr(column_sql).alias("grp"), F.expr(value).alias("x"))
        values = to_domain(df, "x", domain, keep=("grp",))
        return grouped.grouped_quantiles(values, "grp", groups, qs, plan, domain, KEY, count_eps=eps * slices.COUNT_SHARE).select("grp", "i", "q", F.round("z", 6).alias("z"))

    rows = f"SELECT {column_sql} AS g, {sql.clamp(f'CAST({value} AS DOUBLE)', domain)} AS value FROM {relation} WHERE {value} IS NOT NULL"
    return run, f"SELECT g AS grp, CAST(i AS INTEGER) AS i, q, round(z, 6) AS z FROM ({sql.grouped(rows, groups, qs, plan, domain, eps * slices.COUNT_SHARE)})"


PRIORITIES = ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"]
LANGS = ["de", "en", "es", "fr", "it"]


def rollup_lang_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = to_domain(io.table(spark, sf_dir, "documents", "lang", "n_chars"), "n_chars", CHARS[2], keep=("lang",))
    made = grouped.rollup_releases(df, [([], ["all"]), (["lang"], LANGS)], "value", [0.5], 4.0, 1e-6, CHARS[2], KEY)
    return made.select("level", "grp", "i", "q", F.round("z", 6).alias("z"))


def _rollup_sql() -> str:
    plan = accountant.plan(1, 0, CHARS[2].psi, 2.0 * (1 - slices.COUNT_SHARE), 5e-7)
    value, parts = sql.clamp("CAST(n_chars AS DOUBLE)", CHARS[2]), []
    for k, (name, groups) in enumerate((("'all'", ["all"]), ("lang", LANGS))):
        rows = f"SELECT {name} AS g, {value} AS value FROM documents WHERE n_chars IS NOT NULL"
        parts.append(f"SELECT {k} AS level, g AS grp, CAST(i AS INTEGER) AS i, q, round(z, 6) AS z FROM ({sql.grouped(rows, groups, [0.5], plan, CHARS[2], 2.0 * slices.COUNT_SHARE, f'{KEY}/{k}')})")
    return " UNION ALL ".join(parts)


def bounded_user_contributions(spark: SparkSession, sf_dir: str) -> DataFrame:
    kept = grouped.bound_contributions(io.table(spark, sf_dir, "events", "event_id", "user_id"), "user_id", 5, KEY, "event_id")
    return kept.groupBy("user_id").agg(F.count(F.lit(1)).alias("rows"), F.sum("event_id").alias("ids"))


CAP_SQL = f"SELECT user_id, count(*) AS rows, CAST(sum(event_id) AS BIGINT) AS ids FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY {sql.uniform(chr(39) + 'cap' + chr(39), 'event_id')}, event_id) AS k FROM events) WHERE k <= 5 GROUP BY user_id"

EVENT_TYPES = ["click", "error", "purchase", "refund", "signup", "view"]


def noisy_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return grouped.noisy_counts(io.table(spark, sf_dir, "orders", "o_orderpriority"), "o_orderpriority", ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"], 0.5, KEY)


NOISY_SQL = f"SELECT p AS o_orderpriority, CAST(coalesce(c, 0) + {sql.geometric(2.0, chr(39) + 'cnt' + chr(39), 'k')} AS BIGINT) AS rows FROM (VALUES (0, '1-URGENT'), (1, '2-HIGH'), (2, '3-MEDIUM'), (3, '4-NOT SPECIFIED'), (4, '5-LOW')) AS t(k, p) LEFT JOIN (SELECT o_orderpriority AS o, count(*) AS c FROM orders GROUP BY 1) ON o = p"


def tumbling_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = io.table(spark, sf_dir, "events", "ts", "value").select("ts", F.floor("value").alias("value"))
    return windows.windowed_runs(events, "ts", "value", "1 day").select(F.unix_micros(F.col("start").cast("timestamp")).alias("start"), F.col("value").cast("bigint").alias("value"), "rows")


def sliding_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = io.table(spark, sf_dir, "events", "ts", "value").select("ts", F.lit(0.0).alias("value"))
    return windows.windowed_runs(events, "ts", "value", "1 day", "6 hours").select(F.unix_micros(F.col("start").cast("timestamp")).alias("start"), "rows")


SLIDING_SQL = "SELECT epoch_us(time_bucket(INTERVAL '6 hours', ts)) - CAST(k AS BIGINT) * 21600000000 AS start, count(*) AS rows FROM events, range(4) AS t(k) GROUP BY 1"


def session_lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = windows.session_lengths(io.table(spark, sf_dir, "events", "ts", "user_id"), "ts", "user_id", "6 hours")
    return made.select("user_id", F.unix_micros(F.col("start").cast("timestamp")).alias("start"), "events", "micros")


SESSION_SQL = """WITH g AS (SELECT user_id, epoch_us(ts) AS t, CASE WHEN epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) < 21600000000 THEN 0 ELSE 1 END AS new FROM events),
  s AS (SELECT user_id, t, sum(new) OVER (PARTITION BY user_id ORDER BY t) AS k FROM g)
  SELECT user_id, min(t) AS start, count(*) AS events, CAST(max(t) - min(t) AS DOUBLE) AS micros FROM s GROUP BY user_id, k"""


JANUARY = (dt.datetime(2024, 1, 1), dt.datetime(2024, 2, 1))


def window_median(size: str, slide: str | None, delta: float) -> tuple[Query, str]:
    """Medians of the windows of a public calendar of January 2024, empty ones included."""
    starts, share = windows.calendar(*JANUARY, size, slide), windows.windows_of_event(size, slide)

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        events = io.table(spark, sf_dir, "events", "ts", "value").select(F.col("ts").cast("timestamp").alias("ts"), F.greatest(F.lit(0.0), F.least(F.lit(1024.0), "value")).alias("value"))
        made = windows.window_quantiles(windows.windowed_runs(events, "ts", "value", size, slide), starts, [0.5], 1.0, delta, EVENT[2], KEY, share)
        return made.select(F.unix_micros("start").alias("start"), "i", "q", F.round("z", 6).alias("z"))

    step, long = (int(windows._seconds(x) * 1_000_000) for x in (slide or size, size))
    plan = accountant.plan(1, 0, EVENT[2].psi, 1.0 / share * (1 - slices.COUNT_SHARE), delta / share)
    rows = f"SELECT CAST((epoch_us(ts) // {step} - k) * {step} AS VARCHAR) AS g, {sql.clamp('value', EVENT[2])} AS value FROM events, range({long // step}) AS t(k) WHERE value IS NOT NULL"
    text = sql.grouped(rows, [str(s) for s in starts], [0.5], plan, EVENT[2], slices.COUNT_SHARE / share)
    return run, f"SELECT CAST(g AS BIGINT) AS start, CAST(i AS INTEGER) AS i, q, round(z, 6) AS z FROM ({text})"


def private_running_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    hours = io.table(spark, sf_dir, "events", "ts").select(F.floor((F.unix_micros(F.col("ts").cast("timestamp")) - 1704067200000000) / 3600000000).alias("step"))
    return windows.running_counts(hours, "step", 744, 1.0, KEY)


def _running_sql() -> str:
    z = sql.geometric(counting.node_scale(744, 1.0, 2), "'cc'", "l", "t")
    return f"""WITH e AS (SELECT CAST(floor((epoch_us(ts) - 1704067200000000) / 3600000000) AS BIGINT) AS step, count(*) AS c FROM events GROUP BY 1),
    r AS (SELECT s.step AS step, CAST(sum(coalesce(c, 0)) OVER (ORDER BY s.step) AS BIGINT) AS rows FROM range(744) AS s(step) LEFT JOIN e ON e.step = s.step),
    z AS (SELECT i, CAST(sum({z}) AS BIGINT) AS noise FROM (SELECT i, l, ((i >> l) - 1) AS t FROM range(1, 745) AS a(i), range(10) AS b(l) WHERE (i >> l) % 2 = 1) GROUP BY i)
    SELECT step, rows, rows + noise AS noisy FROM r JOIN z ON z.i = r.step + 1"""


def contribution_semi_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Balances of customers with and without orders, by public nation keys."""
    customer, orders = io.table(spark, sf_dir, "customer", "c_custkey", "c_nationkey"), io.table(spark, sf_dir, "orders", "o_custkey")
    nation = io.table(spark, sf_dir, "nation", "n_nationkey", "n_name")
    with_orders = customer.join(orders, F.col("c_custkey") == F.col("o_custkey"), "left_semi").withColumn("ordered", F.lit(True))
    without = customer.join(orders, F.col("c_custkey") == F.col("o_custkey"), "left_anti").withColumn("ordered", F.lit(False))
    both = with_orders.unionByName(without).join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey"))
    return both.groupBy("n_name", "ordered").agg(F.count(F.lit(1)).alias("rows"))


SEMI_SQL = "SELECT n_name, c_custkey IN (SELECT o_custkey FROM orders) AS ordered, count(*) AS rows FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1, 2"


def adjacent_pair(kind: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        x = column(spark, sf_dir, TOTAL)
        point = spark.createDataFrame([(1234.5,)], "value double")
        y = x.union(point) if kind == "add" else x.exceptAll(x.agg(F.min("value").alias("value")))
        return y.agg(F.count(F.lit(1)).alias("rows"), F.round(F.sum("value"), 2).alias("total"))

    return run


ADJACENT_SQL = {
    "add": f"WITH {_cte(TOTAL)} SELECT count(*) AS rows, round(sum(value), 2) AS total FROM (SELECT value FROM v UNION ALL SELECT 1234.5)",
    "remove": f"WITH {_cte(TOTAL)} SELECT count(*) AS rows, round(sum(value), 2) AS total FROM (SELECT value FROM o WHERE rn > 1)",
}


def symmetric_difference(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = column(spark, sf_dir, QUANTITY)
    y = x.union(spark.createDataFrame([(3.5,), (4.5,)], "value double"))
    return x.exceptAll(y).union(y.exceptAll(x)).groupBy("value").agg(F.count(F.lit(1)).alias("rows"))


def cdf_lookup_asof(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = slices.result_frame(spark, DECILES, UNEVEN_Z)
    points = io.table(spark, sf_dir, "lineitem", "l_extendedprice").select(F.col("l_extendedprice").alias("x")).distinct()
    return slices.cdf_lookup(made, points, PRICE[2]).select("x", F.round("cdf", 9).alias("cdf"))


CDF_SQL = f"""WITH z AS (SELECT * FROM (VALUES (0.0::DOUBLE, 0.0::DOUBLE), {', '.join(f'({z!r}::DOUBLE, {q!r}::DOUBLE)' for q, z in zip(DECILES, UNEVEN_Z, strict=True))}, (131072.0::DOUBLE, 1.0::DOUBLE)) AS t(z, q)),
  k AS (SELECT z, max(q) OVER (ORDER BY z) AS q FROM z), n AS (SELECT z, q, lead(z) OVER (ORDER BY z) AS z2, lead(q) OVER (ORDER BY z) AS q2 FROM k),
  p AS (SELECT DISTINCT l_extendedprice AS x FROM lineitem)
  SELECT x, round(q + (q2 - q) * (x - z) / (z2 - z), 9) AS cdf FROM p ASOF JOIN n ON p.x >= n.z"""


def sketch_quantiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.sketch_quantiles(column(spark, sf_dir, TOTAL), DECILES)


def kll_quantiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    return baselines.kll_quantiles(column(spark, sf_dir, TOTAL), DECILES)


def tree_quantiles(spark: SparkSession, sf_dir: str) -> DataFrame:
    made = baselines.tree_quantiles(column(spark, sf_dir, TOTAL), DECILES, 1.0, TOTAL[2], KEY, 256, 5)
    return made.select("i", "q", F.round("z", 6).alias("z"))


def workload(name: str | list[str], settings: Callable[[], list[experiments.Setting]], trials: int) -> Query:
    """Mean of the maximum rank error by method over common trials, with its interval; of several columns, each named."""

    def one(spark: SparkSession, sf_dir: str, source: str) -> DataFrame:
        values, domain = experiments.column(spark, sf_dir, source)
        return experiments.summary(materialize(experiments.run(spark, values, domain, settings(), trials), "trials"))

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        if isinstance(name, str):
            return one(spark, sf_dir, name)
        parts = [one(spark, sf_dir, source).withColumn("column", F.lit(source)) for source in name]
        return functools.reduce(DataFrame.unionByName, parts)

    return run


WORKLOADS = {
    "w1_age_substitute": ("age", lambda: experiments.sweep_m("substitute", SWEEP), RUNS),
    "w2_hours_substitute": ("hours", lambda: experiments.sweep_m("substitute", SWEEP), RUNS),
    "w3_age_addremove": ("age", lambda: experiments.sweep_m("add_remove", SWEEP), RUNS),
    "w4_hours_addremove": ("hours", lambda: experiments.sweep_m("add_remove", SWEEP), RUNS),
    "w7_budgets": ("age", lambda: experiments.sweep_budget(9, "add_remove", [0.25, 0.5, 1.0, 2.0, 4.0], [1e-6, 1e-10, 1e-16]), RUNS),
    "w8_histogram": (["age", "hours", "money", "total", "skewed"], lambda: [experiments.Setting("histogram", "add_remove", 10, bins=b) for b in (64, 256, 1024)] + [experiments.Setting(k, "add_remove", 10) for k in ("independent", *experiments.METHODS)], RUNS),
    "w10_budget_split": ("age", lambda: experiments.sweep_split(9, "add_remove", [k / 10 for k in range(1, 10)]), RUNS),
    "w13_headline": ("age", lambda: experiments.sweep_m("substitute", [200]), RUNS),
    "w14_delta": ("age", lambda: [s for m in (9, 50) for a in accountant.ADJACENCIES for s in experiments.sweep_budget(m, a, [1.0], [1e-4, 1e-8, 1e-16])], RUNS),
    "w15_ablations": ("age", lambda: [s for m in (9, 50) for s in experiments.ablations(m, "add_remove")], RUNS),
}


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Deciles of the price under add/remove adjacency."""
    return RELEASES["private_deciles_price_addremove"].run(spark, sf_dir)


def _pairs() -> dict[str, tuple[Query, str | None]]:
    scores = f"{_SLICE_SQL}, {sql.select_sql('s', 0.25, PRICE[2], _H)} SELECT CAST(i AS INTEGER) AS i, CAST(j AS BIGINT) AS j, round(log_weight, 6) AS log_weight, round(log_weight + g, 6) AS score FROM scored"
    median_run, median_sql = select_interval_query()
    found: dict[str, tuple[Query, str | None]] = {
        "target_ranks_deciles": (target_ranks_deciles, f"SELECT CAST(i AS INTEGER) AS i, q, CAST(floor(q * n + 1e-9) AS BIGINT) AS r FROM {sql.quantile_rows(DECILES)}, (SELECT count(*) AS n FROM lineitem)"),
        "feasible_gap_check": (feasible_gap_check, FEASIBLE_SQL),
        "merge_close_quantiles": (merge_close_quantiles, _merge_sql()),
        "merged_release": (merged_release, None),
        "trial_quantile_sample": (trial_quantile_sample, SAMPLE_SQL),
        "two_sided_geometric_noise": (geometric_noise, f"SELECT id, {sql.geometric(20.0, chr(39) + 'tsg' + chr(39), 'id')} AS z FROM range(5000) AS t(id)"),
        "rank_noise_kary": (rank_noise(5), rank_noise_sql(5)),
        "rank_noise_binary": (rank_noise_binary, f"SELECT i, rows, noise, rows + noise AS noisy FROM ({rank_noise_sql(2)}) JOIN (SELECT i, CAST(sum(n) OVER (ORDER BY i) AS BIGINT) AS rows FROM (SELECT o_orderkey % 60 + 1 AS i, count(*) AS n FROM orders GROUP BY 1)) USING (i)"),
        "rank_noise_laplace": (rank_noise_laplace, f"SELECT CAST(i AS INTEGER) AS i, CAST(round(sum(s * {sql.laplace(counting.node_scale(30, 0.5, 3), chr(39) + 'cc' + chr(39), 'l', 't')})) AS BIGINT) AS noise FROM {sql.node_rows(30, 3)} GROUP BY i"),
        "rank_noise_independent": (rank_noise_independent, f"SELECT i, {sql.geometric(120.0, chr(39) + 'ind' + chr(39), 'i')} AS noise FROM range(1, 61) AS t(i)"),
        "noise_sup_norm": (noise_sup_norm, NOISE_SUP_SQL),
        "slices_extendedprice": plain_slices(PRICE, 20),
        "slices_quantity_ties": plain_slices(QUANTITY, 20),
        "exact_quantiles_totalprice": (exact_quantiles_totalprice, EXACT_SQL),
        "interval_scores": (interval_scores, scores),
        "select_interval_median": (median_run, median_sql),
        "select_interval_target": select_interval_query(10.5),
        "select_interval_grid": select_interval_query(grid=True),
        "select_interval_array": (select_interval_array, median_sql),
        "select_pluggable": (select_pluggable, PLUGGABLE_SQL),
        "random_release": (random_release, RANDOM_SQL),
        "bisection_pure": bisection_query("pure"),
        "bisection_zcdp": bisection_query("zcdp"),
        "bisection_pure_substitute": bisection_query("pure", "substitute"),
        "independent_quantiles": independent_query(),
        "independent_zcdp": independent_query("zcdp"),
        "histogram_quantiles": histogram_query(256),
        "histogram_quantiles_coarse": histogram_query(64),
        "tree_cdf": (tree_cdf, TREE_SQL),
        "tree_quantiles": (tree_quantiles, sql.tree_quantiles(*TOTAL, DECILES, 1.0, 256, 5)),
        "sketch_quantiles": (sketch_quantiles, None),
        "kll_quantiles": (kll_quantiles, None),
        "rank_error_by_quantile": (rank_error_by_quantile, f"{_ERRORS} SELECT CAST(i AS INTEGER) AS i, q, r, below, abs(below - r) AS error, round(abs(below - r) / CAST(n AS DOUBLE), 9) AS share FROM e"),
        "max_rank_error": (max_rank_error, f"{_ERRORS} SELECT max(abs(below - r)) AS max_error, round(avg(abs(below - r)), 6) AS mean_error FROM e"),
        "value_errors": (value_errors, VALUE_ERRORS_SQL),
        "trial_errors": (trial_errors, f"SELECT method, trial, max_error, failed FROM {_TRIALS_SQL}"),
        "trial_means": (trial_means, f"SELECT method, round(avg(max_error), 6) AS mean_max_error, count(*) AS trials FROM {_TRIALS_SQL} GROUP BY method"),
        "bootstrap_ci": (bootstrap_ci, BOOTSTRAP_SQL),
        "improvement_ratio": (improvement_ratio, f"SELECT 9 AS m, round(avg(max_error) FILTER (method = 'binary') / avg(max_error) FILTER (method = 'kary'), 6) AS factor FROM {_TABLE_TRIALS_SQL}"),
        "failure_rate": (failure_rate, f"SELECT method, avg(CAST(failed AS INTEGER)) AS failure_rate FROM {_TABLE_TRIALS_SQL} GROUP BY method"),
        "w_closed_sweep": (w_closed_sweep, SWEEP_SQL),
        "w_chernoff_grid": (w_chernoff_grid, _chernoff_sql()),
        "gap_sweep": (gap_sweep, _gap_sql()),
        "bounds_table": (bounds_table, BOUNDS_SQL),
        "pure_worked_example": (pure_worked_example, PURE_EXAMPLE_SQL),
        "replicate_x12": (replicate_x12, f"WITH {_cte(QUANTITY)} SELECT value, count(*) * 12 AS rows FROM v GROUP BY value"),
        "jitter_row_key": (jitter_row_key, JITTER_SQL),
        "gaussian_jitter": (gaussian_jitter, GAUSSIAN_SQL),
        "sorted_index_spread": (sorted_index_spread, SPREAD_SQL),
        "value_distribution": (value_distribution, DISTRIBUTION_SQL),
        "affine_reduction": (unit_interval, "SELECT c_custkey, round((greatest(-1024.0, least(16384.0, c_acctbal)) + 1024.0) / 0.01, 6) AS u FROM customer"),
        "null_policy": (null_policy, NULL_SQL),
        "grouped_deciles_returnflag": (grouped_deciles_returnflag, _grouped_sql()),
        "rollup_lang": (rollup_lang_source, _rollup_sql()),
        "grouped_totalprice_priority": by_group("orders", "o_orderpriority", "o_totalprice", PRIORITIES, QUARTILES, 1.0, 1e-9, TOTAL[2]),
        "grouped_value_event_type": by_group("events", "event_type", "value", EVENT_TYPES, [0.5], 1.0, 1e-9, EVENT[2]),
        "grouped_acctbal_segment": by_group("customer", "c_mktsegment", "c_acctbal", ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"], [0.5], 2.0, 1e-6, BALANCE[2]),
        "grouped_chars_source": by_group("documents", "source", "n_chars", [f"src{k}" for k in range(4)], [0.5], 4.0, 1e-6, CHARS[2]),
        "bounded_user_contributions": (bounded_user_contributions, CAP_SQL),
        "noisy_counts": (noisy_counts, NOISY_SQL),
        "tumbling_runs": (tumbling_runs, "SELECT epoch_us(date_trunc('day', ts)) AS start, CAST(floor(value) AS BIGINT) AS value, count(*) AS rows FROM events GROUP BY 1, 2"),
        "sliding_runs": (sliding_runs, SLIDING_SQL),
        "session_lengths": (session_lengths, SESSION_SQL),
        "tumbling_private_median": window_median("7 days", None, 1e-16),
        "sliding_private_median": window_median("14 days", "7 days", 1e-10),
        "private_running_count": (private_running_count, _running_sql()),
        "contribution_semi_join": (contribution_semi_join, SEMI_SQL),
        "adjacent_add": (adjacent_pair("add"), ADJACENT_SQL["add"]),
        "adjacent_remove": (adjacent_pair("remove"), ADJACENT_SQL["remove"]),
        "symmetric_difference": (symmetric_difference, "SELECT * FROM (VALUES (3.5::DOUBLE, 1::BIGINT), (4.5::DOUBLE, 1::BIGINT)) AS t(value, rows)"),
        "cdf_lookup_asof": (cdf_lookup_asof, CDF_SQL),
    }
    found |= {name: (r.run, r.sql) for name, r in RELEASES.items()}
    found |= {name: (workload(*w), None) for name, w in WORKLOADS.items()}
    found |= PAIRS
    return found


def queries() -> dict[str, Query]:
    return {name: run for name, (run, _) in _pairs().items()}


def oracle_sql() -> dict[str, str]:
    return {name: text for name, (_, text) in _pairs().items() if text is not None}
