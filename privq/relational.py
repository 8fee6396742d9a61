"""Operators around a release: preparation, joins, windows, set operations and reports, with their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from privq.functions import prf
from privq.functions.domain import Domain, clamp
from privq.operators import baselines, locate, slices
from privq.operators.locate import bucket
from privq.oracle import KEY, histogram, uniform, values_cte
from privq.sources import io

PRICE = Domain(0.0, 131072.0)


def filtered_prices(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Row-wise public predicates before a release: range, membership, pattern, missing, case."""
    df = io.table(spark, sf_dir, "lineitem", "l_shipdate", "l_returnflag", "l_extendedprice", "l_quantity", "l_partkey")
    part = io.table(spark, sf_dir, "part", "p_partkey", "p_type")
    kept = df.where("l_shipdate BETWEEN TIMESTAMP_NTZ'1996-01-01' AND TIMESTAMP_NTZ'1997-12-31' AND l_returnflag IN ('A', 'R') AND l_extendedprice IS NOT NULL")
    kept = kept.join(part.where("p_type LIKE '%S%'"), F.col("l_partkey") == F.col("p_partkey"), "left_semi")
    size = F.when(F.col("l_quantity") < 10, "small").when(F.col("l_quantity") < 30, "medium").otherwise("large")
    return kept.groupBy(size.alias("size")).agg(F.count(F.lit(1)).alias("rows"), F.round(F.sum("l_extendedprice"), 2).alias("total"))


FILTERED_SQL = """SELECT CASE WHEN l_quantity < 10 THEN 'small' WHEN l_quantity < 30 THEN 'medium' ELSE 'large' END AS size, count(*) AS rows, round(sum(l_extendedprice), 2) AS total
  FROM lineitem WHERE l_shipdate BETWEEN TIMESTAMP '1996-01-01' AND TIMESTAMP '1997-12-31' AND l_returnflag IN ('A', 'R') AND l_extendedprice IS NOT NULL
  AND l_partkey IN (SELECT p_partkey FROM part WHERE p_type LIKE '%S%') GROUP BY 1"""


def bucket_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Public buckets of the first pass."""
    df = io.table(spark, sf_dir, "lineitem", "l_extendedprice").select(clamp(F.col("l_extendedprice"), PRICE).alias("value"))
    return df.groupBy(bucket(F.col("value"), PRICE, 128).cast("bigint").alias("b")).agg(F.count(F.lit(1)).alias("rows"), F.min("value").alias("least"), F.max("value").alias("most"))


BUCKET_SQL = "SELECT least(127, CAST(floor(l_extendedprice / 1024) AS BIGINT)) AS b, count(*) AS rows, min(l_extendedprice) AS least, max(l_extendedprice) AS most FROM lineitem GROUP BY 1"


def math_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = F.col("l_quantity")
    made = [F.log(x), F.exp(-x), F.sqrt(x), F.pow(x, 0.5), F.log2(x), F.log1p(x), F.expm1(-x), F.abs(x - 25), F.greatest(x, F.lit(10.0)), F.least(x, F.lit(40.0))]
    names = ["ln", "exp", "sqrt", "pow", "log2", "log1p", "expm1", "abs", "greatest", "least"]
    return io.table(spark, sf_dir, "lineitem", "l_quantity").distinct().select("l_quantity", *[F.round(c, 9).alias(n) for c, n in zip(made, names, strict=True)])


MATH_SQL = """SELECT l_quantity, round(ln(l_quantity), 9) AS ln, round(exp(-l_quantity), 9) AS exp, round(sqrt(l_quantity), 9) AS sqrt, round(pow(l_quantity, 0.5), 9) AS pow, round(log2(l_quantity), 9) AS log2,
  round(ln(1 + l_quantity), 9) AS log1p, round(exp(-l_quantity) - 1, 9) AS expm1, abs(l_quantity - 25) AS abs, greatest(l_quantity, 10.0) AS greatest, least(l_quantity, 40.0) AS least FROM (SELECT DISTINCT l_quantity FROM lineitem)"""


def text_lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lengths of pages, conversations and documents as columns to release."""
    pages = io.table(spark, sf_dir, "pages", "page_id", "html").select(F.lit("page").alias("kind"), F.col("page_id").alias("id"), F.length("html").cast("bigint").alias("value"))
    turns = io.table(spark, sf_dir, "conversations", "conv_id", "text").groupBy("conv_id").agg(F.sum(F.length("text")).alias("value")).select(F.lit("conversation").alias("kind"), F.col("conv_id").alias("id"), "value")
    docs = io.table(spark, sf_dir, "documents", "doc_id", "text").select(F.lit("document").alias("kind"), F.col("doc_id").alias("id"), F.size(F.split("text", " ")).cast("bigint").alias("value"))
    return pages.unionByName(turns).unionByName(docs)


TEXT_SQL = """SELECT 'page' AS kind, page_id AS id, length(html) AS value FROM pages
  UNION ALL SELECT 'conversation', conv_id, CAST(sum(length(text)) AS BIGINT) FROM conversations GROUP BY conv_id
  UNION ALL SELECT 'document', doc_id, len(string_split(text, ' ')) FROM documents"""


def date_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Medians of days by year of shipping (F8): the exact ones, as ground truth."""
    days = io.table(spark, sf_dir, "lineitem", "l_shipdate").select(F.year("l_shipdate").alias("y"), F.datediff("l_shipdate", F.lit("1970-01-01").cast("date")).alias("d"))
    return days.groupBy("y").agg(F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY d)").cast("bigint").alias("median_day"), F.count(F.lit(1)).alias("rows"))


DATE_SQL = "SELECT CAST(year(l_shipdate) AS INTEGER) AS y, CAST(quantile_disc(date_diff('day', DATE '1970-01-01', CAST(l_shipdate AS DATE)), 0.5) AS BIGINT) AS median_day, count(*) AS rows FROM lineitem GROUP BY 1"


def embedding_norms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Norms of nested vectors: an all-ties column."""
    square = F.aggregate("embedding", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double"))
    return io.table(spark, sf_dir, "embeddings", "vec_id", "embedding").select("vec_id", F.round(F.sqrt(square), 5).alias("norm"))


NORM_SQL = "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE)))), 5) AS norm FROM embeddings"


def release_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A release as a map and back."""
    made = slices.result_frame(spark, [0.25, 0.5, 0.75], [1.5, 2.5, 9.0])
    packed = made.agg(F.map_from_entries(F.collect_list(F.struct("q", "z"))).alias("m"))
    return packed.select(F.explode("m").alias("q", "z"))


def decimal_totals(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Decimal columns are read as doubles."""
    df = io.table(spark, sf_dir, "orders", "o_orderpriority", "o_totalprice").withColumn("d", F.col("o_totalprice").cast("decimal(18,2)"))
    return df.groupBy("o_orderpriority").agg(F.max(F.col("d").cast("double")).alias("most"), F.count(F.lit(1)).alias("rows"))


DECIMAL_SQL = "SELECT o_orderpriority, max(CAST(CAST(o_totalprice AS DECIMAL(18, 2)) AS DOUBLE)) AS most, count(*) AS rows FROM orders GROUP BY 1"


def ranking_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All ranking functions within public groups, and gaps between neighbours."""
    df = io.table(spark, sf_dir, "customer", "c_custkey", "c_nationkey", "c_acctbal")
    by, tied = Window.partitionBy("c_nationkey").orderBy("c_acctbal", "c_custkey"), Window.partitionBy("c_nationkey").orderBy("c_acctbal")
    return df.select("c_custkey", F.row_number().over(by).cast("bigint").alias("rn"), F.rank().over(tied).cast("bigint").alias("rk"), F.dense_rank().over(tied).cast("bigint").alias("dr"), F.ntile(4).over(by).cast("bigint").alias("quarter"), F.round(F.percent_rank().over(tied), 9).alias("pr"), F.round(F.cume_dist().over(tied), 9).alias("cd"), F.round(F.col("c_acctbal") - F.lag("c_acctbal").over(by), 6).alias("gap"))


RANKING_SQL = """SELECT c_custkey, row_number() OVER w AS rn, rank() OVER t AS rk, dense_rank() OVER t AS dr, ntile(4) OVER w AS quarter, round(percent_rank() OVER t, 9) AS pr, round(cume_dist() OVER t, 9) AS cd, round(c_acctbal - lag(c_acctbal) OVER w, 6) AS gap
  FROM customer WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey), t AS (PARTITION BY c_nationkey ORDER BY c_acctbal)"""


def running_sums(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cumulative counts by row and by range frames."""
    df = io.table(spark, sf_dir, "part", "p_size").groupBy("p_size").agg(F.count(F.lit(1)).alias("rows"))  # 50 rows
    by = Window.orderBy("p_size")
    return df.select("p_size", F.sum("rows").over(by.rowsBetween(Window.unboundedPreceding, 0)).alias("upto"), F.sum("rows").over(by.rangeBetween(-5, 0)).alias("near"))


RUNNING_SQL = """SELECT p_size, CAST(sum(rows) OVER (ORDER BY p_size ROWS UNBOUNDED PRECEDING) AS BIGINT) AS upto, CAST(sum(rows) OVER (ORDER BY p_size RANGE BETWEEN 5 PRECEDING AND CURRENT ROW) AS BIGINT) AS near
  FROM (SELECT p_size, count(*) AS rows FROM part GROUP BY p_size)"""


def top_prices(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sorted, offset and limited (K1); the limit is the feature."""
    return io.table(spark, sf_dir, "orders", "o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(20)


TOP_SQL = "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 5"


def set_operations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Intersections and differences of multisets and sets."""
    a = io.table(spark, sf_dir, "lineitem", "l_quantity").select(F.col("l_quantity").cast("bigint").alias("v"))
    b = io.table(spark, sf_dir, "part", "p_size").select(F.col("p_size").cast("bigint").alias("v"))
    made = {"intersect": a.intersect(b), "intersect_all": a.intersectAll(b), "except": b.subtract(a.where("v < 25")), "union": a.union(b).distinct()}
    out = None
    for name, df in made.items():
        part = df.agg(F.lit(name).alias("operation"), F.count(F.lit(1)).alias("rows"), F.coalesce(F.sum("v"), F.lit(0)).alias("total"))
        out = part if out is None else out.unionByName(part)
    return out


SET_SQL = """WITH a AS (SELECT CAST(l_quantity AS BIGINT) AS v FROM lineitem), b AS (SELECT CAST(p_size AS BIGINT) AS v FROM part)
  SELECT 'intersect' AS operation, count(*) AS rows, CAST(sum(v) AS BIGINT) AS total FROM (SELECT v FROM a INTERSECT SELECT v FROM b)
  UNION ALL SELECT 'intersect_all', count(*), CAST(sum(v) AS BIGINT) FROM (SELECT v FROM a INTERSECT ALL SELECT v FROM b)
  UNION ALL SELECT 'except', count(*), CAST(sum(v) AS BIGINT) FROM (SELECT v FROM b EXCEPT SELECT v FROM a WHERE v < 25)
  UNION ALL SELECT 'union', count(*), CAST(sum(v) AS BIGINT) FROM (SELECT v FROM a UNION SELECT v FROM b)"""


def distinct_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Profile of a column's ties."""
    df = io.table(spark, sf_dir, "lineitem", "l_returnflag", "l_quantity", "l_extendedprice")
    return df.groupBy("l_returnflag").agg(F.countDistinct("l_quantity").alias("quantities"), F.max_by("l_quantity", F.struct("l_extendedprice", "l_quantity")).alias("at_top"), F.bool_and(F.col("l_quantity") > 0).alias("positive"))


DISTINCT_SQL = "SELECT l_returnflag, count(DISTINCT l_quantity) AS quantities, arg_max(l_quantity, (l_extendedprice, l_quantity)) AS at_top, bool_and(l_quantity > 0) AS positive FROM lineitem GROUP BY 1"


def cube_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts of all groupings; each level of a release spends its own budget."""
    df = io.table(spark, sf_dir, "documents", "lang", "source")
    return df.cube("lang", "source").agg(F.count(F.lit(1)).alias("rows"), F.grouping_id().cast("bigint").alias("level"))


CUBE_SQL = "SELECT lang, source, count(*) AS rows, CAST(grouping(lang) * 2 + grouping(source) AS BIGINT) AS level FROM documents GROUP BY CUBE (lang, source)"


def _results(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rank errors of 120 keyed estimates of a median, each in its own part of the orders."""
    z = spark.range(120).select("id", (prf.uniform(KEY, "rep", F.col("id")) * 524288.0).alias("z"))
    orders = io.table(spark, sf_dir, "orders", "o_orderkey", "o_totalprice").where("o_totalprice IS NOT NULL").select(F.pmod("o_orderkey", F.lit(120)).alias("id"), "o_totalprice")
    error = F.abs(F.sum((F.col("o_totalprice") < F.col("z")).cast("bigint")) - F.floor(F.count(F.lit(1)) / 2))
    method = F.element_at(F.array(F.lit("slices"), F.lit("bisection")), (F.col("id") % 2 + 1).cast("int"))
    found = orders.join(F.broadcast(z), "id").groupBy("id").agg(error.alias("error"))
    return found.select(method.alias("method"), (F.floor(F.col("id") / 2) % 3 * 10 + 10).alias("m"), F.floor(F.col("id") / 6).alias("trial"), "error")


_RESULTS = f"""(SELECT CASE WHEN id % 2 = 0 THEN 'slices' ELSE 'bisection' END AS method, (id // 2) % 3 * 10 + 10 AS m, id // 6 AS trial, error FROM (SELECT id, CAST(abs(sum(CASE WHEN o_totalprice < z THEN 1 ELSE 0 END) - count(*) // 2) AS BIGINT) AS error
  FROM (SELECT id, {uniform(chr(39) + 'rep' + chr(39), 'id')} * 524288.0 AS z FROM range(120) AS t(id)) JOIN orders ON o_orderkey % 120 = id WHERE o_totalprice IS NOT NULL GROUP BY id))"""


def pivot_report(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Methods side by side."""
    return _results(spark, sf_dir).groupBy("m").pivot("method", ["slices", "bisection"]).agg(F.round(F.avg("error"), 6))


PIVOT_SQL = f"SELECT m, round(avg(error) FILTER (method = 'slices'), 6) AS slices, round(avg(error) FILTER (method = 'bisection'), 6) AS bisection FROM {_RESULTS} GROUP BY m"


def paired_trials(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Self join by trial: how often one method beats the other."""
    r = _results(spark, sf_dir)
    a, b = r.where("method = 'slices'").select("m", "trial", F.col("error").alias("a")), r.where("method = 'bisection'").select("m", "trial", F.col("error").alias("b"))
    return a.join(b, ["m", "trial"]).groupBy("m").agg(F.count(F.lit(1)).alias("trials"), F.sum((F.col("a") < F.col("b")).cast("bigint")).alias("wins"))


PAIRED_SQL = f"SELECT a.m AS m, count(*) AS trials, CAST(sum(CASE WHEN a.error < b.error THEN 1 ELSE 0 END) AS BIGINT) AS wins FROM {_RESULTS} a JOIN {_RESULTS} b ON a.m = b.m AND a.trial = b.trial AND a.method = 'slices' AND b.method = 'bisection' GROUP BY a.m"


TOTAL = Domain(0.0, 524288.0)


def outer_alignment(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Release and truth of the orders side by side, missing ones too."""
    values = io.table(spark, sf_dir, "orders", "o_totalprice").where("o_totalprice IS NOT NULL").select(clamp(F.col("o_totalprice"), TOTAL).alias("value"))
    made = baselines.histogram_quantiles(values, [0.25, 0.5], 1.0, TOTAL, KEY, 64).select("i", F.round("z", 6).alias("z"))
    truth = locate.exact_quantiles(values, TOTAL, [0.5, 0.75]).select((F.col("i") + 1).alias("i"), "x")
    return made.join(truth, "i", "full_outer")


ALIGNMENT_SQL = f"""WITH {values_cte('orders', 'o_totalprice', TOTAL)}, z AS ({histogram('orders', 'o_totalprice', TOTAL, [0.25, 0.5], 1.0, 64)}),
  x AS (SELECT i, value AS x FROM (VALUES (2, 0.5::DOUBLE), (3, 0.75::DOUBLE)) AS t(i, q), n, o WHERE rn = CAST(floor(q * n + 1e-9) AS BIGINT))
  SELECT CAST(coalesce(z.i, x.i) AS INTEGER) AS i, z, x FROM z FULL JOIN x ON z.i = x.i"""


def enriched_prices(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Equi-join of two large tables before a release (J2), and small public keys by broadcast."""
    line = io.table(spark, sf_dir, "lineitem", "l_orderkey", "l_extendedprice")
    order, customer = io.table(spark, sf_dir, "orders", "o_orderkey", "o_custkey"), io.table(spark, sf_dir, "customer", "c_custkey", "c_nationkey")
    nation, region = io.table(spark, sf_dir, "nation", "n_nationkey", "n_regionkey"), io.table(spark, sf_dir, "region", "r_regionkey", "r_name")
    keys = F.broadcast(nation.join(region, F.col("n_regionkey") == F.col("r_regionkey")))  # 25 rows
    joined = line.join(order, F.col("l_orderkey") == F.col("o_orderkey")).join(customer, F.col("o_custkey") == F.col("c_custkey")).join(keys, F.col("c_nationkey") == F.col("n_nationkey"))
    return joined.groupBy("r_name").agg(F.count(F.lit(1)).alias("rows"), F.round(F.max("l_extendedprice"), 2).alias("most"))


ENRICHED_SQL = """SELECT r_name, count(*) AS rows, round(max(l_extendedprice), 2) AS most FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
  JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1"""


def windows_of_trials(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Slices of many trials at once: windows go to the cells they meet, an equi-join finds the runs."""
    values = io.table(spark, sf_dir, "orders", "o_totalprice").select(F.col("o_totalprice").alias("value"))
    index = locate.Index(values, Domain(0.0, 524288.0), cap=2000)
    windows = [(t * 3 + k, index.n * (k + 1) // 4 + 7 * t - 2, index.n * (k + 1) // 4 + 7 * t + 2) for t in range(10) for k in range(3)]
    return index.order_statistics(windows)


TRIAL_WINDOWS_SQL = """WITH o AS (SELECT o_totalprice AS x, row_number() OVER (ORDER BY o_totalprice) AS rn, count(*) OVER () AS n FROM orders),
  w AS (SELECT t * 3 + k AS i, (SELECT count(*) FROM orders) * (k + 1) // 4 + 7 * t AS c FROM range(10) AS a(t), range(3) AS b(k))
  SELECT CAST(i AS INTEGER) AS i, rn AS rank, x FROM w JOIN o ON rn BETWEEN c - 2 AND c + 2"""


PAIRS: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str]] = {
    "filtered_prices": (filtered_prices, FILTERED_SQL),
    "bucket_counts": (bucket_counts, BUCKET_SQL),
    "math_functions": (math_functions, MATH_SQL),
    "text_lengths": (text_lengths, TEXT_SQL),
    "date_parts": (date_parts, DATE_SQL),
    "embedding_norms": (embedding_norms, NORM_SQL),
    "release_map": (release_map, "SELECT * FROM (VALUES (0.25::DOUBLE, 1.5::DOUBLE), (0.5::DOUBLE, 2.5::DOUBLE), (0.75::DOUBLE, 9.0::DOUBLE)) AS t(q, z)"),
    "decimal_totals": (decimal_totals, DECIMAL_SQL),
    "ranking_windows": (ranking_windows, RANKING_SQL),
    "running_sums": (running_sums, RUNNING_SQL),
    "top_prices": (top_prices, TOP_SQL),
    "set_operations": (set_operations, SET_SQL),
    "distinct_counts": (distinct_counts, DISTINCT_SQL),
    "cube_counts": (cube_counts, CUBE_SQL),
    "pivot_report": (pivot_report, PIVOT_SQL),
    "paired_trials": (paired_trials, PAIRED_SQL),
    "outer_alignment": (outer_alignment, ALIGNMENT_SQL),
    "enriched_prices": (enriched_prices, ENRICHED_SQL),
    "windows_of_trials": (windows_of_trials, TRIAL_WINDOWS_SQL),
}
