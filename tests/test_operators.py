import datetime as dt

import numpy as np
import pytest
from pyspark.sql import functions as F
from pyspark.sql import types as T

from privq import sqlapi
from privq.functions import local, prf
from privq.functions.domain import Domain, separate, to_domain
from privq.operators import baselines, bisection, experiments, grouped, locate, measures, select, slices
from privq.plans import accountant, counting, ranks
from privq.sources import io
from privq.streaming import windows

DOMAIN = Domain(-50.0, 150.0)


def frame(spark, xs):
    return spark.createDataFrame([(float(x),) for x in xs], "value double")


def test_noise_is_the_same_on_both_sides(spark):
    rows = spark.range(300).select("id", prf.uniform("k", "a", F.col("id")).alias("u"), prf.two_sided_geometric("k", 5.0, "b", F.col("id")).alias("g"), prf.gumbel("k", "c", F.col("id")).alias("w"), prf.laplace("k", 2.0, "d", F.col("id")).alias("l")).collect()
    for r in rows:
        assert r["u"] == prf.uniform_of("k", "a", r["id"])
        assert r["g"] == prf.two_sided_geometric_of("k", 5.0, "b", r["id"])
        assert r["w"] == pytest.approx(prf.gumbel_of("k", "c", r["id"]))
        assert r["l"] == pytest.approx(prf.laplace_of("k", 2.0, "d", r["id"]))
    for arity in (2, 3, 5):
        found = {r["i"]: r["noise"] for r in counting.prefix_noise_frame(spark, 40, 0.5, arity, "k").collect()}
        assert [found[i] for i in range(1, 41)] == counting.prefix_noise(40, 0.5, arity, "k")


CASES = {
    "random": lambda g: g.normal(30, 40, 4000),
    "ties": lambda g: g.integers(0, 6, 4000) * 10.0,
    "constant": lambda g: np.full(500, 7.0),
    "outside": lambda g: np.full(300, 1e9),
    "negative": lambda g: -g.random(1000) * 60,
    "hot": lambda g: np.concatenate([np.full(3000, 42.0), g.random(1500) * 100]),
    "one": lambda g: np.array([3.0]),
}


@pytest.mark.parametrize("case", CASES)
@pytest.mark.parametrize("cap", [50, 1 << 16])
def test_order_statistics_match_a_sort(spark, case, cap):
    x = np.sort(np.clip(CASES[case](np.random.default_rng(5)), DOMAIN.lo, DOMAIN.hi))
    n = len(x)
    index = locate.Index(frame(spark, x), DOMAIN, buckets=64, cap=cap)
    wanted = sorted({1, n // 3 + 1, n // 2 + 1, n})
    got = {(r["i"], r["rank"]): r["x"] for r in index.order_statistics([(k, r - 12, r + 12) for k, r in enumerate(wanted)]).collect()}
    assert got == {(k, j): x[j - 1] for k, r in enumerate(wanted) for j in range(max(1, r - 12), min(n, r + 12) + 1)}


def test_empty_and_small_inputs(spark):
    index = locate.Index(frame(spark, []), DOMAIN)
    assert index.n == 0 and index.order_statistics([(1, 1, 3)]).count() == 0
    assert locate.exact_quantiles(frame(spark, [5.0]), DOMAIN, [0.5]).collect()[0]["x"] == 5.0
    p = accountant.plan(3, 0, DOMAIN.psi, 1.0, 1e-6, "substitute")
    for x in ([1, 2, 3], []):
        with pytest.raises(ranks.GapTooSmall):
            slices.release(frame(spark, x), [0.25, 0.5, 0.75], p, DOMAIN, "k")
        with pytest.raises(ranks.GapTooSmall):
            slices.release_counted(frame(spark, x), [0.25, 0.5, 0.75], 1.0, 1e-6, DOMAIN, "k")


def test_private_number_of_rows(spark):
    tracker, group = spark.sparkContext.statusTracker(), "private-n"
    values, qs, d = frame(spark, np.arange(20_000) / 200), [0.25, 0.5, 0.75], DOMAIN
    spark.sparkContext.setJobGroup(group, "none")
    with pytest.raises(ValueError, match="private"):
        slices.release(values, qs, accountant.plan(3, 0, d.psi, 1.0, 1e-6), d, "k")
    assert not tracker.getJobIdsForGroup(group)
    for clip in ("none", "adaptive"):
        z = sorted((r["i"], r["z"]) for r in slices.release_counted(values, qs, 1.0, 1e-6, d, "k", clip=clip).collect())
        assert all(abs(v - 100 * q) < 3 for (_, v), q in zip(z, qs, strict=True))
    # a public number above the true one: ranks beyond the last row read the upper bound
    p = accountant.plan(1, 0, d.psi, 1.0, 1e-6)
    out = slices.release(values, [0.5], p, d, "k", n_public=40_060).collect()
    assert len(out) == 1 and out[0]["z"] >= 98


def test_earlier_accounting_costs_ln_2(spark):
    values, d = frame(spark, np.arange(30_000) / 300), DOMAIN
    out = slices.release_doubling(values, [0.25, 0.5, 0.75], 1.0, 1e-6, d, "k", 30_000).collect()
    assert len(out) == 3 and accountant.plan_doubling(3, d.psi, 1.0, 1e-6).w > accountant.plan(3, 0, d.psi, 1.0, 1e-6).w
    with pytest.raises(ValueError, match="ln 2"):
        accountant.plan_doubling(3, d.psi, 0.69, 1e-6)


def test_precheck_starts_no_job(spark):
    tracker, group = spark.sparkContext.statusTracker(), "precheck"
    values = frame(spark, range(100))
    spark.sparkContext.setJobGroup(group, "none")
    with pytest.raises(ranks.GapTooSmall):
        slices.release(values, [0.25, 0.5, 0.75], accountant.plan(3, 100, DOMAIN.psi, 1.0, 1e-6), DOMAIN, "k", n_public=100)
    assert not tracker.getJobIdsForGroup(group)


def test_locating_has_no_single_partition_exchange(spark):
    index = locate.Index(frame(spark, np.random.default_rng(1).random(3000) * 100), DOMAIN, buckets=64, cap=10)
    plan = locate.slices(index, [500, 1500], 20)._jdf.queryExecution().executedPlan().toString()
    assert "SinglePartition" not in plan


def test_release_is_accurate_and_repeatable(spark):
    x = np.sort(np.random.default_rng(8).random(30_000) * 1000)
    d, qs = Domain(0.0, 1024.0), ranks.even_quantiles(9)
    p = accountant.plan(9, len(x), d.psi, 1.0, 1e-16)
    for clip in ("none", "adaptive"):
        out = slices.release(frame(spark, x), qs, p, d, "7", len(x), clip)
        z = [r["z"] for r in sorted(out.collect(), key=lambda r: r["i"])]
        errors = np.abs(np.searchsorted(x, z) - np.array(ranks.target_ranks(qs, len(x))))
        assert errors.max() <= p.margin
        again = slices.release(frame(spark, x).repartition(7), qs, p, d, "7", len(x), clip)
        assert [r["z"] for r in sorted(again.collect(), key=lambda r: r["i"])] == z
        local_z, failed = local.release_keyed(x, qs, p, d.lo, d.hi, "7", len(x), clip == "adaptive")
        assert not failed and local_z == pytest.approx(z)
        assert [r["z"] for r in slices.release(frame(spark, x), qs, p, d, "7", len(x), clip, monotone=True).collect()] == pytest.approx(sorted(z))


def test_adaptive_levels_agree_on_and_off_the_driver(spark):
    x = np.random.default_rng(8).random(9000) * 1000
    d = Domain(0.0, 1024.0)
    p = accountant.plan(5, len(x), d.psi, 1.0, 1e-6)
    found = locate.slices(locate.Index(frame(spark, x), d), [1500, 3000, 4500, 6000, 7500], p.h)
    assert slices.adaptive(found, 5, p, d, "k") == pytest.approx(slices.adaptive(found, 5, p, d, "k", most_local=0))


def test_pure_release_is_on_the_grid(spark):
    x = np.random.default_rng(8).integers(0, 65, 20_000)
    d = Domain(0.0, 64.0)
    p = accountant.plan(3, 0, d.psi, 1.0, gamma=0.01, grid_size=65)
    for clip in ("none", "adaptive"):
        assert all(r["z"] == int(r["z"]) for r in slices.release(frame(spark, x), [0.25, 0.5, 0.75], p, d, "7", len(x), clip).collect())
    low = Domain(-64.0, 0.0)
    z = slices.release(frame(spark, -x), [0.25, 0.5, 0.75], p, low, "7", len(x)).collect()
    assert all(-64 <= r["z"] <= 0 and r["z"] == int(r["z"]) for r in z)
    assert all(0 <= r["z"] <= 64 and r["z"] == int(r["z"]) for r in slices.random_release(spark, [0.5] * 20, d, "9", grid=True).collect())


def test_select_matches_the_array_form_and_zero_lengths(spark):
    rows = [(1, k + 1, float(v)) for k, v in enumerate([3, 3, 3, 8, 9])] + [(2, k + 1, 5.0) for k in range(5)]
    made = spark.createDataFrame(rows, "i int, pos bigint, x double")
    d = Domain(0.0, 10.0)
    a = {r["i"]: r["z"] for r in select.select_interval(made, 1.0, d, 2, "k").collect()}
    arrays = made.groupBy("i").agg(F.array_sort(F.collect_list("x")).alias("p"))
    b = {r["i"]: r["z"] for r in arrays.select("i", select.select_interval_array(F.col("p"), 1.0, d, "k", F.col("i")).alias("z")).collect()}
    assert a == pytest.approx(b)
    bounds = spark.createDataFrame([(1, 4.0, 6.0), (2, 5.0, 5.0)], "i int, lo double, hi double")
    c = {r["i"]: r["z"] for r in select.select_interval(made, 1.0, d, 2, "k", bounds=bounds).collect()}
    assert 4 <= c[1] <= 6 and c[2] == 5.0


def test_rivals_run_on_ties(spark):
    x = np.repeat(np.arange(0, 50, 5.0), 300)
    index = locate.build_index(frame(spark, x), DOMAIN)
    for out in (bisection.bisection(frame(spark, x), [0.25, 0.5, 0.75], 0.5, DOMAIN, "k", index), bisection.independent(frame(spark, x), [0.25, 0.5, 0.75], 0.3, DOMAIN, "k", index)):
        z = [r["z"] for r in sorted(out.collect(), key=lambda r: r["i"])]
        assert z[0] < z[1] < z[2] and 5 <= z[0] and z[2] <= 45
    z = [r["z"] for r in baselines.histogram_quantiles(frame(spark, x), [0.5], 1.0, DOMAIN, "k", 64).collect()]
    assert 15 < z[0] < 30


def test_measures(spark):
    values = frame(spark, [1, 2, 2, 3, 10])
    both = {r["z"]: (r["below"], r["upto"]) for r in measures.rank_of(values, [2.0, 5.0], "interval").collect()}
    assert both == {2.0: (1, 3), 5.0: (4, 4)}
    index = locate.build_index(values, DOMAIN)
    zs = spark.createDataFrame([(2.0,), (5.0,), (150.0,)], "z double")
    assert {r["z"]: r["below"] for r in measures.rank_of_index(index, zs).collect()} == {2.0: 1, 5.0: 4, 150.0: 5}
    cost = measures.engine_cost(values.groupBy("value").count())
    assert cost["exchanges"] >= 1 and cost["seconds"] > 0


def test_domain_types(spark):
    row = (dt.date(1970, 1, 11), dt.datetime(1970, 1, 1, 0, 0, 1), 3, float("nan"), True, "x")
    df = spark.createDataFrame([row], "d date, t timestamp_ntz, k int, f double, b boolean, s string")
    wide = Domain(-1e9, 1e9)
    assert to_domain(df, "d", wide).collect()[0]["value"] == 10
    assert to_domain(df, "t", wide).collect()[0]["value"] == 1e6
    assert to_domain(df, "k", Domain(5.0, 6.0)).collect()[0]["value"] == 5
    assert to_domain(df, "f", wide).count() == 0 and to_domain(df, "f", wide, "hi").collect()[0]["value"] == 1e9
    for name in ("b", "s"):
        with pytest.raises(TypeError):
            to_domain(df, name, wide)
    spread = separate(spark.range(50).withColumn("value", F.lit(1.0)), "row_key", "k", 0.5, ["id"]).collect()
    assert len({r["value"] for r in spread}) == 50 and all(1 <= r["value"] < 1.5 for r in spread)


def test_groups_and_caps(spark):
    g = np.random.default_rng(4)
    rows = [("a", float(v)) for v in g.random(4000) * 100] + [("b", float(v)) for v in g.random(100) * 100]
    df = spark.createDataFrame(rows, "grp string, value double")
    d = Domain(0.0, 128.0)
    p = accountant.plan(3, 0, d.psi, 1.0, 1e-9)
    with pytest.raises(ValueError, match="sizes"):
        grouped.grouped_quantiles(df, "grp", ["a"], [0.5], p, d, "k")
    out = grouped.grouped_quantiles(df, "grp", ["a", "b", "none"], [0.25, 0.5, 0.75], p, d, "k", count_eps=0.1).collect()
    assert sorted((r["grp"], r["i"]) for r in out) == [(k, i) for k in ("a", "b", "none") for i in (1, 2, 3)]
    assert all(abs(r["z"] - 100 * r["q"]) < 10 for r in out if r["grp"] == "a") and all(0 <= r["z"] <= 128 for r in out)
    alone = grouped.grouped_release(df, "grp", ["a", "b", "none"], [0.25, 0.5, 0.75], 1.0, 1e-9, d, "k").collect()
    assert sorted((r["grp"], r["i"]) for r in alone) == sorted((r["grp"], r["i"]) for r in out)
    rolled = grouped.rollup_releases(df, [([], ["all"]), (["grp"], ["a", "b"])], "value", [0.5], 2.0, 1e-6, d, "k").collect()
    assert sorted((r["level"], r["grp"]) for r in rolled) == [(0, "all"), (1, "a"), (1, "b")]
    capped = grouped.bound_contributions(df.withColumn("id", F.monotonically_increasing_id()), "grp", 7, "k", "id")
    assert {r["grp"]: r["count"] for r in capped.groupBy("grp").count().collect()} == {"a": 7, "b": 7}


def test_trials_run_in_parallel(spark):
    x = np.round(np.random.default_rng(4).normal(40, 12, 60_000)) + 0.5
    made = experiments.run(spark, to_domain(frame(spark, x), "value", Domain(0.0, 100.0)), Domain(0.0, 100.0), experiments.sweep_m("add_remove", [5]), 3)
    means = {r["method"]: r["mean_max_error"] for r in measures.trial_mean(made, "method").collect()}
    assert set(means) == set(experiments.METHODS) and all(v < 600 for v in means.values())


def test_trials_from_windows_equal_those_from_all_rows(spark):
    d = Domain(0.0, 100.0)
    values = frame(spark, np.round(np.random.default_rng(4).normal(40, 12, 30_000), 1).clip(0, 100))
    whole = experiments.read_column(values, d, least=1).points(True)
    parts = experiments.read_column(values, d, least=1, most=10, reach=700)
    assert [w[0] for w in parts.windows] == [lo for lo, _ in experiments.grid_windows(30_000, 700)]
    near = experiments.read_column(values, d, least=1, most=10, reach=40).points(True)
    assert len(near.starts) > 50 and whole.n == near.n
    for r in (np.array([120, 239, 14_945]), np.array([29_870])):
        assert (whole.around(r, 30, 30) == near.around(r, 30, 30)).all()
    with pytest.raises(IndexError):
        near.around(np.array([180]), 30, 30)
    for method in experiments.METHODS:
        s = experiments.Setting(method, "add_remove", 5)
        qs = ranks.even_quantiles(5)
        a, b = (experiments.one_trial(np.random.default_rng(1), x, qs, s, d)[0] for x in (whole, parts.points(True)))
        assert (a == b).all() and (local.rank_errors(whole, qs, a) == local.rank_errors(parts.points(True), qs, b)).all()


def test_refused_trials_are_recorded(spark):
    d = Domain(0.0, 100.0)
    made = experiments.run(spark, frame(spark, np.arange(2000) / 20), d, experiments.sweep_m("add_remove", [3, 60]), 2, least=1)
    rows = made.collect()
    assert len(rows) == 12 and {(r["method"], r["refused"]) for r in rows if r["m"] == 60} == {("slices", True), ("bisection_pure", False), ("bisection_zcdp", False)}
    assert all((r["max_error"] is None) == r["refused"] for r in rows)
    means = experiments.summary(made, reps=20).collect()
    assert all(r["trials"] is None and r["refused"] == (2 if r["method"] == "slices" else 0) for r in means if r["m"] == 60)


def test_bisection_reads_parts_near_its_targets(spark):
    index = locate.build_index(frame(spark, np.arange(200_000) / 2000), DOMAIN)
    parts = bisection.Parts.of(index)
    assert len(parts.rows) > 5 and parts.n == 200_000
    read = parts.for_node(0.0, 100.0, 100_000, 1.0)
    assert 0 < len(read) < len(parts.rows) and any(r[0] in read and r[3] <= 100_000 <= r[4] for r in parts.rows)
    plan = bisection.select_over_index(index, parts, [(1, 0.0, 100.0, 100_000)], 1.0, "k")._jdf.queryExecution().executedPlan().toString()
    assert "NestedLoop" not in plan and "SinglePartition" not in plan


def test_skewed_cells_are_cut_until_they_are_small(spark):
    x = np.concatenate([np.random.default_rng(5).random(4000) * 1e-6, [99.0]])
    index = locate.Index(frame(spark, x), DOMAIN, buckets=64, cap=100)
    cells = index.wanted([(2000, 2010)])
    assert all(c.rows <= 100 for c in cells) and sum(c.rows for c in cells) < 400
    got = {r["rank"]: r["x"] for r in index.order_statistics([(1, 2000, 2010)]).collect()}
    assert got == {k: v for k, v in enumerate(np.sort(x)[1999:2010].tolist(), 2000)}


def test_sql_entry_points(spark):
    g = np.random.default_rng(4)
    sqlapi.register(spark, {"points": spark.createDataFrame([("a", float(v)) for v in g.random(5000) * 100], "grp string, value double")})
    u = spark.sql("SELECT prf_uniform('7', 'cc', 3) AS u, two_sided_geometric('7', 'cc', 3, 20D) AS g").first()
    assert u["u"] == prf.uniform_of("7", "cc", 3) and u["g"] == prf.two_sided_geometric_of("7", 20.0, "cc", 3)
    w = spark.sql("SELECT * FROM rank_windows(6000, array(0.25D, 0.5D, 0.75D), 100D, 1D, 1e-9D, 'add_remove', '7')").collect()
    assert [r["r"] for r in w] == [1500, 3000, 4500] and all(r["hi"] - r["rt"] == r["rt"] - r["lo"] for r in w)
    z = spark.sql("SELECT * FROM private_quantiles(TABLE(points) PARTITION BY (grp), array(0.25D, 0.5D, 0.75D), 0D, 100D, 1D, 1e-9D, '7') ORDER BY i").collect()
    assert [abs(r["z"] - 100 * r["q"]) < 6 for r in z] == [True] * 3
    agg = sqlapi.private_quantile(0.5, 1.0, Domain(0.0, 100.0), "7")
    assert abs(spark.table("points").groupBy("grp").agg(agg("value", "grp").alias("z")).first()["z"] - 50) < 5


def test_formats_and_sinks(spark, tmp_path):
    df = spark.createDataFrame([(1, "a"), (2, None)], "k int, s string")
    for kind in ("csv", "json", "orc", "parquet"):
        df.write.format(kind).save(f"{tmp_path}/{kind}")
        assert sorted(io.read(spark, f"{tmp_path}/{kind}", kind, "k int, s string").collect()) == sorted(df.collect())
    made = slices.result_frame(spark, [0.5], [3.0])
    io.write_release(made, f"{tmp_path}/out", method="slices", eps=1.0)
    io.write_release(made, f"{tmp_path}/out", method="bisection", eps=1.0)
    assert spark.read.parquet(f"{tmp_path}/out").count() == 2
    io.write_index(locate.build_index(frame(spark, range(100)), DOMAIN), f"{tmp_path}/index", 4)
    assert spark.read.parquet(f"{tmp_path}/index").agg(F.max("upto")).first()[0] == 100


def _events(spark, tmp_path):
    t0 = dt.datetime(2024, 1, 1)
    g = np.random.default_rng(6)
    rows = [(t0 + dt.timedelta(minutes=10 * k), float(v)) for k, v in enumerate(g.random(4000) * 100)]
    df = spark.createDataFrame(rows, "ts timestamp, value double")
    for k in range(2):
        df.where((F.day("ts") <= 14) if k == 0 else (F.day("ts") > 14)).coalesce(1).write.mode("append").parquet(f"{tmp_path}/events")
    return df


def test_stream_windows_are_released_once(spark, tmp_path):
    events = _events(spark, tmp_path)
    schema = T.StructType([T.StructField("ts", T.TimestampType()), T.StructField("value", T.DoubleType())])
    found = []
    d = Domain(0.0, 128.0)
    writer = windows.release_closed_windows(io.stream(spark, f"{tmp_path}/events", schema), "ts", "value", "7 days", "1 hour", lambda z, _: found.extend(z.collect()), [0.5], 1.0, 1e-6, d, "k")
    query = writer.option("checkpointLocation", f"{tmp_path}/check").trigger(availableNow=True).start()
    query.awaitTermination()
    starts = [r["start"] for r in found]
    assert len(starts) == len(set(starts)) >= 2
    runs = windows.windowed_runs(events, "ts", "value", "7 days")
    starts = windows.calendar(dt.datetime(2024, 1, 1), dt.datetime(2024, 3, 1), "7 days")
    batch = {r["start"]: r["z"] for r in windows.window_quantiles(runs, starts, [0.5], 1.0, 1e-6, d, "k").collect()}
    assert len(batch) == len(starts)  # empty windows too
    assert all(batch[r["start"]] == pytest.approx(r["z"]) for r in found if r["start"] in batch)


def test_stream_static_join_and_duplicates(spark, tmp_path):
    _events(spark, tmp_path)
    schema = T.StructType([T.StructField("ts", T.TimestampType()), T.StructField("value", T.DoubleType())])
    stream = io.stream(spark, f"{tmp_path}/events", schema).withColumn("kind", (F.col("value") % 3).cast("int"))
    names = spark.createDataFrame([(0, "none"), (1, "one")], "kind int, name string")
    once = windows.deduplicated(stream.unionByName(stream), "ts", "1 hour", ["ts"])
    query = windows.with_reference(once, names, "kind").writeStream.format("memory").queryName("joined").option("checkpointLocation", f"{tmp_path}/check3").trigger(availableNow=True).start()
    query.awaitTermination()
    rows = spark.sql("SELECT kind, name, count(*) AS n FROM joined GROUP BY kind, name").collect()
    assert {(r["kind"], r["name"]) for r in rows} == {(0, "none"), (1, "one"), (2, None)} and sum(r["n"] for r in rows) == 4000


def test_streaming_counter(spark, tmp_path):
    _events(spark, tmp_path)
    schema = T.StructType([T.StructField("ts", T.TimestampType()), T.StructField("value", T.DoubleType())])
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        stream = io.stream(spark, f"{tmp_path}/events", schema).select(F.lit("all").alias("stream"))
        query = windows.streaming_counter(stream, "stream", 16, 1.0, "k").writeStream.format("memory").queryName("counter").outputMode("append").option("checkpointLocation", f"{tmp_path}/check2").start()
        query.processAllAvailable()
        query.stop()
    finally:
        spark.conf.unset("spark.sql.streaming.stateStore.providerClass")
    rows = spark.sql("SELECT * FROM counter ORDER BY step").collect()
    assert [r["step"] for r in rows] == list(range(1, len(rows) + 1))
    assert rows[-1]["noisy"] == 4000 + counting.prefix_noise(16, 1.0, 2, "k/all")[len(rows) - 1]


@pytest.mark.parametrize("spaced", [True, False])
def test_histogram_trials_from_windows_equal_those_from_all_rows(spark, spaced):
    """A third of all rows share one value; random estimates of failed trials and coarse bins lie between the windows."""
    d = Domain(0.0, 100.0)
    x = np.round(np.random.default_rng(4).normal(40, 12, 30_000), 1).clip(0, 100)
    x[::3] = 40.0
    values, x = frame(spark, x), np.sort(x)
    points = np.clip(x + np.arange(len(x)) / len(x), 0, 100) if spaced else x
    edges = [0.0, 39.99, 40.0, 40.25, 40.5, float(points[12_345]), 55.05, 99.9, 100.0]
    index = locate.Index(values, d, buckets=64, cap=100)
    assert experiments.points_below(index, edges, spaced) == np.searchsorted(points, edges, "left").tolist()
    settings = [experiments.Setting("histogram", "add_remove", 5, bins=b) for b in (16, 50)] + [experiments.Setting(k, "add_remove", 5) for k in ("independent", *experiments.METHODS)]
    settings.append(experiments.Setting("slices", "add_remove", 9, eps=0.15, delta=0.9))
    whole, parts = (sorted(experiments.run(spark, values, d, settings, 6, spaced=spaced, least=1, most=most, reach=reach).collect(), key=str) for most, reach in ((10**6, 0), (10, 8000)))
    assert whole == parts
    whole, parts = (sorted(experiments.run(spark, values, d, settings[:2], 6, spaced=spaced, least=1, most=most, reach=5).collect(), key=str) for most in (10**6, 10))
    assert whole == parts
