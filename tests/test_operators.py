"""Operators on small series in Spark."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from slotlens.operators import cleanse, cliquecover, fences, landscape, portraits, series, similarity, spectrum
from slotlens.plans import cost, metrics, pipelines
from slotlens.sources import fixtures as X
from slotlens.sources import tables


def frame(spark, values, name="a"):
    return spark.createDataFrame([(name, i, v) for i, v in enumerate(values)], "series_id string, tick bigint, y double")


def test_empty_and_tiny_series(spark):
    none = frame(spark, [1.0]).limit(0)
    assert portraits.vectors(portraits.by_tick(none, 24), ["series_id", "slot"]).count() == 0
    one = portraits.vectors(portraits.by_tick(frame(spark, [2.0]), 24), ["series_id", "slot"]).first()
    assert (one.theta, one.mad, one.n) == (2.0, 0.0, 1)


@pytest.mark.parametrize("method", ["exact", "one_pass"])
def test_vectors_skip_nulls(spark, method):
    v = portraits.vectors(portraits.by_tick(frame(spark, [1.0, 5.0, None, 5.0, 4.0, 7.0]), 2), ["series_id", "slot"], method=method)
    assert {r.slot: (r.theta, r.mad, r.n) for r in v.collect()} == {0: (2.5, 1.5, 2), 1: (5.0, 0.0, 3)}


def test_partial_period_dropped_or_kept(spark):
    s = frame(spark, [1.0] * 7)
    assert portraits.by_tick(s, 3).count() == 7
    assert portraits.by_tick(s, 3, partial="drop").count() == 6


def test_validate_rejects_repeats(spark):
    with pytest.raises(ValueError):
        series.validate_series(frame(spark, [1.0]).union(frame(spark, [1.0])))
    series.validate_series(frame(spark, [1.0, 2.0]))


def test_gap_defaults(spark):
    s = frame(spark, [1.0, 2.0, 3.0]).where("tick != 1")
    assert [r.y_filled for r in series.fill_gaps(s, 0, 2).orderBy("tick").collect()] == [1.0, 0.0, 3.0]
    assert series.fill_gaps(s, 0, 2, sentinel=True).where("was_missing").first().y_filled == series.SENTINEL
    assert series.fill_gaps(s, 0, 2, default=None).where("y_filled is null").count() == 1
    assert [r.tick for r in series.missing_ticks(s, 0, 2).collect()] == [1]


def test_three_transforms_agree(spark):
    y = np.random.default_rng(0).normal(size=48)
    s = frame(spark, y.tolist())
    want = np.fft.rfft(y)
    for got in (spectrum.dft_bins(s, list(range(25)), 48), spectrum.fft_series(s), spectrum.fft_blocked(s, 48, 6)):
        rows = {r.k: complex(r.re, r.im) for r in got.collect()}
        assert len(rows) == 25
        assert all(abs(rows[k] - want[k]) < 1e-9 for k in rows)


def test_grid_edges_equal_dense_edges(spark):
    rng = np.random.default_rng(5)
    v = spark.createDataFrame([("a", i, float(a), float(b)) for i, (a, b) in enumerate(rng.random((40, 2)))], "series_id string, slot int, theta double, mad double")
    for s0 in (2.0, 7.0):
        dense = {(r.a, r.b) for r in similarity.edges(v, s0).collect()}
        assert dense == {(r.a, r.b) for r in similarity.edges(v, s0, method="grid").collect()}
        bad = cliquecover.violations(cliquecover.greedy(v, s0), v, s0).first()
        assert (bad.pairs_below, bad.not_once) == (0, 0)


def test_parallel_rounds_equal_the_sequential_cover(spark):
    rng = np.random.default_rng(8)
    v = spark.createDataFrame([("a", i, float(a), float(b)) for i, (a, b) in enumerate(rng.random((18, 2)))], "series_id string, slot int, theta double, mad double")
    one = cliquecover.greedy(v, 3.0).toPandas()
    two = cliquecover.greedy_rounds(v.select(F.col("slot").alias("v")), similarity.edges(v, 3.0)).toPandas()
    a = {frozenset(g["slot"]) for _, g in one.groupby("vp_id")}
    assert a == {frozenset(g["v"]) for _, g in two.groupby("seed")}


def test_fences_are_monotone_and_degenerate_groups_are_named(spark):
    s = frame(spark, [float(x) for x in range(1, 41)])
    wide, narrow = fences.normal(s, ["series_id"], alpha=0.01).first(), fences.normal(s, ["series_id"], alpha=0.2).first()
    assert wide.lo < narrow.lo < narrow.hi < wide.hi
    box, far = fences.boxplot(s, ["series_id"]).first(), fences.boxplot(s, ["series_id"], rho=3.0).first()
    assert far.lo < box.lo and far.hi > box.hi
    zero = fences.gamma(frame(spark, [0.0] * 5), ["series_id"]).first()
    assert zero.model == "gamma:iqr" and zero.lo == zero.hi == 0.0
    few = fences.auto(s.limit(5), ["series_id"]).first()
    assert few.model == "iqr:small"


def test_detection_is_strict_and_replacement_obeys_verdicts(spark):
    s = frame(spark, [1.0, 2.0, 3.0])
    f = spark.createDataFrame([("a", 1.0, 2.0, 1.5, "own")], "series_id string, lo double, hi double, centre double, model string")
    told = cleanse.detect(s, f, ["series_id"], fence_rows=1)
    assert [r.is_outlier for r in told.orderBy("tick").collect()] == [False, False, True]
    assert cleanse.replace(told).where("tick = 2").first().y_clean == 1.5
    verdicts = spark.createDataFrame([("a", 2, "keep")], "series_id string, tick bigint, verdict string")
    assert cleanse.replace(cleanse.review(told, verdicts)).where("tick = 2").first().y_clean == 3.0


def test_month_pipeline_beats_the_floor(spark, sf):
    m = X.month(spark, sf)
    assert m.count() == 720 and m.where("is_polluted").count() == 46
    assert pipelines.period_of(m, 720).first().period_ticks == 24
    assert metrics.scores(pipelines.stationary(m, 24, "iqr")).first().f_measure > 0.7


def test_whole_outage_is_found_once_small_groups_are_absorbed(spark):
    y = [10.0 + (t % 4) + 0.01 * (t % 7) for t in range(160)]
    y[80:88] = [0.0] * 8
    s = frame(spark, y)
    told = pipelines.nonstationary(s, 4, "iqr", 2, least=3)
    assert told.where("tick between 80 and 87 and not is_outlier").count() == 0
    assert landscape.route(s, 4).first().route == "stationary"


def test_one_exchange_serves_slot_vectors(spark):
    rows = portraits.by_tick(frame(spark, [1.0, 2.0, 3.0]).union(frame(spark, [4.0, 5.0], "b")), 2).repartition(4, "series_id")
    shape = cost.plan_shape(portraits.vectors(rows, ["series_id", "slot"]))
    assert shape["Exchange hashpartitioning"] == 1 and shape["Exchange SinglePartition"] == 0


def test_series_layout_round_trip(spark, sf, tmp_path):
    m = X.month(spark, sf).select("series_id", "ts", "tick", "y")
    tables.write_series(m, str(tmp_path / "s"))
    assert tables.read_series(spark, str(tmp_path / "s")).count() == 720
    spark.dataSource.register(tables.MeterSource)
    assert spark.read.format("slot_meters").option("meters", 2).option("ticks", 5).load().count() == 10


def test_parallel_cover_of_a_path_is_whole(spark):
    n = 120
    edges = spark.range(n - 1).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    vertices = spark.range(n).withColumnRenamed("id", "v")
    rows = cliquecover.greedy_rounds(vertices, edges).collect()
    assert sorted(r.v for r in rows) == list(range(n))
    groups = {}
    for r in rows:
        groups.setdefault(r.seed, []).append(r.v)
    assert all(len(g) == 1 or len(g) == 2 and abs(g[0] - g[1]) == 1 for g in groups.values())
    with pytest.raises(RuntimeError):
        cliquecover.greedy_rounds(vertices, edges, ties="id", most_rounds=2)


def test_smoother_in_groups_skips_nulls(spark):
    from slotlens.operators import smoother

    values = [float(t % 5) for t in range(40)]
    values[7], values[20] = None, 50.0
    s = frame(spark, values).withColumn("vp_id", F.lit(0))
    told = {r.tick: r for r in smoother.fit_in_groups(s, 8).collect()}
    assert told[7].y_hat is not None and not told[7].is_outlier and told[20].is_outlier
    assert smoother.fit_in_groups(s.withColumn("y", F.lit(None).cast("double")), 8).where("is_outlier").count() == 0


def test_transform_places_values_at_their_ticks(spark):
    y = [float(np.cos(2 * np.pi * t / 8)) for t in range(64)]
    holes = frame(spark, y).where("tick not in (10, 11, 40)").withColumn("y", F.when(F.col("tick") != 30, F.col("y")))
    power = {r.k: r.power for r in spectrum.fft_series(holes).collect()}
    assert max(power, key=power.get) == 8 and len(power) == 33 and all(p == p for p in power.values())


def test_exact_cover_of_all_slots_is_no_larger_than_greedy(spark, sf):
    v = portraits.vectors(portraits.by_tick(X.month(spark, sf), 24), ["series_id", "slot"])
    one, two = cliquecover.exact(v, 3.3), cliquecover.greedy(v, 3.3)
    assert one.select("vp_id").distinct().count() <= two.select("vp_id").distinct().count() and one.count() == 24


def test_gamma_fit_check_prefers_the_right_model(spark):
    rng = np.random.default_rng(1)
    s = frame(spark, rng.gamma(1.5, 2.0, 800).tolist())
    wrong, right = (fences.fit_check(s, ["series_id"], model=m).first() for m in ("normal", "gamma"))
    assert right.distance < wrong.distance and right.count_statistic < wrong.count_statistic


def test_gaps_are_filled_found_and_repaired_in_one_call(spark):
    s = frame(spark, [10.0 + (t % 2) for t in range(40)]).where("tick != 9")
    told = {r.tick: r for r in cleanse.run(s, 2, 0, 39).collect()}
    assert told[9].was_missing and told[9].is_outlier and told[9].y_clean > 10 and told[9].y is None
    none = {r.tick: r for r in cleanse.run(s, 2, 0, 39, default=None).collect()}
    assert none[9].y_clean == 11.0 and not none[9].is_outlier


def test_meter_dumps_and_buckets(spark, tmp_path):
    rows = spark.createDataFrame([("a", "2024-01-01 00:00:00", 1.5), ("b", "2024-01-01 01:00:00", 2.5)], "series_id string, ts string, y double")
    rows.write.csv(str(tmp_path / "c"), header=True)
    rows.write.json(str(tmp_path / "j"))
    for read, folder in ((tables.read_meter_csv, "c"), (tables.read_meter_json, "j")):
        assert sorted((r.series_id, r.y) for r in read(spark, str(tmp_path / folder)).collect()) == [("a", 1.5), ("b", 2.5)]
