"""Queries whose rows come from a given table: small tables against plain Python."""

import statistics
from datetime import datetime, timedelta

import pytest

from slotlens import queries
from slotlens.functions import gamma


def with_events(spark, folder, rows):
    """A folder whose events table has the rows (event_type, hours since 2024, value); a null hour is a null time."""
    told = [(i, None if h is None else datetime(2024, 1, 1) + timedelta(hours=h), kind, v) for i, (kind, h, v) in enumerate(rows)]
    df = spark.createDataFrame(told, "event_id bigint, ts timestamp_ntz, event_type string, value double")
    df.write.parquet(f"{folder}/events.parquet")
    return str(folder)


def reads_events(df):
    return bool(df.inputFiles()) and all("events.parquet" in f for f in df.inputFiles())


def by_slot(rows):
    return [[r.y for r in rows if r.tick % 24 == slot] for slot in range(24)]


def test_asked_quantiles_follow_the_values_of_each_type(spark, sf, tmp_path):
    assert reads_events(queries.asked_quantiles(spark, sf))
    values = {"a": [1.0, 2.0, 6.0, 7.5], "b": [400.0, 401.0, 430.0, 390.0, 405.0], None: [0.5, 3.0]}
    rows = [(kind, 1, v) for kind, vs in values.items() for v in vs]
    rows += [("a", 1, None), ("one", 1, 5.0), ("same", 1, 3.0), ("same", 1, 3.0), ("below", 1, -1.0), ("below", 1, -4.0)]
    found = {(r.event_type, r.q): r.value for r in queries.asked_quantiles(spark, with_events(spark, tmp_path, rows)).collect()}
    assert set(found) == {(kind, q) for kind in (*values, "one", "same", "below") for q in (0.025, 0.5, 0.975)}
    for (kind, q), value in found.items():
        if kind in values:
            mean, var = statistics.mean(values[kind]), statistics.variance(values[kind])
            assert gamma.cdf(value, mean * mean / var, var / mean) == pytest.approx(q, abs=1e-5)
        else:
            assert value is None


def test_portrait_spans_follow_the_medians_of_the_slots(spark, sf, tmp_path):
    assert reads_events(queries.portrait_spans(spark, sf))
    # Much more load in every hour 3 and 20 and less in 11, 14 and 15, with some spread among the days.
    level = {3: 1000.0, 20: 1000.0, 11: 1.0, 14: 1.0, 15: 1.0}
    rows = [("a", t, level.get(t % 24, 100.0) + t // 24 % 7 + t % 24 / 10) for t in range(720)]
    folder = with_events(spark, tmp_path, rows)
    medians = [statistics.median(ys) for ys in by_slot(queries.X.month(spark, folder).collect())]
    bands = [sum(round(m, 6) >= edge for edge in (1.0, 1.4, 1.7)) for m in medians]
    want = {}
    for slot, band in enumerate(bands):
        span, runs = want.get(band, (0, 0))
        want[band] = (span + 1, runs + (slot == 0 or bands[slot - 1] != band))
    profile = [sum(p >= edge for edge in (100, 140, 170)) for p in queries.X.PROFILE]
    assert bands != profile
    found = {r.vp_id: (r.span, r.n_intervals) for r in queries.portrait_spans(spark, folder).collect()}
    assert found == want


def test_udf_gamma_fence_is_that_of_the_samples_of_each_slot(spark, sf, tmp_path):
    assert reads_events(queries.udf_gamma_fence(spark, sf))
    # Hour 3 is far beyond the clipping of the noise: a constant level without a gamma.
    rows = [("a", t, 9000.0 if t % 24 == 3 else 100.0 + t * 7919 % 50) for t in range(720)]
    folder = with_events(spark, tmp_path, rows)
    found = {(r.slot, r.q): r.value for r in queries.udf_gamma_fence(spark, folder).collect()}
    assert set(found) == {(slot, q) for slot in range(24) for q in (0.025, 0.5, 0.975)}
    for slot, ys in enumerate(by_slot(queries.X.month(spark, folder).collect())):
        theta = statistics.median(ys)
        mad = 1.4826 * statistics.median(abs(y - theta) for y in ys)
        for q in (0.025, 0.5, 0.975):
            if slot == 3:
                assert found[slot, q] is None
            else:
                assert gamma.cdf(found[slot, q], (theta / mad) ** 2, mad * mad / theta) == pytest.approx(q, abs=1e-4)


def test_udtf_period_ticks_spans_the_days_of_each_type(spark, sf, tmp_path):
    assert reads_events(queries.udtf_period_ticks(spark, sf))
    # Days before the origin, a type without a name, repeated hours, null times and values.
    hours = {"a": [-30, -29.5, -1, 0, 5, 5.25, 100], "b": [47, 48], None: [3, 75.5]}
    rows = [(kind, h, None if h == 100 else 1.0) for kind, hs in hours.items() for h in hs]
    rows += [("a", None, 1.0), ("never", None, 1.0)]
    found = {(r.event_type, r.slot): (r.n, r.n_held) for r in queries.udtf_period_ticks(spark, with_events(spark, tmp_path, rows)).collect()}
    want = {}
    for kind, hs in hours.items():
        held = {int(h // 1) for h in hs}
        for tick in range(min(held) // 24 * 24, max(held) // 24 * 24 + 24):
            n, k = want.get((kind, tick % 24), (0, 0))
            want[kind, tick % 24] = (n + 1, k + (tick in held))
    assert found == want
