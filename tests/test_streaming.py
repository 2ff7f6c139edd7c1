"""Streams give what the same batch gives."""

from pyspark.sql import functions as F

from slotlens.operators import fences, portraits
from slotlens.sources.tables import read_table
from slotlens.streaming import scoring


def _files(spark, sf, folder):
    events = read_table(spark, sf, "events").orderBy("ts")
    events.repartitionByRange(6, "ts").write.parquet(folder)
    return events


def test_stream_of_hours_equals_batch(spark, sf, tmp_path):
    events = _files(spark, sf, str(tmp_path / "in"))
    stream = scoring.meter_stream(spark, str(tmp_path / "in"), events.schema)
    q = scoring.hourly(stream, "event_type", "400 days").writeStream.outputMode("complete").format("memory").queryName("hours").trigger(availableNow=True)
    run = q.option("checkpointLocation", str(tmp_path / "c")).start()
    run.awaitTermination(120)
    got = {(r.series_id, str(r.hour)): r.y for r in spark.table("hours").collect()}
    want = (
        events.groupBy("event_type", F.date_trunc("hour", F.col("ts").cast("timestamp")).alias("hour"))
        .agg((F.sum(F.round(F.col("value") * 100).cast("bigint")) / 100.0).alias("y"))
        .collect()
    )
    assert got == {(r.event_type, str(r.hour)): r.y for r in want}


def test_scored_stream_writes_flags(spark, sf, tmp_path):
    events = _files(spark, sf, str(tmp_path / "in"))
    hours = events.select(F.col("event_type").alias("series_id"), F.date_trunc("hour", F.col("ts").cast("timestamp")).alias("hour"), F.col("value").alias("y"))
    hours.write.parquet(str(tmp_path / "h"))
    slotted = hours.withColumn("slot", F.hour("hour"))
    f = fences.boxplot(slotted, ["series_id", "slot"])
    stream = spark.readStream.schema(hours.schema).parquet(str(tmp_path / "h"))
    scoring.write_clean(scoring.score(stream, f), str(tmp_path / "out"), str(tmp_path / "k")).awaitTermination(120)
    got = spark.read.parquet(str(tmp_path / "out"))
    want = scoring.score(hours, f)
    assert got.count() == want.count()
    assert got.where("is_outlier").count() == want.where("is_outlier").count()


def test_slot_state_keeps_the_last_values(spark, tmp_path):
    rows = [("a", 0, f"2024-01-{d:02d} 00:00:00", float(d)) for d in range(1, 6)]
    df = spark.createDataFrame(rows, "series_id string, slot int, hour string, y double").withColumn("hour", F.col("hour").cast("timestamp"))
    df.coalesce(1).write.parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(df.schema).parquet(str(tmp_path / "in"))
    run = scoring.slot_state(stream, keep=3).writeStream.outputMode("update").format("memory").queryName("slots").option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start()
    run.awaitTermination(120)
    r = spark.table("slots").first()
    assert (r.theta, r.mad, r.n) == (4.0, 1.0, 3)
    assert portraits.mid("x") is not None


def _run(df, name, folder, mode="append"):
    q = df.writeStream.outputMode(mode).format("memory").queryName(name).option("checkpointLocation", str(folder)).trigger(availableNow=True)
    q.start().awaitTermination(120)
    return df.sparkSession.table(name)


def _hours(spark, rows, folder):
    df = spark.createDataFrame(rows, "series_id string, hour string, y double, is_outlier boolean").withColumn("hour", F.col("hour").cast("timestamp"))
    df.coalesce(1).write.parquet(str(folder))
    return spark.readStream.schema(df.schema).parquet(str(folder))


def test_sliding_medians_cover_each_day(spark, sf, tmp_path):
    events = _files(spark, sf, str(tmp_path / "in"))
    stream = scoring.meter_stream(spark, str(tmp_path / "in"), events.schema)
    got = _run(scoring.sliding_medians(stream, "event_type", "400 days"), "medians", tmp_path / "c", "complete")
    hours = events.select(F.date_trunc("hour", F.col("ts").cast("timestamp")).alias("h"), "event_type").distinct().count()
    assert got.count() >= hours and got.where("median is null").count() == 0


def test_repeats_go_and_late_rows_are_dropped(spark, tmp_path):
    import datetime as dt

    t0 = dt.datetime(2024, 1, 1, 12)
    # Rows are late against the watermark that stood before the last batch, hence the batch between.
    batches = [[(1, t0), (1, t0), (2, t0 + dt.timedelta(hours=9))], [(4, t0 + dt.timedelta(hours=10))], [(3, t0 - dt.timedelta(hours=8)), (5, t0 + dt.timedelta(hours=30))]]
    for k, rows in enumerate(batches):
        df = spark.createDataFrame([(i, t, 1.0, "a") for i, t in rows], "event_id bigint, ts timestamp, value double, event_type string")
        df.coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    stream = spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    kept = _run(scoring.without_repeats(stream), "once", tmp_path / "c")
    assert sorted(r.event_id for r in kept.collect()) == [1, 2, 4, 5]
    hours = _run(scoring.hourly(stream, "event_type", "2 hours"), "final_hours", tmp_path / "d")
    # Event 3 came eight hours behind the watermark's reach; the last hour is still open.
    assert sorted((r.hour.hour, r.y) for r in hours.collect()) == [(12, 2.0), (21, 1.0), (22, 1.0)]


def test_sessions_join_neighbouring_outliers(spark, tmp_path):
    rows = [("a", f"2024-01-01 {h:02d}:00:00", 1.0, h in (2, 3, 4, 12)) for h in range(24)] + [("a", "2024-01-05 00:00:00", 1.0, True)]
    got = _run(scoring.regions(_hours(spark, rows, tmp_path / "in")), "runs", tmp_path / "c", "complete")
    assert sorted((r["first"].day, r["first"].hour, r.n) for r in got.collect()) == [(1, 2, 3), (1, 12, 1), (5, 0, 1)]


def test_reviews_meet_their_samples(spark, tmp_path):
    flagged = _hours(spark, [("a", f"2024-01-01 {h:02d}:00:00", float(h), True) for h in range(6)], tmp_path / "in")
    rows = [("a", "2024-01-01 02:00:00", "2024-01-01 05:00:00", "keep"), ("a", "2024-01-01 03:00:00", "2024-01-03 05:00:00", "replace")]
    v = spark.createDataFrame(rows, "series_id string, hour string, decided_at string, verdict string")
    v = v.withColumn("hour", F.col("hour").cast("timestamp")).withColumn("decided_at", F.col("decided_at").cast("timestamp"))
    v.coalesce(1).write.parquet(str(tmp_path / "v"))
    told = _run(scoring.reviewed(flagged, spark.readStream.schema(v.schema).parquet(str(tmp_path / "v"))), "told", tmp_path / "c")
    assert [(r.y, r.verdict) for r in told.collect()] == [(2.0, "keep")]
