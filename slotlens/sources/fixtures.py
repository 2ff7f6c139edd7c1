"""Test inputs derived from the given tables: a fixed profile modulated by noise of the tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from slotlens.operators import series as S
from slotlens.sources.tables import read_table

# Hundredths of the hourly profile, of the seasons by month, of the weekly profile.
PROFILE = [79, 78, 77, 84, 99, 130, 169, 176, 169, 160, 150, 140, 135, 130, 130, 140, 160, 190, 210, 215, 200, 170, 130, 95]
SEASON = [200, 190, 150, 100, 70, 60, 90, 140, 120, 80, 70, 160]
MILD = [120, 115, 105, 95, 90, 100, 125, 130, 110, 95, 100, 115]
WEEK = [100, 104, 106, 105, 110, 80, 70]


def _pick(values: list[int], at: Column) -> Column:
    return F.get(F.array(*map(F.lit, values)), at.cast("int"))


def hourly(spark: SparkSession, sf_dir: str) -> DataFrame:
    """sum of events.value per hour of the 30 days, absent hours absent."""
    events = read_table(spark, sf_dir, "events").withColumn("series_id", F.lit("all"))
    return S.regularise(events, "ts", "value", "2024-01-01", 3600, keys=["series_id"])


def robust_z(df: DataFrame, v: str, keys: list[str]) -> DataFrame:
    """Column z: (v - median) / MAD clipped to [-3, 3]; 0 where the MAD is 0."""
    w = Window.partitionBy(*keys)
    df = df.withColumn("_m", F.median(v).over(w)).withColumn("_d", F.median(F.abs(F.col(v) - F.col("_m"))).over(w))
    z = F.coalesce((F.col(v) - F.col("_m")) / F.nullif(F.col("_d"), F.lit(0.0)), F.lit(0.0))
    return df.withColumn("z", F.greatest(F.lit(-3.0), F.least(F.lit(3.0), z))).drop("_m", "_d")


def pollute(df: DataFrame) -> DataFrame:
    """Adds is_polluted, style and y from y_true by the quadratic rule (about 5 percent of the ticks)."""
    t = F.col("tick")
    style = F.pmod(F.pmod(13 * t * t + 5 * t + 3, F.lit(1009)), F.lit(3)).cast("int")
    bad = F.pmod(31 * t * t + 17 * t + 7, F.lit(10007)) < 500
    wrong = F.when(style == 0, F.lit(0.0)).when(style == 1, F.col("y_true") * 2.0).otherwise(F.col("y_true") * 0.5)
    return df.withColumns({"is_polluted": bad, "style": style, "y": F.when(bad, wrong).otherwise(F.col("y_true"))})


def _stamp(origin: str, step: int) -> Column:
    return F.timestamp_seconds(F.unix_timestamp(F.lit(origin), "yyyy-MM-dd") + F.col("tick") * step).cast("timestamp_ntz")


_OUT = ["series_id", "ts", "tick", "y", "y_true", "is_polluted", "style"]


def month(spark: SparkSession, sf_dir: str) -> DataFrame:
    """720 hourly ticks, daily profile with 3 percent noise of the hourly sums, polluted."""
    full = S.fill_gaps(hourly(spark, sf_dir), 0, 719, default=0.0)
    z = robust_z(full, "y_filled", ["series_id"])
    true = _pick(PROFILE, F.pmod("tick", F.lit(24))) / 100.0 * (1.0 + 0.03 * F.col("z"))
    return pollute(z.withColumn("y_true", true).withColumn("ts", _stamp("2024-01-01", 3600))).select(*_OUT)


def fleet(spark: SparkSession, sf_dir: str, by: str = "event_type") -> DataFrame:
    """as F2 per event type (or user), each series scaled by 1 + index / 10."""
    events = read_table(spark, sf_dir, "events").withColumn("series_id", F.col(by).cast("string"))
    full = S.fill_gaps(S.regularise(events, "ts", "value", "2024-01-01", 3600, keys=["series_id"]), 0, 719, default=0.0)
    z = robust_z(full, "y_filled", ["series_id"])
    names = events.select("series_id").distinct()
    index = names.withColumn("ix", F.row_number().over(Window.orderBy("series_id")) - 1)
    z = z.join(index, "series_id")
    scale = 1.0 + F.col("ix") / 10.0
    true = scale * (_pick(PROFILE, F.pmod("tick", F.lit(24))) / 100.0) * (1.0 + 0.03 * F.col("z"))
    return pollute(z.withColumn("y_true", true).withColumn("ts", _stamp("2024-01-01", 3600))).select(*_OUT)


def daily_quantity(spark: SparkSession, sf_dir: str, first: str, days: int) -> DataFrame:
    """(tick, v): sum of l_quantity per ship day from ``first``, absent days 0."""
    line = read_table(spark, sf_dir, "lineitem").withColumn("series_id", F.lit("all"))
    line = line.where((F.col("l_shipdate") >= F.lit(first).cast("timestamp_ntz"))).where(
        F.col("l_shipdate") < F.date_add(F.lit(first).cast("date"), days).cast("timestamp_ntz")
    )
    per_day = S.regularise(line, "l_shipdate", "l_quantity", first, 86400, keys=["series_id"])
    return S.fill_gaps(per_day, 0, days - 1, default=0.0).select("series_id", "tick", F.col("y_filled").alias("v"))


def year_true(spark: SparkSession, sf_dir: str, season: list[int] = SEASON) -> DataFrame:
    """F4 (or F4m with the mild season) before pollution: 8760 hourly ticks of 1997."""
    days = robust_z(daily_quantity(spark, sf_dir, "1997-01-01", 365), "v", ["series_id"]).withColumnRenamed("tick", "day")
    hours = days.withColumn("h", F.explode(F.sequence(F.lit(0), F.lit(23)))).withColumn("tick", F.col("day") * 24 + F.col("h"))
    t = F.col("tick")
    noise = F.pmod(37 * t * t + 11 * t + 5, F.lit(9973)) / 9973.0 - 0.5
    m = F.month(F.date_add(F.lit("1997-01-01").cast("date"), F.col("day").cast("int"))) - 1
    true = _pick(PROFILE, F.col("h")) / 100.0 * (_pick(season, m) / 100.0) * (1.0 + 0.02 * F.col("z") + 0.06 * noise)
    return hours.withColumn("y_true", true).withColumn("ts", _stamp("1997-01-01", 3600)).select("series_id", "ts", "tick", "y_true")


def year(spark: SparkSession, sf_dir: str, season: list[int] = SEASON) -> DataFrame:
    return pollute(year_true(spark, sf_dir, season)).select(*_OUT)


def weekly(spark: SparkSession, sf_dir: str) -> DataFrame:
    """2499 daily ticks with a weekly profile and the strong season."""
    days = robust_z(daily_quantity(spark, sf_dir, "1995-01-02", 2499), "v", ["series_id"])
    m = F.month(F.date_add(F.lit("1995-01-02").cast("date"), F.col("tick").cast("int"))) - 1
    y = _pick(WEEK, F.pmod("tick", F.lit(7))) / 100.0 * (1.0 + 0.03 * F.col("z")) * (_pick(SEASON, m) / 100.0)
    return days.withColumn("y", y).withColumn("ts", _stamp("1995-01-02", 86400)).select("series_id", "ts", "tick", "y")


def _labelled(df: DataFrame, bad: Column, wrong: Column) -> DataFrame:
    return df.withColumns({"is_polluted": bad, "style": F.lit(0), "y": F.when(bad, wrong).otherwise(F.col("y_true"))}).select(*_OUT)


def outage(spark: SparkSession, sf_dir: str) -> DataFrame:
    """the clean year with ticks 3920 to 3975 lost and set to zero."""
    return _labelled(year_true(spark, sf_dir), F.col("tick").between(3920, 3975), F.lit(0.0))


def holidays(spark: SparkSession, sf_dir: str) -> DataFrame:
    """F6b: three days in a row at 1.6 times their level."""
    return _labelled(year_true(spark, sf_dir), F.floor(F.col("tick") / 24).between(180, 182), F.col("y_true") * 1.6)


def hidden(spark: SparkSession, sf_dir: str) -> DataFrame:
    """polluted ticks of F2 take the next day's value of the same hour."""
    base = month(spark, sf_dir)
    lead = F.lead("y_true", 24).over(Window.partitionBy("series_id").orderBy("tick"))
    base = base.withColumn("_next", F.coalesce(lead, F.col("y_true")))
    return base.withColumn("y", F.when(F.col("is_polluted"), F.col("_next")).otherwise(F.col("y_true"))).select(*_OUT)
