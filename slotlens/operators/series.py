"""Even spacing, gap filling and validation of series."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

SENTINEL = 1e12


def epoch(ts: str) -> Column:
    """Seconds of a time stamp without zone, read as UTC."""
    return F.unix_timestamp(F.col(ts).cast("timestamp"))


def regularise(df: DataFrame, ts: str, value: str, origin: str, step: int, agg: str = "sum", keys: list[str] | None = None) -> DataFrame:
    """Samples to an even grid: keys, tick, y, where tick counts steps of ``step`` seconds from ``origin``.

    ``agg`` is sum, mean, last (the larger of two at one time) or count. Sums add whole hundredths, so the order of rows cannot change them.
    Rows of null time are left out; a tick without rows stays absent; one shuffle after map-side partials.
    """
    keys = keys or ["series_id"]
    start = F.unix_timestamp(F.lit(origin), "yyyy-MM-dd")
    rows = df.where(F.col(ts).isNotNull()).withColumn("tick", F.floor((epoch(ts) - start) / step).cast("bigint"))
    v = F.col(value).cast("double")
    how = {
        "sum": F.sum(F.round(v * 100).cast("bigint")) / 100.0,
        "mean": F.avg(v),
        "last": F.max_by(v, F.struct(F.col(ts), v)),
        "count": F.count(v).cast("double"),
    }[agg]
    return rows.groupBy(*keys, "tick").agg(how.alias("y"))


def grid(series: DataFrame, first: int, last: int, keys: list[str]) -> DataFrame:
    return series.select(*keys).distinct().withColumn("tick", F.explode(F.sequence(F.lit(first).cast("bigint"), F.lit(last).cast("bigint"))))


def fill_gaps(series: DataFrame, first: int, last: int, default: float | None = 0.0, sentinel: bool = False, keys: list[str] | None = None) -> DataFrame:
    """Every tick from ``first`` to ``last``: adds was_missing and y_filled.

    The default is zero; ``sentinel`` takes a very large value instead, for series whose true load reaches zero;
    ``default=None`` leaves null. A series without any sample has no ticks.
    """
    keys = keys or ["series_id"]
    value = F.lit(SENTINEL) if sentinel else F.lit(default).cast("double")
    joined = grid(series, first, last, keys).join(series, [*keys, "tick"], "left")
    return joined.withColumn("was_missing", F.col("y").isNull()).withColumn("y_filled", F.coalesce("y", value))


def missing_ticks(series: DataFrame, first: int, last: int, keys: list[str] | None = None) -> DataFrame:
    """The absent ticks themselves, by anti join."""
    keys = keys or ["series_id"]
    return grid(series, first, last, keys).join(series.where("y is not null"), [*keys, "tick"], "left_anti")


def problems(series: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """One row of counts: null ticks, repeated ticks, negative and non-finite values."""
    keys = keys or ["series_id"]
    per = series.groupBy(*keys, "tick").agg(
        F.count("*").alias("n"),
        F.count_if(F.col("y") < 0).alias("negative"),
        F.count_if(F.isnan("y") | (F.abs("y") == float("inf"))).alias("not_finite"),
    )
    return per.agg(
        F.coalesce(F.sum(F.when(F.col("tick").isNull(), F.col("n"))), F.lit(0)).alias("null_ticks"),
        F.coalesce(F.sum(F.when(F.col("n") > 1, F.col("n") - 1)), F.lit(0)).alias("repeated_ticks"),
        F.coalesce(F.sum("negative"), F.lit(0)).alias("negative_values"),
        F.coalesce(F.sum("not_finite"), F.lit(0)).alias("not_finite_values"),
    )


def validate_series(series: DataFrame, period_ticks: int | None = None) -> DataFrame:
    """Raises on null or repeated ticks and non-finite values; a period must span at least two samples."""
    found = problems(series).first()
    bad = {k: v for k, v in found.asDict().items() if k != "negative_values" and v}
    if bad:
        raise ValueError(f"series is not valid: {bad}")
    if period_ticks is not None and period_ticks < 2:
        raise ValueError("the period must be at least two sampling steps")
    return series
