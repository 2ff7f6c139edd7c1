"""Regrouping by position within the period, robust vectors, merged groups."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from slotlens.operators.series import epoch


def by_tick(series: DataFrame, period: int, ticks_per_slot: int = 1, partial: str = "keep") -> DataFrame:
    """Adds slot and period_ix from the tick; no shuffle unless incomplete periods are to go (``partial='drop'``)."""
    tick = F.col("tick")
    out = series.withColumn("slot", F.floor(F.pmod(tick, F.lit(period)) / ticks_per_slot).cast("int")).withColumn(
        "period_ix", F.floor(tick / period).cast("bigint")
    )
    if partial == "drop":
        n = F.count("*").over(Window.partitionBy("series_id", "period_ix"))
        out = out.withColumn("_n", n).where(F.col("_n") == period).drop("_n")
    return out


def by_interval(df: DataFrame, ts: str, origin: str, period_seconds: float, slices: int) -> DataFrame:
    """Irregular points to even slices of the period: slot = the slice that holds the point, half-open."""
    since = epoch(ts) - F.unix_timestamp(F.lit(origin), "yyyy-MM-dd")
    at = F.pmod(since.cast("double"), F.lit(float(period_seconds)))
    return df.withColumn("slot", F.floor(at / (period_seconds / slices)).cast("int")).withColumn(
        "period_ix", F.floor(since / period_seconds).cast("bigint")
    )


def spans(groups: DataFrame, span: float) -> DataFrame:
    """Span of each merged group: member count times the slot's span, and its runs of adjacent slots."""
    w = Window.partitionBy("series_id", "vp_id").orderBy("slot")
    runs = groups.withColumn("_r", F.col("slot") - F.row_number().over(w))
    runs = runs.groupBy("series_id", "vp_id", "_r").agg(F.min("slot").alias("a"), F.max("slot").alias("b"))
    return runs.groupBy("series_id", "vp_id").agg(
        (F.sum(F.col("b") - F.col("a") + 1) * F.lit(span)).alias("span"),
        F.sort_array(F.collect_list(F.struct((F.col("a") * span).alias("from"), ((F.col("b") + 1) * span).alias("until")))).alias("intervals"),
    )


def vectors(series: DataFrame, by: list[str], y: str = "y", method: str = "exact", mad_scale: float = 1.0) -> DataFrame:
    """(theta, mad, n) of each group of ``by``; nulls take no part.

    exact: window medians, one exchange in all. one_pass: one sorted array a group and higher-order functions.
    approx: quantile sketches in two mergeable passes, for groups beyond one task. mean_sd: the pair that
    outliers can spoil, kept for comparison. An empty ``by`` is the whole series as one group.
    """
    rows = series.where(F.col(y).isNotNull())
    keys = by or [F.lit(0).alias("_all")]
    if not by:
        rows, by, keys = rows.withColumn("_all", F.lit(0)), ["_all"], ["_all"]
    if method == "exact":
        w = Window.partitionBy(*by)
        told = rows.withColumn("theta", F.median(y).over(w))
        out = told.groupBy(*by).agg(
            F.first("theta").alias("theta"), (F.median(F.abs(F.col(y) - F.col("theta"))) * mad_scale).alias("mad"), F.count("*").alias("n")
        )
    elif method == "one_pass":
        a = rows.groupBy(*by).agg(F.sort_array(F.collect_list(y)).alias("_v"))
        a = a.withColumn("theta", mid("_v"))
        a = a.withColumn("_d", F.array_sort(F.transform("_v", lambda x: F.abs(x - F.col("theta")))))
        out = a.select(*by, "theta", (mid("_d") * mad_scale).alias("mad"), F.size("_v").cast("bigint").alias("n"))
    elif method == "approx":
        theta = rows.groupBy(*by).agg(F.percentile_approx(y, 0.5, 10_000).alias("theta"), F.count("*").alias("n"))
        out = rows.join(theta, by).groupBy(*by).agg(
            F.first("theta").alias("theta"),
            (F.percentile_approx(F.abs(F.col(y) - F.col("theta")), 0.5, 10_000) * mad_scale).alias("mad"),
            F.first("n").alias("n"),
        )
    elif method == "mean_sd":
        out = rows.groupBy(*by).agg(F.avg(y).alias("theta"), F.stddev_samp(y).alias("mad"), F.count("*").alias("n"))
    else:
        raise ValueError(f"unknown method {method}")
    return out.drop("_all")


def mid(name: str) -> Column:
    """Median of a sorted array column, by the mean of its two middle values."""
    n = F.size(name)
    return (F.get(name, F.floor((n - 1) / 2).cast("int")) + F.get(name, F.floor(n / 2).cast("int"))) / 2.0


def matrix_view(slotted: DataFrame, slots: int) -> DataFrame:
    """Periods as rows, slots as columns; for inspection of one or few series."""
    return slotted.groupBy("series_id", "period_ix").pivot("slot", list(range(slots))).agg(F.first("y"))


def attach(slotted: DataFrame, groups: DataFrame, on: list[str]) -> DataFrame:
    """Rows with their group number; the map has one row a slot (or period) of a series."""
    return slotted.join(groups, on)
