"""Flagging, imputation, replacement, review."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from slotlens.operators import fences as FE
from slotlens.operators.portraits import by_tick, vectors
from slotlens.operators.series import fill_gaps

#: Rows of a fence table that are broadcast at most; larger tables join by shuffle on their keys.
SMALL_TABLE = 200_000


def detect(grouped: DataFrame, fences: DataFrame, by: list[str], y: str = "y", fence_rows: int | None = None) -> DataFrame:
    """Adds lo, hi, centre, model and is_outlier: strictly outside the fences. No fence or no value: not an outlier.

    ``fence_rows`` is the known number of groups; only a number up to SMALL_TABLE broadcasts the fences.
    """
    right = fences.select(*by, "lo", "hi", "centre", "model")
    if fence_rows is not None and fence_rows <= SMALL_TABLE:
        right = F.broadcast(right)
    out = (F.col(y) < F.col("lo")) | (F.col(y) > F.col("hi"))
    return grouped.join(right, by, "left").withColumn("is_outlier", F.coalesce(out, F.lit(False)))


def impute(flagged: DataFrame, medians: DataFrame, by: list[str], y: str = "y") -> DataFrame:
    """Missing values take the median of their group: column y_clean, others as they are."""
    m = medians.select(*by, F.col("theta").alias("_theta"))
    return flagged.join(m, by, "left").withColumn("y_clean", F.coalesce(F.col(y), F.col("_theta"))).drop("_theta")


def replace(flagged: DataFrame, policy: str = "centre", y: str = "y") -> DataFrame:
    """Outliers take their fence's centre (the mean, or the gamma mean), the middle of the fences, the group's median
    (a column ``median`` of the rows), or stay.

    A ``verdict`` column, if there is one, decides: only ``replace`` rows change; without one all outliers do.
    """
    named = {"centre": "centre", "median": "median", "leave": y}
    value: Column = (F.col("lo") + F.col("hi")) / 2 if policy == "middle" else F.col(named[policy])
    bad = F.col("is_outlier")
    if "verdict" in flagged.columns:
        bad = bad & (F.col("verdict") == "replace")
    return flagged.withColumn("y_clean", F.when(bad, value).otherwise(F.col(y)))


def review(flagged: DataFrame, verdicts: DataFrame, exempt: DataFrame | None = None) -> DataFrame:
    """Adds verdict to outliers: the user's, ``keep`` inside an exempt span (series_id, lo_tick, hi_tick), else pending."""
    out = flagged.join(verdicts.select("series_id", "tick", F.col("verdict").alias("_v")), ["series_id", "tick"], "left")
    if exempt is not None:
        e = exempt.select(F.col("series_id").alias("_s"), "lo_tick", "hi_tick")
        spans = out.select("series_id", "tick").join(
            e, (F.col("series_id") == F.col("_s")) & (F.col("tick") >= F.col("lo_tick")) & (F.col("tick") < F.col("hi_tick")), "left_semi"
        )
        out = out.join(spans.distinct().withColumn("_e", F.lit(True)), ["series_id", "tick"], "left")
    else:
        out = out.withColumn("_e", F.lit(None).cast("boolean"))
    told = F.coalesce("_v", F.when(F.col("_e"), "keep"), F.lit("pending"))
    return out.withColumn("verdict", F.when(F.col("is_outlier"), told)).drop("_v", "_e")


def run(series: DataFrame, period: int, first: int, last: int, model: str = "iqr", default: float | None = 0.0, sentinel: bool = False, small: bool = False, **options) -> DataFrame:
    """Gaps filled, slots, fences, flags and replacement in one: y_clean beside y, for every tick from first to last.

    A missing tick enters the fences with its default and is replaced if that lies outside; with ``default=None`` it
    has no value, is no outlier and takes its slot's median.
    """
    full = by_tick(fill_gaps(series, first, last, default, sentinel), period).withColumnRenamed("y", "_y").withColumnRenamed("y_filled", "y")
    by = ["series_id", "slot"]
    f = FE.auto(full, by, "y", model, **options) if small else FE.build(model, full, by, **options)
    clean = replace(detect(full, f, by))
    if default is None and not sentinel:
        kept = clean.withColumnRenamed("y_clean", "_clean")
        clean = impute(kept, vectors(full, by), by, "_clean").drop("_clean")
    return clean.withColumnRenamed("y", "y_filled").withColumnRenamed("_y", "y")
