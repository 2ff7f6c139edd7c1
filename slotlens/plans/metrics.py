"""Accuracy measures against labels."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def confusion(flagged: DataFrame, by: list[str] | None = None, label: str = "is_polluted", flag: str = "is_outlier") -> DataFrame:
    """tp, fp, tn, fn in one aggregate; an unknown flag counts as not flagged."""
    a, b = F.coalesce(F.col(label), F.lit(False)), F.coalesce(F.col(flag), F.lit(False))
    return flagged.groupBy(*(by or [])).agg(
        F.count_if(a & b).alias("tp"), F.count_if(~a & b).alias("fp"), F.count_if(~a & ~b).alias("tn"), F.count_if(a & ~b).alias("fn")
    )


def ratios(counts: DataFrame) -> DataFrame:
    p, r = F.try_divide("tp", F.col("tp") + F.col("fp")), F.try_divide("tp", F.col("tp") + F.col("fn"))
    return (
        counts.withColumn("accuracy", F.try_divide(F.col("tp") + F.col("tn"), F.col("tp") + F.col("fp") + F.col("tn") + F.col("fn")))
        .withColumn("precision", p)
        .withColumn("recall", r)
        .withColumn("f_measure", F.try_divide(2.0 * F.col("precision") * F.col("recall"), F.col("precision") + F.col("recall")))
    )


def scores(flagged: DataFrame, by: list[str] | None = None, **columns) -> DataFrame:
    """Point-wise accuracy, precision, recall and F-measure; null where a ratio has no cases."""
    return ratios(confusion(flagged, by, **columns))


def macro_scores(flagged: DataFrame, group: list[str], **columns) -> DataFrame:
    """Plain means of each group's ratios."""
    per = scores(flagged, group, **columns)
    return per.agg(*(F.avg(c).alias(c) for c in ("accuracy", "precision", "recall", "f_measure")), F.count("*").alias("groups"))


def regions(flagged: DataFrame, column: str, keys: list[str] | None = None) -> DataFrame:
    """Runs of adjacent ticks where the boolean column holds: (keys, first_tick, last_tick)."""
    keys = keys or ["series_id"]
    w = Window.partitionBy(*keys).orderBy("tick")
    runs = flagged.where(F.col(column)).withColumn("_r", F.col("tick") - F.row_number().over(w))
    return runs.groupBy(*keys, "_r").agg(F.min("tick").alias("first_tick"), F.max("tick").alias("last_tick")).drop("_r")


def region_scores(flagged: DataFrame, keys: list[str] | None = None, label: str = "is_polluted", flag: str = "is_outlier") -> DataFrame:
    """Region form: a detected run is right if it meets a labelled one, a labelled run found if a detected one meets it."""
    keys = keys or ["series_id"]
    a, b = regions(flagged, label, keys), regions(flagged, flag, keys)
    x, y = a.alias("x"), b.alias("y")
    meets = (F.col("x.first_tick") <= F.col("y.last_tick")) & (F.col("y.first_tick") <= F.col("x.last_tick"))
    for k in keys:
        meets = meets & (F.col(f"x.{k}") == F.col(f"y.{k}"))
    found = x.join(y, meets, "left_semi").agg(F.count("*").alias("found"))
    right = y.join(x, meets, "left_semi").agg(F.count("*").alias("right"))
    n = a.agg(F.count("*").alias("labelled")).crossJoin(b.agg(F.count("*").alias("detected"))).crossJoin(found).crossJoin(right)
    n = n.withColumn("precision", F.try_divide("right", "detected")).withColumn("recall", F.try_divide("found", "labelled"))
    return n.withColumn("f_measure", F.try_divide(2.0 * F.col("precision") * F.col("recall"), F.col("precision") + F.col("recall")))


def imputation_error(cleaned: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Mean absolute error of y_clean on polluted points, beside that of the polluted values themselves."""
    bad = cleaned.where("is_polluted")
    return bad.groupBy(*(by or [])).agg(
        F.avg(F.abs(F.col("y_clean") - F.col("y_true"))).alias("mae_clean"), F.avg(F.abs(F.col("y") - F.col("y_true"))).alias("mae_polluted")
    )


def outage_recall(flagged: DataFrame, first: int, last: int) -> DataFrame:
    """Share of the ticks of an outage that are flagged."""
    return flagged.where(F.col("tick").between(first, last)).groupBy("series_id").agg(
        F.avg(F.col("is_outlier").cast("double")).alias("outage_recall"), F.count("*").alias("n")
    )
