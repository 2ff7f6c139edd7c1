"""Pairwise similarity of robust vectors and the threshold graph."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from slotlens.functions.covers import SLACK


def _distance(a: str, b: str) -> Column:
    return F.sqrt((F.col(f"{a}.theta") - F.col(f"{b}.theta")) ** 2 + (F.col(f"{a}.mad") - F.col(f"{b}.mad")) ** 2)


def pairs(vectors: DataFrame, item: str = "slot") -> DataFrame:
    """(series_id, a, b, dist, s) for a < b inside each series; coinciding vectors have infinite similarity.

    r items of one series give r (r - 1) / 2 rows: the items are slots of a period, not rows of the data.
    """
    a, b = vectors.alias("a"), vectors.alias("b")
    on = (F.col("a.series_id") == F.col("b.series_id")) & (F.col(f"a.{item}") < F.col(f"b.{item}"))
    d = _distance("a", "b")
    return a.join(b, on).select(
        F.col("a.series_id").alias("series_id"),
        F.col(f"a.{item}").alias("a"),
        F.col(f"b.{item}").alias("b"),
        d.alias("dist"),
        F.when(d == 0, F.lit(float("inf"))).otherwise(1.0 / d).alias("s"),
    )


def edges(vectors: DataFrame, s0: float, item: str = "slot", method: str = "dense") -> DataFrame:
    """Pairs whose similarity reaches s0. grid: cells of side 1 / s0, each vector met in the 3 x 3 around its own."""
    if method == "dense":
        return pairs(vectors, item).where(F.col("dist") * s0 <= 1 + SLACK)
    side = (1 / s0) * (1 + 1e-9)
    celled = vectors.withColumn("cx", F.floor(F.col("theta") / side)).withColumn("cy", F.floor(F.col("mad") / side))
    around = F.array(*(F.struct(F.lit(x).alias("dx"), F.lit(y).alias("dy")) for x in (-1, 0, 1) for y in (-1, 0, 1)))
    spread = celled.withColumn("c", F.explode(around)).withColumn("cx", F.col("cx") + F.col("c.dx")).withColumn("cy", F.col("cy") + F.col("c.dy"))
    a, b = celled.alias("a"), spread.alias("b")
    on = (
        (F.col("a.series_id") == F.col("b.series_id"))
        & (F.col("a.cx") == F.col("b.cx"))
        & (F.col("a.cy") == F.col("b.cy"))
        & (F.col(f"a.{item}") < F.col(f"b.{item}"))
    )
    d = _distance("a", "b")
    near = a.join(b, on).select(
        F.col("a.series_id").alias("series_id"), F.col(f"a.{item}").alias("a"), F.col(f"b.{item}").alias("b"), d.alias("dist")
    )
    near = near.withColumn("s", F.when(F.col("dist") == 0, F.lit(float("inf"))).otherwise(1.0 / F.col("dist")))
    return near.where(F.col("dist") * s0 <= 1 + SLACK)
