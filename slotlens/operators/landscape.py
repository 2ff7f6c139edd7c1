"""Whole periods as blocks, merged into groups of like level: the route for non-stationary series."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from slotlens.operators import cliquecover, threshold
from slotlens.operators.portraits import by_tick, vectors


def block_vectors(slotted: DataFrame, y: str = "y") -> DataFrame:
    """(series_id, period_ix, theta, mad, n) of each period."""
    return vectors(slotted, ["series_id", "period_ix"], y)


def build_virtual(slotted: DataFrame, n: int | None = None, s0: float | None = None, rule: str = "chord", y: str = "y", least: int = 1) -> DataFrame:
    """(series_id, period_ix, vld_id): periods merged at a given threshold, to a given number of groups, or by the elbow.

    ``least`` above 1 gives groups of fewer periods to the nearest larger group: days lost as a whole would
    otherwise be a group of their own, whose fences hold nothing but the loss.
    """
    found = _merge(slotted, n, s0, rule, y)
    return found if least <= 1 else absorb_small(slotted, found, least, y)


def absorb_small(slotted: DataFrame, groups: DataFrame, least: int, y: str = "y") -> DataFrame:
    """Groups under ``least`` periods take the number of the nearest group that has them; a series without any keeps its own."""
    v = vectors(attach(slotted, groups), ["series_id", "vld_id"], y)
    size = groups.groupBy("series_id", "vld_id").agg(F.count("*").alias("periods"))
    told = v.join(size, ["series_id", "vld_id"])
    small = told.where(F.col("periods") < least).select("series_id", F.col("vld_id").alias("s_id"), F.col("theta").alias("s_t"), F.col("mad").alias("s_m"))
    large = told.where(F.col("periods") >= least).select(F.col("series_id").alias("l_series"), F.col("vld_id").alias("l_id"), "theta", "mad")
    away = F.hypot(F.col("s_t") - F.col("theta"), F.col("s_m") - F.col("mad"))
    near = small.join(large, F.col("series_id") == F.col("l_series")).groupBy("series_id", "s_id").agg(F.min_by("l_id", F.struct(away, F.col("l_id"))).alias("to_id"))
    near = near.withColumnRenamed("series_id", "n_series")
    moved = groups.join(near, (F.col("series_id") == F.col("n_series")) & (F.col("vld_id") == F.col("s_id")), "left")
    return moved.select("series_id", "period_ix", F.coalesce("to_id", "vld_id").alias("vld_id"))


def _merge(slotted: DataFrame, n: int | None, s0: float | None, rule: str, y: str) -> DataFrame:
    v = block_vectors(slotted, y)
    if s0 is not None:
        return cliquecover.greedy(v, s0, "period_ix", "vld_id", kind="bigint")
    values = slotted.select("series_id", "period_ix", F.col(y).alias("y")).where("y is not null")
    return threshold.build(
        values, v, "period_ix", "vld_id", "bigint", rule="fixed_n" if n else rule, fixed=n, most_groups=None if n is None else 4 * n
    )


def attach(slotted: DataFrame, groups: DataFrame) -> DataFrame:
    return slotted.join(groups, ["series_id", "period_ix"])


def route(series: DataFrame, period: int, spread: float = 0.25) -> DataFrame:
    """(series_id, level_spread, route): direct for a level that hardly moves between periods, else by blocks.

    level_spread is the MAD of the block medians over their median; the threshold is a choice of this package.
    """
    blocks = block_vectors(by_tick(series, period))
    told = vectors(blocks.select("series_id", F.col("theta").alias("y")), ["series_id"])
    return told.select(
        "series_id",
        (F.col("mad") / F.nullif(F.col("theta"), F.lit(0.0))).alias("level_spread"),
        F.when(F.col("mad") <= spread * F.abs("theta"), "stationary").otherwise("nonstationary").alias("route"),
    )
