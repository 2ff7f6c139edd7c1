"""The two pipelines: stationary series directly, non-stationary ones by merged periods first."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from slotlens.operators import cleanse, cliquecover, fences, landscape, portraits, spectrum, threshold


def period_of(series: DataFrame, length: int, trend_ticks: int = 168) -> DataFrame:
    """Fundamental period of each series from its detrended spectrum."""
    return spectrum.fundamental(spectrum.fft_series(spectrum.detrended(series, trend_ticks=trend_ticks)), length)


def virtual_portraits(slotted: DataFrame, keys: list[str], s0: float | None = None, n: int | None = None, rule: str = "chord", y: str = "y") -> DataFrame:
    """(keys, slot, vp_id): slots merged at a threshold, to a number of groups, or by the elbow; s0 = inf merges equals only."""
    v = portraits.vectors(slotted, [*keys, "slot"], y)
    if s0 is not None:
        return cliquecover.greedy(v, s0, "slot", "vp_id", keys)
    values = slotted.select(*keys, "slot", F.col(y).alias("y")).where("y is not null")
    return threshold.build(values, v, "slot", "vp_id", "int", keys, "fixed_n" if n else rule, fixed=n)


def stationary(series: DataFrame, period: int, model: str = "iqr", s0: float | None = None, n: int | None = None, y: str = "y", **options) -> DataFrame:
    """Slots, merged slots, fences, flags, replacement: rows with vp_id, lo, hi, is_outlier, y_clean."""
    slotted = portraits.by_tick(series, period)
    groups = virtual_portraits(slotted, ["series_id"], s0, n, y=y)
    joined = slotted.join(groups, ["series_id", "slot"])
    by = ["series_id", "vp_id"]
    return cleanse.replace(cleanse.detect(joined, fences.build(model, joined, by, y=y, **options), by, y), y=y)


def nonstationary(series: DataFrame, period: int, model: str = "gamma", vlds: int | None = None, s0: float | None = None, portrait_s0: float | None = None, y: str = "y", n_min: int = fences.SMALL_GROUP, least: int = 1, **options) -> DataFrame:
    """Merged periods first, then slots merged inside each of them; small groups fall to the boxplot."""
    slotted = portraits.by_tick(series, period)
    blocks = landscape.build_virtual(slotted, vlds, s0, y=y, least=least)
    staged = landscape.attach(slotted, blocks)
    groups = virtual_portraits(staged, ["series_id", "vld_id"], portrait_s0, y=y)
    joined = staged.join(groups, ["series_id", "vld_id", "slot"])
    by = ["series_id", "vld_id", "vp_id"]
    return cleanse.replace(cleanse.detect(joined, fences.auto(joined, by, y, model, n_min, **options), by, y), y=y)


def landscape_only(series: DataFrame, model: str = "iqr", y: str = "y", **options) -> DataFrame:
    """Ablation: one group for the whole series."""
    by = ["series_id"]
    return cleanse.replace(cleanse.detect(series, fences.build(model, series, by, y=y, **options), by, y), y=y)
