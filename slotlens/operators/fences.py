"""Outlier regions of a group: normal, gamma, boxplot, small-sample choice, own strategies."""

from __future__ import annotations

from collections.abc import Callable
from statistics import NormalDist

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf
from pyspark.sql.types import DoubleType

from slotlens.functions import gamma as G
from slotlens.operators.portraits import vectors

ALPHA, RHO, EXTREME = 0.05, 1.5, 3.0
#: Makes a MAD comparable to a standard deviation under normality.
CONSISTENT = 1.4826
SMALL_GROUP = 30

_strategies: dict[str, Callable[[DataFrame, list[str]], DataFrame]] = {}


def region(quantile: Callable[[float], float | Column], alpha: float = ALPHA) -> tuple:
    """Fences (lo, hi) of any distribution given by its quantile function; ``alpha`` is the probability outside."""
    if not 0 < alpha < 1:
        raise ValueError("alpha must lie between 0 and 1")
    return quantile(alpha / 2), quantile(1 - alpha / 2)


def _estimates(series: DataFrame, by: list[str], y: str, estimator: str, mad_scale: float) -> DataFrame:
    """theta and mad hold centre and deviation: robust (scaled), literal (unscaled) or moments."""
    if estimator == "moments":
        return vectors(series, by, y, "mean_sd")
    return vectors(series, by, y, "exact", 1.0 if estimator == "literal" else mad_scale)


def normal(series: DataFrame, by: list[str], y: str = "y", alpha: float = ALPHA, estimator: str = "robust", mad_scale: float = CONSISTENT) -> DataFrame:
    """(by, n, lo, hi, centre, model) from centre and deviation."""
    e = _estimates(series, by, y, estimator, mad_scale)
    low, high = region(NormalDist().inv_cdf, alpha)
    return e.select(
        *by, "n", (F.col("theta") + low * F.col("mad")).alias("lo"), (F.col("theta") + high * F.col("mad")).alias("hi"), F.col("theta").alias("centre"), F.lit("normal").alias("model")
    )


def gamma_quantile(q: float):
    """Column function (shape, scale) -> quantile; meant for fence tables, which have a row a group."""

    @pandas_udf("double")
    def run(shape: pd.Series, scale: pd.Series) -> pd.Series:
        return pd.Series([G.quantile(q, a, b) if a is not None and a == a and b == b else float("nan") for a, b in zip(shape, scale, strict=True)])

    return run


def gamma(
    series: DataFrame, by: list[str], y: str = "y", alpha: float = ALPHA, estimator: str = "robust", mad_scale: float = CONSISTENT, on_degenerate: str = "iqr", replacement: str = "mean"
) -> DataFrame:
    """Fences from shape = centre^2 / deviation^2 and scale = deviation^2 / centre.

    Where centre or deviation is not positive there is no gamma: ``iqr`` falls back to the boxplot, ``point``
    fences the centre itself, ``none`` leaves nulls. ``replacement``: mean (shape times scale) or ratio (the
    quotient, as one reading of the method has it).
    """
    e = _estimates(series, by, y, estimator, mad_scale)
    fine = (F.col("theta") > 0) & (F.col("mad") > 0)
    e = e.withColumn("shape", F.when(fine, (F.col("theta") / F.col("mad")) ** 2)).withColumn("scale", F.when(fine, F.col("mad") ** 2 / F.col("theta")))
    centre = F.col("shape") * F.col("scale") if replacement == "mean" else F.col("shape") / F.col("scale")
    out = e.select(
        *by,
        "n",
        F.nanvl(gamma_quantile(alpha / 2)("shape", "scale"), F.lit(None)).alias("lo"),
        F.nanvl(gamma_quantile(1 - alpha / 2)("shape", "scale"), F.lit(None)).alias("hi"),
        F.coalesce(centre, "theta").alias("centre"),
        F.when(fine, "gamma").otherwise(f"gamma:{on_degenerate}").alias("model"),
        F.col("theta").alias("_theta"),
    )
    if on_degenerate == "point":
        return out.select(*by, "n", F.coalesce("lo", "_theta").alias("lo"), F.coalesce("hi", "_theta").alias("hi"), "centre", "model")
    if on_degenerate == "iqr":
        box = boxplot(series, by, y).select(*by, F.col("lo").alias("b_lo"), F.col("hi").alias("b_hi"))
        out = out.join(box, by)
        return out.select(*by, "n", F.coalesce("lo", "b_lo").alias("lo"), F.coalesce("hi", "b_hi").alias("hi"), "centre", "model")
    return out.drop("_theta")


def boxplot(series: DataFrame, by: list[str], y: str = "y", rho: float = RHO, quartile: str = "linear") -> DataFrame:
    """Fences at rho interquartile ranges outside the quartiles. quartile: linear, hinge (halves by the median), approx."""
    rows = series.where(F.col(y).isNotNull())
    if quartile == "linear":
        q = F.percentile(y, F.array(F.lit(0.25), F.lit(0.75)))
    elif quartile == "approx":
        q = F.percentile_approx(y, [0.25, 0.75], 10_000)
    else:
        v = F.sort_array(F.collect_list(y))
        half = F.ceil(F.size(v) / 2).cast("int")

        def mid(a: Column) -> Column:
            n = F.size(a)
            return (F.get(a, F.floor((n - 1) / 2).cast("int")) + F.get(a, F.floor(n / 2).cast("int"))) / 2.0

        q = F.array(mid(F.slice(v, 1, half)), mid(F.slice(v, F.size(v) - half + 1, half)))
    e = rows.groupBy(*by).agg(q.alias("q"), F.avg(y).alias("mean"), F.count("*").alias("n"))
    span = F.col("q")[1] - F.col("q")[0]
    return e.select(*by, "n", (F.col("q")[0] - rho * span).alias("lo"), (F.col("q")[1] + rho * span).alias("hi"), F.col("mean").alias("centre"), F.lit("iqr").alias("model"))


def severity(series: DataFrame, by: list[str], y: str = "y") -> DataFrame:
    """Rows with none, mild (beyond 1.5) or extreme (beyond 3 interquartile ranges), by one window pass."""
    from pyspark.sql import Window

    q = F.percentile(y, F.array(F.lit(0.25), F.lit(0.75))).over(Window.partitionBy(*by))
    told = series.withColumn("_q", q)
    span = F.col("_q")[1] - F.col("_q")[0]
    away = F.greatest(F.col("_q")[0] - F.col(y), F.col(y) - F.col("_q")[1])
    kind = F.when(away > EXTREME * span, "extreme").when(away > RHO * span, "mild").otherwise("none")
    return told.withColumn("severity", kind).drop("_q")


def auto(series: DataFrame, by: list[str], y: str = "y", model: str = "normal", n_min: int = SMALL_GROUP, **options) -> DataFrame:
    """The named model for groups of at least n_min samples, the boxplot for smaller ones."""
    large = build(model, series, by, y=y, **options)
    small = boxplot(series, by, y).select(*by, F.col("lo").alias("s_lo"), F.col("hi").alias("s_hi"), F.col("centre").alias("s_centre"))
    few = F.col("n") < n_min
    return large.join(small, by).select(
        *by,
        "n",
        F.when(few, F.col("s_lo")).otherwise(F.col("lo")).alias("lo"),
        F.when(few, F.col("s_hi")).otherwise(F.col("hi")).alias("hi"),
        F.when(few, F.col("s_centre")).otherwise(F.col("centre")).alias("centre"),
        F.when(few, "iqr:small").otherwise(F.col("model")).alias("model"),
    )


def register(name: str, strategy: Callable[[DataFrame, list[str]], DataFrame]) -> None:
    """A user's own fences: takes (series, by) and returns (by, n, lo, hi, centre, model)."""
    _strategies[name] = strategy


def build(name: str, series: DataFrame, by: list[str], **options) -> DataFrame:
    own = {"normal": normal, "gamma": gamma, "iqr": boxplot}
    if name in own:
        return own[name](series, by, **options)
    return _strategies[name](series, by)


@pandas_udf(DoubleType())
def gamma_probability(x: pd.Series, shape: pd.Series, scale: pd.Series) -> pd.Series:
    return pd.Series([G.cdf(*row) if row[1] > 0 and row[2] > 0 else None for row in zip(x, shape, scale, strict=True)], dtype=float)


def fit_check(series: DataFrame, by: list[str], y: str = "y", bins: int = 10, model: str = "normal") -> DataFrame:
    """Distance of each group from a normal or gamma of its own mean and deviation: largest gap of the distribution
    functions, and a binned count statistic. A diagnostic for clean groups; pollution misleads it. A group without
    spread, or without a positive mean for the gamma, has nulls."""
    from pyspark.sql import Window

    w = Window.partitionBy(*by)
    told = series.where(F.col(y).isNotNull()).withColumns(
        {"_u": (F.col(y) - F.avg(y).over(w)) / F.nullif(F.stddev_samp(y).over(w), F.lit(0.0)), "_c": F.cume_dist().over(w.orderBy(y)), "_n": F.count("*").over(w)}
    )
    # A rational form of the normal distribution function, good to 7 digits. Its coefficients.
    a = F.abs(F.col("_u"))
    t = 1.0 / (1.0 + 0.2316419 * a)
    tail = F.exp(-a * a / 2) / (2 * 3.141592653589793) ** 0.5 * t * (0.31938153 + t * (-0.356563782 + t * (1.781477937 + t * (-1.821255978 + t * 1.330274429))))
    if model == "gamma":
        mean, var = F.avg(y).over(w), F.var_samp(y).over(w)
        fine = (mean > 0) & (var > 0)
        told = told.withColumns({"_shape": F.when(fine, mean * mean / var), "_scale": F.when(fine, var / mean)})
        told = told.withColumn("_p", F.when(F.col("_shape").isNotNull(), gamma_probability(y, "_shape", "_scale")))
    else:
        told = told.withColumn("_p", F.when(F.col("_u") >= 0, 1 - tail).otherwise(tail))
    gap = told.groupBy(*by).agg(F.max(F.greatest(F.abs(F.col("_c") - F.col("_p")), F.abs(F.col("_c") - 1 / F.col("_n") - F.col("_p")))).alias("distance"), F.first("_n").alias("n"))
    cell = told.withColumn("_b", F.least(F.floor(F.col("_p") * bins), F.lit(bins - 1))).groupBy(*by, "_b", "_n").count()
    # Empty cells add their expectation each, which the sum of squares over all cells holds.
    chi = cell.groupBy(*by, "_n").agg((F.sum(F.col("count") ** 2) * bins / F.col("_n") - F.col("_n")).alias("count_statistic"))
    return gap.join(chi.drop("_n"), by)
