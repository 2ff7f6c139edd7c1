"""Baseline: least squares on local cubic basis functions over equally spaced knots."""

from __future__ import annotations

from statistics import NormalDist

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

RIDGE = 1e-9


def local_basis(series: DataFrame, df: int, last: str = "last_tick", at: str = "tick") -> DataFrame:
    """Adds j (first of four basis functions that are not zero) and b, their four values; pure column arithmetic."""
    m = df - 3
    u = F.col(at).cast("double") * m / F.greatest(F.col(last).cast("double"), F.lit(1.0))
    j = F.least(F.floor(u), F.lit(m - 1)).cast("int")
    out = series.withColumn("_u", u).withColumn("j", j).withColumn("_f", F.col("_u") - F.col("j"))
    f = F.col("_f")
    values = F.array(
        (1 - f) ** 3 / 6, (3 * f**3 - 6 * f**2 + 4) / 6, (-3 * f**3 + 3 * f**2 + 3 * f + 1) / 6, f**3 / 6
    )
    return out.withColumn("b", values).drop("_u", "_f")


def normal_equations(based: DataFrame, keys: list[str], y: str = "y") -> DataFrame:
    """Banded sums (keys, i, off, s) with off 0..3 for the matrix and 9 for the right side; map-side combined."""
    terms = [
        F.struct((F.col("j") + a).alias("i"), F.lit(c - a).alias("off"), (F.col("b")[a] * F.col("b")[c]).alias("v"))
        for a in range(4)
        for c in range(a, 4)
    ]
    terms += [F.struct((F.col("j") + a).alias("i"), F.lit(9).alias("off"), (F.col("b")[a] * F.col(y)).alias("v")) for a in range(4)]
    rows = based.where(F.col(y).isNotNull()).select(*keys, F.explode(F.array(*terms)).alias("t"))
    return rows.groupBy(*keys, F.col("t.i").alias("i"), F.col("t.off").alias("off")).agg(F.sum("t.v").alias("s"))


def solve_banded(band: np.ndarray, rhs: np.ndarray) -> np.ndarray:
    """Cholesky of a symmetric matrix with three off-diagonals: band[k, i] = A[i, i + k]. Linear in the size."""
    n = len(rhs)
    low = np.zeros((4, n))
    for i in range(n):
        for k in range(min(3, i), 0, -1):
            v = band[k, i - k]
            for q in range(k + 1, min(3, i) + 1):
                v -= low[q, i] * low[q - k, i - k]
            low[k, i] = v / low[0, i - k]
        low[0, i] = max(band[0, i] - (low[1:4, i] ** 2).sum(), 1e-300) ** 0.5
    z = np.zeros(n)
    for i in range(n):
        z[i] = (rhs[i] - sum(low[k, i] * z[i - k] for k in range(1, min(3, i) + 1))) / low[0, i]
    x = np.zeros(n)
    for i in range(n - 1, -1, -1):
        x[i] = (z[i] - sum(low[k, i + k] * x[i + k] for k in range(1, min(3, n - 1 - i) + 1))) / low[0, i]
    return x


def fit(series: DataFrame, df: int, keys: list[str] | None = None, y: str = "y", at: str = "tick", dense: bool = False) -> DataFrame:
    """Rows with y_hat. Each row meets four coefficients, found by interval; the solve is one Arrow group a series.

    dense keeps the whole design matrix in the task, as a plain implementation would; its cost is N x df.
    """
    keys = keys or ["series_id"]
    last = F.max(at).over(Window.partitionBy(*keys))
    held = series.withColumn("last_tick", last)
    if dense:
        return _dense(held, df, keys, y, at)
    based = local_basis(held, df, at=at)
    equations = normal_equations(based, keys, y)
    types = dict(series.dtypes)
    schema = ", ".join(f"{k} {types[k]}" for k in keys) + ", j int, c array<double>"

    def solve(pdf: pd.DataFrame) -> pd.DataFrame:
        band, rhs = np.zeros((4, df)), np.zeros(df)
        right = pdf["off"] == 9
        rhs[pdf["i"][right]] = pdf["s"][right]
        band[pdf["off"][~right], pdf["i"][~right]] = pdf["s"][~right]
        band[0] += RIDGE * max(1.0, band[0].max())
        x = solve_banded(band, rhs)
        out = pd.DataFrame({"j": np.arange(df - 3, dtype=np.int32), "c": [x[i : i + 4] for i in range(df - 3)]})
        for k in keys:
            out.insert(0, k, pdf[k].iloc[0])
        return out[[*keys, "j", "c"]]

    coefficients = equations.groupBy(*keys).applyInPandas(solve, schema)
    fitted = based.join(coefficients, [*keys, "j"])
    hat = sum((F.col("b")[i] * F.col("c")[i] for i in range(1, 4)), F.col("b")[0] * F.col("c")[0])
    return fitted.withColumn("y_hat", hat).drop("b", "c", "j", "last_tick")


def design(t: np.ndarray, last: float, df: int) -> np.ndarray:
    m = df - 3
    u = t * m / max(last, 1.0)
    j = np.minimum(np.floor(u), m - 1).astype(int)
    f = u - j
    x = np.zeros((len(t), df))
    r = np.arange(len(t))
    for k, v in enumerate(((1 - f) ** 3 / 6, (3 * f**3 - 6 * f**2 + 4) / 6, (-3 * f**3 + 3 * f**2 + 3 * f + 1) / 6, f**3 / 6)):
        x[r, j + k] = v
    return x


def _dense(held: DataFrame, df: int, keys: list[str], y: str, at: str) -> DataFrame:
    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        x = design(pdf[at].to_numpy(float), float(pdf["last_tick"].iloc[0]), df)
        ok = pdf[y].notna().to_numpy()
        c = np.linalg.lstsq(x[ok], pdf[y].to_numpy(float)[ok], rcond=None)[0]
        return pdf.assign(y_hat=x @ c).drop(columns="last_tick")

    schema = ", ".join(f"{n} {t}" for n, t in held.drop("last_tick").dtypes) + ", y_hat double"
    return held.groupBy(*keys).applyInPandas(run, schema)


def fit_penalised(series: DataFrame, df: float, basis: int = 200, y: str = "y") -> DataFrame:
    """Second-difference penalty on a rich basis; the penalty is found so that the trace of the hat matrix is ``df``."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("tick")
        t = pdf["tick"].to_numpy(float)
        x = design(t, t.max(), basis)
        ok = pdf[y].notna().to_numpy()
        d = np.diff(np.eye(basis), 2, axis=0)
        gram, penalty = x[ok].T @ x[ok] + RIDGE * np.eye(basis), d.T @ d
        low, high = -12.0, 12.0
        for _ in range(60):
            mid = (low + high) / 2
            trace = np.trace(np.linalg.solve(gram + 10**mid * penalty, gram))
            low, high = (mid, high) if trace > df else (low, mid)
        c = np.linalg.solve(gram + 10**low * penalty, x[ok].T @ pdf[y].to_numpy(float)[ok])
        return pdf.assign(y_hat=x @ c)

    schema = ", ".join(f"{n} {t}" for n, t in series.dtypes) + ", y_hat double"
    return series.groupBy("series_id").applyInPandas(run, schema)


def detect(fitted: DataFrame, df: int, alpha: float = 0.05, keys: list[str] | None = None, y: str = "y") -> DataFrame:
    """is_outlier where the residual exceeds z times its own spread, RSS / (N - df); the rule is this package's choice."""
    keys = keys or ["series_id"]
    w = Window.partitionBy(*keys)
    r = F.col(y) - F.col("y_hat")
    spread = F.sqrt(F.sum(r * r).over(w) / F.greatest(F.count(y).over(w) - df, F.lit(1)))
    z = NormalDist().inv_cdf(1 - alpha / 2)
    return fitted.withColumn("sigma", spread).withColumn("is_outlier", F.coalesce(F.abs(r) > z * F.col("sigma"), F.lit(False)))


def train(series: DataFrame, grid: list[int], by: str = "gcv", y: str = "y") -> DataFrame:
    """(series_id, df, value, best): generalised cross-validation, or the F-measure on labels, for each df of the grid."""
    out = None
    for df in grid:
        f = fit(series, df, y=y)
        if by == "gcv":
            rss, n = F.sum((F.col(y) - F.col("y_hat")) ** 2), F.count(y)
            one = f.groupBy("series_id").agg((n * rss / F.greatest(n - df, F.lit(1)) ** 2).alias("value"))
        else:
            from slotlens.plans.metrics import scores

            one = scores(detect(f, df, y=y), ["series_id"]).select("series_id", (-F.coalesce("f_measure", F.lit(0.0))).alias("value"))
        one = one.withColumn("df", F.lit(df))
        out = one if out is None else out.unionByName(one)
    w = Window.partitionBy("series_id").orderBy("value", "df")
    value = F.col("value") if by == "gcv" else -F.col("value")
    return out.withColumn("best", F.row_number().over(w) == 1).select("series_id", "df", value.alias("value"), "best")


def fit_in_groups(grouped: DataFrame, df: int, group: str = "vp_id", y: str = "y", alpha: float = 0.05) -> DataFrame:
    """A smoother inside each merged group: its points in time order, df shared out by group size (4 at least).

    Null values take no part in the fit, have a fitted value and are no outliers; a group without values has neither.
    """
    z = NormalDist().inv_cdf(1 - alpha / 2)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("tick")
        values = pdf[y].to_numpy(float)
        ok = ~np.isnan(values)
        n = int(ok.sum())
        own = int(max(4, min(n - 1, round(df * len(pdf) / pdf["_all"].iloc[0])))) if n > 5 else 0
        if own:
            x = design(np.arange(len(pdf), dtype=float), len(pdf) - 1, own)
            hat = x @ np.linalg.lstsq(x[ok], values[ok], rcond=None)[0]
        else:
            hat, own = np.full(len(pdf), values[ok].mean() if n else np.nan), 1
        spread = (((values - hat)[ok] ** 2).sum() / max(1, n - own)) ** 0.5
        return pdf.assign(y_hat=hat, is_outlier=ok & (np.abs(np.where(ok, values - hat, 0)) > z * spread)).drop(columns="_all")

    schema = ", ".join(f"{n} {t}" for n, t in grouped.dtypes) + ", y_hat double, is_outlier boolean"
    counted = grouped.withColumn("_all", F.count("*").over(Window.partitionBy("series_id")))
    return counted.groupBy("series_id", group).applyInPandas(run, schema)
