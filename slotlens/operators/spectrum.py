"""Spectra and the fundamental period."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from slotlens.schemas import SPECTRUM

#: Ticks of one bucket of the range join.
BUCKET = 256


def detrended(series: DataFrame, how: str = "running", trend_ticks: int = 168, keys: list[str] | None = None) -> DataFrame:
    """Takes away a centred running mean, the mean, or nothing; the column stays ``y``."""
    keys = keys or ["series_id"]
    if how == "none":
        return series
    w = Window.partitionBy(*keys)
    if how == "running":
        half = trend_ticks // 2
        w = w.orderBy("tick").rowsBetween(-half, trend_ticks - half - 1)
    return series.withColumn("y", F.col("y") - F.avg("y").over(w))


def dft_bins(series: DataFrame, bins: list[int], length: int) -> DataFrame:
    """Chosen bins of the transform by sums of cosines and sines: one pass, map-side partials, no sort.

    Bins are a short list from the caller, laid beside each row; ``freq`` is cycles a tick.
    """
    k = F.explode(F.array(*map(F.lit, bins))).alias("k")
    rows = series.select("series_id", "tick", "y", k)
    angle = 2.0 * np.pi * F.pmod(F.col("k") * F.col("tick"), F.lit(length)) / float(length)
    out = rows.groupBy("series_id", "k").agg(
        F.sum(F.col("y") * F.cos(angle)).alias("re"), (-F.sum(F.col("y") * F.sin(angle))).alias("im")
    )
    return out.select(
        "series_id", "k", (F.col("k") / float(length)).alias("freq"), "re", "im", (F.col("re") ** 2 + F.col("im") ** 2).alias("power")
    )


def fft_series(series: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """Half spectrum of each series by the fast transform, one Arrow group a series (a series fits a task).

    Values stand at their ticks, from the first to the last of the series. Missing ticks and null or undefined values
    take the series' mean, which adds nothing to any line but the constant; of a repeated tick one value counts.
    """
    keys = keys or ["series_id"]
    extra = "".join(f"{k} {t}, " for k, t in series.dtypes if k in keys and k != "series_id")

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values(["tick", "y"])
        tick = pdf["tick"].to_numpy() - pdf["tick"].iloc[0]
        y = np.full(int(tick[-1]) + 1, np.nan)
        y[tick] = pdf["y"].to_numpy(float)
        hole = ~np.isfinite(y)
        y[hole] = 0.0 if hole.all() else y[~hole].mean()
        z = np.fft.rfft(y)
        k = np.arange(len(z), dtype=np.int32)
        out = pd.DataFrame({"series_id": key[0], "k": k, "freq": k / max(1, len(y)), "re": z.real, "im": z.imag, "power": np.abs(z) ** 2})
        for i, name in enumerate(keys[1:]):
            out.insert(0, name, key[i + 1])
        return out[[c.split()[0] for c in (extra + SPECTRUM).split(", ")]]

    return series.select(*keys, "tick", "y").groupBy(*keys).applyInPandas(run, extra + SPECTRUM)


def fft_blocked(series: DataFrame, length: int, rows: int) -> DataFrame:
    """Transform of one giant series in two shuffles: length = rows x columns, tick = column + columns * row.

    First transform along rows for each column, twiddle, then along columns for each row frequency.
    """
    columns = length // rows
    if rows * columns != length:
        raise ValueError("length must be rows times columns")
    inner = "series_id string, c long, q long, re double, im double"

    def first(key, pdf: pd.DataFrame) -> pd.DataFrame:
        y = np.zeros(rows)
        y[pdf["r"].to_numpy()] = pdf["y"].to_numpy()
        q = np.arange(rows)
        z = np.fft.fft(y) * np.exp(-2j * np.pi * key[1] * q / length)
        return pd.DataFrame({"series_id": key[0], "c": key[1], "q": q, "re": z.real, "im": z.imag})

    def second(key, pdf: pd.DataFrame) -> pd.DataFrame:
        z = np.zeros(columns, complex)
        z[pdf["c"].to_numpy()] = pdf["re"].to_numpy() + 1j * pdf["im"].to_numpy()
        z = np.fft.fft(z)
        k = key[1] + rows * np.arange(columns)
        keep = k <= length // 2
        z, k = z[keep], k[keep].astype(np.int32)
        return pd.DataFrame({"series_id": key[0], "k": k, "freq": k / length, "re": z.real, "im": z.imag, "power": np.abs(z) ** 2})

    split = series.select("series_id", F.pmod("tick", F.lit(columns)).alias("c"), F.floor(F.col("tick") / columns).alias("r"), "y")
    partial = split.groupBy("series_id", "c").applyInPandas(first, inner)
    return partial.groupBy("series_id", "q").applyInPandas(second, SPECTRUM)


def harmonics(spectrum: DataFrame, length: int, fundamental_k: int, count: int = 5) -> DataFrame:
    """Constant, fundamental and further harmonics as amplitude and phase."""
    own = spectrum.where(F.pmod("k", F.lit(fundamental_k)) == 0).withColumn("harmonic", (F.col("k") / fundamental_k).cast("int"))
    amplitude = F.when(F.col("k") == 0, F.col("re") / length).otherwise(2.0 * F.hypot("re", "im") / length)
    return own.where(F.col("harmonic") <= count).select(
        "series_id", "harmonic", amplitude.alias("amplitude"), F.when(F.col("k") == 0, 0.0).otherwise(F.atan2("im", "re")).alias("phase")
    )


def fundamental(
    spectrum: DataFrame, length: int, rule: str = "descend", share: float = 0.05, gate: float = 25.0, max_div: int = 6, snap: bool = True, keys: list[str] | None = None
) -> DataFrame:
    """One row a series: k, period_ticks, power_ratio (to the median power); null where no line stands out.

    descend: from the strongest line to the lowest sub-harmonic k / m that holds ``share`` of its power.
    second_peak: the first local maximum after the zero-frequency term that passes the gate. lowest_share: the
    lowest local maximum with ``share`` of the strongest. max_power: the strongest line as it is.
    """
    keys = keys or ["series_id"]
    w = Window.partitionBy(*keys).orderBy("k")
    lines = spectrum.where("k > 0").withColumns(
        {
            "before": F.coalesce(F.lag("power").over(w), F.lit(-1.0)),
            "after": F.coalesce(F.lead("power").over(w), F.lit(-1.0)),
            "middle": F.median("power").over(Window.partitionBy(*keys)),
            "most": F.max("power").over(Window.partitionBy(*keys)),
        }
    )
    peaks = lines.where("power >= before and power >= after")
    strong = peaks.where(F.col("power") >= gate * F.col("middle"))
    if rule == "max_power":
        pick = strong.groupBy(*keys).agg(F.max_by("k", "power").alias("k"))
    elif rule == "second_peak":
        pick = strong.groupBy(*keys).agg(F.min("k").alias("k"))
    elif rule == "lowest_share":
        pick = strong.where(F.col("power") >= share * F.col("most")).groupBy(*keys).agg(F.min("k").alias("k"))
    elif rule == "descend":
        top = strong.groupBy(*keys).agg(F.max_by("k", "power").alias("top"), F.max("power").alias("top_power"))
        tries = top.withColumn("m", F.explode(F.sequence(F.lit(1), F.lit(max_div)))).withColumn("near", F.round(F.col("top") / F.col("m")).cast("int"))
        tries = tries.withColumn("k", F.explode(F.array(F.col("near") - 1, F.col("near"), F.col("near") + 1)))
        tries = tries.where((F.col("m") > 1) | (F.col("k") == F.col("top")))
        held = tries.join(peaks.select(*keys, "k", "power"), [*keys, "k"]).where(F.col("power") >= share * F.col("top_power"))
        pick = held.groupBy(*keys).agg(F.max_by("k", F.struct("m", "power")).alias("k"))
    else:
        raise ValueError(f"unknown rule {rule}")
    told = pick.join(lines.select(*keys, "k", "power", "middle"), [*keys, "k"])
    period = F.lit(float(length)) / F.col("k")
    told = told.select(*keys, "k", (F.round(period) if snap else period).alias("period_ticks"), (F.col("power") / F.col("middle")).alias("power_ratio"))
    return spectrum.select(*keys).distinct().join(told, keys, "left")


def period_ladder(series: DataFrame, length: int, trend_ticks: tuple[int, ...] = (28, 56, 168, 672)) -> DataFrame:
    """Periods under several trend lengths, and the one that most of them agree on."""
    found = None
    for n in trend_ticks:
        one = fundamental(fft_series(detrended(series, trend_ticks=n)), length).withColumn("trend_ticks", F.lit(n))
        found = one if found is None else found.unionByName(one)
    votes = found.where("period_ticks is not null").groupBy("series_id", "period_ticks").agg(F.count("*").alias("votes"))
    return votes.groupBy("series_id").agg(
        F.max_by("period_ticks", F.struct("votes", -F.col("period_ticks"))).alias("period_ticks"), F.max("votes").alias("votes")
    )


def random_windows(spark, draws: int, ticks: int, least: int, most: int, seed: int = 0) -> DataFrame:
    """(draw, lo, hi): windows of random length and place, by hash of the draw; exact and repeatable."""
    d = spark.range(draws).withColumnRenamed("id", "draw")
    length = F.lit(least) + F.pmod(F.xxhash64("draw", F.lit(seed)), F.lit(most - least + 1))
    start = F.pmod(F.xxhash64("draw", F.lit(seed + 1)), F.lit(ticks) - F.col("n") + 1)
    return d.withColumn("n", length).withColumn("lo", start).withColumn("hi", F.col("lo") + F.col("n")).select("draw", "lo", "hi")


def window_fundamentals(series: DataFrame, windows: DataFrame, trend_ticks: int = 168, snap: bool = False) -> DataFrame:
    """Period of each (series, window): range join on the tick, then the fast transform a window.

    Ticks and windows meet by buckets of ``BUCKET`` ticks, an equal join that Spark may broadcast or shuffle; a
    window is one row a bucket. Periods are refined by a parabola through the line.
    """
    span = F.sequence(F.floor(F.col("lo") / BUCKET), F.floor((F.col("hi") - 1) / BUCKET))
    pieces = windows.where("hi > lo").withColumn("bucket", F.explode(span))
    rows = series.withColumn("bucket", F.floor(F.col("tick") / BUCKET)).join(pieces, "bucket").where("tick >= lo and tick < hi")

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        y = pdf.sort_values("tick")["y"].to_numpy(float)
        n = len(y)
        kernel = np.ones(min(trend_ticks, n))
        y = y - np.convolve(y, kernel, "same") / np.convolve(np.ones(n), kernel, "same")
        p = np.abs(np.fft.rfft(y)) ** 2
        return pd.DataFrame({"series_id": [key[0]], "draw": [key[1]], "period_ticks": [pick_period(p, n, snap)]})

    return rows.select("series_id", "draw", "tick", "y").groupBy("series_id", "draw").applyInPandas(
        run, "series_id string, draw long, period_ticks double"
    )


def pick_period(power: np.ndarray, n: int, snap: bool, share: float = 0.05, gate: float = 25.0, max_div: int = 6) -> float | None:
    """The descend rule on one power array, with parabolic refinement of the line unless snapped."""
    if len(power) < 4:
        return None
    k = int(power[1:].argmax()) + 1
    if power[k] < gate * np.median(power[1:]):
        return None
    local = lambda i: 0 < i < len(power) - 1 and power[i] >= power[i - 1] and power[i] >= power[i + 1]
    for m in range(max_div, 1, -1):
        near = [i for i in (round(k / m) + j for j in (-1, 0, 1)) if local(i) and power[i] >= share * power[k]]
        if near:
            k = max(near, key=lambda i: power[i])
            break
    if snap:
        return float(round(n / k))
    if not local(k):
        return n / k
    a, b, c = np.sqrt(power[k - 1 : k + 2])
    # Share of the neighbours places the line between bins.
    shift = (c - a) / (a + b + c) if a + b + c > 0 else 0.0
    return n / (k + shift)


def period_sensitivity(series: DataFrame, draws: int, ticks: int, least: int, most: int, seed: int = 0) -> DataFrame:
    """Mean and variance of the periods found in random windows."""
    windows = random_windows(series.sparkSession, draws, ticks, least, most, seed)
    return window_fundamentals(series, windows).groupBy("series_id").agg(
        F.count("period_ticks").alias("found"), F.avg("period_ticks").alias("mean_period"), F.var_samp("period_ticks").alias("var_period")
    )


def window_periods(series: DataFrame, window_ticks: int) -> DataFrame:
    """Period of each consecutive window, as a check that it hardly moves through the year."""
    most = series.agg(F.max("tick")).first()[0] or 0
    windows = series.sparkSession.range(0, most // window_ticks + 1).select(
        F.col("id").alias("draw"), (F.col("id") * window_ticks).alias("lo"), ((F.col("id") + 1) * window_ticks).alias("hi")
    )
    return window_fundamentals(series, windows, snap=True).withColumnRenamed("draw", "window_ix")
