"""Threshold sweep, separation of the merged groups, and the elbow."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from slotlens.functions import covers
from slotlens.schemas import CURVE


def _fresh(df: DataFrame) -> DataFrame:
    """The same columns under new ids, so that two sides of one lineage can be grouped together."""
    return df.select(*(F.col(c).alias(c) for c in df.columns))


def _mid(values: np.ndarray) -> tuple[float, float]:
    theta = float(np.median(values))
    return theta, float(np.median(np.abs(values - theta)))


def separation_of(v: np.ndarray, infinite: str = "skip", cap: float = 1e6) -> tuple[float | None, float | None]:
    """Mean over pairs of group vectors: of the similarity (as printed) and of the distance; None below two groups."""
    if len(v) < 2:
        return None, None
    d = covers.distances(v)[np.triu_indices(len(v), 1)]
    with np.errstate(divide="ignore"):
        s = 1 / d
    if infinite == "skip":
        s = s[np.isfinite(s)]
    elif infinite == "cap":
        s = np.minimum(s, cap)
    return (float(s.mean()) if len(s) else None), float(d.mean())


def separation(vectors: DataFrame, group: str = "vp_id") -> DataFrame:
    """The same two means by a self-join of the group vectors; coinciding pairs count in the distance alone."""
    from slotlens.operators.similarity import pairs

    return pairs(vectors, group).groupBy("series_id").agg(
        F.avg(F.when(F.col("dist") > 0, F.col("s"))).alias("score_literal"), F.avg("dist").alias("score_distance")
    )


def sweep(values: DataFrame, vectors: DataFrame, item: str = "slot", most_groups: int | None = None, grid: list[float] | None = None) -> DataFrame:
    """Curve of each series: thresholds from small to large with the number of groups and both separation scores.

    ``values`` holds (series_id, item, y); group vectors are taken on the unions, as merged groups would be.
    One Arrow group a series on both sides.
    """

    def run(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        right = right.sort_values(item)
        v = right[["theta", "mad"]].to_numpy(float)
        limit = most_groups or len(v)
        rows = {i: g["y"].to_numpy(float) for i, g in left.groupby(item)}
        out = []
        for s0, label in covers.cover_curve(v, None if grid is None else np.array(grid), limit):
            merged = []
            for g in range(int(label.max()) + 1):
                members = right[item].to_numpy()[label == g]
                merged.append(_mid(np.concatenate([rows[m] for m in members])))
            lit, dist = separation_of(np.array(merged))
            out.append((right["series_id"].iloc[0], s0, int(label.max()) + 1, lit, dist))
        return pd.DataFrame(out, columns=["series_id", "s0", "n_groups", "score_literal", "score_distance"])

    return (
        values.select("series_id", item, "y")
        .groupBy("series_id")
        .cogroup(_fresh(vectors.select("series_id", item, "theta", "mad")).groupBy("series_id"))
        .applyInPandas(run, CURVE)
    )


def elbow(curve: DataFrame, rule: str = "chord", score: str = "score_distance", fixed: float | None = None) -> DataFrame:
    """(series_id, n_groups, s0) chosen from a curve.

    chord: farthest from the line between the ends of the curve over the number of groups. second_diff: largest
    change of slope. fixed_n: the threshold that first gives ``fixed`` groups or the nearest number to it.
    fixed_s0: the curve's point at the threshold nearest to ``fixed``.
    """

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        c = pdf.sort_values(["n_groups", "s0"]).drop_duplicates("n_groups")
        if rule == "fixed_n":
            row = c.iloc[(c["n_groups"] - fixed).abs().argsort(kind="stable").iloc[0]]
        elif rule == "fixed_s0":
            row = c.iloc[(c["s0"] - fixed).abs().argsort(kind="stable").iloc[0]]
        else:
            k = c.dropna(subset=[score])
            if len(k) < 3:
                row = c.iloc[-1]
            else:
                x, y = k["n_groups"].to_numpy(float), k[score].to_numpy(float)
                x = (x - x[0]) / (x[-1] - x[0])
                y = (y - y.min()) / (np.ptp(y) or 1)
                if rule == "chord":
                    away = np.abs(y - (y[0] + (y[-1] - y[0]) * x))
                else:
                    away = np.concatenate([[0], np.abs(np.diff(np.diff(y))), [0]])
                row = k.iloc[int(away.argmax())]
        return pd.DataFrame({"series_id": [row["series_id"]], "n_groups": [int(row["n_groups"])], "s0": [float(row["s0"])]})

    return curve.groupBy("series_id").applyInPandas(run, "series_id string, n_groups int, s0 double")


def build(values: DataFrame, vectors: DataFrame, item: str, group: str, kind: str = "int", keys: list[str] | None = None, rule: str = "chord", score: str = "score_distance", fixed: float | None = None, most_groups: int | None = None) -> DataFrame:
    """(keys, item, group): sweep, pick and cover of each series in one Arrow group."""
    keys = keys or ["series_id"]
    types = dict(vectors.dtypes)
    schema = ", ".join(f"{k} {types[k]}" for k in keys) + f", {item} {kind}, {group} int"

    def run(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        right = right.sort_values(item)
        v = right[["theta", "mad"]].to_numpy(float)
        limit = most_groups or len(v)
        if rule == "fixed_n":
            limit = max(limit, int(fixed))
        rows = {i: g["y"].to_numpy(float) for i, g in left.groupby(item)}
        curve = covers.cover_curve(v, None, limit)
        points = []
        for s0, label in curve:
            merged = [_mid(np.concatenate([rows[m] for m in right[item].to_numpy()[label == g]])) for g in range(int(label.max()) + 1)]
            points.append((int(label.max()) + 1, *separation_of(np.array(merged))))
        n = np.array([p[0] for p in points])
        if rule == "fixed_n":
            at = int(np.abs(n - fixed).argmin())
        else:
            y = np.array([np.nan if p[2 if score == "score_distance" else 1] is None else p[2 if score == "score_distance" else 1] for p in points])
            order = [i for i in np.argsort(n, kind="stable") if np.isfinite(y[i])]
            at = int(n.argmax())
            if len(order) >= 3:
                x, z = n[order].astype(float), y[order]
                x, z = (x - x[0]) / (x[-1] - x[0]), (z - z.min()) / (np.ptp(z) or 1)
                at = order[int(np.abs(z - (z[0] + (z[-1] - z[0]) * x)).argmax())]
        out = right[[*keys, item]].copy()
        out[group] = curve[at][1].astype(np.int32) if curve else 0
        return out

    v = _fresh(vectors.select(*keys, F.col(item).cast(kind).alias(item), "theta", "mad"))
    return values.select(*keys, F.col(item).cast(kind).alias(item), "y").groupBy(*keys).cogroup(v.groupBy(*keys)).applyInPandas(run, schema)
