"""What a SQL-only user needs: functions, a table function and views."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType

from slotlens.functions import gamma


@udtf(returnType="tick bigint, slot int, period_ix bigint")
class PeriodTicks:
    """Every tick of a number of periods with its slot and period."""

    def eval(self, periods: int, r: int):
        for t in range(periods * r):
            yield t, t % r, t // r


@pandas_udf(DoubleType())
def gamma_quantile_of(q: pd.Series, shape: pd.Series, scale: pd.Series) -> pd.Series:
    return pd.Series([gamma.quantile(*row) for row in zip(q, shape, scale, strict=True)], dtype=float)


def register(spark: SparkSession) -> None:
    """SQL functions gamma_quantile_of, slot_of, period_of_tick, similarity_of, mad_of and the table function period_ticks."""
    spark.udtf.register("period_ticks", PeriodTicks)
    spark.udf.register("gamma_quantile_of", gamma_quantile_of)
    for statement in (
        "CREATE OR REPLACE TEMPORARY FUNCTION slot_of(tick BIGINT, r INT) RETURNS INT RETURN CAST(pmod(tick, r) AS INT)",
        "CREATE OR REPLACE TEMPORARY FUNCTION period_of_tick(tick BIGINT, r INT) RETURNS BIGINT RETURN CAST(floor(tick / r) AS BIGINT)",
        "CREATE OR REPLACE TEMPORARY FUNCTION similarity_of(a DOUBLE, m DOUBLE, b DOUBLE, n DOUBLE) RETURNS DOUBLE "
        "RETURN CASE WHEN a = b AND m = n THEN double('infinity') ELSE 1.0D / sqrt((a - b) * (a - b) + (m - n) * (m - n)) END",
        "CREATE OR REPLACE TEMPORARY FUNCTION middle_of(v ARRAY<DOUBLE>) RETURNS DOUBLE "
        "RETURN (get(array_sort(v), CAST(floor((size(v) - 1) / 2) AS INT)) + get(array_sort(v), CAST(floor(size(v) / 2) AS INT))) / 2.0D",
        "CREATE OR REPLACE TEMPORARY FUNCTION mad_of(v ARRAY<DOUBLE>) RETURNS DOUBLE RETURN middle_of(transform(v, x -> abs(x - middle_of(v))))",
    ):
        spark.sql(statement)
