"""Sources and sinks: tables, meter dumps, the partitioned series layout, a Python data source."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_meter_csv(spark: SparkSession, path: str, schema: str = "series_id string, ts timestamp_ntz, y double") -> DataFrame:
    """Meter dump with a header; the schema is given, never inferred."""
    return spark.read.csv(path, schema=schema, header=True)


def read_meter_json(spark: SparkSession, path: str, schema: str = "series_id string, ts timestamp_ntz, y double") -> DataFrame:
    return spark.read.json(path, schema=schema)


def write_series(series: DataFrame, path: str, mode: str = "overwrite") -> None:
    """Parquet by month, rows of a series together and in time order: time filters prune folders and row groups."""
    laid = series.withColumn("month", F.date_format("ts", "yyyy-MM"))
    laid.repartition("month", "series_id").sortWithinPartitions("month", "series_id", "tick").write.partitionBy(
        "month"
    ).mode(mode).parquet(path)


def read_series(spark: SparkSession, path: str, months: list[str] | None = None) -> DataFrame:
    """Reads the layout; ``months`` prunes to those folders, as for a period found on a short window."""
    df = spark.read.parquet(path)
    if months:
        df = df.where(F.col("month").isin(months))
    return df.drop("month")


def write_bucketed(series: DataFrame, table: str, buckets: int) -> None:
    """Table bucketed and sorted by series: grouping or joining by series later needs no exchange."""
    series.write.bucketBy(buckets, "series_id").sortBy("series_id", "tick").mode("overwrite").saveAsTable(table)


class _MeterReader(DataSourceReader):
    def __init__(self, options):
        self.meters = int(options.get("meters", 4))
        self.ticks = int(options.get("ticks", 48))

    def partitions(self):
        return [InputPartition(i) for i in range(self.meters)]

    def read(self, partition):
        m = partition.value
        for t in range(self.ticks):
            yield f"m{m}", t, float((t % 24) + m)


class MeterSource(DataSource):
    """``slot_meters``: plain daily ramps, one partition a meter; for smoke tests and demonstrations."""

    @classmethod
    def name(cls):
        return "slot_meters"

    def schema(self):
        return "series_id string, tick bigint, y double"

    def reader(self, schema):
        return _MeterReader(self.options)
