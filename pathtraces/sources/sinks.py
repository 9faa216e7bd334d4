"""Writing results and graphs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def write_traces(traces: DataFrame, path: str) -> None:
    """Parquet, a folder for each length."""
    traces.withColumn("len", F.size(F.split("trace", ">"))).write.mode("overwrite").partitionBy("len").parquet(path)


def write_bucketed(df: DataFrame, table: str, key: str, buckets: int, path: str) -> None:
    """A table at ``path`` whose joins and counts on ``key`` need no exchange."""
    df.write.mode("overwrite").option("path", path).bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def write_text(traces: DataFrame, path: str, kind: str) -> None:
    writer = traces.write.mode("overwrite")
    writer.csv(path, header=True) if kind == "csv" else writer.json(path)
