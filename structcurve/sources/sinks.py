"""Sinks: format round trips, bucketed and curve-ordered files."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def roundtrip(df: DataFrame, fmt: str, path: str) -> DataFrame:
    """Write in a format and read back under the same schema."""
    options = {"header": "true"} if fmt == "csv" else {}
    df.write.mode("overwrite").options(**options).format(fmt).save(path)
    return df.sparkSession.read.schema(df.schema).options(**options).format(fmt).load(path)


def write_bucketed(df: DataFrame, path: str, key: str = "structure_id", buckets: int = 16) -> DataFrame:
    """One folder per bucket of the key; readers prune folders by a bucket filter."""
    out = df.withColumn("bucket", F.pmod(F.col(key), F.lit(buckets)).cast("int"))
    out.repartition("bucket").write.mode("overwrite").partitionBy("bucket").parquet(path)
    return df.sparkSession.read.parquet(path)


def write_ordered(df: DataFrame, path: str, key: str, files: int | None = None) -> DataFrame:
    """Files in order of a curve index, so each row group spans few indexes; range-partitioned, sorted inside."""
    dealt = df.repartitionByRange(files, key) if files else df.repartitionByRange(key)
    dealt.sortWithinPartitions(key).write.mode("overwrite").parquet(path)
    return df.sparkSession.read.parquet(path)
