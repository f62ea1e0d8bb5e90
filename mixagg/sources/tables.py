"""Tables and sinks: Parquet by default, other formats by name; factors written by their leading variable."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from mixagg.model import Factor


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, path: str, kind: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    reader = spark.read.format(kind).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def write_factor(factor: Factor, path: str, buckets: int | None = None, name: str | None = None) -> None:
    """Sorted by the variables; bucketed by the leading one when written as a table, so joins on it need no shuffle."""
    if buckets and name:
        factor.df.write.bucketBy(buckets, factor.vars[0]).sortBy(*factor.vars).mode("overwrite").option("path", path).saveAsTable(name)
    else:
        factor.df.repartitionByRange(factor.vars[0]).sortWithinPartitions(*factor.vars).write.mode("overwrite").parquet(path)


def read_factor(spark: SparkSession, path: str) -> Factor:
    df = spark.read.parquet(path)
    return Factor(tuple(c for c in df.columns if c != "val"), df)
