"""Factors kept up to date from streams: any semiring sum of a batch merges with the sum so far."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from mixagg.functions.algebra import Algebra
from mixagg.model import Factor


def merge(old: Factor | None, new: Factor, algebra: Algebra, plus: str) -> Factor:
    if old is None:
        return new
    both = old.df.unionByName(new.df).groupBy(*new.vars).agg(algebra.plus[plus](F.col("val")).alias("val"))
    return Factor(new.vars, both.where(algebra.nonzero(F.col("val"))))


def maintain(stream: DataFrame, algebra: Algebra, variables: dict, value, plus: str, path: str, checkpoint: str) -> StreamingQuery:
    """Each micro-batch is folded to a partial factor and appended; ``current`` sums the partial factors."""

    def one(batch: DataFrame, epoch: int) -> None:
        Factor.build(batch, algebra, variables, value, plus).df.write.mode("overwrite").parquet(f"{path}/epoch={epoch}")

    return stream.writeStream.foreachBatch(one).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def current(spark, path: str, algebra: Algebra, plus: str) -> Factor:
    df = spark.read.parquet(path).drop("epoch")
    names = tuple(c for c in df.columns if c != "val")
    return Factor(names, df.groupBy(*names).agg(algebra.plus[plus](F.col("val")).alias("val")).where(algebra.nonzero(F.col("val"))))


def windowed(stream: DataFrame, time: str, keys: list[str], value: str, size: str = "1 hour", late: str = "10 minutes") -> DataFrame:
    """Counts and sums per window; rows later than the watermark are dropped."""
    return stream.withWatermark(time, late).groupBy(F.window(time, size), *keys).agg(F.count("*").alias("n"), F.sum(value).alias("total"))


def per_batch(stream: DataFrame, fn: Callable[[DataFrame], None], checkpoint: str) -> StreamingQuery:
    return stream.writeStream.foreachBatch(lambda df, _: fn(df)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
