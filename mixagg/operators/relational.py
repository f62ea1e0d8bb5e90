"""Joins by order rather than equality: points in intervals, and the latest row before each row."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def range_join(points: DataFrame, intervals: DataFrame, point: str, low: str, high: str, width: float) -> DataFrame:
    """Pairs with low <= point <= high (nulls match nothing), by bins of ``width``.

    Each interval goes to every bin that it meets and each point to one, so no pair is found twice.
    """
    bin_of = lambda c: F.floor(F.col(c) / F.lit(width)).cast("long")
    left = points.withColumn("__bin", bin_of(point))
    right = intervals.where(F.col(low) <= F.col(high)).withColumn("__bin", F.explode(F.sequence(bin_of(low), bin_of(high))))
    return left.join(right, "__bin").where(F.col(point).between(F.col(low), F.col(high))).drop("__bin")


def latest_before(left: DataFrame, right: DataFrame, by: str, left_time: str, right_time: str, payload: list[str], stretch: Column) -> DataFrame:
    """``left`` with the payload of the last ``right`` row of its key that is not later (ties: the largest payload).

    The payload's names must not be among those of ``left``.

    ``stretch`` is a rising function of the column ``__at`` (a truncated time, say).  Windows hold one key and stretch;
    what earlier stretches leave behind is carried over by one row a stretch, so a hot key is not one task's work.
    Rows of ``left`` with a null key or time stay and match nothing.
    """
    l_row, r_row = F.struct(*left.columns), F.struct(F.col(right_time).alias("__at"), *payload)
    mine = left.select(F.col(by).alias("__by"), F.col(left_time).alias("__at"), F.lit(1).alias("__turn"), l_row.alias("__left"))
    theirs = right.where(F.col(by).isNotNull() & F.col(right_time).isNotNull()).select(F.col(by).alias("__by"), F.col(right_time).alias("__at"), F.lit(0).alias("__turn"), r_row.alias("__right"))
    known = mine.where(F.col("__by").isNotNull() & F.col("__at").isNotNull())
    both = known.unionByName(theirs, allowMissingColumns=True).withColumn("__stretch", stretch)
    order = Window.partitionBy("__by", "__stretch").orderBy("__at", "__turn", "__right").rowsBetween(Window.unboundedPreceding, 0)
    found = both.withColumn("__last", F.last("__right", ignorenulls=True).over(order)).where("__turn = 1")
    ends = both.groupBy("__by", "__stretch").agg(F.max("__right").alias("__end"))
    before = Window.partitionBy("__by").orderBy("__stretch").rowsBetween(Window.unboundedPreceding, -1)
    carried = ends.select("__by", "__stretch", F.last("__end", ignorenulls=True).over(before).alias("__carried"))
    got = found.join(carried, ["__by", "__stretch"]).select("__left", F.coalesce("__last", "__carried").alias("__last"))
    lost = mine.where(F.col("__by").isNull() | F.col("__at").isNull()).select("__left")
    return got.unionByName(lost, allowMissingColumns=True).select("__left.*", *[F.col(f"__last.{c}").alias(c) for c in payload])
