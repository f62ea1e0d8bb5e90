"""The discrete Fourier transform of length p**m as a query over digits: one factor a pair of digits."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mixagg.functions.algebra import COMPLEX
from mixagg.model import Factor, FactorQuery
from mixagg.operators.evaluate import answer


def dft(vector: DataFrame, p: int, m: int, key: str | None = None) -> DataFrame:
    """``vector``: n, re, im with 0 <= n < p**m; returns x, re, im with kernel exp(+2 pi i x n / N).

    With ``key`` there is one vector a value of that column, as one more free variable.

    x and n are read in digits; digit pairs j, k of x and n with j + k < m carry a phase, the others carry none.
    Eliminating n's digits from the highest down touches one more digit of x each time.
    """
    spark = vector.sparkSession
    digits = spark.range(p).select(F.col("id").cast("int").alias("d"))
    n = F.col("n").cast("long")
    keys = (key,) if key else ()
    inputs = vector.select(*keys, *[F.floor(n / p**k).cast("int").__mod__(p).alias(f"y{k}") for k in range(m)], F.struct(F.col("re").cast("double").alias("re"), F.col("im").cast("double").alias("im")).alias("val"))
    factors = [Factor((*keys, *(f"y{k}" for k in range(m))), inputs.where("val.re != 0 or val.im != 0"))]
    for j in range(m):
        for k in range(m - j):
            a, b = digits.select(F.col("d").alias(f"x{j}")), digits.select(F.col("d").alias(f"y{k}"))
            turn = F.col(f"x{j}") * F.col(f"y{k}") * (2 * math.pi / p ** (m - j - k))
            factors.append(Factor((f"x{j}", f"y{k}"), a.crossJoin(b).withColumn("val", F.struct(F.cos(turn).alias("re"), F.sin(turn).alias("im")))))  # p * p rows
    q = FactorQuery((*keys, *(f"x{j}" for j in range(m))), tuple((f"y{k}", "sum") for k in range(m)), tuple(factors), COMPLEX)
    out = answer(q, order="given", indicators=False, output="direct")
    x = sum((F.col(f"x{j}").cast("long") * p**j for j in range(1, m)), F.col("x0").cast("long"))
    return out.select(*keys, x.alias("x"), F.col("val.re").alias("re"), F.col("val.im").alias("im"))


def butterfly(vector: DataFrame, p: int, m: int, key: str | None = None) -> DataFrame:
    """The radix-p butterfly written out: m rounds, each of which trades the highest digit of n left for one more digit of x
    and multiplies by the phase of that pair; rows stay p**m, times p within a round."""
    n, keys = p**m, (key,) if key else ()
    cur = vector.select(*keys, F.col("n").cast("long").alias("n"), F.lit(0).cast("long").alias("x"), F.col("re").cast("double").alias("re"), F.col("im").cast("double").alias("im"))
    for j in range(m):
        size = p ** (m - 1 - j)  # n's digit k = m - 1 - j meets digits 0..j of x
        wide = cur.withColumn("high", F.floor(F.col("n") / size)).withColumn("n", F.col("n") % size).withColumn("digit", F.explode(F.sequence(F.lit(0), F.lit(p - 1))))
        wide = wide.withColumn("x", F.col("x") + F.col("digit") * p**j)
        turn = (F.col("x") * F.col("high") * size % n) * (2 * math.pi / n)
        re, im = F.col("re") * F.cos(turn) - F.col("im") * F.sin(turn), F.col("re") * F.sin(turn) + F.col("im") * F.cos(turn)
        cur = wide.select(*keys, "n", "x", re.alias("re"), im.alias("im")).groupBy(*keys, "n", "x").agg(F.sum("re").alias("re"), F.sum("im").alias("im"))
    return cur.select(*keys, "x", "re", "im")


def dft_quadratic(vector: DataFrame, n: int, key: str | None = None) -> DataFrame:
    """The quadratic baseline: every output from every input; with ``key``, for each of its vectors."""
    turn = F.col("x") * F.col("n") % n * (2 * math.pi / n)
    keys = (key,) if key else ()
    grid = vector.crossJoin(F.broadcast(vector.sparkSession.range(n).withColumnRenamed("id", "x")))  # n rows
    return grid.groupBy(*keys, "x").agg(F.sum(F.col("re") * F.cos(turn) - F.col("im") * F.sin(turn)).alias("re"), F.sum(F.col("re") * F.sin(turn) + F.col("im") * F.cos(turn)).alias("im"))
