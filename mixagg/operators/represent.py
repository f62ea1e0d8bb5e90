"""Functions given other than by their rows, each as a query whose answer is the listing.

The queries can be answered by themselves or put in place of a factor with ``model.compose``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from mixagg.functions.algebra import Algebra
from mixagg.model import Factor, FactorQuery


def terms(groups: list[Factor], term: str, algebra: Algebra, plus: str) -> FactorQuery:
    """A sum of terms, each a product of small lists: every group lists (term, some variables) and values.

    A term without a row in some group is zero there, as ever with factors.
    """
    free = tuple(dict.fromkeys(v for g in groups for v in g.vars if v != term))
    return FactorQuery(free, ((term, plus),), tuple(groups), algebra)


def diagram(spark: SparkSession, layers: list[DataFrame], variables: list[str], root: int, leaves: DataFrame, algebra: Algebra, plus: str) -> FactorQuery:
    """A layered decision diagram: layer i has rows (node, value, child); ``leaves`` has rows (node, val).

    Nodes become bound variables, so the layers form a chain; an assignment follows one path, hence sums one term.
    """
    node = [f"__node{i}" for i in range(len(layers) + 1)]
    made = [Factor((node[0],), spark.range(1).select(F.lit(root).cast("long").alias(node[0]), algebra.one().alias("val")))]
    for i, (layer, v) in enumerate(zip(layers, variables)):
        rows = layer.select(F.col("node").cast("long").alias(node[i]), F.col("value").alias(v), F.col("child").cast("long").alias(node[i + 1]))
        made.append(Factor((node[i], v, node[i + 1]), rows.withColumn("val", algebra.one())))
    ends = leaves.select(F.col("node").cast("long").alias(node[-1]), F.col("val").cast(algebra.dtype).alias("val"))
    made.append(Factor((node[-1],), ends.where(algebra.nonzero(F.col("val")))))
    return FactorQuery(tuple(variables), tuple((n, plus) for n in node), tuple(made), algebra)


def structured_product(matrices: list[Factor], vector: Factor, algebra: Algebra, plus: str = "sum") -> FactorQuery:
    """A product of sparse factors times a vector; neighbours share a variable, the first variable is the result's."""
    first = matrices[0].vars[0]
    others = dict.fromkeys(v for m in (*matrices, vector) for v in m.vars if v != first)
    return FactorQuery((first,), tuple((v, plus) for v in others), (*matrices, vector), algebra)
