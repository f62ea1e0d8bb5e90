"""Hypergraphs whose edges are named by the rows of lineitem, for the workloads that measure plans.

A line's supplier says which shape it belongs to and its part which edge of it the line names; a shape has the edges that
some line names.  Measures are taken of these edges in Spark's tasks, and of the same edges in SQL.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mixagg.sources.tables import table


def read_shapes(spark, d, shapes: dict[str, str]) -> DataFrame:
    """name, edges (sorted array), lines of the ``shapes`` (name: edges by spaces) that lines name."""
    rows = [(i, name, len(text.split()), j, e) for i, (name, text) in enumerate(shapes.items()) for j, e in enumerate(text.split())]
    named = spark.createDataFrame(rows, "shape int, name string, many int, place int, edge string")
    line = table(spark, d, "lineitem").groupBy((F.col("l_suppkey") % len(shapes)).alias("s"), (F.col("l_partkey") % 5040).alias("p")).agg(F.count("*").alias("n"))
    met = line.join(F.broadcast(named), (F.col("s") == F.col("shape")) & (F.col("p") % F.col("many") == F.col("place")))
    return met.groupBy("name").agg(F.array_sort(F.collect_set("edge")).alias("edges"), F.sum("n").alias("lines"))


def measured(shapes: DataFrame, measure: Callable[[str, list[str]], list[tuple]], schema: str) -> DataFrame:
    """The rows that ``measure(name, edges)`` gives for each shape, with its number of lines at the end."""
    def run(frames):
        import pandas as pd

        for pdf in frames:
            rows = [(*r, n) for name, edges, n in zip(pdf["name"], pdf["edges"], pdf["lines"]) for r in measure(name, list(edges))]
            yield pd.DataFrame(rows, columns=[c.split()[0] for c in (schema + ", lines long").split(", ")])

    return shapes.mapInPandas(run, schema + ", lines long")


def shapes_sql(shapes: dict[str, str], told: str, name: str) -> str:
    """SQL for ``measured``: the hand-worked values ``told`` (a query) of the shapes whose edges the lines name."""
    rows = ", ".join(f"({i}, '{n}', {len(t.split())}, {j}, '{e}')" for i, (n, t) in enumerate(shapes.items()) for j, e in enumerate(t.split()))
    want = ", ".join(f"('{n}', '{' '.join(sorted(set(t.split())))}')" for n, t in shapes.items())
    return f"""WITH named AS (SELECT * FROM (VALUES {rows}) t(shape, name, many, place, edge)),
met AS (SELECT name, edge, COUNT(*) AS n FROM lineitem JOIN named ON l_suppkey % {len(shapes)} = shape AND (l_partkey % 5040) % many = place GROUP BY 1, 2),
have AS (SELECT name AS shape_name, string_agg(edge, ' ' ORDER BY edge) AS edges, SUM(n)::BIGINT AS lines FROM met GROUP BY 1)
SELECT told.*, have.lines FROM ({told}) told JOIN have ON CAST(told.{name} AS VARCHAR) = have.shape_name JOIN (VALUES {want}) w(n, e) ON w.n = have.shape_name AND w.e = have.edges"""
