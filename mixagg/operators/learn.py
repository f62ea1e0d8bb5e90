"""Models fitted from sums that were pushed below a join; the solve is as small as the number of features."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from mixagg.functions import algebra
from mixagg.model import Factor, FactorQuery
from mixagg.operators import evaluate


def moments(df: DataFrame, columns: list[str]) -> DataFrame:
    """One row: the count, each column's sum and all second moments, named n, s_x and xx_x_y (the materialized way)."""
    pairs = [(a, b) for i, a in enumerate(columns) for b in columns[i:]]
    return df.agg(F.count("*").alias("n"), *[F.sum(c).alias(f"s_{c}") for c in columns], *[F.sum(F.col(a) * F.col(b)).alias(f"xx_{a}_{b}") for a, b in pairs])


def joined_moments(atoms: list[tuple[DataFrame, dict[str, str], dict[str, Column]]], **options) -> DataFrame:
    """The row of ``moments`` of a join that is never built: the engine eliminates all join variables over values that carry
    the moments.  An atom is a table, its join variables (variable: column) and its integer features (name: expression);
    rows with a null feature leave the join, and a join without rows has zeros."""
    names = [x for _, _, features in atoms for x in features]
    ring = algebra.moments(names)
    factors = []
    for df, variables, features in atoms:
        x = {a: e.cast("long") for a, e in features.items()}
        parts = [F.lit(1).cast("long").alias("n")]
        parts += [x.get(a, F.lit(0).cast("long")).alias(f"s_{a}") for a in names]
        parts += [(x[a] * x[b] if a in x and b in x else F.lit(0).cast("long")).alias(f"xx_{a}_{b}") for i, a in enumerate(names) for b in names[i:]]
        for e in x.values():
            df = df.where(e.isNotNull())
        factors.append(Factor.build(df, ring, variables, F.struct(*parts), "sum"))
    variables = dict.fromkeys(v for f in factors for v in f.vars)
    return evaluate.answer(FactorQuery((), tuple((v, "sum") for v in variables), tuple(factors), ring), **options).select("val.*")


def linear_regression(n: float, sums: dict[str, float], second: dict[tuple[str, str], float], features: list[str], target: str) -> dict[str, float]:
    """Least squares with an intercept (named ``1``) from moments; dependent features get the smallest coefficients."""
    at = lambda a, b: second[a, b] if (a, b) in second else second[b, a]
    size = len(features) + 1
    gram, right = np.empty((size, size)), np.empty(size)
    gram[0, 0], right[0] = n, sums[target]
    for i, a in enumerate(features, 1):
        gram[0, i] = gram[i, 0] = sums[a]
        right[i] = at(a, target)
        for j, b in enumerate(features, 1):
            gram[i, j] = at(a, b)
    # scaled to a unit diagonal first, as moments differ by orders of magnitude
    scale = 1 / np.sqrt(np.maximum(np.diag(gram), 1e-300))
    solved = np.linalg.lstsq(gram * scale[:, None] * scale[None], right * scale, rcond=None)[0] * scale
    return dict(zip(["1", *features], solved.tolist()))
