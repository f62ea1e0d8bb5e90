"""Joins of several factors: Catalyst's binary joins, a stepwise join within the size bound, or one round over a hypercube.

All return the joined variables and one value column a factor (``v0``, ``v1``, ...).
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from mixagg.model import Factor
from mixagg.plans import widths


def connected_order(factors: list[Factor]) -> list[int]:
    """Each next factor shares as many variables as possible with those before."""
    left, seen, out = list(range(len(factors))), set(), []
    while left:
        i = max(left, key=lambda i: (len(seen & set(factors[i].vars)), -len(set(factors[i].vars) - seen), -i))
        out.append(i)
        left.remove(i)
        seen |= set(factors[i].vars)
    return out


def binary_join(factors: list[Factor]) -> DataFrame:
    out, seen = None, set()
    for i in connected_order(factors):
        side = factors[i].df.select(*factors[i].vars, F.col("val").alias(f"v{i}"))
        shared = [v for v in factors[i].vars if v in seen]
        # without shared variables the product is wanted: scalar factors have one row, other parts are components
        out = side if out is None else out.join(side, shared) if shared else out.crossJoin(side)
        seen |= set(factors[i].vars)
    return out


def stepwise_join(factors: list[Factor], order: list[str]) -> DataFrame:
    """Binds one variable at a time: each prefix is extended by the factor that offers it the fewest values, and the
    other factors with that variable filter the result, so no step makes more rows than the prefix's size bound."""
    prefix: DataFrame | None = None
    bound: list[str] = []
    for x in order:
        near = [(i, [v for v in f.vars if v in bound]) for i, f in enumerate(factors) if x in f.vars]
        tables = [(i, on, factors[i].project((*on, x))) for i, on in near]
        if prefix is None:
            prefix = reduce(lambda a, b: a.join(b, x, "left_semi"), [t for _, _, t in tables])
        elif len(tables) == 1 or not any(on for _, on, _ in tables):
            _, on, t = tables[0]
            prefix = prefix.join(t, on) if on else prefix.crossJoin(t)
            for _, on2, t2 in tables[1:]:
                prefix = prefix.join(t2, [*on2, x], "left_semi")
        else:
            counted = prefix
            ways = [w for w in tables if w[1]]
            for i, on, t in ways:
                counted = counted.join(t.groupBy(*on).agg(F.count("*").alias(f"c{i}")), on)
            counts = [F.col(f"c{i}") for i, _, _ in ways]
            least = F.least(*counts) if len(counts) > 1 else counts[0]
            pick: Column = F.lit(ways[-1][0])
            for (i, _, _), c in reversed(list(zip(ways[:-1], counts[:-1]))):
                pick = F.when(c == least, F.lit(i)).otherwise(pick)
            chosen = counted.withColumn("__way", pick).drop(*[f"c{i}" for i, _, _ in ways])
            parts = []
            for i, on, t in ways:
                part = chosen.where(F.col("__way") == i).drop("__way").join(t, on)
                for j, on2, t2 in tables:
                    if j != i:
                        part = part.join(t2, [*on2, x], "left_semi")
                parts.append(part.select(*bound, x))
            prefix = reduce(DataFrame.unionByName, parts)
        bound.append(x)
    out = prefix
    for i, f in enumerate(factors):
        out = out.join(f.df.select(*f.vars, F.col("val").alias(f"v{i}")), list(f.vars)) if f.vars else out.crossJoin(f.df.select(F.col("val").alias(f"v{i}")))
    return out


def hypercube_join(factors: list[Factor], shares: dict[str, int]) -> DataFrame:
    """A join in one round: the result's space is cut into a cell for each combination of hashed variables, ``shares``
    says into how many parts per variable.  A row goes to all cells that it can meet another in, so it is copied by the
    shares of the variables it lacks; each result lies in exactly one cell, and no intermediate join is shuffled again."""
    def dealt(i: int) -> DataFrame:
        f = factors[i]
        df = f.df.select(*f.vars, F.col("val").alias(f"v{i}"))
        for v, parts in shares.items():
            here = F.pmod(F.xxhash64(v), F.lit(parts)).cast("int") if v in f.vars else F.explode(F.sequence(F.lit(0), F.lit(parts - 1)))
            df = df.withColumn(f"cell_{v}", here)
        return df.withColumn("cell", F.hash(*[f"cell_{v}" for v in shares])).drop(*[f"cell_{v}" for v in shares]).repartition("cell")

    out, seen = None, set()
    for i in connected_order(factors):
        side = dealt(i)
        out = side if out is None else out.join(side, ["cell", *(v for v in factors[i].vars if v in seen)])
        seen |= set(factors[i].vars)
    return out.drop("cell")


def first_join_rows(factors: list[Factor]) -> int:
    """Exactly how many rows the first of the binary joins makes, from the counts of its keys."""
    a, b = (factors[i] for i in connected_order(factors)[:2])
    on = [v for v in a.vars if v in b.vars]
    counted = lambda f, n: f.df.groupBy(*on).agg(F.count("*").alias(n))
    return (counted(a, "m").join(counted(b, "n"), on) if on else counted(a, "m").crossJoin(counted(b, "n"))).agg(F.sum(F.col("m") * F.col("n"))).first()[0] or 0


def choose(factors: list[Factor]) -> str:
    """Binary joins, unless the factors form a cycle and the first join alone makes more rows than the whole bag may have."""
    factors = [f for f in factors if f.vars]
    edges = [frozenset(f.vars) for f in factors]
    if len(factors) < 3 or widths.is_alpha_acyclic(edges):
        return "binary"
    bound = widths.size_bound(edges, frozenset().union(*edges), [max(f.size(), 1) for f in factors])
    return "stepwise" if first_join_rows(factors) > bound else "binary"


def join(factors: list[Factor], how: str = "binary") -> DataFrame:
    if how == "auto":
        how = choose(factors)
    if how == "stepwise":
        order: list[str] = []
        for i in connected_order(factors):
            order += [v for v in factors[i].vars if v not in order]
        return stepwise_join(factors, order)
    if how == "hypercube":
        names = dict.fromkeys(v for f in factors for v in f.vars if sum(v in g.vars for g in factors) > 1)
        return hypercube_join(factors, dict.fromkeys(names, 3))
    if how != "binary":
        raise ValueError(how)
    return binary_join(factors)
