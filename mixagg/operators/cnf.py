"""Satisfiability and weighted model counting of many formulas at once, by eliminating variables from clauses.

A clause is a set of literals, +v or -v.  Formulas are independent groups; within one, elimination is sequential.
"""

from __future__ import annotations

from collections.abc import Iterable
from fractions import Fraction
from itertools import product

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from mixagg.functions.algebra import REAL
from mixagg.model import Factor, FactorQuery
from mixagg.plans.widths import Edge, nested_order
from mixagg.sources.steps import kept

Clause = frozenset


def resolve_out(clauses: set[Clause], v: int) -> set[Clause]:
    """Replaces the clauses with ``v`` by their resolvents; tautologies and supersets go."""
    pos, neg = [c - {v} for c in clauses if v in c], [c - {-v} for c in clauses if -v in c]
    rest = {c for c in clauses if v not in c and -v not in c}
    made = {a | b for a in pos for b in neg if not any(-x in b for x in a)}
    return {c for c in rest | made if not any(d < c for d in rest | made)}


def satisfiable(clauses: Iterable[Clause], order: Iterable[int] | None = None, sizes: list[int] | None = None) -> bool:
    """Davis-Putnam elimination; along a nested order the number of clauses never grows (``sizes`` collects it)."""
    live = {Clause(c) for c in clauses}
    variables = sorted({abs(x) for c in live for x in c})
    order = order or (nested_order([Edge(map(abs, c)) for c in live if c]) if any(live) else None) or variables
    for v in reversed(list(order)):
        live = resolve_out(live, v)
        if sizes is not None:
            sizes.append(len(live))
    return Clause() not in live


def weighted_count_nested(clauses: list[tuple[Clause, Fraction]], order: Iterable[int]) -> Fraction:
    """Sum over assignments of the product of the weights of falsified clauses, along a nested elimination order.

    The clauses around a variable form a chain of variable sets; each is replaced by its own rest, weighted so that the
    chain's prefix products equal the sum over the variable's two values.
    """
    total, live = Fraction(1), list(clauses)
    for v in reversed(list(order)):
        around = sorted((c for c in live if v in c[0] or -v in c[0]), key=lambda c: len(c[0]))
        live = [c for c in live if v not in c[0] and -v not in c[0]]
        total *= 2
        before: list[tuple[Clause, Fraction, int]] = []
        for c, w in around:
            rest = c - {v, -v}

            def value(members, rest=rest):
                out = [Fraction(1), Fraction(1)]
                for r, x, sign in members:
                    if r <= rest:
                        out[sign] *= x
                return out[0] + out[1]

            was = value(before)
            before.append((rest, w, int(v in c)))
            now = value(before)
            ratio = now / was if was else Fraction(0)
            if rest:
                live.append((rest, ratio))
            else:
                total *= ratio
    for c, w in live:
        total *= w
    return total


def truth_table(clauses: list[tuple[Clause, Fraction]], variables: list[int]) -> Fraction:
    total = Fraction(0)
    for bits in product((0, 1), repeat=len(variables)):
        true = {v if b else -v for v, b in zip(variables, bits)}
        w = Fraction(1)
        for c, x in clauses:
            if not c & true:
                w *= x
        total += w
    return total


def as_query(spark: SparkSession, clauses: list[tuple[Clause, float]]) -> FactorQuery:
    """The weighted count as a query for the engine, whatever the formula's shape: a factor a clause, all variables summed.

    A clause of k variables lists 2**k rows, so this is for short clauses; the engine's order bounds the rest.
    """
    factors = []
    for c, weight in clauses:
        names = sorted({abs(x) for x in c})
        rows = [(*bits, 1.0 if any((bits[names.index(abs(x))] == 1) == (x > 0) for x in c) else float(weight)) for bits in product((0, 1), repeat=len(names))]
        fields = ", ".join([*(f"x{v} int" for v in names), "val double"])
        factors.append(Factor(tuple(f"x{v}" for v in names), spark.createDataFrame([r for r in rows if r[-1]], fields)))
    names = dict.fromkeys(v for f in factors for v in f.vars)
    return FactorQuery((), tuple((v, "sum") for v in names), tuple(factors), REAL)


def weighted_per_formula(rows: DataFrame, variables: int) -> DataFrame:
    """``rows``: formula, lits, num, den (a falsified clause weighs num / den) -> formula, weight: the weighted count over
    ``variables`` variables.  Repeated clauses of a formula count once, with their smallest weight."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        least: dict[Clause, Fraction] = {}
        for lits, num, den in zip(pdf["lits"], pdf["num"], pdf["den"]):
            c, w = Clause(int(x) for x in lits), Fraction(int(num), int(den))
            least[c] = min(w, least.get(c, w))
        clauses = sorted(least.items(), key=lambda x: sorted(x[0]))
        order = nested_order([Edge(map(abs, c)) for c in least if c]) if any(least) else ()
        used = sorted({abs(x) for c in least for x in c})
        total = truth_table(clauses, used) if order is None else weighted_count_nested(clauses, order)
        return pd.DataFrame({"formula": [pdf["formula"].iloc[0]], "weight": [float(total * 2 ** (variables - len(used)))]})

    return rows.groupBy("formula").applyInPandas(run, "formula string, weight double")


def per_formula(rows: DataFrame, variables: int) -> DataFrame:
    """``rows``: formula, lits (array of non-zero ints) -> formula, sat, models over ``variables`` variables.

    A formula has at most 3**variables distinct clauses, which bounds a group.
    """

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        clauses = {Clause(int(x) for x in lits) for lits in pdf["lits"]}
        order = nested_order([Edge(map(abs, c)) for c in clauses if c]) if any(clauses) else ()
        free = variables - len(order or ())
        weighted = [(c, Fraction(0)) for c in clauses]
        if order is None:
            used = sorted({abs(x) for c in clauses for x in c})
            models, free = truth_table(weighted, used), variables - len(used)
        else:
            models = weighted_count_nested(weighted, order)
        return pd.DataFrame({"formula": [pdf["formula"].iloc[0]], "sat": [satisfiable(clauses, order or None)], "models": [int(models * 2**free)]})

    return rows.dropDuplicates(["formula", "lits"]).groupBy("formula").applyInPandas(run, "formula string, sat boolean, models long")


def satisfiable_by_joins(rows: DataFrame, order: Iterable[int]) -> DataFrame:
    """``rows``: formula, lits -> formula, sat.  All formulas lose one variable at a time, the last of ``order`` first: a
    step joins the clauses that have it with those that have its negation, so one large formula is spread over tasks.

    ``order`` names every variable.  Each step's clauses are written, since the next one reads them several times.
    """
    def clash(lits: Column) -> Column:
        return F.arrays_overlap(lits, F.transform(lits, lambda x: -x))

    def cleaned(df: DataFrame) -> DataFrame:
        df = kept(df.where(~clash(F.col("lits"))).dropDuplicates(["formula", "lits"]))
        less = df.select("formula", F.col("lits").alias("less"))
        inside = (df["formula"] == less["formula"]) & (F.size("less") < F.size("lits")) & (F.size(F.array_except("less", "lits")) == 0)
        return df.join(less, inside, "left_anti")

    live = cleaned(rows.select("formula", F.sort_array(F.array_distinct(F.col("lits").cast("array<int>"))).alias("lits")))
    for v in reversed(list(order)):
        live = kept(live)
        has = lambda x: F.array_contains("lits", x)
        pos = live.where(has(v)).select("formula", F.array_remove("lits", v).alias("p"))
        neg = live.where(has(-v)).select("formula", F.array_remove("lits", -v).alias("n"))
        made = pos.join(neg, "formula").select("formula", F.sort_array(F.array_union("p", "n")).alias("lits"))
        live = cleaned(live.where(~has(v) & ~has(-v)).unionByName(made))
    failed = live.where(F.size("lits") == 0).select("formula").distinct().withColumn("failed", F.lit(True))
    return rows.select("formula").distinct().join(failed, "formula", "left").select("formula", F.col("failed").isNull().alias("sat"))
