"""Evaluation of mixed-aggregate queries: elimination, conditioned search, output forms, calibration.

``eliminate`` takes the innermost variable first.  A sum folds the factors around its variable into one new factor
(join, semi-joins with what else meets the bag, one aggregation); a product aggregate is pushed into each factor by
itself.  A factor that lies wholly in the bag joins it at once, instead of filtering now and joining later, and one that
meets the bag only where an incident factor already has all those variables waits: neither is read twice.  What still
filters now and joins later is written once and read back.  All else is lazy, so Catalyst sees one plan.
"""

from __future__ import annotations

import time
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mixagg.model import PRODUCT, Factor, FactorQuery
from mixagg.operators import multijoin
from mixagg.operators.bags import over_bags
from mixagg.plans import ordering
from mixagg.plans.widths import join_tree
from mixagg.sources.steps import kept


@dataclass
class Meter:
    """What each step worked on: variable, bag, and, if counting is on, rows joined and rows kept."""

    count: bool = False
    steps: list[dict] = field(default_factory=list)

    def note(self, k: str, bag, joined: DataFrame | None, out: DataFrame) -> None:
        row = {"variable": k, "bag": sorted(bag)}
        if self.count:
            row |= {"joined": joined.count() if joined is not None else None, "rows": out.count()}
        self.steps.append(row)


def _meeting(joined: DataFrame, others: list[Factor], around: list[Factor]) -> tuple[DataFrame, list[Factor]]:
    """Rows that every other live factor allows on variables that no single factor of the bag covers; the others, of which
    those that were used are kept steps now."""
    bag = {v for f in around for v in f.vars}
    out = []
    for f in others:
        shared = [v for v in f.vars if v in bag]
        if len(shared) > 1 and not any(set(shared) <= set(g.vars) for g in around):
            f = Factor(f.vars, kept(f.df))
            joined = joined.join(f.df.select(*shared), shared, "left_semi")
        out.append(f)
    return joined, out


def semiring_step(q: FactorQuery, live: list[Factor], k: str, agg: str, indicators: bool, how: str, meter: Meter | None) -> list[Factor]:
    around = [f for f in live if k in f.vars]
    rest = [f for f in live if k not in f.vars]
    bag = {v for f in around for v in f.vars}
    keep = tuple(v for v in q.order if v in bag and v != k)
    if indicators:  # a sum distributes over factors without its variable
        around += [f for f in rest if f.vars and set(f.vars) <= bag]
        rest = [f for f in rest if not (f.vars and set(f.vars) <= bag)]
    joined = multijoin.join(around, how)
    if indicators:
        joined, rest = _meeting(joined, rest, around)
    value = q.algebra.fold([F.col(f"v{i}") for i in range(len(around))])
    rows = joined.select(*keep, value.alias("val"))
    out = rows.groupBy(*keep).agg(q.algebra.plus[agg](F.col("val")).alias("val")) if keep else rows.agg(q.algebra.plus[agg](F.col("val")).alias("val")).where(F.col("val").isNotNull())
    out = out.where(q.algebra.nonzero(F.col("val")))
    if meter:
        meter.note(k, bag, joined, out)
    return [*rest, Factor(keep, out)]


def product_step(q: FactorQuery, live: list[Factor], k: str, meter: Meter | None) -> list[Factor]:
    """Each factor with the variable is multiplied out over the whole declared domain (a missing row is a zero); the
    others are raised to the domain's size, except idempotent values."""
    size, out = q.domains[k].size, []
    for f in live:
        if k in f.vars:
            out.append(f.product_marginal(k, q.domains[k], q.algebra))
        else:
            out.append(Factor(f.vars, f.df.select(*f.vars, q.algebra.powered(F.col("val"), size).alias("val"))))
    if meter:
        meter.note(k, {v for f in live if k in f.vars for v in f.vars}, None, out[0].df)
    return out


def filter_bags(q: FactorQuery, live: list[Factor]) -> list[DataFrame]:
    """For each free variable, last first, the join of indicator projections over its bag; no dead ends remain."""
    edges = [f.project(f.vars) for f in live if f.vars]
    bags = []
    for k in reversed(q.free):
        around = [e for e in edges if k in e.columns]
        bag = {c for e in around for c in e.columns}
        joined = multijoin.binary_join([Factor(tuple(e.columns), e.withColumn("val", F.lit(True))) for e in around]).select(*[v for v in q.free if v in bag])
        for e in edges:
            shared = [c for c in e.columns if c in bag]
            if k not in e.columns and shared:
                joined = joined.join(e.select(*shared), shared, "left_semi")
        bags.append(joined)
        rest = [v for v in q.free if v in bag and v != k]
        edges = [e for e in edges if k not in e.columns] + ([joined.select(*rest).distinct()] if rest else [])
    return bags[::-1]


@dataclass
class Result:
    """Residual factors on the free variables and, unless asked not to, the filters that remove dead ends."""

    query: FactorQuery
    factors: list[Factor]
    bags: list[DataFrame]

    def listing(self) -> DataFrame:
        q = self.query
        value = q.algebra.fold([F.col(f"v{i}") for i in range(len(self.factors))])
        if not q.free:
            return scalar(q, self.factors)
        joined = multijoin.join(self.factors)
        for b in self.bags if len(self.factors) > 2 else ():  # a join of two has no dead ends to begin with
            if b.columns != list(q.free):
                joined = joined.join(b, b.columns, "left_semi")
        return joined.select(*q.free, value.alias("val")).where(q.algebra.nonzero(F.col("val")))

    def value(self, points: DataFrame) -> DataFrame:
        """The function at given points, by probing every residual factor; zero where one has no row."""
        out = points
        for i, f in enumerate(self.factors):
            side = f.df.select(*f.vars, F.col("val").alias(f"v{i}"))
            out = out.join(side, list(f.vars), "left") if f.vars else out.crossJoin(side)
        known = [F.col(f"v{i}") for i in range(len(self.factors))]
        total = self.query.algebra.fold(known)
        missing = F.greatest(*[c.isNull() for c in known]) if len(known) > 1 else known[0].isNull()
        return out.select(*points.columns, F.when(missing, self.query.algebra.zero()).otherwise(total).alias("val"))

    def enumerated(self) -> DataFrame:
        """The listing in the order of the free variables, range-partitioned, so each partition can be read with constant
        delay and the partitions one after the other give the whole order."""
        return self.listing().repartitionByRange(*self.query.free).sortWithinPartitions(*self.query.free)

    def factorized(self) -> list[DataFrame]:
        """One relation a free variable, range-partitioned and sorted by the variables before it."""
        return [b.repartitionByRange(*b.columns).sortWithinPartitions(*b.columns) for b in self.bags]


def scalar(q: FactorQuery, live: list[Factor]) -> DataFrame:
    """One row; the zero where some factor is empty."""
    out = None
    for i, f in enumerate(live):
        side = f.df.agg(F.first("val").alias(f"v{i}"))
        out = side if out is None else out.crossJoin(side)
    value = q.algebra.fold([F.col(f"v{i}") for i in range(len(live))])
    return out.select(F.coalesce(value, q.algebra.zero()).alias("val"))


def eliminate(q: FactorQuery, order: tuple[str, ...] | str | None = None, indicators: bool = True, how: str = "binary", output: str = "filtered",
              check: bool = True, meter: Meter | None = None, idempotent_inputs: bool = False) -> Result:
    """Runs the query along a safe order: a given one, 'given' (the query's own), or the planner's."""
    q = q.normalise()
    if order is None:
        order = ordering.plan(q, idempotent_inputs).order
    elif order == "given":
        order = q.order
    elif check and not ordering.theory(q, idempotent_inputs).is_safe(order):
        raise ValueError(f"{order} may give another function")
    q = checked(q.reordered(tuple(order)), idempotent_inputs)
    live = list(q.factors)
    for k, agg in reversed(q.bound):
        live = product_step(q, live, k, meter) if agg == PRODUCT else semiring_step(q, live, k, agg, indicators, how, meter)
    if output == "filtered" and len(live) > 2:
        live = [Factor(f.vars, kept(f.df)) if f.vars else f for f in live]
    return Result(q, live, filter_bags(q, live) if output == "filtered" and q.free else [])


def _refuse(q: FactorQuery, bad, why: str) -> FactorQuery:
    failing = F.when(bad(F.col("val")), F.raise_error(F.lit(why)).cast(q.algebra.dtype)).otherwise(F.col("val"))
    return replace(q, factors=tuple(Factor(f.vars, f.df.withColumn("val", failing)) for f in q.factors))


def checked(q: FactorQuery, idempotent_inputs: bool = False) -> FactorQuery:
    """The query with factors that fail, as their rows are read, on values that its plan can't take: negative or NaN under
    a maximum; v * v unlike v where the caller says that no input has such."""
    if q.algebra.non_negative and any(a == "max" for _, a in q.bound):
        q = _refuse(q, lambda v: (v < 0) | F.isnan(v.cast("double")), "max needs non-negative values")
    if idempotent_inputs and any(a == PRODUCT for _, a in q.bound) and q.algebra.dtype != "array":
        q = _refuse(q, lambda v: ~q.algebra.idempotent(v), "an input is not idempotent")
    return q


def answer(q: FactorQuery, **options) -> DataFrame:
    return eliminate(q, **options).listing()


def search(q: FactorQuery, how: str = "stepwise") -> DataFrame:
    """Conditioned search in bulk: binds all variables outermost first, then folds the sums from the innermost out."""
    if any(a == PRODUCT for _, a in q.bound):
        raise ValueError("conditioned search takes sums only")
    q = q.normalise()
    factors = [f for f in q.factors]
    joined = multijoin.stepwise_join(factors, list(q.order)) if how == "stepwise" else multijoin.join(factors, how)
    rows = joined.select(*q.order, q.algebra.fold([F.col(f"v{i}") for i in range(len(factors))]).alias("val"))
    return fold_sums(q, rows)


def fold_sums(q: FactorQuery, rows: DataFrame) -> DataFrame:
    names = list(q.order)
    for _, agg in reversed(q.bound):
        names.pop()
        total = q.algebra.plus[agg](F.col("val")).alias("val")
        rows = rows.groupBy(*names).agg(total) if names else rows.agg(F.coalesce(total, q.algebra.zero()).alias("val"))
    return rows.where(q.algebra.nonzero(F.col("val"))) if names else rows


def calibrate(q: FactorQuery, agg: str) -> list[Factor]:
    """Message passing on a join tree of an acyclic query with one sum: each bag ends with the whole query's marginal.

    A cyclic query's bags are those of a tree decomposition, each written once; otherwise they are its factors, in order.
    Messages leave out the edge they are sent over, so no division is needed.
    """
    tree = join_tree(q.edges)
    if tree is None:
        q = over_bags(q)
        q = replace(q, factors=tuple(Factor(f.vars, kept(f.df)) for f in q.factors))
        tree = join_tree(q.edges)
    near: dict[int, list[int]] = {i: [] for i in range(len(q.factors))}
    for i, j in tree:
        near[i].append(j)
        near[j].append(i)
    sent: dict[tuple[int, int], Factor] = {}

    def gathered(i: int, skip: int | None) -> Factor:
        parts = [q.factors[i], *(message(j, i) for j in near[i] if j != skip)]
        joined = multijoin.join(parts)
        return Factor(q.factors[i].vars, joined.select(*q.factors[i].vars, q.algebra.fold([F.col(f"v{n}") for n in range(len(parts))]).alias("val")))

    def message(i: int, j: int) -> Factor:
        if (i, j) not in sent:
            shared = tuple(v for v in q.factors[i].vars if v in q.factors[j].vars)
            g = gathered(i, j)
            sent[i, j] = Factor(shared, g.df.groupBy(*shared).agg(q.algebra.plus[agg](F.col("val")).alias("val")))
        return sent[i, j]

    return [gathered(i, None) for i in range(len(q.factors))]


def output_times(q: FactorQuery, points: DataFrame) -> list[tuple[str, str, int, float]]:
    """(form, phase, rows, seconds) of the three ways to give a result: what is made before it is asked, the values at
    ``points`` (columns: the free variables), and reading the whole result."""
    out = []

    def timed(form: str, phase: str, make):
        start = time.perf_counter()
        df = kept(make())
        out.append((form, phase, df.count(), time.perf_counter() - start))
        return df

    zero = q.algebra.zero()
    listed = timed("listing", "before", lambda: eliminate(q).listing())
    timed("listing", "values", lambda: points.join(listed, list(q.free), "left").withColumn("val", F.coalesce("val", zero)))
    timed("listing", "reading", lambda: listed)
    query = eliminate(q, output="query")
    timed("query", "values", lambda: query.value(points))
    timed("query", "reading", lambda: query.listing())
    whole = eliminate(q)
    whole.bags = [timed("factorized", f"before {v}", lambda b=b: b) for v, b in zip(whole.query.free, whole.factorized())]
    timed("factorized", "values", lambda: whole.value(points))
    timed("factorized", "reading", lambda: whole.enumerated())
    return out


def lift_variance(df: DataFrame, keys: list[str], value: str) -> DataFrame:
    """A population variance as three sums that combine, finished by one expression."""
    v = F.col(value)
    parts = df.groupBy(*keys).agg(F.sum(v).alias("total"), F.sum(v * v).alias("squares"), F.count(v).alias("n"))
    return parts.withColumn("variance", F.col("squares") / F.col("n") - F.pow(F.col("total") / F.col("n"), 2))


def lift_average(df: DataFrame, keys: list[str], value: str) -> DataFrame:
    """An average as a pair of sums that combine, finished by one division."""
    parts = df.groupBy(*keys).agg(F.sum(value).alias("total"), F.count(value).alias("n"))
    return parts.withColumn("avg", F.col("total") / F.col("n"))
