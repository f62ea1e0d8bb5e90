"""Variables, domains, factors and queries.

A factor is a function from a few variables to values, stored as its non-zero rows: a DataFrame with one column a
variable and a column ``val``, unique on the variables.  A query lists free variables, then bound ones, outermost first,
each with its aggregate, over a product of factors.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from mixagg.functions.algebra import Algebra

PRODUCT = "product"


@dataclass(frozen=True)
class Domain:
    """The declared values of a variable; product aggregates need its size, not the values that occur."""

    df: DataFrame  # one column, distinct
    size: int

    @staticmethod
    def range(spark: SparkSession, name: str, n: int) -> Domain:
        return Domain(spark.range(n).select(F.col("id").cast("int").alias(name)), n)

    @staticmethod
    def values(spark: SparkSession, name: str, items: list, dtype: str = "string") -> Domain:
        return Domain(spark.createDataFrame([(x,) for x in items], f"{name} {dtype}"), len(set(items)))

    @staticmethod
    def column(df: DataFrame, source: str, name: str) -> Domain:
        distinct = df.select(F.col(source).alias(name)).where(F.col(name).isNotNull()).distinct()
        return Domain(distinct, distinct.count())


@dataclass(frozen=True)
class Factor:
    vars: tuple[str, ...]
    df: DataFrame

    @staticmethod
    def build(df: DataFrame, algebra: Algebra, variables: dict[str, Column | str], value: Column | None = None, plus: str | None = None) -> Factor:
        """Rows grouped to unique keys by a sum; null keys and zeros are left out, as absent means zero."""
        names = tuple(variables)
        value = (algebra.one() if value is None else value).cast(algebra.dtype) if algebra.dtype != "array" else value
        rows = df.select(*[(F.col(c) if isinstance(c, str) else c).alias(v) for v, c in variables.items()], value.alias("val"))
        rows = rows.dropna(subset=list(names))
        if plus is None:
            rows = rows.dropDuplicates(list(names))  # a relation: every occurrence has the same value
        else:
            rows = rows.groupBy(*names).agg(algebra.plus[plus](F.col("val")).alias("val"))
        return Factor(names, rows.where(algebra.nonzero(F.col("val"))))

    @staticmethod
    def dense(df: DataFrame, algebra: Algebra, key: str, array: str, names: tuple[str, str], value=lambda v: v) -> Factor:
        """A truth table: one row a key with an array over the second variable."""
        rows = df.select(F.col(key).alias(names[0]), F.posexplode(array).alias(names[1], "__x"))
        return Factor(names, rows.select(*names, value(F.col("__x")).cast(algebra.dtype).alias("val")).where(algebra.nonzero(F.col("val"))))

    def size(self) -> int:
        return self.df.count()

    def project(self, on: tuple[str, ...]) -> DataFrame:
        """The indicator projection: which values of ``on`` have a non-zero row."""
        return self.df.select(*on).distinct()

    def value_at(self, points: DataFrame, algebra: Algebra) -> DataFrame:
        """The factor's values at points that name all its variables; zero where it has no row."""
        found = points.join(self.df.select(*self.vars, F.col("val").alias("__val")), list(self.vars), "left")
        return found.select(*points.columns, F.coalesce("__val", algebra.zero()).alias("val"))

    def next_value(self, points: DataFrame, variable: str, least: str) -> DataFrame:
        """For points over some other variables and a bound in column ``least``: the factor's smallest value of ``variable``
        there that is not below the bound; null if there is none."""
        on = [v for v in self.vars if v in points.columns]
        rows = self.project((*on, variable))
        near = points.join(rows, on, "left") if on else points.crossJoin(F.broadcast(rows.agg(F.sort_array(F.collect_set(variable)).alias("all"))).select(F.explode("all").alias(variable)))
        return near.groupBy(*points.columns).agg(F.min(F.when(F.col(variable) >= F.col(least), F.col(variable))).alias("next"))

    def product_marginal(self, k: str, domain: Domain, algebra: Algebra) -> Factor:
        """The factor with one variable multiplied out over its whole domain."""
        keep = tuple(v for v in self.vars if v != k)
        inside = self.df.join(domain.df.select(F.col(domain.df.columns[0]).alias(k)), k, "left_semi")
        grouped = inside.groupBy(*keep).agg(F.count("*").alias("__n"), algebra.product(F.col("val")).alias("val"))
        return Factor(keep, grouped.where((F.col("__n") == domain.size) & algebra.nonzero(F.col("val"))).select(*keep, "val"))

    def given(self, **values) -> Factor:
        """The factor under a partial assignment."""
        df = self.df
        for v, x in values.items():
            df = df.where(F.col(v) == F.lit(x))
        return Factor(tuple(v for v in self.vars if v not in values), df.drop(*values))

    def rename(self, names: dict[str, str]) -> Factor:
        return Factor(tuple(names.get(v, v) for v in self.vars), self.df.withColumnsRenamed(names))


@dataclass(frozen=True)
class FactorQuery:
    free: tuple[str, ...]
    bound: tuple[tuple[str, str], ...]
    factors: tuple[Factor, ...]
    algebra: Algebra
    domains: dict[str, Domain] = field(default_factory=dict)

    def __post_init__(self):
        for v, agg in self.bound:
            if agg != PRODUCT and agg not in self.algebra.plus:
                raise ValueError(f"{agg} is no sum of the algebra {self.algebra.name}")
            if agg == PRODUCT and v not in self.domains:
                raise ValueError(f"{v} is multiplied out, so its domain must be declared")
        names = [*self.free, *(v for v, _ in self.bound)]
        if len(set(names)) < len(names):
            raise ValueError("a variable is listed twice")
        if loose := {v for f in self.factors for v in f.vars} - set(names):
            raise ValueError(f"variables of factors are not in the query: {sorted(loose)}")

    @property
    def order(self) -> tuple[str, ...]:
        return (*self.free, *(v for v, _ in self.bound))

    @property
    def tags(self) -> dict[str, str]:
        return {**dict.fromkeys(self.free, "free"), **dict(self.bound)}

    @property
    def edges(self) -> tuple[frozenset[str], ...]:
        return tuple(frozenset(f.vars) for f in self.factors)

    def normalise(self) -> FactorQuery:
        """A variable in no factor gets the unit factor on its domain."""
        covered = set().union(*self.edges) if self.factors else set()
        extra = []
        for v in self.order:
            if v not in covered:
                if v not in self.domains:
                    raise ValueError(f"{v} is in no factor and has no domain")
                extra.append(Factor((v,), self.domains[v].df.select(v).withColumn("val", self.algebra.one())))
        return replace(self, factors=(*self.factors, *extra))

    def reordered(self, order: tuple[str, ...]) -> FactorQuery:
        tags = self.tags
        return replace(self, free=tuple(v for v in order if tags[v] == "free"), bound=tuple((v, tags[v]) for v in order if tags[v] != "free"))

    def check_values(self) -> None:
        """Max is a sum of this product only on non-negative values."""
        if self.algebra.non_negative and any(a == "max" for _, a in self.bound):
            for f in self.factors:
                low = f.df.agg(F.min("val")).first()[0]
                if low is not None and low < 0:
                    raise ValueError("max needs non-negative values")

    @staticmethod
    def parse(text: str, factors: dict[str, DataFrame], algebra: Algebra, domains: dict[str, Domain] | None = None) -> FactorQuery:
        """``free a; sum b; forall c; max d : R(a, b), S(b, c, d)``; forall and exists are the 0/1 product and max."""
        head, _, body = text.partition(":")
        free, bound = [], []
        for part in filter(None, (p.strip() for p in head.split(";"))):
            tag, *names = re.split(r"[\s,]+", part)
            tag = {"forall": PRODUCT, "exists": "max" if "max" in algebra.plus else "or"}.get(tag, tag)
            for v in names:
                free.append(v) if tag == "free" else bound.append((v, tag))
        made = []
        for name, args in re.findall(r"(\w+)\s*\(([^)]*)\)", body):
            v = tuple(a.strip() for a in args.split(","))
            df = factors[name]
            columns = [c for c in df.columns if c != "val"]
            if len(columns) != len(v):
                raise ValueError(f"{name} has {len(columns)} variables")
            made.append(Factor(v, df.select(*[F.col(c).alias(x) for c, x in zip(columns, v)], F.col("val") if "val" in df.columns else algebra.one().alias("val"))))
        return FactorQuery(tuple(free), tuple(bound), tuple(made), algebra, domains or {})


def compose(outer: FactorQuery, name_factor: int, inner: FactorQuery, prefix: str = "in_") -> FactorQuery:
    """Feeds a query's output into an outer query as its factor number ``name_factor``, as one query.

    Legal as one query when the inner bound variables may stand innermost: with the outer's aggregates all sums of the
    algebra and no product aggregate; otherwise evaluate the inner query first.
    """
    if any(a == PRODUCT for _, a in outer.bound):
        raise ValueError("evaluate the inner query first: the outer one multiplies out a variable")
    to = dict(zip(inner.free, outer.factors[name_factor].vars)) | {v: prefix + v for v, _ in inner.bound}
    factors = tuple(f for i, f in enumerate(outer.factors) if i != name_factor) + tuple(f.rename(to) for f in inner.factors)
    domains = outer.domains | {to[v]: Domain(d.df.withColumnRenamed(v, to[v]), d.size) for v, d in inner.domains.items() if v in to}
    return replace(outer, bound=(*outer.bound, *((to[v], a) for v, a in inner.bound)), factors=factors, domains=domains)
