"""The problems of the engine as plain calls: quantified and counted conjunctive queries, marginals, most likely
assignments, pattern counts.  Atoms are (DataFrame, {variable: column}) pairs.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mixagg.functions.algebra import BOOL, COUNT, Algebra
from mixagg.model import PRODUCT, Domain, Factor, FactorQuery
from mixagg.operators import multijoin
from mixagg.operators.evaluate import answer, checked

Atom = tuple[DataFrame, dict[str, str]]


def relations(atoms: list[Atom], algebra: Algebra = COUNT) -> tuple[Factor, ...]:
    return tuple(Factor.build(df, algebra, columns) for df, columns in atoms)


def _quantified(prefix: list[tuple[str, str]]) -> tuple[tuple[str, str], ...]:
    return tuple((v, PRODUCT if kind == "forall" else "max") for v, kind in prefix)


def qcq(free: list[str], prefix: list[tuple[str, str]], atoms: list[Atom], domains: dict[str, Domain]) -> DataFrame:
    """The free assignments that satisfy a quantified conjunctive query; ``prefix``: (variable, 'forall' or 'exists')."""
    q = FactorQuery(tuple(free), _quantified(prefix), relations(atoms), COUNT, domains)
    out = answer(q, idempotent_inputs=True)
    return out.select(*free) if free else out.select((F.col("val") > 0).alias("holds"))


def count_qcq(count: list[str], prefix: list[tuple[str, str]], atoms: list[Atom], domains: dict[str, Domain], by: list[str] = ()) -> DataFrame:
    """How many assignments of ``count`` satisfy the quantified query, for each of ``by``: ``by``, val."""
    q = FactorQuery(tuple(by), (*((v, "sum") for v in count), *_quantified(prefix)), relations(atoms), COUNT, domains)
    return answer(q, idempotent_inputs=True)


def cq(free: list[str], atoms: list[Atom]) -> DataFrame:
    """The distinct free assignments of a conjunctive query."""
    factors = relations(atoms, BOOL)
    bound = dict.fromkeys(v for f in factors for v in f.vars if v not in free)
    return answer(FactorQuery(tuple(free), tuple((v, "or") for v in bound), factors, BOOL)).select(*free)


def count_cq(count: list[str], atoms: list[Atom]) -> DataFrame:
    """How many distinct assignments of ``count`` a conjunctive query has: val."""
    factors = relations(atoms)
    bound = dict.fromkeys(v for f in factors for v in f.vars if v not in count)
    return answer(FactorQuery((), (*((v, "sum") for v in count), *((v, "max") for v in bound)), factors, COUNT))


def marginal(of: list[str], factors: list[Factor], algebra: Algebra) -> DataFrame:
    """The marginal of a factor product on some variables (not normalised)."""
    bound = dict.fromkeys(v for f in factors for v in f.vars if v not in of)
    return answer(FactorQuery(tuple(of), tuple((v, "sum") for v in bound), tuple(factors), algebra))


def most_likely(given: list[str], choose: list[str], factors: list[Factor], algebra: Algebra) -> DataFrame:
    """``given``, ``choose``, val: for each given assignment the choice of largest value; ties go to the larger values of
    ``choose``, first variable first.  Each eliminated variable leaves a table of its best value, read back outermost first."""
    q = checked(FactorQuery(tuple(given), tuple((v, "max") for v in choose), tuple(factors), algebra).normalise())
    live, best = list(q.factors), []
    for k in reversed(choose):
        around = [f for f in live if k in f.vars]
        keep = tuple(v for v in q.order if v != k and any(v in f.vars for f in around))
        value = q.algebra.fold([F.col(f"v{i}") for i in range(len(around))])
        rows = multijoin.join(around).select(*keep, F.struct(value.alias("val"), F.col(k).alias("at")).alias("x"))
        top = (rows.groupBy(*keep) if keep else rows).agg(F.max("x").alias("x")).where(F.col("x").isNotNull())
        best.append((k, keep, top.select(*keep, F.col("x.at").alias(k))))
        live = [f for f in live if k not in f.vars] + [Factor(keep, top.select(*keep, F.col("x.val").alias("val")).where(q.algebra.nonzero(F.col("val"))))]
    parts = [f for f in live]
    out = multijoin.join(parts).select(*given, q.algebra.fold([F.col(f"v{i}") for i in range(len(parts))]).alias("val"))
    for k, keep, table in reversed(best):
        out = out.join(table, list(keep)) if keep else out.crossJoin(F.broadcast(table))  # one row
    return out.select(*given, *choose, "val")


def count_pattern(edges: DataFrame, source: str, target: str, pattern: list[tuple[str, str]]) -> DataFrame:
    """How often a small directed pattern maps into a graph (homomorphisms): val."""
    names = dict.fromkeys(v for e in pattern for v in e)
    return answer(FactorQuery((), tuple((v, "sum") for v in names), relations([(edges, {a: source, b: target}) for a, b in pattern]), COUNT))
