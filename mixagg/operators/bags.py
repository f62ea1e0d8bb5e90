"""A cyclic query as an acyclic one over the bags of a tree decomposition."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import functions as F

from mixagg.model import Factor, FactorQuery
from mixagg.operators import multijoin
from mixagg.plans import widths


def over_bags(q: FactorQuery) -> FactorQuery:
    """The query with one factor a maximal bag of the best order's decomposition: the factors that the bag is the first to
    cover, joined, and what other factors allow on variables that those leave open."""
    bags, _ = widths.order_to_decomposition(q.edges, widths.best_order(q.edges))
    tops = [u for u in set(bags.values()) if not any(u < w for w in bags.values())]
    left, parts = list(q.factors), []
    for bag in sorted(tops, key=sorted):
        own = [f for f in left if set(f.vars) <= bag]
        left = [f for f in left if not set(f.vars) <= bag]
        part = {v for f in own for v in f.vars}
        ones = [Factor(on, f.project(on).withColumn("val", q.algebra.one())) for f in q.factors if f not in own and (on := tuple(v for v in f.vars if v in bag)) and not set(on) <= part]
        names = tuple(v for v in q.order if v in bag)
        joined = multijoin.join([*own, *ones])
        parts.append(Factor(names, joined.select(*names, q.algebra.fold([F.col(f"v{i}") for i in range(len(own) + len(ones))]).alias("val"))))
    return replace(q, factors=tuple(parts))
