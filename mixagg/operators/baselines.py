"""The plain ways to evaluate the same queries, for comparison."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mixagg.model import PRODUCT, Factor, FactorQuery
from mixagg.operators import evaluate, multijoin
from mixagg.operators.bags import over_bags
from mixagg.plans import ordering, widths


def nested(q: FactorQuery) -> DataFrame:
    """The definition itself: the grid of all declared domains, zeros filled in, aggregates from the innermost out."""
    grid = None
    for v in q.order:
        side = q.domains[v].df.select(F.col(q.domains[v].df.columns[0]).alias(v))
        grid = side if grid is None else grid.crossJoin(side)  # tiny domains only
    for i, f in enumerate(q.factors):
        side = f.df.select(*f.vars, F.col("val").alias(f"v{i}"))
        grid = grid.join(side, list(f.vars), "left") if f.vars else grid.crossJoin(side)
    rows = grid.select(*q.order, q.algebra.fold([F.coalesce(F.col(f"v{i}"), q.algebra.zero()) for i in range(len(q.factors))]).alias("val"))
    names = list(q.order)
    for _, agg in reversed(q.bound):
        names.pop()
        total = (q.algebra.product if agg == PRODUCT else q.algebra.plus[agg])(F.col("val")).alias("val")
        rows = rows.groupBy(*names).agg(total) if names else rows.agg(total)
    return rows.where(q.algebra.nonzero(F.col("val"))) if names else rows


def join_then_aggregate(q: FactorQuery) -> DataFrame:
    """One full join, then the sums."""
    return evaluate.search(q, how="binary")


def without_indicators(q: FactorQuery, order=None) -> DataFrame:
    return evaluate.answer(q, order=order, indicators=False)


def given_order(q: FactorQuery) -> DataFrame:
    return evaluate.answer(q, order="given")


def blocks_only(q: FactorQuery) -> tuple:
    """The best order that only permutes variables within blocks of one aggregate, blind to the hypergraph."""
    from itertools import permutations, product

    blocks = [list(permutations(vs)) for _, vs in ordering.tag_blocks(q.order, q.tags)]
    return min((sum(c, ()) for c in product(*blocks)), key=lambda o: widths.elim_width(q.edges, o, q.tags))


def by_width(q: FactorQuery, kind: str) -> tuple:
    """The best safe order by another measure: 'tw' (bag size), 'ghtw' (integral covers) or 'prefix' (bag size, sums only)."""
    g = {"tw": lambda e, b: len(b) - 1, "ghtw": widths.rho_int, "prefix": lambda e, b: len(b)}[kind]
    t = ordering.theory(q)
    return min(t.extensions(), key=lambda o: max((g(q.edges, u) for k, u in widths.elimination_sequence(q.edges, o, q.tags).items() if q.tags[k] != PRODUCT), default=0))


def prefix_width(q: FactorQuery) -> int:
    o = by_width(q, "prefix")
    return max((len(u) for k, u in widths.elimination_sequence(q.edges, o, q.tags).items() if q.tags[k] != PRODUCT), default=0)


def acyclic_join(q: FactorQuery) -> DataFrame:
    """The two-phase semi-join program on a join tree, then joins without dead ends."""
    tree = widths.join_tree(q.edges)
    if tree is None:
        raise ValueError("not acyclic")
    dfs = {i: f.df for i, f in enumerate(q.factors)}
    near: dict[int, list[int]] = {i: [] for i in dfs}
    for i, j in tree:
        near[i].append(j)
        near[j].append(i)
    walk, seen = [], set()

    def visit(i, parent):
        seen.add(i)
        for j in near[i]:
            if j != parent:
                visit(j, i)
        walk.append((i, parent))

    for i in dfs:
        if i not in seen:
            visit(i, None)
    reduce_by = lambda a, b: dfs[a].join(dfs[b].select(*on), list(on), "left_semi") if (on := set(q.factors[a].vars) & set(q.factors[b].vars)) else dfs[a]
    for i, p in walk:
        if p is not None:
            dfs[p] = reduce_by(p, i)
    for i, p in reversed(walk):
        if p is not None:
            dfs[i] = reduce_by(i, p)
    parts = [type(f)(f.vars, dfs[i]) for i, f in enumerate(q.factors)]
    joined = multijoin.join(parts)
    return joined.select(*q.order, q.algebra.fold([F.col(f"v{i}") for i in range(len(parts))]).alias("val"))


def count_distinct_projection(q: FactorQuery) -> DataFrame:
    """Counting a conjunctive query by listing its distinct free part."""
    return multijoin.join(list(q.factors)).select(*q.free).distinct().agg(F.count("*").alias("val"))


def decomposition_join(q: FactorQuery) -> DataFrame:
    """Joins each bag of the best order's tree decomposition by itself, then the bags along their tree."""
    return acyclic_join(over_bags(q))


def union_all(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)
