"""Hypergraphs put in place of a hypergraph's edges: the composed hypergraph, a decomposition of it, bounds on its width."""

from __future__ import annotations

from fractions import Fraction

from mixagg.plans import widths
from mixagg.plans.widths import Edge

Tree = tuple[list[Edge], list[tuple[int, int]]]  # bags, links between their numbers


def composed_edges(inner: dict[Edge, list[Edge]]) -> tuple[Edge, ...]:
    """``inner`` gives, for every outer edge, the edges that stand in its place and cover its vertices."""
    for outer, edges in inner.items():
        if Edge().union(*edges) != outer:
            raise ValueError(f"the edges in place of {sorted(outer)} have other vertices")
    return tuple(dict.fromkeys(e for edges in inner.values() for e in edges))


def best_tree(edges) -> Tree:
    """The bags of an order of least fractional width, as one tree; the first bag is its root."""
    order = widths.best_order(tuple(edges))
    bags, parents = widths.order_to_decomposition(tuple(edges), order)
    at = {v: i for i, v in enumerate(order)}
    return [bags[v] for v in order], [(at[v], at[parents[v]] if parents[v] is not None else 0) for v in order[1:]]


def product_bound(inner: dict[Edge, list[Edge]]) -> Fraction:
    """The outer width times the largest fractional cover of what stands in an edge's place."""
    return widths.fractional_hypertree_width(tuple(inner)) * max(widths.rho(tuple(e), o) for o, e in inner.items())


def spread(tree: Tree) -> list[Edge]:
    """The bags with each vertex added wherever it is missing between two of its bags."""
    bags, links = tree
    near: dict[int, list[int]] = {i: [] for i in range(len(bags))}
    for i, j in links:
        near[i].append(j)
        near[j].append(i)
    out = [set(b) for b in bags]
    for v in Edge().union(*bags):
        has = {i for i, b in enumerate(bags) if v in b}
        left = {i: set(n) for i, n in near.items()}
        loose = [i for i in left if len(left[i]) <= 1 and i not in has]
        while loose:  # cut leaves without the vertex until every leaf has it
            i = loose.pop()
            for j in left.pop(i):
                left[j].discard(i)
                if len(left[j]) <= 1 and j not in has:
                    loose.append(j)
        for i in left:
            out[i].add(v)
    return [Edge(b) for b in out]


def composed_tree(inner: dict[Edge, list[Edge]]) -> tuple[Tree, list[Edge]]:
    """A decomposition of the composed hypergraph, and its bags before vertices were spread.

    Every bag of the outer tree becomes the union of the root bags of the trees of the outer edges that it meets; the
    rest of each of those trees hangs below it.
    """
    outer_bags, outer_links = best_tree(inner)
    own = {o: best_tree(e) for o, e in inner.items()}
    bags, links = [Edge()] * len(outer_bags), list(outer_links)
    for i, b in enumerate(outer_bags):
        for o, (below, below_links) in own.items():
            if o & b:
                bags[i] |= below[0]
                shift = len(bags) - 1
                links += [(x + shift, y + shift if y else i) for x, y in below_links]
                bags += below[1:]
    return (spread((bags, links)), links), bags


def tree_width(edges, bags) -> Fraction:
    return max(widths.rho(tuple(edges), b) for b in bags if b)


def additive_bound(inner: dict[Edge, list[Edge]]) -> Fraction:
    """The width of the bags before vertices were spread, plus the cover of what spreading added to a bag.

    The first term is the product of the outer and the largest inner width where a bag meets no edges but those of its
    cover; a bag that meets more takes in the roots of all of them and can be wider.
    """
    edges = composed_edges(inner)
    (after, _), before = composed_tree(inner)
    return tree_width(edges, before) + max((widths.rho(edges, a - b) for a, b in zip(after, before) if a - b), default=Fraction(0))


def is_decomposition(edges, tree: Tree) -> bool:
    """Every edge lies in a bag, and the bags of every vertex are connected."""
    bags, links = tree
    if not all(any(e <= b for b in bags) for e in edges):
        return False
    return all(sum(v in b for b in bags) - sum(v in bags[i] and v in bags[j] for i, j in links) == 1 for v in Edge().union(*edges))
