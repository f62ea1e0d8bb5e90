"""Safe orders by their definition: the same function for every input, tried on random small factors.

For tests and teaching: the grid of all variables is laid out, so only a few variables with two or three values will do.
Orders that ever differ come with the input that shows it; orders that never do are safe as far as was tried.
"""

from __future__ import annotations

from itertools import permutations, product

import numpy as np

_REDUCE = {"sum": np.sum, "max": np.max, "product": np.prod}


def evaluated(factors: list[tuple[tuple, np.ndarray]], order: tuple, tags: dict, size: int) -> np.ndarray:
    """The query's value along an order; free variables stay, in a fixed order."""
    names = sorted(order, key=str)
    grid = np.ones((size,) * len(names))
    for variables, values in factors:
        at = sorted(range(len(variables)), key=lambda i: names.index(variables[i]))
        shape = [size if v in variables else 1 for v in names]
        grid = grid * np.transpose(values, at).reshape(shape)
    for v in reversed(order):
        if tags[v] != "free":
            grid = _REDUCE[tags[v]](grid, axis=names.index(v), keepdims=True)
    return grid


def random_factors(edges, size: int, rng: np.random.Generator, ones: bool) -> list[tuple[tuple, np.ndarray]]:
    made = []
    for e in edges:
        variables = tuple(sorted(e, key=str))
        made.append((variables, rng.integers(0, 2 if ones else 4, (size,) * len(variables)) * (rng.random((size,) * len(variables)) < 0.8)))
    return made


def witness(edges, order: tuple, other: tuple, tags: dict, ones: bool = False, trials: int = 60, size: int = 2, seed: int = 0):
    """An input on which two orders differ, as (factors, value, other value); None if none of the trials shows one."""
    rng = np.random.default_rng(seed)
    for _ in range(trials):
        factors = random_factors(edges, size, rng, ones)
        a, b = evaluated(factors, order, tags, size), evaluated(factors, other, tags, size)
        if not np.array_equal(a, b):
            return factors, a, b
    return None


def safe_by_definition(edges, order: tuple, tags: dict, **options) -> set[tuple]:
    """All orders, free variables first, that no trial tells from the given one."""
    return {p for p in permutations(order) if all(tags[v] != "free" for v in p[sum(t == "free" for t in tags.values()) :]) and witness(edges, order, p, tags, **options) is None}


def relation(outer: str, inner: str, values=(0, 1, 2), size: int = 2, matrices=None) -> str:
    """'identical' aggregates are one; 'commuting' ones may change places on every matrix (of ``matrices``, if given); all others are 'different'."""
    if outer == inner:
        return "identical"
    for cells in product(values, repeat=size * size) if matrices is None else matrices:
        m = np.array(cells).reshape(size, size)
        if _REDUCE[outer](_REDUCE[inner](m, axis=1)) != _REDUCE[inner](_REDUCE[outer](m, axis=0)):
            return "different"
    return "commuting"
