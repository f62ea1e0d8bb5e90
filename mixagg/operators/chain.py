"""Matrix chains: the textbook parenthesisation as an elimination order, and left to right for comparison."""

from __future__ import annotations

from mixagg.functions.algebra import SIGNED_EXACT, Algebra
from mixagg.model import Factor, FactorQuery
from mixagg.operators.evaluate import answer


def dp_order(dims: list[int]) -> tuple[int, list[int]]:
    """Least cost of multiplying matrices of these dimensions, and the inner indices in order of elimination."""
    n = len(dims) - 1
    best: dict[tuple[int, int], tuple[int, int]] = {(i, i + 1): (0, -1) for i in range(n)}
    for span in range(2, n + 1):
        for a in range(n - span + 1):
            b = a + span
            best[a, b] = min((best[a, k][0] + best[k, b][0] + dims[a] * dims[k] * dims[b], k) for k in range(a + 1, b))

    def inner(a: int, b: int) -> list[int]:
        k = best[a, b][1]
        return [] if k < 0 else [*inner(a, k), *inner(k, b), k]

    return best[0, n][0], inner(0, n)


def multiply(matrices: list[Factor], dims: list[int], algebra: Algebra = SIGNED_EXACT, how: str = "dp"):
    """The product of matrices given as two-variable factors whose neighbours share a variable."""
    names = [matrices[0].vars[0], *(m.vars[1] for m in matrices)]
    first = dp_order(dims)[1] if how == "dp" else list(range(1, len(dims) - 1))
    bound = tuple((names[i], "sum") for i in reversed(first))
    q = FactorQuery((names[0], names[-1]), bound, tuple(matrices), algebra)
    return answer(q, order="given", indicators=False)
