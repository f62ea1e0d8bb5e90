"""Value domains: one product and several sums that share its zero and one.

Every operation is a Spark Column expression or aggregate, so steps stay inside whole-stage code generation.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Algebra:
    """``plus`` maps a sum's name to its aggregate; ``idempotent`` tells per value whether v * v = v."""

    name: str
    dtype: str
    one: Callable[[], Column]
    zero: Callable[[], Column]
    times: Callable[[Column, Column], Column]
    plus: dict[str, Callable[[Column], Column]]
    idempotent: Callable[[Column], Column]
    product: Callable[[Column], Column]  # aggregate by the product
    non_negative: bool = False

    def nonzero(self, v: Column) -> Column:
        return v != self.zero()

    def fold(self, values: list[Column]) -> Column:
        out = self.one()
        for i, v in enumerate(values):
            out = v if i == 0 else self.times(out, v)
        return out

    def power(self, v: Column, d: int) -> Column:
        """v ** d by repeated squaring: about 2 log2 d multiplications, as one expression."""
        if d == 1:
            return v
        half = self.power(v, d // 2)
        square = self.times(half, half)
        return self.times(square, v) if d % 2 else square

    def powered(self, v: Column, d: int) -> Column:
        """As ``power``, with idempotent values passed through."""
        return F.when(self.idempotent(v), v).otherwise(self.power(v, d))


def _lit(value, dtype):
    return lambda: F.lit(value).cast(dtype)


def _exact_product(v: Column) -> Column:
    # groups are bounded by the variable's domain
    return F.aggregate(F.collect_list(v), F.lit(1).cast("long"), lambda a, b: a * b)


def _numeric(name, dtype, sums, product, non_negative):
    return Algebra(name, dtype, _lit(1, dtype), _lit(0, dtype), lambda a, b: a * b, sums, lambda v: (v == 0) | (v == 1), product, non_negative)


COUNT = _numeric("count", "bigint", {"sum": F.sum, "max": F.max}, _exact_product, True)
REAL = _numeric("real", "double", {"sum": F.sum, "max": F.max}, F.product, True)
SIGNED = _numeric("signed", "double", {"sum": F.sum}, F.product, False)
SIGNED_EXACT = _numeric("signed exact", "bigint", {"sum": F.sum}, _exact_product, False)
BOOL = Algebra("bool", "boolean", _lit(True, "boolean"), _lit(False, "boolean"), lambda a, b: a & b, {"or": F.bool_or, "max": F.bool_or}, lambda v: F.lit(True), F.bool_and)


def _pair(re: Column, im: Column) -> Column:
    return F.struct(re.alias("re"), im.alias("im"))


COMPLEX = Algebra(
    "complex", "struct<re:double,im:double>", lambda: _pair(F.lit(1.0), F.lit(0.0)), lambda: _pair(F.lit(0.0), F.lit(0.0)),
    lambda a, b: _pair(a["re"] * b["re"] - a["im"] * b["im"], a["re"] * b["im"] + a["im"] * b["re"]),
    {"sum": lambda v: _pair(F.sum(v["re"]), F.sum(v["im"]))},
    lambda v: (v["im"] == 0) & ((v["re"] == 0) | (v["re"] == 1)),
    lambda v: F.aggregate(F.collect_list(v), _pair(F.lit(1.0), F.lit(0.0)), lambda a, b: _pair(a["re"] * b["re"] - a["im"] * b["im"], a["re"] * b["im"] + a["im"] * b["re"])),
)
MIN_PLUS = Algebra("min-plus", "double", _lit(0.0, "double"), _lit(float("inf"), "double"), lambda a, b: a + b, {"min": F.min}, lambda v: (v == 0) | (v == float("inf")), F.sum)
MAX_PLUS = Algebra("max-plus", "double", _lit(0.0, "double"), _lit(float("-inf"), "double"), lambda a, b: a + b, {"max": F.max}, lambda v: (v == 0) | (v == float("-inf")), F.sum)


def sets(universe: list) -> Algebra:
    """Subsets of a finite universe: intersection as product, union as sum."""
    full = lambda: F.array(*[F.lit(x) for x in universe])
    return Algebra(
        "sets", "array", full, lambda: F.slice(full(), 1, 0), lambda a, b: F.array_intersect(a, b),
        {"union": lambda v: F.sort_array(F.array_distinct(F.flatten(F.collect_set(v))))}, lambda v: F.lit(True),
        lambda v: F.aggregate(F.collect_list(v), full(), lambda a, b: F.array_intersect(a, b)),
    )


def moments(features: list[str]) -> Algebra:
    """Counts, sums and second moments of some features, as one value: n, s_x, xx_x_y.

    The product is that of independent parts of a row, so moments of a join are a sum of products over its factors.
    """
    pairs = [(a, b) for i, a in enumerate(features) for b in features[i:]]
    names = ["n", *(f"s_{a}" for a in features), *(f"xx_{a}_{b}" for a, b in pairs)]

    def made(n: Column, s: dict, xx: dict) -> Column:
        return F.struct(n.alias("n"), *[s[a].alias(f"s_{a}") for a in features], *[xx[p].alias(f"xx_{p[0]}_{p[1]}") for p in pairs])

    def only(n: int):
        zero = F.lit(0).cast("long")
        return lambda: made(F.lit(n).cast("long"), dict.fromkeys(features, zero), dict.fromkeys(pairs, zero))

    def times(u: Column, v: Column) -> Column:
        s = {a: u["n"] * v[f"s_{a}"] + v["n"] * u[f"s_{a}"] for a in features}
        both = lambda a, b: u["n"] * v[f"xx_{a}_{b}"] + v["n"] * u[f"xx_{a}_{b}"] + u[f"s_{a}"] * v[f"s_{b}"] + v[f"s_{a}"] * u[f"s_{b}"]
        return made(u["n"] * v["n"], s, {p: both(*p) for p in pairs})

    total = lambda v: F.when(F.count(v) > 0, F.struct(*[F.sum(v[x]).alias(x) for x in names]))
    return Algebra("moments", f"struct<{','.join(f'{x}:bigint' for x in names)}>", only(1), only(0), times, {"sum": total}, lambda v: F.lit(False), lambda v: F.aggregate(F.collect_list(v), only(1)(), times))
