"""More workloads: other joins, factor oracles, dependencies, heuristics, transforms, export baselines."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F

from mixagg.functions.algebra import BOOL, COUNT, SIGNED_EXACT
from mixagg.model import Domain, Factor, FactorQuery
from mixagg.operators import cnf, evaluate, fourier, multijoin, represent
from mixagg.plans import ordering, widths
from mixagg.plans.widths import Edge
from mixagg.sources.tables import table
from mixagg.workloads import _SPO, ORACLES, line, pairs, spo, workload
from mixagg.workloads_shapes import measured, read_shapes, shapes_sql
from mixagg.workloads_plans import _DFT, _GRAPHS, _formulas, values


@workload(_SPO)
def triangle_spo_hypercube(spark, d):
    """The triangle in one round over 3 x 3 x 3 cells."""
    q = spo(spark, d)
    return multijoin.join(list(q.factors), "hypercube").agg(F.count("*").alias("val"))


@workload("SELECT o_custkey AS c, MIN(o_orderkey)::BIGINT AS next FROM orders WHERE o_orderkey >= 1000 GROUP BY 1 UNION ALL SELECT c_custkey, NULL FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_orderkey >= 1000)")
def factor_next(spark, d):
    """A factor's next value: each customer's first order from 1000 on."""
    f = pairs(table(spark, d, "orders"), c="o_custkey", o="o_orderkey")
    return f.next_value(table(spark, d, "customer").select(F.col("c_custkey").alias("c"), F.lit(1000).alias("least")), "o", "least").select("c", "next")


@workload("SELECT c_custkey AS c, 7::BIGINT AS o, CASE WHEN EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderkey = 7) THEN 1 ELSE 0 END::BIGINT AS val FROM customer")
def factor_value(spark, d):
    """A factor's value at given points."""
    f = pairs(table(spark, d, "orders"), c="o_custkey", o="o_orderkey")
    return f.value_at(table(spark, d, "customer").select(F.col("c_custkey").alias("c"), F.lit(7).cast("long").alias("o")), COUNT)


@workload("""SELECT c, CAST(ROUND(EXP(SUM(LN(k)))) AS BIGINT) AS val FROM (SELECT o_custkey AS c, o_orderpriority, COUNT(*) AS k FROM orders GROUP BY 1, 2)
GROUP BY 1 HAVING COUNT(*) = (SELECT COUNT(DISTINCT o_orderpriority) FROM orders)""")
def product_marginal(spark, d):
    """A factor's product over one variable's whole domain: zero where a value is missing."""
    o = table(spark, d, "orders")
    f = Factor.build(o, COUNT, {"c": "o_custkey", "pri": "o_orderpriority"}, F.lit(1), "sum")
    return f.product_marginal("pri", Domain.column(o, "o_orderpriority", "pri"), COUNT).df


@workload("SELECT o_orderpriority AS pri, 3 * COUNT(*)::BIGINT AS val FROM orders GROUP BY 1")
def uncovered_variable(spark, d):
    """A variable in no factor counts its whole domain."""
    o = table(spark, d, "orders")
    q = FactorQuery(("pri",), (("z", "sum"), ("o", "sum")), (pairs(o, pri="o_orderpriority", o="o_orderkey"),), COUNT, {"z": Domain.range(spark, "z", 3)})
    return evaluate.answer(q)


@workload(shapes_sql(_GRAPHS, values("graph VARCHAR, fill BIGINT, degree BIGINT, sums DOUBLE", [("triangle", 2, 2, 1.5), ("path", 1, 1, 1), ("star", 1, 1, 1), ("cycle4", 2, 2, 2), ("cycle5", 2, 2, 2), ("clique4", 3, 3, 2), ("clique5", 4, 4, 2.5), ("covered triangle", 2, 2, 1), ("nested", 2, 2, 1)]), "graph"))
def plan_heuristics(spark, d):
    """Tree widths of two heuristic orders, and the best order's width with sums alone, which is the fractional width."""
    def measure(name, edges):
        e = [Edge(x) for x in edges]
        by = [int(widths.induced_width(e, widths.heuristic_order(e, rule), lambda _, b: len(b) - 1)) for rule in ("fill", "degree")]
        names = tuple(sorted(Edge().union(*e)))
        t = ordering.Theory(names, tuple(e), dict.fromkeys(names, "sum"), "semiring")
        return [(name, *by, float(t.width(t.best())))]

    return measured(read_shapes(spark, d, _GRAPHS), measure, "graph string, fill long, degree long, sums double")


_DEPENDENT = {"triangle, a fixes b": "ab bc ca a>b", "path, b fixes c": "ab bc b>c", "cycle4, a fixes b and c fixes d": "ab bc cd da a>b c>d"}


@workload(shapes_sql(_DEPENDENT, values("case_name VARCHAR, free_bound DOUBLE, bound DOUBLE", [("triangle, a fixes b", 1.5, 1), ("path, b fixes c", 2, 1), ("cycle4, a fixes b and c fixes d", 2, 2)]), "case_name"))
def plan_dependencies(spark, d):
    """Covers without and with functional dependencies."""
    def measure(name, read):
        e, fds = [Edge(x) for x in read if ">" not in x], [x.split(">") for x in read if ">" in x]
        bag = Edge().union(*e)
        return [(name, float(widths.rho(e, bag)), float(widths.rho(widths.with_dependencies(e, [(frozenset(x), y) for x, y in fds]), bag)))]

    return measured(read_shapes(spark, d, _DEPENDENT), measure, "case_name string, free_bound double, bound double")


_CENTRES = {"three arms": "ax bx cx", "path, ends free": "ax xy yb", "all free": "ab bc", "two centres": "ax bx cy dy"}
_FREE = {"three arms": "abc", "path, ends free": "ab", "all free": "abc", "two centres": "abcd"}


@workload(shapes_sql(_CENTRES, values("case_name VARCHAR, star BIGINT", [("three arms", 3), ("path, ends free", 2), ("all free", 0), ("two centres", 2)]), "case_name"))
def plan_star_sizes(spark, d):
    """The measure that bounds counting of conjunctive queries."""
    return measured(read_shapes(spark, d, _CENTRES), lambda name, edges: [(name, widths.star_size([Edge(x) for x in edges], _FREE[name]))], "case_name string, star long")


@workload("""SELECT formula, COUNT(DISTINCT k * 1000000000 + bits)::BIGINT AS clauses, FALSE AS grows FROM (
SELECT p_brand || '/' || CAST(p_size % 5 AS VARCHAR) AS formula, 2 + p_partkey % 7 AS k, (p_partkey // 7) & ((1 << CAST(2 + p_partkey % 7 AS INT)) - 1) AS bits FROM part) GROUP BY 1""")
def clause_counts(spark, d):
    """Clauses of each formula, and whether elimination along a nested order ever has more."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        clauses, sizes = {cnf.Clause(int(x) for x in lits) for lits in pdf["lits"]}, []
        cnf.satisfiable(clauses, widths.nested_order([Edge(map(abs, c)) for c in clauses]), sizes)
        return pd.DataFrame({"formula": [pdf["formula"].iloc[0]], "clauses": [len(clauses)], "grows": [max(sizes) > len(clauses)]})

    return _formulas(spark, d).groupBy("formula").applyInPandas(run, "formula string, clauses long, grows boolean")


@workload("SELECT c_nationkey AS n, SUM(CAST(ROUND(o_totalprice) AS BIGINT))::BIGINT AS val FROM customer JOIN orders ON o_custkey = c_custkey GROUP BY 1 HAVING SUM(CAST(ROUND(o_totalprice) AS BIGINT)) <> 0")
def structured_matvec(spark, d):
    """A product of sparse matrices times a vector."""
    o = table(spark, d, "orders")
    matrices = [pairs(table(spark, d, "customer"), SIGNED_EXACT, n="c_nationkey", c="c_custkey"), pairs(o, SIGNED_EXACT, c="o_custkey", o="o_orderkey")]
    return evaluate.answer(represent.structured_product(matrices, pairs(o, SIGNED_EXACT, F.round("o_totalprice").cast("long"), o="o_orderkey"), SIGNED_EXACT))


@workload(_DFT)
def dft_butterfly(spark, d):
    """The written-out butterfly, 4**3."""
    vec = table(spark, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("n", "re")).withColumn("im", F.lit(0.0))
    rounded = lambda c: (F.round(c, 3) + F.lit(0.0)).alias(c)
    return fourier.butterfly(vec, 4, 3, key="vec_id").select("vec_id", "x", rounded("re"), rounded("im"))


@workload(ORACLES["gram_lineitem"])
def gram_lineitem_export(spark, d):
    """The export baseline: the whole join is written, then its moments are taken."""
    j = line(spark, d).join(table(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(table(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    x = evaluate.kept(j.select(F.col("l_quantity").cast("long").alias("q"), F.floor(F.col("o_totalprice") / 1000).alias("t"), F.floor(F.col("c_acctbal") / 100).alias("a")))
    s = lambda c, name: F.sum(c).cast("long").alias(name)
    q, t, a = F.col("q"), F.col("t"), F.col("a")
    return x.agg(F.count("*").alias("n"), s(q, "s_q"), s(t, "s_t"), s(a, "s_a"), s(q * q, "qq"), s(q * t, "qt"), s(q * a, "qa"), s(t * t, "tt"), s(t * a, "ta"), s(a * a, "aa"))


@workload("SELECT n_regionkey AS r, n_nationkey AS n, c_custkey AS c FROM nation JOIN customer ON c_nationkey = n_nationkey WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def enumerated_output(spark, d):
    """The listing in the order of its variables."""
    q = FactorQuery(("r", "n", "c"), (("o", "or"),), (pairs(table(spark, d, "nation"), BOOL, r="n_regionkey", n="n_nationkey"), pairs(table(spark, d, "customer"), BOOL, n="c_nationkey", c="c_custkey"), pairs(table(spark, d, "orders"), BOOL, c="o_custkey", o="o_orderkey")), BOOL)
    return evaluate.eliminate(q, order="given").enumerated().drop("val")
