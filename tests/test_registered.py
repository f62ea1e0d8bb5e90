"""Every workload on plans, front ends and baselines against its SQL."""

import math

import duckdb
import pytest

from mixagg import workloads, workloads_more, workloads_outputs, workloads_plans  # noqa: F401
from mixagg.model import Factor, FactorQuery
from mixagg.functions.algebra import COUNT
from mixagg.operators import cnf, evaluate
from mixagg.plans import cost, ordering
from pyspark.errors import PySparkException

SF = "/root/testdata/sf0.001"
NAMES = sorted(n for n, f in workloads.QUERIES.items() if f.__module__ in ("mixagg.workloads_plans", "mixagg.workloads_more", "mixagg.workloads_outputs"))
TABLES = "region nation customer supplier part orders lineitem events embeddings".split()


@pytest.mark.parametrize("name", NAMES)
def test_workload_equals_sql(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    got = workloads.QUERIES[name](spark, SF)
    want = con.execute(workloads.ORACLES[name])
    columns = [c[0] for c in want.description]
    assert sorted(columns) == sorted(got.columns)
    key = lambda r: tuple((x is None, x) for x in r)
    rows, told = sorted((tuple(r) for r in got.select(*columns).collect()), key=key), sorted(want.fetchall(), key=key)
    assert len(rows) == len(told)
    for a, b in zip(rows, told):
        assert all(math.isclose(x, y, abs_tol=1.1e-3) if isinstance(x, float) else x == y for x, y in zip(a, b)), (a, b)


def test_max_refuses_negative_values(spark):
    f = Factor(("a", "b"), spark.createDataFrame([(1, 1, 2), (1, 2, -3)], "a int, b int, val long"))
    with pytest.raises(PySparkException, match="non-negative"):
        evaluate.answer(FactorQuery(("a",), (("b", "max"),), (f,), COUNT)).collect()


def test_costs_of_a_product():
    edges, tags = [frozenset("ab"), frozenset("bc")], {"a": "free", "b": "sum", "c": "product"}
    c = cost.predicted(edges, "abc", tags, [100, 50])
    assert (c.products, c.powers) == (50, 100) and cost.predicted(edges, "abc", tags, [100, 50], idempotent=True).powers == 0
    t = ordering.Theory(tuple("abcd"), (frozenset("ab"), frozenset("bc"), frozenset("cd")), dict.fromkeys("abcd", "sum"), "semiring")
    assert t.is_safe(cost.greedy_order(t, [1000, 10, 10]))


def test_weighted_query_equals_truth_table(spark):
    clauses = [(cnf.Clause(c), 0.25) for c in ({1, -2}, {2, 3}, {-3, 1}, {-1})]
    assert evaluate.answer(cnf.as_query(spark, clauses)).first()[0] == float(cnf.truth_table(clauses, [1, 2, 3]))


def test_wrong_claims_of_idempotent_inputs_fail(spark):
    f = Factor(("a", "b"), spark.createDataFrame([(1, 1, 2), (1, 2, 1)], "a int, b int, val long"))
    from mixagg.model import PRODUCT, Domain

    q = FactorQuery(("a",), (("b", PRODUCT),), (f,), COUNT, {"b": Domain.values(spark, "b", [1, 2], "int")})
    with pytest.raises(PySparkException, match="not idempotent"):
        evaluate.answer(q, idempotent_inputs=True).collect()
    assert [tuple(r) for r in evaluate.answer(q).collect()] == [(1, 2)]


@pytest.mark.parametrize("name", ["plan_aggregate_relations", "plan_composed_widths", "plan_dependencies", "plan_heuristics", "plan_prefix_gap", "plan_safe_by_definition", "plan_safe_orders", "plan_sequences", "plan_star_sizes", "plan_widths"])
def test_shapes_are_read_from_lineitem(spark, name):
    assert any("lineitem" in f for f in workloads.QUERIES[name](spark, SF).inputFiles())


def test_weighted_clauses_are_read_from_lineitem(spark):
    assert {r["formula"] for r in workloads.QUERIES["wcount_general"](spark, SF).where("lines > 0").collect()} == {"cycle", "nested"}
