"""Other input forms, order joins and fitting, against SQL and brute force."""

import random

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from mixagg import workloads_extra
from mixagg.functions.algebra import COUNT, SIGNED_EXACT
from mixagg.model import Factor
from mixagg.operators import evaluate, learn, relational, represent
from mixagg.workloads import ORACLES

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["sum_of_terms", "decision_diagram", "range_join_bands", "latest_view_before_purchase", "fit_quantity"])
def test_workload_equals_sql(spark, name):
    con = duckdb.connect()
    for t in ("part", "lineitem", "nation", "events", "orders", "customer"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    got = getattr(workloads_extra, name)(spark, SF)
    want = con.execute(ORACLES[name])
    columns = [c[0] for c in want.description]
    key = lambda r: tuple((x is None, x) for x in r)
    assert sorted((tuple(r) for r in got.select(*columns).collect()), key=key) == sorted(want.fetchall(), key=key)


def test_latest_before_takes_nulls_and_ties(spark):
    r = random.Random(4)
    some = lambda top: None if r.random() < 0.1 else r.randrange(top)
    left = [(i, some(4), some(60)) for i in range(120)]
    right = [(some(4), some(60), i) for i in range(80)] + [(1, 7, 500), (1, 7, 501)]
    got = relational.latest_before(spark.createDataFrame(left, "id long, k long, at long"), spark.createDataFrame(right, "k long, at long, other long"), "k", "at", "at", ["other"], F.floor(F.col("__at") / 10))
    want = {}
    for i, k, at in left:
        fits = [(t, o) for k2, t, o in right if None not in (k, at, k2, t) and k2 == k and t <= at]
        want[i] = max(fits)[1] if fits else None
    assert {x.id: x.other for x in got.collect()} == want


def test_range_join_finds_each_pair_once(spark):
    points = [(i, x) for i, x in enumerate([0.0, 4.9, 5.0, 5.1, 10.0, -3.0, None])]
    spans = [(0, 0.0, 5.0), (1, 5.0, 10.0), (2, -9.0, 99.0), (3, 6.0, 1.0), (4, None, 5.0)]
    got = relational.range_join(spark.createDataFrame(points, "p long, x double"), spark.createDataFrame(spans, "s long, lo double, hi double"), "x", "lo", "hi", 5.0)
    want = sorted((p, s) for p, x in points for s, lo, hi in spans if None not in (x, lo, hi) and lo <= x <= hi)
    assert sorted((r.p, r.s) for r in got.select("p", "s").collect()) == want


def test_structured_product_equals_dense(spark):
    r = np.random.default_rng(5)
    a, b, x = r.integers(-2, 3, (4, 5)), r.integers(-2, 3, (5, 3)), r.integers(-2, 3, 3)
    rows = lambda m: [(*map(int, at), int(m[at])) for at in np.ndindex(m.shape) if m[at]]
    factor = lambda m, *v: Factor(v, spark.createDataFrame(rows(m), ", ".join([*(f"{n} int" for n in v), "val long"])))
    q = represent.structured_product([factor(a, "i", "j"), factor(b, "j", "k")], factor(x, "k"), SIGNED_EXACT)
    assert {(t.i, t.val) for t in evaluate.answer(q).collect()} == {(i, int(v)) for i, v in enumerate(a @ b @ x) if v}


def test_terms_can_share_variables(spark):
    f = Factor(("t", "x"), spark.createDataFrame([(0, 1, 2), (0, 2, 3), (1, 1, 5)], "t int, x int, val long"))
    g = Factor(("t", "x", "y"), spark.createDataFrame([(0, 1, 0, 7), (1, 1, 0, 1), (1, 2, 1, 4)], "t int, x int, y int, val long"))
    assert {tuple(r) for r in evaluate.answer(represent.terms([f, g], "t", COUNT, "sum")).collect()} == {(1, 0, 2 * 7 + 5 * 1)}


def test_regression_equals_least_squares(spark):
    r = np.random.default_rng(6)
    x = r.normal(size=(50, 2))
    y = 3 + x @ [2.0, -1.0] + r.normal(size=50) / 10
    m = learn.moments(spark.createDataFrame([(float(a), float(b), float(c)) for (a, b), c in zip(x, y)], "a double, b double, y double"), ["a", "b", "y"]).first().asDict()
    second = {(u, v): m[f"xx_{u}_{v}"] for i, u in enumerate("aby") for v in "aby"[i:]}
    fit = learn.linear_regression(m["n"], {c: m[f"s_{c}"] for c in "aby"}, second, ["a", "b"], "y")
    want = np.linalg.lstsq(np.c_[np.ones(50), x], y, rcond=None)[0]
    assert np.allclose([fit["1"], fit["a"], fit["b"]], want)
