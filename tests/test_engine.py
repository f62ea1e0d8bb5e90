"""Evaluation against the defining expression on small random factors, and the operators around it."""

import random
from itertools import product as cross

import numpy as np
import pytest
from pyspark.sql import functions as F

from mixagg.functions import algebra as A
from mixagg.model import PRODUCT, Domain, Factor, FactorQuery
from mixagg.operators import baselines, boxes, cnf, evaluate, fourier
from mixagg.streaming import maintain


def random_query(spark, free, bound, edges, ones=False, seed=0):
    r = random.Random(seed)
    data, factors = {}, []
    for e in edges:
        rows = {p: (1 if ones else r.randrange(1, 4)) for p in cross(range(2), repeat=len(e)) if r.random() < 0.75}
        data[e] = rows
        schema = ", ".join(f"{v} int" for v in e) + ", val long"
        factors.append(Factor(tuple(e), spark.createDataFrame([(*k, v) for k, v in rows.items()], schema)))
    names = [*free, *(v for v, _ in bound)]
    return FactorQuery(tuple(free), tuple(bound), tuple(factors), A.COUNT, {v: Domain.range(spark, v, 2) for v in names}), data


def defined(free, bound, data):
    ops = {"sum": sum, "max": max, PRODUCT: lambda x: int(np.prod(list(x)))}

    def go(point, rest):
        if not rest:
            out = 1
            for e, rows in data.items():
                out *= rows.get(tuple(point[v] for v in e), 0)
            return out
        v, agg = rest[0]
        return ops[agg]([go({**point, v: x}, rest[1:]) for x in range(2)])

    out = {p: go(dict(zip(free, p)), list(bound)) for p in cross(range(2), repeat=len(free))}
    return {p: v for p, v in out.items() if v or not free}


def rows(df, names):
    return {tuple(r[v] for v in names): r["val"] for r in df.collect()}


CASES = [
    ("", [("a", "sum"), ("b", "max"), ("c", "sum")], ["ab", "ac"], False),
    ("a", [("b", "sum"), ("c", "max")], ["ab", "bc", "ca"], False),
    ("ab", [("c", PRODUCT), ("d", "sum")], ["ac", "bd", "cd"], False),
    ("", [("a", "max"), ("b", PRODUCT), ("c", "sum"), ("d", "max")], ["abc", "bd", "ad"], False),
    ("a", [("b", "max"), ("c", PRODUCT), ("d", "max")], ["abc", "cd", "ad"], True),
    ("ab", [], ["a", "b"], False),
    ("", [("a", "sum"), ("b", PRODUCT)], ["a"], False),
]


@pytest.mark.parametrize("case", range(len(CASES)))
def test_elimination_equals_the_definition(spark, case):
    free, bound, edges, ones = CASES[case]
    for seed in range(2):
        q, data = random_query(spark, free, bound, edges, ones, seed)
        want = defined(free, bound, data)
        assert rows(evaluate.answer(q, order="given"), free) == want
        assert rows(evaluate.answer(q, idempotent_inputs=ones), free) == want
        assert rows(baselines.without_indicators(q), free) == want
        if not any(a == PRODUCT for _, a in bound):
            assert rows(evaluate.search(q), free) == want
            assert rows(evaluate.search(q, how="binary"), free) == want


def test_declared_domains_and_bad_queries(spark):
    f = Factor(("a", "b"), spark.createDataFrame([(0, 0, 2), (0, 1, 3), (1, 0, 5)], "a int, b int, val long"))
    two, three = Domain.range(spark, "b", 2), Domain.range(spark, "b", 3)
    assert rows(evaluate.answer(FactorQuery(("a",), (("b", PRODUCT),), (f,), A.COUNT, {"b": two})), "a") == {(0,): 6}
    assert rows(evaluate.answer(FactorQuery(("a",), (("b", PRODUCT),), (f,), A.COUNT, {"b": three})), "a") == {}
    with pytest.raises(ValueError):
        FactorQuery(("a",), (("b", PRODUCT),), (f,), A.COUNT)
    with pytest.raises(ValueError):
        FactorQuery(("a",), (("b", "min"),), (f,), A.COUNT)
    q = FactorQuery((), (("a", "sum"), ("b", "max")), (f,), A.COUNT)
    with pytest.raises(ValueError):
        evaluate.answer(q, order=("b", "a"))
    empty = Factor(("a", "b"), f.df.limit(0))
    assert rows(evaluate.answer(FactorQuery((), (("a", "sum"), ("b", "max")), (empty,), A.COUNT)), "") == {(): 0}
    bad = FactorQuery((), (("a", "max"), ("b", "max")), (Factor(("a", "b"), f.df.withColumn("val", -F.col("val"))),), A.COUNT)
    with pytest.raises(ValueError):
        bad.check_values()
    parsed = FactorQuery.parse("free a; exists b : R(a, b)", {"R": f.df}, A.COUNT)
    assert rows(evaluate.answer(parsed), "a") == {(0,): 3, (1,): 5}


def test_other_algebras(spark):
    e = spark.createDataFrame([(0, 1, 1.0), (1, 2, 2.0), (0, 2, 9.0)], "a int, b int, val double")
    q = FactorQuery((), (("a", "min"), ("b", "min"), ("c", "min")), (Factor(("a", "b"), e), Factor(("b", "c"), e.toDF("b", "c", "val"))), A.MIN_PLUS)
    assert evaluate.answer(q).first().val == 3.0
    s = A.sets([1, 2, 3])
    f = Factor(("a",), spark.createDataFrame([(0, [1, 2]), (1, [3])], "a int, val array<int>"))
    g = Factor(("a",), spark.createDataFrame([(0, [2, 3]), (1, [3, 1])], "a int, val array<int>"))
    assert evaluate.answer(FactorQuery((), (("a", "union"),), (f, g), s)).first().val == [2, 3]
    v = spark.range(1).select((A.COUNT.power(F.lit(3).cast("long"), 13)).alias("p")).first().p
    assert v == 3**13


def test_fourier_matches_numpy(spark):
    x = np.random.default_rng(0).standard_normal(64) + 1j * np.random.default_rng(1).standard_normal(64)
    vec = spark.createDataFrame([(i, float(v.real), float(v.imag)) for i, v in enumerate(x)], "n int, re double, im double")
    want = np.fft.ifft(x) * 64
    for p, m in ((2, 6), (4, 3)):
        got = {r.x: complex(r.re, r.im) for r in fourier.dft(vec, p, m).collect()}
        assert all(abs(got[k] - want[k]) < 1e-9 for k in range(64))
    got = {r.x: complex(r.re, r.im) for r in fourier.dft_quadratic(vec, 64).collect()}
    assert all(abs(got[k] - want[k]) < 1e-9 for k in range(64))


def test_weighted_counts_match_truth_tables():
    from fractions import Fraction

    r = random.Random(3)
    for _ in range(200):
        n = r.randrange(1, 7)
        clauses = {}
        for _ in range(r.randrange(0, 9)):
            k = r.randrange(1, n + 1)
            clauses[cnf.Clause(v if r.random() < 0.5 else -v for v in range(1, k + 1))] = Fraction(r.randrange(4), 3)
        pairs = list(clauses.items())
        variables = list(range(1, n + 1))
        assert cnf.weighted_count_nested(pairs, variables) == cnf.truth_table(pairs, variables)
        hard = [(c, Fraction(0)) for c in clauses]
        sizes = []
        assert cnf.satisfiable(clauses, variables, sizes) == (cnf.truth_table(hard, variables) > 0)
        assert all(s <= len(clauses) for s in sizes)


def test_box_gaps(spark):
    r = random.Random(1)
    data = [(g, x, min(9, x + r.randrange(6)), y, min(5, y + r.randrange(5))) for g in range(12) for _ in range(8) for x, y in [(r.randrange(10), r.randrange(6))]]
    got = {b.g: (b.x, b.y) for b in boxes.find_gap(spark.createDataFrame(data, "g int, x1 int, x2 int, y1 int, y2 int"), "g", ("x1", "x2"), ("y1", "y2"), (0, 9), (0, 5)).collect()}
    for g in range(12):
        free = [(x, y) for x in range(10) for y in range(6) if not any(d[0] == g and d[1] <= x <= d[2] and d[3] <= y <= d[4] for d in data)]
        assert got.get(g) == (min(free) if free else None)


def test_output_forms_and_calibration(spark):
    q, data = random_query(spark, "abc", [("d", "sum")], ["ab", "bc", "cd"], seed=4)
    want = defined("abc", [("d", "sum")], data)
    result = evaluate.eliminate(q, order="given")
    assert rows(result.listing(), "abc") == want
    a, b, c = result.factorized()
    assert {(r.a, r.b, r.c) for r in a.join(b, "a").join(c, ["b"]).collect()} == set(want)
    points = spark.createDataFrame(list(cross(range(2), repeat=3)), "a int, b int, c int")
    assert {(r.a, r.b, r.c): r.val for r in result.value(points).collect() if r.val} == want
    full = FactorQuery((), tuple((v, "sum") for v in "abcd"), q.factors, A.COUNT)
    total = evaluate.answer(full).first().val
    assert all(f.df.agg(F.sum("val")).first()[0] == total for f in evaluate.calibrate(full, "sum"))


def test_stream_keeps_a_factor(spark, tmp_path):
    src = str(tmp_path / "in")
    for i in range(3):
        spark.createDataFrame([(j % 2, i + j) for j in range(10)], "k int, v int").coalesce(1).write.mode("append").parquet(src)
    stream = spark.readStream.schema("k int, v int").option("maxFilesPerTrigger", 1).parquet(src)
    maintain.maintain(stream, A.COUNT, {"k": "k"}, F.col("v"), "sum", str(tmp_path / "out"), str(tmp_path / "cp")).awaitTermination(60)
    got = maintain.current(spark, str(tmp_path / "out"), A.COUNT, "sum")
    whole = Factor.build(spark.read.parquet(src), A.COUNT, {"k": "k"}, F.col("v"), "sum")
    assert rows(got.df, "k") == rows(whole.df, "k")
