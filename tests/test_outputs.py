"""Box joins, clause joins, moments, compositions and output forms against brute force."""

import random
from itertools import product

import numpy as np
import pytest
from pyspark.sql import functions as F

from mixagg.functions.algebra import COUNT
from mixagg.model import Factor, FactorQuery
from mixagg.operators import boxes, cnf, evaluate, learn, multijoin
from mixagg.plans import compose, widths
from mixagg.plans.widths import Edge


@pytest.mark.parametrize("parts", [1, 3])
def test_uncovered_points_of_three_variables(spark, parts):
    rng = random.Random(parts)
    grid = {"x": (0, 6), "y": (-2, 4), "z": (1, 5)}
    made = []
    for _ in range(12):
        row = []
        for low, high in grid.values():
            a, b = sorted((rng.randint(low, high), rng.randint(low, high)))
            row += [low, high] if rng.random() < 0.3 else [a, b]
        made.append(tuple(row))
    fields = ", ".join(f"{s}_{v} long" for v in grid for s in ("lo", "hi"))
    cells = boxes.uncovered(spark.createDataFrame(made, fields), grid, parts)
    got = [tuple(r) for r in boxes.points(cells, grid).collect()]
    want = {p for p in product(*(range(a, b + 1) for a, b in grid.values())) if not any(all(r[2 * i] <= c <= r[2 * i + 1] for i, c in enumerate(p)) for r in made)}
    assert len(got) == len(set(got)) and set(got) == want
    assert boxes.uncovered(spark.createDataFrame([], fields), grid, parts).count() >= 1  # without boxes all is uncovered


def test_join_by_gap_boxes(spark):
    rng = random.Random(5)
    sides = [{(rng.randint(0, 7), rng.randint(0, 7)) for _ in range(n)} for n in (20, 20, 0)]
    made = lambda s, u, v: Factor((u, v), spark.createDataFrame([(*r, 1) for r in s], f"{u} int, {v} int, val long"))
    grid = dict.fromkeys("abc", (0, 7))
    got = {tuple(r) for r in boxes.cover_join([made(sides[0], "a", "b"), made(sides[1], "b", "c")], grid, 3).select("a", "b", "c").collect()}
    assert got == {(a, b, c) for a, b in sides[0] for x, c in sides[1] if x == b}
    assert boxes.cover_join([made(sides[0], "a", "b"), made(sides[2], "b", "c")], grid, 3).count() == 0


def test_clause_joins_equal_resolution(spark):
    rng = random.Random(3)
    formulas = {f"f{i}": [[v * rng.choice((1, -1)) for v in rng.sample(range(1, 6), rng.randint(1, 3))] for _ in range(rng.randint(1, 14))] for i in range(30)}
    formulas |= {"empty clause": [[]], "tautology": [[1, -1]], "repeated literal": [[2, 2], [-2]]}
    rows = spark.createDataFrame([(f, c) for f, cs in formulas.items() for c in cs], "formula string, lits array<int>")
    got = dict(tuple(r) for r in cnf.satisfiable_by_joins(rows, range(1, 6)).collect())

    def brute(clauses):
        return any(all(any((bits[abs(x) - 1] == 1) == (x > 0) for x in c) for c in clauses) for bits in product((0, 1), repeat=5))

    assert got == {f: brute(cs) for f, cs in formulas.items()} and set(got.values()) == {True, False}


def test_joined_moments(spark):
    rng = np.random.default_rng(0)
    r = spark.createDataFrame([(int(a), int(x)) for a, x in rng.integers(-3, 4, (40, 2))], "a long, x long")
    s = spark.createDataFrame([(int(a), int(b), int(y)) for a, b, y in rng.integers(-3, 4, (30, 3))], "a long, b long, y long")
    t = spark.createDataFrame([(int(b), None if i == 0 else int(z)) for i, (b, z) in enumerate(rng.integers(-3, 4, (20, 2)))], "b long, z long")
    atoms = lambda t: [(r, {"a": "a"}, {"x": F.col("x")}), (s, {"a": "a", "b": "b"}, {"y": F.col("y")}), (t, {"b": "b"}, {"z": F.col("z")})]
    joined = r.join(s, "a").join(t.dropna(), "b")
    want = learn.moments(joined, ["x", "y", "z"])
    got = learn.joined_moments(atoms(t))
    assert got.columns == want.columns and tuple(got.first()) == tuple(want.first())
    assert set(learn.joined_moments(atoms(t.where("false"))).first()) == {0}  # a join without rows


def test_composed_decomposition_on_random_hypergraphs():
    rng = random.Random(1)
    for _ in range(15):
        outer = {Edge(rng.sample("abcdef", rng.randint(2, 3))) for _ in range(3)}
        inner = {o: [Edge(p) for p in zip(sorted(o), sorted(o)[1:])] for o in outer}
        edges = compose.composed_edges(inner)
        tree, _ = compose.composed_tree(inner)
        width = widths.fractional_hypertree_width(edges)
        assert compose.is_decomposition(edges, tree)
        assert width <= compose.product_bound(inner) and width <= compose.tree_width(edges, tree[0]) <= compose.additive_bound(inner)
    with pytest.raises(ValueError):
        compose.composed_edges({Edge("abc"): [Edge("ab")]})


def test_calibrated_bags_of_a_cycle(spark):
    rng = random.Random(2)
    rows = [{(rng.randint(0, 3), rng.randint(0, 3)): rng.randint(1, 5) for _ in range(9)} for _ in range(4)]
    names = ["ab", "bc", "cd", "da"]
    factors = tuple(Factor(tuple(n), spark.createDataFrame([(*k, v) for k, v in r.items()], f"{n[0]} int, {n[1]} int, val long")) for n, r in zip(names, rows))
    q = FactorQuery((), tuple((v, "sum") for v in "abcd"), factors, COUNT)
    for bag in evaluate.calibrate(q, "sum"):
        got = {tuple(r)[:-1]: r["val"] for r in bag.df.select(*bag.vars, "val").collect() if r["val"]}
        want = {}
        for p in product(range(4), repeat=4):
            at = dict(zip("abcd", p))
            w = 1
            for n, r in zip(names, rows):
                w *= r.get((at[n[0]], at[n[1]]), 0)
            if w:
                key = tuple(at[v] for v in bag.vars)
                want[key] = want.get(key, 0) + w
        assert got == want


def test_binary_joins_unless_the_first_makes_too_much(spark):
    chain = [Factor(tuple(n), spark.createDataFrame([(1, 1, 1)], f"{n[0]} int, {n[1]} int, val long")) for n in ("ab", "bc")]
    assert multijoin.choose(chain) == "binary"
    empty = [Factor(tuple(n), spark.createDataFrame([], f"{n[0]} int, {n[1]} int, val long")) for n in ("ab", "bc", "ca")]
    assert multijoin.choose(empty) == "binary" and multijoin.join(empty, "auto").count() == 0


def test_ties_of_the_host_cost_go_to_the_smallest_first_join(spark):
    from mixagg.plans import cost
    from mixagg.workloads import spo

    q = spo(spark, "/root/testdata/sf0.001")
    assert cost.host_order(q, lambda o: evaluate.answer(q, order=o, indicators=False))[-1] == "o"
