"""Workloads on outputs, compositions, box joins, moments pushed by the engine, clause joins and the host's cost, with SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from mixagg.functions.algebra import COUNT
from mixagg.model import FactorQuery
from mixagg.operators import baselines, boxes, cnf, evaluate, learn, multijoin
from mixagg.plans import compose, cost, widths
from mixagg.plans.widths import Edge
from mixagg.sources.tables import table
from mixagg.workloads import _CNF, _NATIONS, _SPO, ORACLES, _nation_pairs, line, pairs, spo, workload
from mixagg.workloads_plans import _formulas, values
from mixagg.workloads_shapes import measured, read_shapes, shapes_sql


@workload(ORACLES["gram_lineitem"])
def gram_engine(spark, d):
    """The moments of ``gram_lineitem``, with the pushing below the join planned by the engine."""
    got = learn.joined_moments([
        (line(spark, d), {"o": "l_orderkey"}, {"q": F.col("l_quantity")}),
        (table(spark, d, "orders"), {"o": "o_orderkey", "c": "o_custkey"}, {"t": F.floor(F.col("o_totalprice") / 1000)}),
        (table(spark, d, "customer"), {"c": "c_custkey"}, {"a": F.floor(F.col("c_acctbal") / 100)})])
    return got.withColumnsRenamed({f"xx_{a}_{b}": a + b for a, b in ("qq", "qt", "qa", "tt", "ta", "aa")})


_CYCLE = _NATIONS + ", j AS (SELECT w.a, w.b, x.b AS c, y.b AS d FROM e w JOIN e x ON w.b = x.a JOIN e y ON x.b = y.a JOIN e z ON y.b = z.a AND z.b = w.a) "


@workload(_CYCLE + " UNION ALL ".join(f"SELECT '{v}' AS v, {v}::BIGINT AS k, COUNT(*)::BIGINT AS val FROM j GROUP BY 2" for v in "abcd"))
def calibrate_cycle4(spark, d):
    """Marginals of every variable of a cyclic query, from bags that were calibrated once."""
    e = _nation_pairs(spark, d)
    q = FactorQuery((), tuple((v, "sum") for v in "abcd"), (e("a", "b"), e("b", "c"), e("c", "d"), e("d", "a")), COUNT)
    bags = evaluate.calibrate(q, "sum")
    one = lambda v: next(b for b in bags if v in b.vars).df.groupBy(F.col(v).cast("long").alias("k")).agg(F.sum("val").alias("val")).select(F.lit(v).alias("v"), "k", "val")
    return baselines.union_all([one(v) for v in "abcd"])


@workload(_SPO)
def triangle_spo_auto(spark, d):
    """Binary or stepwise joins, as the sizes tell."""
    return evaluate.answer(spo(spark, d), how="auto")


@workload(_SPO)
def triangle_spo_host_order(spark, d):
    """The order that Spark's own optimizer holds to be the cheapest."""
    q = spo(spark, d)
    return evaluate.answer(q, order=cost.host_order(q, lambda o: evaluate.answer(q, order=o, indicators=False)))


@workload(f"SELECT formula, sat FROM ({_CNF})")
def sat_by_joins(spark, d):
    """Resolution of all formulas at once, as joins of clause tables."""
    return cnf.satisfiable_by_joins(_formulas(spark, d), range(1, 9))


@workload(_NATIONS + "SELECT x.a::BIGINT AS a, x.b::BIGINT AS b, y.b::BIGINT AS c FROM e x JOIN e y ON x.b = y.a JOIN e z ON y.b = z.a AND z.b = x.a")
def box_join_triangle(spark, d):
    """The directed triangles of nations as the points that no gap box covers."""
    e = _nation_pairs(spark, d)
    return boxes.cover_join([e("a", "b"), e("b", "c"), e("c", "a")], dict.fromkeys("abc", (0, 24)), parts=8).select(*"abc")


@workload("""WITH b AS (SELECT l_orderkey % 200 AS g, MIN(l_quantity)::INT x1, MAX(l_quantity)::INT x2, MIN(ROUND(l_discount * 100))::INT y1, MAX(ROUND(l_discount * 100))::INT y2 FROM lineitem GROUP BY l_orderkey HAVING COUNT(*) >= 2)
SELECT g.range::BIGINT AS g, x.range::BIGINT AS x, y.range::BIGINT AS y FROM range(200) g, range(1, 51) x, range(0, 11) y
WHERE NOT EXISTS (SELECT 1 FROM b WHERE b.g = g.range AND x.range BETWEEN x1 AND x2 AND y.range BETWEEN y1 AND y2)""")
def box_uncovered(spark, d):
    """All points that no box covers, of three variables: the group is the first."""
    cents = F.round(F.col("l_discount") * 100)
    g = F.col("l_orderkey") % 200
    b = line(spark, d).groupBy("l_orderkey").agg(*[f(c).cast("long").alias(n) for n, f, c in (("lo_x", F.min, "l_quantity"), ("hi_x", F.max, "l_quantity"), ("lo_y", F.min, cents), ("hi_y", F.max, cents))], F.count("*").alias("k")).where("k >= 2")
    grid = {"g": (0, 199), "x": (1, 50), "y": (0, 10)}
    return boxes.points(boxes.uncovered(b.withColumn("lo_g", g).withColumn("hi_g", g), grid), grid)


@workload("""WITH c AS (SELECT COUNT(*) AS n FROM customer), o AS (SELECT COUNT(DISTINCT o_custkey) AS n FROM orders)
SELECT f AS form, p AS phase, CASE WHEN p = 'values' THEN c.n ELSE o.n END::BIGINT AS rows FROM c, o,
(VALUES ('listing', 'before'), ('listing', 'values'), ('listing', 'reading'), ('query', 'values'), ('query', 'reading'), ('factorized', 'before c'), ('factorized', 'values'), ('factorized', 'reading')) t(f, p)""")
def output_phases(spark, d):
    """The phases of the three output forms and how many rows each makes; their seconds are in ``evaluate.output_times``."""
    c = table(spark, d, "customer").select(F.col("c_custkey").alias("c"))
    q = FactorQuery(("c",), (("o", "sum"),), (pairs(table(spark, d, "orders"), c="o_custkey", o="o_orderkey"),), COUNT)
    return spark.createDataFrame([r[:3] for r in evaluate.output_times(q, c)], "form string, phase string, rows long")


def _stars(n: int) -> dict[Edge, list[Edge]]:
    """n outer edges that share n vertices and have one of their own; in the place of each a star around another vertex."""
    shared = [f"a{i}" for i in range(n)]
    return {Edge([*shared, f"b{i}"]): [Edge({f"a{i}", x}) for x in (*shared, f"b{i}") if x != f"a{i}"] for i in range(n)}


_STAR_SHAPES = {str(n): " ".join(f"{i}:{'.'.join(sorted(x))}" for i, xs in enumerate(_stars(n).values()) for x in xs) for n in (2, 3, 4)}


@workload(shapes_sql(_STAR_SHAPES, values("n BIGINT, outer_width DOUBLE, inner_width DOUBLE, width DOUBLE, product_bound DOUBLE, valid BOOLEAN, bounded BOOLEAN", [(n, 1.0, 1.0, max(n / 2, 1.0), float(n), "true", "true") for n in (2, 3, 4)]), "n"))
def plan_composed_widths(spark, d):
    """Stars put in place of a star's edges make a clique: the width grows although neither part's does, and stays within
    the bounds; the composed decomposition is valid."""
    def measure(name, read):
        n, stars = int(name), {}
        for x in read:
            at, ends = x.split(":")
            stars.setdefault(at, []).append(Edge(ends.split(".")))
        inner = {Edge().union(*xs): xs for xs in stars.values()}
        edges = compose.composed_edges(inner)
        tree, _ = compose.composed_tree(inner)
        width, made = widths.fractional_hypertree_width(edges), compose.tree_width(edges, tree[0])
        return [(n, float(widths.fractional_hypertree_width(tuple(inner))), float(max(widths.fractional_hypertree_width(tuple(e)) for e in inner.values())), float(width), float(compose.product_bound(inner)),
                 compose.is_decomposition(edges, tree), width <= made <= compose.additive_bound(inner))]

    return measured(read_shapes(spark, d, _STAR_SHAPES), measure, "n long, outer_width double, inner_width double, width double, product_bound double, valid boolean, bounded boolean")


@workload("""WITH r AS (SELECT * FROM (VALUES (0)) t(h)), p AS (SELECT COUNT(DISTINCT s_suppkey) AS n FROM supplier) SELECT 'stepwise' AS hub, 'binary' AS lineitem, (3 * n + 1)::BIGINT AS val FROM p""")
def join_choice(spark, d):
    """A hub with an edge to and from every supplier and itself: binary joins would pair all of them, so the sizes call for
    stepwise joins; the triangle of lineitem keeps binary ones."""
    s = table(spark, d, "supplier").select(F.col("s_suppkey").alias("x"))
    hub = s.select("x", F.lit(-1).cast("long").alias("y")).unionByName(s.select(F.lit(-1).cast("long").alias("x"), F.col("x").alias("y")))
    hub = hub.unionByName(spark.sql("SELECT -1L AS x, -1L AS y"))
    q = FactorQuery((), tuple((v, "sum") for v in "abc"), tuple(pairs(hub, **{u: "x", v: "y"}) for u, v in ("ab", "bc", "ca")), COUNT)
    return evaluate.answer(q, how="auto").select(F.lit(multijoin.choose(list(q.factors))).alias("hub"), F.lit(multijoin.choose(list(spo(spark, d).factors))).alias("lineitem"), "val")
