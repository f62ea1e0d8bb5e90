"""Workloads for planning, measures, front ends and compared baselines, with their SQL.

Queries about plans alone return small tables; their SQL states the values worked out by hand for the named hypergraphs.
"""

from __future__ import annotations

from itertools import permutations

from pyspark.sql import functions as F

from mixagg import frontends
from mixagg.functions.algebra import BOOL, COUNT
from mixagg.model import Factor, FactorQuery
from mixagg.operators import baselines, chain, cnf, evaluate, fourier
from mixagg.plans import brute, cost, ordering, widths
from mixagg.plans.widths import Edge
from mixagg.sources.tables import table
from mixagg.workloads_shapes import measured, read_shapes, shapes_sql
from mixagg.workloads import _ALL, _CNF, _EVENTS, _EXAMPLES, _LISTING, _NATIONS, _SPO, ORACLES, QUERIES, _example, _example_sql, _priorities, line, long_value, pairs, spo, workload


def values(columns: str, rows: list[tuple]) -> str:
    """A SQL table of constants; columns: name type, ..."""
    names = [c.split()[0] for c in columns.split(", ")]
    kinds = [c.split()[1] for c in columns.split(", ")]
    cell = lambda x: f"'{x}'" if isinstance(x, str) else str(x)
    body = ", ".join("(" + ", ".join(cell(x) for x in r) + ")" for r in rows)
    return f"SELECT {', '.join(f'CAST({n} AS {k}) AS {n}' for n, k in zip(names, kinds))} FROM (VALUES {body}) t({', '.join(names)})"


# -- hypergraph measures ----------------------------------------------------------------------------------------

_GRAPHS = {"triangle": "ab bc ca", "path": "ab bc cd", "star": "ab ac ad", "cycle4": "ab bc cd da", "cycle5": "ab bc cd de ea", "clique4": "ab ac ad bc bd cd",
           "clique5": "ab ac ad ae bc bd be cd ce de", "covered triangle": "ab bc ca abc", "nested": "a ab abc"}


@workload(shapes_sql(_GRAPHS, values("graph VARCHAR, tw BIGINT, ghtw BIGINT, fhtw DOUBLE, rho DOUBLE, alpha BOOLEAN, beta BOOLEAN", [
    ("triangle", 2, 2, 1.5, 1.5, "false", "false"), ("path", 1, 1, 1, 2, "true", "true"), ("star", 1, 1, 1, 3, "true", "true"), ("cycle4", 2, 2, 2, 2, "false", "false"),
    ("cycle5", 2, 2, 2, 2.5, "false", "false"), ("clique4", 3, 2, 2, 2, "false", "false"), ("clique5", 4, 3, 2.5, 2.5, "false", "false"), ("covered triangle", 2, 1, 1, 1, "true", "false"), ("nested", 2, 1, 1, 1, "true", "true")]), "graph"))
def plan_widths(spark, d):
    """Tree, hypertree and fractional width, fractional cover and acyclicity of small patterns."""
    def measure(name, edges):
        e = [Edge(x) for x in edges]
        return [(name, widths.treewidth(e), widths.hypertree_width(e), float(widths.fractional_hypertree_width(e)), float(widths.rho(e, Edge().union(*e))), widths.is_alpha_acyclic(e), widths.nested_order(e) is not None)]

    return measured(read_shapes(spark, d, _GRAPHS), measure, "graph string, tw long, ghtw long, fhtw double, rho double, alpha boolean, beta boolean")


_STEPS = {"plain": {6: "236", 5: "125", 4: "134", 3: "123", 2: "12", 1: "1"}, "product rule": {6: "236", 5: "125", 4: "134", 3: "123", 2: "12", 1: "1"}}
_SEQUENCES = {"running": "15 25 134 236", "split": "13 23"}
_SEQUENCE_TAGS = {"running": {1: "max", 2: "max", 3: "product", 4: "sum", 5: "max", 6: "max"}, "split": {1: "sum", 2: "sum", 3: "product"}}
_SPLIT = {"plain": {3: "123", 2: "12", 1: "1"}, "product rule": {3: "123", 2: "2", 1: "1"}}


def _bags(example: str, edges: list[str], tags: dict) -> list[tuple]:
    order = tuple(sorted(tags))
    e = [Edge(map(int, x)) for x in edges]
    runs = {"plain": widths.elimination_sequence(e, order), "product rule": widths.elimination_sequence(e, order, tags)}
    return [(example, rule, k, "".join(map(str, sorted(u)))) for rule, bags in runs.items() for k, u in bags.items()]


@workload(shapes_sql(_SEQUENCES, values("example VARCHAR, rule VARCHAR, variable BIGINT, bag VARCHAR", [("running", r, k, u) for r, bags in _STEPS.items() for k, u in bags.items()] + [("split", r, k, u) for r, bags in _SPLIT.items() for k, u in bags.items()]), "example"))
def plan_sequences(spark, d):
    """Bags of two orders, innermost first: a product variable leaves its edges without joining them."""
    return measured(read_shapes(spark, d, _SEQUENCES), lambda name, edges: _bags(name, edges, _SEQUENCE_TAGS[name]), "example string, rule string, variable long, bag string")


_SAFE = [
    ("sum max prefix", "S1 S2 M3 S4 S5 M6 M7", "12 135 14 246 27 37", "semiring", 48, 114, 2, 2), ("sum max sum star", "S1 M2 S3", "12 13", "semiring", 2, 3, 1, 1),
    ("two sums two maxima", "S1 S2 M3 M4 S5", "15 25 13 24", "semiring", 12, 30, 2, 1), ("closed form", "S1 M2 P3 M4 M5 P6", "123 125 14 34 6", "closed", 10, 20, 1.5, 1.5),
    ("path with tail", "S1 M2 S3 S4", "12 23 14", "semiring", 2, 4, 1, 1), ("sum around a product", "S1 P2 S3", "13 2", "general", 1, 1, 1, 1),
    ("running, general", "M1 M2 P3 S4 M5 M6", "15 25 134 236", "general", 12, 12, 2, 2), ("alternating", "M1 S2 M3 S4", "13 24", "semiring", 24, 24, 1, 1), ("forall exists", "P1 P2 P3 M4", "123 14 24 34", "closed", 6, 6, 5 / 3, 5 / 3)]
_SAFE_SHAPES = {name: edges for name, _, edges, *_ in _SAFE}
_SMALL_SHAPES = {name: _SAFE_SHAPES[name] for name in ("sum max sum star", "path with tail", "alternating", "sum around a product")}
_MODES = {name: (spec, mode) for name, spec, _, mode, *_ in _SAFE}
_TAG = {"S": "sum", "M": "max", "P": "product"}


def _theory(spec: str, edges: str, mode: str) -> ordering.Theory:
    return ordering.Theory(tuple(int(s[1:]) for s in spec.split()), tuple(Edge(map(int, e)) for e in edges.split()), {int(s[1:]): _TAG[s[0]] for s in spec.split()}, mode, frozenset({"max"} if mode == "closed" else ()))


@workload(shapes_sql(_SAFE_SHAPES, values("example VARCHAR, extensions BIGINT, safe BIGINT, given_width DOUBLE, best_width DOUBLE", [(n, e, s, round(g, 4), round(b, 4)) for n, _, _, _, e, s, g, b in _SAFE]), "example"))
def plan_safe_orders(spark, d):
    """Linear extensions, safe orders among all permutations, and widths of the given and the best order."""
    def measure(name, edges):
        spec, mode = _MODES[name]
        t = _theory(spec, " ".join(edges), mode)
        return [(name, t.count_extensions(), sum(t.is_safe(p) for p in permutations(t.order)), round(float(t.width(t.order)), 4), round(float(t.width(t.best())), 4))]

    return measured(read_shapes(spark, d, _SAFE_SHAPES), measure, "example string, extensions long, safe long, given_width double, best_width double")


@workload(shapes_sql(_SMALL_SHAPES, values("example VARCHAR, safe BIGINT, agree BIGINT, witnessed BIGINT", [("sum max sum star", 3, 3, 3), ("path with tail", 4, 4, 20), ("alternating", 24, 24, 0), ("sum around a product", 1, 1, 5)]), "example"))
def plan_safe_by_definition(spark, d):
    """Safe orders against the definition: orders that agree on all tried inputs, and orders shown unsafe by one."""
    def measure(name, edges):
        spec, mode = _MODES[name]
        t = _theory(spec, " ".join(edges), mode)
        agree = brute.safe_by_definition(t.edges, t.order, t.tags)
        every = list(permutations(t.order))
        return [(name, sum(t.is_safe(p) for p in every), len(agree), len(every) - len(agree))]

    return measured(read_shapes(spark, d, _SMALL_SHAPES), measure, "example string, safe long, agree long, witnessed long")


_FOLD = {"sum": "({} + {})", "max": "GREATEST({}, {})", "product": "({} * {})"}


def _relation_sql(a: str, b: str) -> str:
    one, other = _FOLD[a].format(_FOLD[b].format("w", "x"), _FOLD[b].format("y", "z")), _FOLD[b].format(_FOLD[a].format("w", "y"), _FOLD[a].format("x", "z"))
    return f"SELECT '{a}' AS a, '{b}' AS b, CASE WHEN {a == b} THEN 'identical' WHEN BOOL_OR({one} <> {other}) THEN 'different' ELSE 'commuting' END AS relation FROM m"


@workload("WITH m AS (SELECT " + ", ".join(f"MAX(CASE WHEN l_linenumber = {i} THEN CAST(l_quantity AS BIGINT) % 3 END) AS {c}" for i, c in enumerate("wxyz", 1)) + " FROM lineitem GROUP BY l_orderkey HAVING w IS NOT NULL AND x IS NOT NULL AND y IS NOT NULL AND z IS NOT NULL) "
          + " UNION ALL ".join(_relation_sql(a, b) for a in _FOLD for b in _FOLD))
def plan_aggregate_relations(spark, d):
    """Whether two neighbouring aggregates are one, may change places, or neither, on the two-by-two matrices of the orders'
    first four quantities, modulo three."""
    cell = lambda i, c: F.max(F.when(F.col("l_linenumber") == i, F.col("l_quantity").cast("long") % 3)).alias(c)
    m = line(spark, d).groupBy("l_orderkey").agg(*[cell(i, c) for i, c in enumerate("wxyz", 1)]).na.drop().select(*"wxyz").distinct()

    def run(frames):
        import pandas as pd

        for pdf in frames:
            told = [(a, b, brute.relation(a, b, matrices=pdf.to_numpy().tolist())) for a in _FOLD for b in _FOLD]
            yield pd.DataFrame(told, columns=["a", "b", "relation"])

    found = m.mapInPandas(run, "a string, b string, relation string")
    return found.groupBy("a", "b").agg(F.max(F.struct((F.col("relation") == "different").alias("worse"), "relation"))["relation"].alias("relation"))


_GAPS = {str(n): "".join(map(str, range(1, n + 1))) + " " + " ".join(f"{i}{n + 1}" for i in range(1, n + 1)) for n in (2, 3, 4)}


@workload(shapes_sql(_GAPS, values("n BIGINT, width DOUBLE, prefix BIGINT", [(n, round(2 - 1 / n, 4), n + 1) for n in (2, 3, 4)]), "n"))
def plan_prefix_gap(spark, d):
    """The forall-exists family: the width of the planned order stays below two, the prefix measure grows with n."""
    def measure(name, edges):
        n = int(name)
        t = _theory(" ".join(f"P{i}" for i in range(1, n + 1)) + f" M{n + 1}", " ".join(edges), "closed")
        prefix = min(max(len(u) for k, u in widths.elimination_sequence(t.edges, o, t.tags).items() if t.tags[k] != "product") for o in t.extensions())
        return [(n, round(float(t.width(t.best())), 4), prefix)]

    return measured(read_shapes(spark, d, _GAPS), measure, "n long, width double, prefix long")


@workload("""WITH sp AS (SELECT DISTINCT l_suppkey s, l_partkey p FROM lineitem), po AS (SELECT DISTINCT l_partkey p, l_orderkey o FROM lineitem), os AS (SELECT DISTINCT l_orderkey o, l_suppkey s FROM lineitem),
n AS (SELECT (SELECT COUNT(*) FROM sp) a, (SELECT COUNT(*) FROM po) b, (SELECT COUNT(*) FROM os) c)
SELECT a::BIGINT AS sp, b::BIGINT AS po, c::BIGINT AS os, ROUND(LN(SQRT(a::DOUBLE * b * c)), 3) AS log_bound, (SELECT COUNT(*) FROM sp JOIN po USING (p) JOIN os ON os.o = po.o AND os.s = sp.s)::BIGINT AS joined FROM n""")
def size_bound_triangle(spark, d):
    """Factor sizes, the size bound of the triangle's bag, and the join it bounds."""
    q = spo(spark, d)
    a, b, c = cost.sizes_of(q)
    bound = widths.size_bound(list(q.edges), Edge("spo"), [a, b, c])
    return evaluate.answer(q).select(F.lit(a).cast("long").alias("sp"), F.lit(b).cast("long").alias("po"), F.lit(c).cast("long").alias("os"), F.round(F.log(F.lit(bound)), 3).alias("log_bound"), F.col("val").alias("joined"))


@workload("""WITH sp AS (SELECT DISTINCT l_suppkey s, l_partkey p FROM lineitem), po AS (SELECT DISTINCT l_partkey p, l_orderkey o FROM lineitem), os AS (SELECT DISTINCT l_orderkey o, l_suppkey s FROM lineitem),
t AS (SELECT sp.s, sp.p, po.o FROM sp JOIN po USING (p) JOIN os ON os.o = po.o AND os.s = sp.s)
SELECT 'o' AS variable, COUNT(*)::BIGINT AS joined, (SELECT COUNT(*) FROM (SELECT DISTINCT s, p FROM t))::BIGINT AS kept FROM t
UNION ALL SELECT 'p', (SELECT COUNT(*) FROM (SELECT DISTINCT s, p FROM t))::BIGINT, (SELECT COUNT(DISTINCT s) FROM t)::BIGINT UNION ALL SELECT 's', (SELECT COUNT(DISTINCT s) FROM t)::BIGINT, 1::BIGINT""")
def steps_triangle(spark, d):
    """Rows joined and rows kept by each elimination step."""
    meter = evaluate.Meter(count=True)
    evaluate.eliminate(spo(spark, d), order="given", meter=meter)
    return spark.createDataFrame([(s["variable"], s["joined"], s["rows"]) for s in meter.steps], "variable string, joined long, kept long")


def _chain_costs(spark, d) -> list[tuple]:
    q = FactorQuery((), tuple((v, "sum") for v in "nco"), (pairs(table(spark, d, "customer"), n="c_nationkey", c="c_custkey"), pairs(table(spark, d, "orders"), c="o_custkey", o="o_orderkey")), COUNT)
    sizes, t = cost.sizes_of(q), ordering.theory(q)
    return [("".join(o), cost.predicted(t.edges, o, t.tags, sizes), "".join(cost.greedy_order(t, sizes)), "".join(cost.cheapest(q, sizes))) for o in permutations("nco")]


@workload("""WITH n AS (SELECT (SELECT COUNT(*) FROM customer)::DOUBLE c, (SELECT COUNT(*) FROM orders)::DOUBLE o)
SELECT k AS chosen, CAST(ROUND((o + 2 * c) / 10) AS BIGINT) AS tens FROM n, (VALUES ('con'), ('nco'), ('cno')) t(k)""")
def plan_costs(spark, d):
    """Predicted rows of the bags of a chain's good orders (in tens): no bag is larger than a factor's."""
    rows = [(o, int(round(c.bags / 10))) for o, c, _, _ in _chain_costs(spark, d) if o in ("nco", "cno", "con")]
    return spark.createDataFrame(rows, "chosen string, tens long")


# -- engine paths that other workloads leave out -------------------------------------------------------------------


def _events_query(spark, d, agg: str) -> FactorQuery:
    e = table(spark, d, "events").select((F.col("user_id") % 16).alias("u"), F.col("event_type").alias("t"), F.hour("ts").alias("h"), F.dayofmonth("ts").alias("d"))
    return FactorQuery(("t", "d"), (("u", agg), ("h", agg)), tuple(Factor.build(e, COUNT, {x: x for x in xs}, F.lit(1), "sum") for xs in ("ut", "th", "hd")), COUNT)


@workload(_EVENTS.format(agg="SUM"))
def marginal_events_search(spark, d):
    """Conditioned search with free variables."""
    return evaluate.search(_events_query(spark, d, "sum"))


@workload(_EVENTS.format(agg="SUM"))
def marginal_events_direct(spark, d):
    """The listing without filters on its free part."""
    return evaluate.eliminate(_events_query(spark, d, "sum"), output="direct").listing()


@workload(_EVENTS.format(agg="SUM"))
def marginal_events_frontend(spark, d):
    q = _events_query(spark, d, "sum")
    return frontends.marginal(["t", "d"], list(q.factors), COUNT)


@workload("""WITH ut AS (SELECT user_id % 16 AS u, event_type AS t, COUNT(*) AS v FROM events GROUP BY 1, 2),
th AS (SELECT event_type AS t, hour(ts) AS h, COUNT(*) AS v FROM events GROUP BY 1, 2), hd AS (SELECT hour(ts) AS h, day(ts) AS d, COUNT(*) AS v FROM events GROUP BY 1, 2)
SELECT t, d::INT AS d, u::BIGINT AS u, h::INT AS h, val::BIGINT AS val FROM (SELECT t, d, u, h, ut.v * th.v * hd.v AS val, row_number() OVER (PARTITION BY t, d ORDER BY ut.v * th.v * hd.v DESC, u DESC, h DESC) AS k FROM ut JOIN th USING (t) JOIN hd USING (h)) WHERE k = 1""")
def map_events_argmax(spark, d):
    """The most likely assignment itself, not only its value."""
    q = _events_query(spark, d, "max")
    return frontends.most_likely(["t", "d"], ["u", "h"], list(q.factors), COUNT).select("t", "d", "u", "h", "val")


@workload(_ALL.replace("SELECT c_custkey", "SELECT c_custkey AS c", 1))
def qcq_frontend(spark, d):
    _, dom = _priorities(spark, d)
    return frontends.qcq(["c"], [("pri", "forall")], [(table(spark, d, "orders"), {"c": "o_custkey", "pri": "o_orderpriority"}), (table(spark, d, "customer"), {"c": "c_custkey"})], {"pri": dom})


@workload(f"SELECT c_nationkey AS n, COUNT(*)::BIGINT AS val FROM customer WHERE c_custkey IN ({_ALL}) GROUP BY 1")
def count_qcq_frontend(spark, d):
    _, dom = _priorities(spark, d)
    return frontends.count_qcq(["c"], [("pri", "forall")], [(table(spark, d, "orders"), {"c": "o_custkey", "pri": "o_orderpriority"}), (table(spark, d, "customer"), {"n": "c_nationkey", "c": "c_custkey"})], {"pri": dom}, by=["n"])


@workload(_LISTING)
def cq_frontend(spark, d):
    t = lambda name: table(spark, d, name)
    return frontends.cq(["r", "b", "pri"], [
        (t("nation"), {"r": "n_regionkey", "n": "n_nationkey"}), (t("customer"), {"n": "c_nationkey", "c": "c_custkey"}), (t("orders"), {"c": "o_custkey", "o": "o_orderkey"}),
        (t("orders"), {"o": "o_orderkey", "pri": "o_orderpriority"}), (t("lineitem"), {"o": "l_orderkey", "p": "l_partkey"}), (t("part"), {"p": "p_partkey", "b": "p_brand"})])


def _nation_atoms(spark, d):
    t = lambda name: table(spark, d, name)
    return [(t("supplier"), {"n": "s_nationkey", "s": "s_suppkey"}), (t("lineitem"), {"s": "l_suppkey", "o": "l_orderkey"}), (t("orders"), {"o": "o_orderkey", "c": "o_custkey"}), (t("customer"), {"c": "c_custkey", "m": "c_nationkey"})]


_NATION_COUNT = "SELECT COUNT(*)::BIGINT AS val FROM (SELECT DISTINCT s_nationkey, c_nationkey FROM lineitem JOIN supplier ON s_suppkey = l_suppkey JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey)"


@workload(_NATION_COUNT)
def count_cq_frontend(spark, d):
    return frontends.count_cq(["n", "m"], _nation_atoms(spark, d))


@workload(_NATION_COUNT)
def count_cq_distinct_baseline(spark, d):
    """Counting by listing the distinct free part of the whole join."""
    return baselines.count_distinct_projection(FactorQuery(("n", "m"), (("s", "or"), ("o", "or"), ("c", "or")), frontends.relations(_nation_atoms(spark, d), BOOL), BOOL))


def _nation_edges(spark, d):
    j = line(spark, d).join(table(spark, d, "supplier"), F.col("l_suppkey") == F.col("s_suppkey")).join(table(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(table(spark, d, "customer"), F.col("o_custkey") == F.col("c_custkey"))
    return evaluate.kept(j.select("s_nationkey", "c_nationkey").distinct())


@workload(_NATIONS + "SELECT COUNT(*)::BIGINT AS val FROM e w JOIN e x ON w.b = x.a JOIN e y ON x.b = y.a JOIN e z ON y.b = z.a AND z.b = w.a")
def cycle4_frontend(spark, d):
    return frontends.count_pattern(_nation_edges(spark, d), "s_nationkey", "c_nationkey", [("a", "b"), ("b", "c"), ("c", "d"), ("d", "a")])


@workload(_NATIONS + "SELECT w.a, w.b, x.b AS c, y.b AS d FROM e w JOIN e x ON w.b = x.a JOIN e y ON x.b = y.a JOIN e z ON y.b = z.a AND z.b = w.a WHERE w.a < 5")
def cycle4_decomposition(spark, d):
    """The listing of 4-cycles through the bags of a tree decomposition."""
    e = _nation_edges(spark, d)
    f = lambda a, b: Factor((a, b), e.select(F.col("s_nationkey").alias(a), F.col("c_nationkey").alias(b), F.lit(True).alias("val")))
    small = Factor(("a",), e.where("s_nationkey < 5").select(F.col("s_nationkey").alias("a")).distinct().withColumn("val", F.lit(True)))
    return baselines.decomposition_join(FactorQuery(tuple("abcd"), (), (f("a", "b"), f("b", "c"), f("c", "d"), f("d", "a"), small), BOOL)).select(*"abcd")


def _register_baseline_orders() -> None:
    """Each compared way to choose an order, run on the worked example with sums and maxima."""
    spec = _EXAMPLES["prectree_sum_max"]
    sql = _example_sql(*spec)
    ways = {"blocks": baselines.blocks_only, "treewidth": lambda q: baselines.by_width(q, "tw"), "integral": lambda q: baselines.by_width(q, "ghtw"), "prefix": lambda q: baselines.by_width(q, "prefix"),
            "by_node": lambda q: ordering.theory(q).by_node(), "cheapest": cost.cheapest, "greedy": lambda q: cost.greedy_order(ordering.theory(q), cost.sizes_of(q))}
    for name, way in ways.items():
        def run(spark, d, way=way):
            q = _example(spark, d, *spec)
            return long_value(evaluate.answer(q, order=way(q)))
        QUERIES[f"prectree_{name}_order"], ORACLES[f"prectree_{name}_order"] = run, sql


_register_baseline_orders()


@workload(_SPO)
def triangle_spo_cheapest(spark, d):
    """The order of least predicted cost."""
    q = spo(spark, d)
    return evaluate.answer(q, order=cost.cheapest(q))


@workload("""SELECT n_nationkey AS n, p_brand AS b, SUM(CAST(l_quantity AS BIGINT))::BIGINT AS val
FROM nation JOIN customer ON c_nationkey = n_nationkey JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey GROUP BY 1, 2""")
def mcm_left_to_right(spark, d):
    """The matrix chain multiplied from the left."""
    parts = [pairs(table(spark, d, "customer"), n="c_nationkey", c="c_custkey"), pairs(table(spark, d, "orders"), c="o_custkey", o="o_orderkey"),
             pairs(line(spark, d), value=F.col("l_quantity").cast("long"), plus="sum", o="l_orderkey", p="l_partkey"), pairs(table(spark, d, "part"), p="p_partkey", b="p_brand")]
    return chain.multiply(parts, [25, 1, 1, 1, 25], COUNT, how="left")


@workload("""SELECT o_orderpriority AS pri, COUNT(*)::BIGINT AS n, ROUND(SUM(t * t)::DOUBLE / COUNT(*) - POW(SUM(t)::DOUBLE / COUNT(*), 2), 6) AS variance
FROM (SELECT o_orderpriority, CAST(FLOOR(o_totalprice / 1000) AS BIGINT) AS t FROM orders) GROUP BY 1""")
def variance_lift(spark, d):
    o = table(spark, d, "orders").select(F.col("o_orderpriority").alias("pri"), F.floor(F.col("o_totalprice") / 1000).alias("t"))
    return evaluate.lift_variance(o, ["pri"], "t").select("pri", "n", F.round("variance", 6).alias("variance"))


def _formulas(spark, d):
    k, bits = F.col("p_partkey") % 7 + 2, F.floor(F.col("p_partkey") / 7)
    lits = F.transform(F.sequence(F.lit(1), k.cast("int")), lambda i: F.when(F.floor(bits / F.pow(F.lit(2.0), i - 1)) % 2 == 1, i).otherwise(-i).cast("int"))
    return table(spark, d, "part").select(F.concat("p_brand", F.lit("/"), (F.col("p_size") % 5).cast("string")).alias("formula"), lits.alias("lits"))


@workload(f"SELECT formula, sat FROM ({_CNF})")
def sat_beta(spark, d):
    return cnf.per_formula(_formulas(spark, d), 8).select("formula", "sat")


@workload("""WITH c AS (SELECT DISTINCT p_brand || '/' || CAST(p_size % 5 AS VARCHAR) AS formula, CAST(2 + p_partkey % 7 AS INT) AS k, (p_partkey // 7) & ((1 << CAST(2 + p_partkey % 7 AS INT)) - 1) AS bits FROM part),
a AS (SELECT range AS a FROM range(256)), f AS (SELECT DISTINCT formula FROM c),
n AS (SELECT f.formula, a.a, COUNT(c.k) AS falsified FROM f CROSS JOIN a LEFT JOIN c ON c.formula = f.formula AND xor(a.a::BIGINT, c.bits::BIGINT) & ((1::BIGINT << c.k) - 1) = ((1::BIGINT << c.k) - 1) GROUP BY 1, 2)
SELECT formula, SUM(POW(0.5, falsified)) AS weight FROM n GROUP BY 1""")
def wcount_sat_beta(spark, d):
    """Every falsified clause weighs one half."""
    return cnf.weighted_per_formula(_formulas(spark, d).withColumn("num", F.lit(1)).withColumn("den", F.lit(2)), 8)


_DFT = """WITH v AS (SELECT vec_id, unnest(embedding)::DOUBLE AS re, unnest(range(64)) AS n FROM embeddings), x AS (SELECT range AS x FROM range(64))
SELECT vec_id, x::BIGINT AS x, ROUND(SUM(re * COS(2 * PI() * ((x * n) % 64) / 64)), 3) + 0.0 AS re, ROUND(SUM(re * SIN(2 * PI() * ((x * n) % 64) / 64)), 3) + 0.0 AS im FROM v CROSS JOIN x GROUP BY 1, 2"""


def _dft(spark, d, p: int, m: int):
    vec = table(spark, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("n", "re")).withColumn("im", F.lit(0.0))
    rounded = lambda c: (F.round(c, 3) + F.lit(0.0)).alias(c)
    return fourier.dft(vec, p, m, key="vec_id").select("vec_id", "x", rounded("re"), rounded("im"))


ORACLES["dft_embedding"] = _DFT


@workload(_DFT)
def dft_4_3(spark, d):
    """Length 64 as 4**3."""
    return _dft(spark, d, 4, 3)


@workload(_DFT)
def dft_quadratic_baseline(spark, d):
    vec = table(spark, d, "embeddings").select("vec_id", F.posexplode("embedding").alias("n", "re")).withColumn("im", F.lit(0.0))
    rounded = lambda c: (F.round(c, 3) + F.lit(0.0)).alias(c)
    return fourier.dft_quadratic(vec, 64, key="vec_id").select("vec_id", F.col("x").cast("long").alias("x"), rounded("re"), rounded("im"))


_CLAUSES = {"cycle": "12 23 34 41", "nested": "1 12"}


@workload(shapes_sql(_CLAUSES, values("formula VARCHAR, weight DOUBLE", [("cycle", 10.0625), ("nested", 2.75)]), "formula"))
def wcount_general(spark, d):
    """Weighted counts by the engine: a cycle of clauses, which has no nested order, and a nested pair."""
    weighed = lambda edges: [(cnf.Clause(map(int, e)), 0.5) for e in edges]
    one = lambda r: evaluate.answer(cnf.as_query(spark, weighed(r["edges"]))).select(F.lit(r["name"]).alias("formula"), F.col("val").alias("weight"), F.lit(r["lines"]).cast("long").alias("lines"))
    return baselines.union_all([one(r) for r in read_shapes(spark, d, _CLAUSES).collect()])  # two formulas
