"""Workloads on other input forms, order joins and model fitting; importing this registers them."""

from __future__ import annotations

from pyspark.sql import functions as F

from mixagg.functions.algebra import COUNT
from mixagg.operators import evaluate, learn, relational, represent
from mixagg.sources.tables import table
from mixagg.workloads import ORACLES, gram_lineitem, line, pairs, workload


@workload("""WITH a AS (SELECT DISTINCT p_brand AS b, p_type AS t FROM part), c AS (SELECT DISTINCT p_brand AS b, p_size % 5 AS z FROM part)
SELECT t, z, COUNT(*)::BIGINT AS val FROM a JOIN c USING (b) GROUP BY 1, 2""")
def sum_of_terms(spark, d):
    """A term a brand: its types times its sizes."""
    part = table(spark, d, "part")
    return evaluate.answer(represent.terms([pairs(part, b="p_brand", t="p_type"), pairs(part, b="p_brand", z=F.col("p_size") % 5)], "b", COUNT, "sum"))


@workload("""WITH v AS (SELECT DISTINCT l_linenumber AS v FROM lineitem), w AS (SELECT DISTINCT CAST(l_quantity AS INT) AS w FROM lineitem)
SELECT v, w, CASE (v % 2 + w) % 3 WHEN 0 THEN 5 ELSE 7 END::BIGINT AS val FROM v CROSS JOIN w WHERE (v % 2 + w) % 3 <> 1""")
def decision_diagram(spark, d):
    """Two layers: the parity of a line's number, then that plus the quantity modulo 3; one leaf is zero."""
    x = line(spark, d)
    first = x.select(F.lit(0).alias("node"), F.col("l_linenumber").alias("value")).distinct().withColumn("child", F.col("value") % 2)
    second = x.select(F.col("l_quantity").cast("int").alias("value")).distinct().withColumn("node", F.explode(F.array(F.lit(0), F.lit(1)))).withColumn("child", (F.col("node") + F.col("value")) % 3)
    leaves = spark.createDataFrame([(0, 5), (1, 0), (2, 7)], "node long, val long")
    return evaluate.answer(represent.diagram(spark, [first, second], ["v", "w"], 0, leaves, COUNT, "sum"), order="given")


@workload("""SELECT n_nationkey AS n, COUNT(*)::BIGINT AS val FROM nation JOIN lineitem ON l_quantity BETWEEN n_nationkey AND n_nationkey + 2 * n_regionkey GROUP BY 1""")
def range_join_bands(spark, d):
    bands = table(spark, d, "nation").select(F.col("n_nationkey").alias("n"), F.col("n_nationkey").cast("double").alias("lo"), (F.col("n_nationkey") + 2 * F.col("n_regionkey")).cast("double").alias("hi"))
    # equal quantities meet the same bands, so they are counted before the join
    q = line(spark, d).groupBy("l_quantity").agg(F.count("*").alias("k"))
    return relational.range_join(q, bands, "l_quantity", "lo", "hi", 5.0).groupBy("n").agg(F.sum("k").alias("val"))


@workload("""SELECT event_id, view_id FROM (SELECT p.event_id, v.event_id AS view_id, row_number() OVER (PARTITION BY p.event_id ORDER BY v.ts DESC NULLS LAST, v.event_id DESC) AS k
FROM events p LEFT JOIN events v ON v.user_id = p.user_id AND v.event_type = 'view' AND v.ts <= p.ts WHERE p.event_type = 'purchase') WHERE k = 1""")
def latest_view_before_purchase(spark, d):
    e = table(spark, d, "events")
    bought = e.where("event_type = 'purchase'").select("event_id", "user_id", "ts")
    seen = e.where("event_type = 'view'").select("user_id", "ts", F.col("event_id").alias("view_id"))
    return relational.latest_before(bought, seen, "user_id", "ts", "ts", ["view_id"], F.date_trunc("day", "__at")).select("event_id", "view_id")


@workload(f"""WITH m AS ({ORACLES["gram_lineitem"]}), c AS (SELECT *, tt - s_t::DOUBLE * s_t / n AS ctt, aa - s_a::DOUBLE * s_a / n AS caa, ta - s_t::DOUBLE * s_a / n AS cta, qt - s_q::DOUBLE * s_t / n AS cqt, qa - s_q::DOUBLE * s_a / n AS cqa FROM m),
b AS (SELECT *, (cqt * caa - cqa * cta) / (ctt * caa - cta * cta) AS bt, (cqa * ctt - cqt * cta) / (ctt * caa - cta * cta) AS ba FROM c)
SELECT ROUND((s_q - bt * s_t - ba * s_a) / n, 5) AS intercept, ROUND(bt, 5) AS per_price, ROUND(ba, 5) AS per_balance FROM b""")
def fit_quantity(spark, d):
    """Least squares for a line's quantity over a three-way join that is never built."""
    m = gram_lineitem(spark, d).first()
    fit = learn.linear_regression(m.n, {"q": m.s_q, "t": m.s_t, "a": m.s_a}, {("q", "t"): m.qt, ("q", "a"): m.qa, ("t", "t"): m.tt, ("t", "a"): m.ta, ("a", "a"): m.aa}, ["t", "a"], "q")
    row = [tuple(round(fit[k], 5) + 0.0 for k in ("1", "t", "a"))]
    return spark.createDataFrame(row, "intercept double, per_price double, per_balance double")
