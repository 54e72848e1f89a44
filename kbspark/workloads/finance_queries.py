"""Queries of the finance workload."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from kbspark.functions import finance as ff
from kbspark.operators import finance as fin
from kbspark.registry import query
from kbspark.sources.tables import table

LED = """led AS (SELECT strftime(o_orderdate, '%Y%m') AS period, r_name AS region, n_name AS nation, c_mktsegment AS segment, p_brand AS brand, c_custkey AS custkey, l_extendedprice AS a, l_extendedprice * (1 - l_discount) AS b
FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey JOIN part ON l_partkey = p_partkey)"""
GRID = LED + """, per AS (SELECT strftime(m, '%Y%m') AS period FROM (SELECT unnest(generate_series(TIMESTAMP '1995-01-01', TIMESTAMP '2001-08-01', INTERVAL 1 MONTH)) AS m)),
cells AS (SELECT r_name AS region, n_name AS nation, segment, period FROM nation JOIN region ON n_regionkey = r_regionkey, (SELECT DISTINCT c_mktsegment AS segment FROM customer), per),
s AS (SELECT region, nation, segment, period, sum(a) AS a, sum(b) AS b FROM led GROUP BY ALL),
grid AS (SELECT c.*, coalesce(s.a, 0) AS a, coalesce(s.b, 0) AS b FROM cells c LEFT JOIN s USING (region, nation, segment, period))"""


@query(f"WITH {LED} SELECT period, region, nation, segment, round(sum(a) + 1e-6, 2) AS amt_a, round(sum(b) + 1e-6, 2) AS amt_b FROM led GROUP BY ALL")
def ledger_ptd(spark, sf_dir):
    return fin.ledger(spark, sf_dir).groupBy("period", "region", "nation", "segment").agg(ff.money(F.sum("amt_a")).alias("amt_a"), ff.money(F.sum("amt_b")).alias("amt_b"))


@query(f"""WITH {GRID},
w AS (SELECT *, sum(b) OVER (PARTITION BY nation, segment, substr(period, 1, 4) ORDER BY period) AS ytd, coalesce(lag(a, 12) OVER (PARTITION BY nation, segment ORDER BY period), 0) AS pya,
 coalesce(avg(b) OVER (PARTITION BY nation, segment ORDER BY period ROWS BETWEEN 3 PRECEDING AND 1 PRECEDING), 0) AS f FROM grid)
SELECT 71 AS n_columns, count(*) AS n_rows, round(sum(a) + 1e-6, 2) AS usd_ptd_a, round(sum(ytd * 0.9) + 1e-6, 2) AS eur_ytd_b, round(sum(pya * 1.05 * 0.8) + 1e-6, 2) AS gbp_budget_a, round(sum(f) + 1e-6, 2) AS usd_fcst_b FROM w""")
def ledger_wide_shape(spark, sf_dir):
    w = fin.wide(spark, sf_dir)
    s = lambda c: ff.money(F.sum(c)).alias(c)
    return w.agg(F.lit(len(w.columns)).alias("n_columns"), F.count(F.lit(1)).alias("n_rows"), s("usd_ptd_a"), s("eur_ytd_b"), s("gbp_budget_a"), s("usd_fcst_b"))


@query(f"WITH {GRID} SELECT nation, period, round(sum(sum(b)) OVER (PARTITION BY nation, substr(period, 1, 4) ORDER BY period) + 1e-6, 2) AS ytd FROM grid GROUP BY nation, period")
def ytd_window(spark, sf_dir):
    n = fin.grid(spark, sf_dir).groupBy("nation", "period").agg(F.sum("amt_b").alias("b"))
    w = Window.partitionBy("nation", F.substring("period", 1, 4)).orderBy("period").rowsBetween(Window.unboundedPreceding, 0)
    return n.select("nation", "period", ff.money(F.sum("b").over(w)).alias("ytd"))


def _ytd(until: str, amount="amt_b"):
    return F.sum(F.when((F.col("period") >= until[:4] + "01") & (F.col("period") <= until), F.col(amount)))


def _growth_by_region(spark, sf_dir, days=("2000-01-05", "2000-01-20")):
    led, out = fin.ledger(spark, sf_dir), None
    for d in days:
        p = spark.range(1).select(ff.current_period(F.lit(d).cast("timestamp"))).first()[0]
        before = f"{int(p[:4]) - 1}{p[4:]}"
        one = led.groupBy("region").agg(_ytd(p).alias("now"), _ytd(before).alias("before"))
        one = one.select("region", F.lit(p).alias("period"), ff.money(F.coalesce("now", F.lit(0.0))).alias("revenue"), ff.money(F.coalesce("before", F.lit(0.0))).alias("prior"), F.round(ff.growth(F.col("now"), F.col("before")), 6).alias("growth"))
        out = one if out is None else out.union(one)
    return out


GROWTH = f"""WITH {LED}, p(period, prior_p) AS (VALUES ('199912', '199812'), ('200001', '199901')),
g AS (SELECT region, p.period, coalesce(sum(b) FILTER (led.period BETWEEN substr(p.period, 1, 4) || '01' AND p.period), 0) AS n, coalesce(sum(b) FILTER (led.period BETWEEN substr(prior_p, 1, 4) || '01' AND prior_p), 0) AS o FROM led, p GROUP BY ALL)
SELECT region, period, round(n + 1e-6, 2) AS revenue, round(o + 1e-6, 2) AS prior, round(CASE WHEN o = 0 THEN 0 ELSE (n - o) / abs(o) END, 6) AS growth FROM g"""


@query(GROWTH)
def growth_ytd(spark, sf_dir):
    return _growth_by_region(spark, sf_dir)


@query(f"""WITH {LED}, g AS (SELECT custkey, coalesce(sum(b) FILTER (period BETWEEN '199908' AND '199912'), 0) AS n, coalesce(sum(b) FILTER (period BETWEEN '199808' AND '199812'), 0) AS o FROM led GROUP BY 1)
SELECT custkey, round(CASE WHEN o = 0 THEN 0 ELSE (n - o) / abs(o) END, 6) AS growth FROM g ORDER BY 2 DESC, 1 LIMIT 20""")
def growth_top20(spark, sf_dir):
    between = lambda a, b: F.sum(F.when(F.col("period").between(a, b), F.col("amt_b")))
    g = fin.ledger(spark, sf_dir).groupBy("custkey").agg(between("199908", "199912").alias("n"), between("199808", "199812").alias("o"))
    return g.select("custkey", F.round(ff.growth(F.col("n"), F.col("o")), 6).alias("growth")).orderBy(F.desc("growth"), "custkey").limit(20)


@query(f"""WITH {GRID}, n AS (SELECT nation, period, sum(b) AS b FROM grid GROUP BY ALL), y AS (SELECT nation, substr(period, 1, 4) AS year, CAST(substr(period, 5) AS INT) AS m, b FROM n WHERE period < '200101'),
r(m1, m2) AS (VALUES (8, 12), (1, 3), (5, 5))
SELECT nation, year, m1, m2, round(sum(b) FILTER (m <= m2) - coalesce(sum(b) FILTER (m < m1), 0) + 1e-6, 2) AS by_ytd, round(sum(b) FILTER (m BETWEEN m1 AND m2) + 1e-6, 2) AS by_months, true AS equal FROM y, r GROUP BY ALL""")
def ytd_range_equals_sum(spark, sf_dir):
    n = fin.grid(spark, sf_dir).where("period < '200101'").groupBy("nation", F.substring("period", 1, 4).alias("year"), F.substring("period", 5, 2).cast("int").alias("m")).agg(F.sum("amt_b").alias("b"))
    w = Window.partitionBy("nation", "year").orderBy("m").rowsBetween(Window.unboundedPreceding, 0)
    y = n.withColumn("ytd", F.sum("b").over(w))
    out = None
    for m1, m2 in ((8, 12), (1, 3), (5, 5)):
        at = lambda m: F.max(F.when(F.col("m") == m, F.col("ytd")))
        one = y.groupBy("nation", "year").agg(ff.ytd_range(at(m2), at(m1 - 1), F.lit(m1)).alias("d"), F.sum(F.when(F.col("m").between(m1, m2), F.col("b"))).alias("s"))
        one = one.select("nation", "year", F.lit(m1).alias("m1"), F.lit(m2).alias("m2"), ff.money("d").alias("by_ytd"), ff.money("s").alias("by_months"), (F.abs(F.col("d") - F.col("s")) < 0.01).alias("equal"))
        out = one if out is None else out.union(one)
    return out


@query(f"""WITH {GRID}, w AS (SELECT *, coalesce(lag(b, 12) OVER (PARTITION BY nation, segment ORDER BY period), 0) * 1.05 AS bud FROM grid),
k(currency, rate, plan) AS (VALUES ('usd', 1.0, 1.0), ('eur', 0.9, 0.95), ('gbp', 0.8, 0.75)),
g AS (SELECT nation, currency, sum(b * rate) AS x, sum(bud * plan) AS y FROM w, k WHERE period IN ('199911', '199912') AND nation IN ('NATION_0', 'NATION_1') GROUP BY ALL),
q AS (SELECT nation, currency, round(CASE WHEN y = 0 THEN 0 ELSE x / y END, 6) AS ratio FROM g)
SELECT * FROM (SELECT nation, currency, ratio, rank() OVER (PARTITION BY nation ORDER BY ratio DESC) AS rank FROM q) WHERE currency = 'eur'""")
def budget_ratio_rank(spark, sf_dir):
    g = fin.measures(fin.grid(spark, sf_dir).select("region", "nation", "segment", "period", "amt_b"), "amt_b", "b").where(F.col("period").isin("199911", "199912") & F.col("nation").isin("NATION_0", "NATION_1"))
    # Budgets are planned at their own rates, so that currencies differ.
    plan = {"usd": (1.0, 1.0), "eur": (0.9, 0.95), "gbp": (0.8, 0.75)}
    each = g.select("nation", "b_ptd", "b_budget", F.explode(F.array(*(F.struct(F.lit(c).alias("currency"), F.lit(r).alias("rate"), F.lit(p).alias("plan")) for c, (r, p) in plan.items()))).alias("k"))
    by = each.groupBy("nation", F.col("k.currency").alias("currency")).agg(F.sum(F.col("b_ptd") * F.col("k.rate")).alias("x"), F.sum(F.col("b_budget") * F.col("k.plan")).alias("y"))
    by = by.select("nation", "currency", F.round(ff.ratio(F.col("x"), F.col("y")), 6).alias("ratio"))
    return by.withColumn("rank", F.rank().over(Window.partitionBy("nation").orderBy(F.desc("ratio")))).where("currency = 'eur'")


@query("""WITH d(update_day) AS (VALUES (1), (10), (28)), e AS (SELECT ts - INTERVAL 24 YEAR AS t FROM events)
SELECT update_day, strftime(CASE WHEN day(t) < update_day THEN t - INTERVAL 1 MONTH ELSE t END, '%Y%m') AS period, count(*) AS n FROM e, d GROUP BY ALL""")
def effective_period(spark, sf_dir):
    e, out = table(spark, sf_dir, "events").select((F.col("ts") - F.expr("interval 24 years")).alias("t")), None
    for d in (1, 10, 28):
        one = e.groupBy(ff.current_period(F.col("t"), d).alias("period")).agg(F.count(F.lit(1)).alias("n")).select(F.lit(d).alias("update_day"), "period", "n")
        out = one if out is None else out.union(one)
    return out


@query("""SELECT CASE WHEN o_orderpriority IN ('1-URGENT', '2-HIGH') THEN 'fast' ELSE 'normal' END AS channel, count(*) AS n, round(sum(o_totalprice) + 1e-6, 2) AS value FROM orders GROUP BY 1""")
def group_channels(spark, sf_dir):
    ch = F.when(F.col("o_orderpriority").isin("1-URGENT", "2-HIGH"), "fast").otherwise("normal")
    return table(spark, sf_dir, "orders").groupBy(ch.alias("channel")).agg(F.count(F.lit(1)).alias("n"), ff.money(F.sum("o_totalprice")).alias("value"))


@query("""SELECT r_name AS region, round(sum(o_totalprice) + 1e-6, 2) AS with_all, round(coalesce(sum(o_totalprice) FILTER (n_name <> 'NATION_0'), 0) + 1e-6, 2) AS without_special
FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1""")
def exclude_special(spark, sf_dir):
    o, c, n, r = (table(spark, sf_dir, t) for t in ("orders", "customer", "nation", "region"))
    j = o.join(c, F.col("o_custkey") == F.col("c_custkey")).join(n, F.col("c_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey"))
    return j.groupBy(F.col("r_name").alias("region")).agg(ff.money(F.sum("o_totalprice")).alias("with_all"), ff.money(F.coalesce(F.sum(F.when(F.col("n_name") != "NATION_0", F.col("o_totalprice"))), F.lit(0.0))).alias("without_special"))


@query("""SELECT 'calendar' AS kind, year(o_orderdate) AS year, round(sum(o_totalprice) + 1e-6, 2) AS value FROM orders GROUP BY 2
UNION ALL SELECT 'fiscal', year(o_orderdate) + CASE WHEN month(o_orderdate) >= 4 THEN 1 ELSE 0 END, round(sum(o_totalprice) + 1e-6, 2) FROM orders GROUP BY 2""")
def fiscal_vs_calendar(spark, sf_dir):
    o = table(spark, sf_dir, "orders")
    by = lambda kind, y: o.groupBy(y.alias("year")).agg(ff.money(F.sum("o_totalprice")).alias("value")).select(F.lit(kind).alias("kind"), "year", "value")
    return by("calendar", F.year("o_orderdate")).union(by("fiscal", ff.fiscal_year(F.col("o_orderdate"))))


@query(f"""WITH {GRID}, k(currency, rate) AS (VALUES ('usd', 1.0), ('eur', 0.9), ('gbp', 0.8)), c(caliber) AS (VALUES ('a'), ('b'))
SELECT period, currency, caliber, round(sum(CASE WHEN caliber = 'a' THEN a ELSE b END * rate) + 1e-6, 2) AS amount FROM grid, k, c GROUP BY ALL""")
def wide_to_long(spark, sf_dir):
    cols = [f"{c}_ptd_{k}" for c in fin.RATES for k in "ab"]
    long = fin.wide(spark, sf_dir).select("period", *cols).unpivot("period", cols, "column", "v")
    part = F.split("column", "_")
    return long.groupBy("period", part[0].alias("currency"), part[2].alias("caliber")).agg(ff.money(F.sum("v")).alias("amount"))


@query(f"WITH {GRID} SELECT period, round(sum(CASE WHEN period < '199801' THEN a ELSE b END) + 1e-6, 2) AS amount FROM grid GROUP BY period")
def metric_by_period_rule(spark, sf_dir):
    w = fin.wide(spark, sf_dir).select("period", "usd_ptd_a", "usd_ptd_b")
    return w.groupBy("period").agg(ff.money(F.sum(fin.metric_by_period(F.col("usd_ptd_a"), F.col("usd_ptd_b"), F.col("period"), "199801"))).alias("amount"))


PROFILE = """prof AS (SELECT DISTINCT user_id, CASE r_name WHEN 'EUROPE' THEN 'eur' WHEN 'AFRICA' THEN 'gbp' ELSE 'usd' END AS currency, r_name AS region, n_name AS nation, CAST(user_id % 8 AS INT) AS department
FROM events JOIN customer ON user_id = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)"""


@query(f"""WITH {PROFILE}, q AS (SELECT event_id AS q_id, user_id, CASE WHEN event_id % 5 = 0 THEN 'eur' END AS named FROM events)
SELECT q_id, coalesce(named, currency, 'usd') AS currency, CASE WHEN region IS NULL THEN NULL ELSE 'b' END AS caliber, region, nation, department FROM q LEFT JOIN prof USING (user_id)""")
def resolve_user_context(spark, sf_dir):
    text = F.when(F.col("event_id") % 5 == 0, "revenue in EUR this month").otherwise("revenue this month")
    q = table(spark, sf_dir, "events").select(F.col("event_id").alias("q_id"), "user_id", text.alias("text"))
    return fin.resolve(q, fin.user_profile(spark, sf_dir)).select("q_id", "currency", "caliber", "region", "nation", "department")


@query(f"""WITH {PROFILE}, {GRID}, q AS (SELECT event_id AS q_id, user_id, CASE WHEN day(ts) < 10 THEN '199912' ELSE '200001' END AS period FROM events WHERE event_id % 10 = 3),
v AS (SELECT nation, period, sum(b) AS b FROM grid GROUP BY ALL)
SELECT q_id, currency || '_ptd_b' AS col, round(v.b * CASE currency WHEN 'eur' THEN 0.9 WHEN 'gbp' THEN 0.8 ELSE 1 END + 1e-6, 2) AS value FROM q JOIN prof USING (user_id) JOIN v ON prof.nation = v.nation AND q.period = v.period""")
def routed_metric(spark, sf_dir):
    e = table(spark, sf_dir, "events").where("event_id % 10 = 3")
    q = e.select(F.col("event_id").alias("q_id"), "user_id", ff.current_period(F.col("ts") - F.expr("interval 24 years")).alias("period"), F.lit("revenue this month").alias("text"))
    q = fin.resolve(q, fin.user_profile(spark, sf_dir))
    cols = [f"{c}_ptd_b" for c in fin.RATES]
    v = fin.wide(spark, sf_dir).groupBy("nation", "period").agg(*(F.sum(c).alias(c) for c in cols))
    j = q.join(v, ["nation", "period"])
    chosen = F.element_at(F.create_map(*(x for c in fin.RATES for x in (F.lit(c), F.col(f"{c}_ptd_b")))), F.col("currency"))
    return j.select("q_id", F.concat("currency", F.lit("_ptd_b")).alias("col"), ff.money(chosen).alias("value"))


@query(f"""WITH {LED}, p(period, prior_p) AS (VALUES ('199912', '199812'), ('200001', '199901')),
g AS (SELECT p.period, coalesce(sum(b) FILTER (led.period BETWEEN substr(p.period, 1, 4) || '01' AND p.period), 0) AS n, coalesce(sum(b) FILTER (led.period BETWEEN substr(prior_p, 1, 4) || '01' AND prior_p), 0) AS o FROM led, p GROUP BY ALL)
SELECT event_id AS q_id, round(n + 1e-6, 2) AS revenue, round(o + 1e-6, 2) AS prior, round(CASE WHEN o = 0 THEN 0 ELSE (n - o) / abs(o) END, 6) AS growth
FROM events JOIN g ON g.period = CASE WHEN day(ts) < 10 THEN '199912' ELSE '200001' END WHERE event_id % 10 = 3""")
def implicit_growth(spark, sf_dir):
    q = table(spark, sf_dir, "events").where("event_id % 10 = 3").select(F.col("event_id").alias("q_id"), ff.current_period(F.col("ts") - F.expr("interval 24 years")).alias("period"))
    led, ps = fin.ledger(spark, sf_dir), ["199912", "200001"]
    sums = led.agg(*(x for p in ps for x in (_ytd(p).alias(f"n{p}"), _ytd(f"{int(p[:4]) - 1}{p[4:]}").alias(f"o{p}"))))
    by = sums.select(F.inline(F.array(*(F.struct(F.lit(p).alias("period"), F.coalesce(f"n{p}", F.lit(0.0)).alias("n"), F.coalesce(f"o{p}", F.lit(0.0)).alias("o")) for p in ps))))
    return q.join(F.broadcast(by), "period").select("q_id", ff.money("n").alias("revenue"), ff.money("o").alias("prior"), F.round(ff.growth(F.col("n"), F.col("o")), 6).alias("growth"))
