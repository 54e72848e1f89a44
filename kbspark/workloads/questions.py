"""Questions derived from events and templates, and the results of candidates that samples write for them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from kbspark.sources.tables import table
from kbspark.workloads.executed import CANDIDATES_SQL, LETTERS, broken, candidate_results

# The templates as text, gold SQL, whether the order counts, difficulty; {p} and {r} are parameters.
TEMPLATES = [
    ("total order value with status {p}", "SELECT sum(o_totalprice) AS v FROM orders WHERE o_orderstatus = '{p}'", False, "simple"),
    ("how many customers in segment {p}", "SELECT count(*) AS n FROM customer WHERE c_mktsegment = '{p}'", False, "simple"),
    ("top 5 nations by order value in year {p}", "SELECT n_name, sum(o_totalprice) AS v FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey WHERE year(o_orderdate) = {p} GROUP BY n_name ORDER BY v DESC, n_name LIMIT 5", True, "challenging"),
    ("revenue this month", "SELECT sum(l_extendedprice * (1 - l_discount)) AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE date_format(o_orderdate, 'yyyyMM') = '199912'", False, "challenging"),
    ("average discount by return flag", "SELECT l_returnflag, avg(l_discount) AS d FROM lineitem GROUP BY l_returnflag", False, "simple"),
    ("list part names of brand {p} and type {r}", "SELECT DISTINCT p_name FROM part WHERE p_brand = '{p}' AND p_type = '{r}'", False, "moderate"),
    ("suppliers per nation in region {p}", "SELECT n_name, count(*) AS n FROM supplier JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE r_name = '{p}' GROUP BY n_name", False, "moderate"),
    ("net revenue by region, highest first", "SELECT r_name, sum(l_extendedprice * (1 - l_discount)) AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name ORDER BY v DESC", True, "challenging"),
    ("events of type {p} per day", "SELECT cast(ts AS date) AS d, count(*) AS n FROM events WHERE event_type = '{p}' GROUP BY d ORDER BY d", True, "moderate"),
    ("budget ratio by currency this period, with rank", "SELECT 1 AS r", False, "challenging"),
]
DOMAINS = {0: ("orders", "o_orderstatus"), 1: ("customer", "c_mktsegment"), 5: ("part", "p_brand"), 6: ("region", "r_name"), 8: ("events", "event_type")}
YEARS = [str(y) for y in range(1995, 2002)]


def domain(spark: SparkSession, sf_dir: str, tab: str, col: str) -> list[str]:
    """The sorted values of an enum column: a list that a schema bounds, not the data."""
    return [r[0] for r in table(spark, sf_dir, tab).select(col).distinct().orderBy(col).collect()]


def questions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """q_id, asked_at, user_id, template, p, r, text, gold_sql, is_ordered, difficulty, labelled."""
    e = table(spark, sf_dir, "events").select(F.col("event_id").alias("q_id"), F.col("ts").alias("asked_at"), "user_id")
    e = e.withColumns({"template": (F.col("q_id") % 10).cast("int"), "turn": F.floor(F.col("q_id") / 10)})
    pick = lambda vs: F.element_at(F.array(*map(F.lit, vs)), (F.col("turn") % len(vs) + 1).cast("int"))
    p: Column = F.lit("")
    for t, (tab, col) in DOMAINS.items():
        p = F.when(F.col("template") == t, pick(domain(spark, sf_dir, tab, col))).otherwise(p)
    p = F.when(F.col("template") == 2, pick(YEARS)).otherwise(p)
    r = F.when(F.col("template") == 5, pick(domain(spark, sf_dir, "part", "p_type"))).otherwise(F.lit(""))
    of = lambda i, kind: F.element_at(F.array(*(F.lit(t[i]) for t in TEMPLATES)), F.col("template") + 1).cast(kind)
    e = e.withColumns({"p": p, "r": r})
    fill = lambda c: F.replace(F.replace(c, F.lit("{p}"), F.col("p")), F.lit("{r}"), F.col("r"))
    return e.select("q_id", "asked_at", "user_id", "template", "p", "r", fill(of(0, "string")).alias("text"), fill(of(1, "string")).alias("gold_sql"), of(2, "boolean").alias("is_ordered"), of(3, "string").alias("difficulty"), (F.col("q_id") % 2 == 0).alias("labelled"))


def _list(tab, col):
    return f"(SELECT list(DISTINCT {col} ORDER BY {col}) FROM {tab})"


_cases = " ".join(f"WHEN {t} THEN {_list(tab, col)}[turn % len({_list(tab, col)}) + 1]" for t, (tab, col) in DOMAINS.items())
QUESTIONS_SQL = f"""e AS (SELECT event_id AS q_id, ts, user_id, event_id % 10 AS template, event_id // 10 AS turn FROM events),
e2 AS (SELECT *, CASE template {_cases} WHEN 2 THEN CAST(1995 + turn % 7 AS VARCHAR) ELSE '' END AS p, CASE template WHEN 5 THEN {_list('part', 'p_type')}[turn % len({_list('part', 'p_type')}) + 1] ELSE '' END AS r FROM e),
tpl(template, t, difficulty) AS (VALUES {', '.join(f"({i}, '{t[0]}', '{t[3]}')" for i, t in enumerate(TEMPLATES))}),
questions AS (SELECT q_id, ts, user_id, e2.template AS template, p, r, replace(replace(t, '{{p}}', p), '{{r}}', r) AS text, difficulty FROM e2 JOIN tpl ON e2.template = tpl.template)"""

# Per agreement pattern, the candidates that the samples of tiers 1 to 3 write: R the gold query, E one that
# doesn't compile, other letters mutations (see executed.LETTERS), which may give the right result all the same.
PATTERNS = [["RRRR", "RR", "RR"], ["AB", "RRR", "RRR"], ["WW", "RRR", "RRR"], ["EE", "RAR", "RRR"], ["AB", "CD", "RRRF"], ["AB", "CD", "RGHI"], ["EE", "EEE", "EEE"]]
SAMPLES = [(p, t, i, x, 100 * t + 10 * i + (7 * p + 13 * i) % 50) for p, tiers in enumerate(PATTERNS) for t, xs in enumerate(tiers, 1) for i, x in enumerate(xs, 1)]


def period_of(at: Column, calendar: bool = False, update_day: int = 10, years_back: int = 24) -> Column:
    """The month a question means by "this period": the last one that is complete on the update day (or the calendar's)."""
    late = F.lit(0) if calendar else (F.dayofmonth(at) < update_day).cast("int")
    months = (F.year(at) - years_back) * 12 + F.month(at) - 1 - late
    return (F.floor(months / 12) * 100 + months % 12 + 1).cast("string")


def sampled_results(spark: SparkSession, sf_dir: str, schema_only: bool = False) -> DataFrame:
    """q_id, tier, sample_no, status, fp, latency_ms for every question: which candidate a sample writes follows the
    question's agreement pattern; what it gives is what the candidate gave when run (fp `R` if that equals the gold result).

    schema_only: without a knowledge base an enum's meaning, the period and a metric's formula are guessed wrong.
    """
    q = questions(spark, sf_dir)
    own = F.col("template").isin(3, 9)
    q = q.select("q_id", "template", F.when(own, period_of(F.col("asked_at"))).otherwise(F.col("p")).alias("p"), F.when(own, period_of(F.col("asked_at"), calendar=True)).otherwise(F.col("p")).alias("guess"), "r", (F.col("q_id") % 7).alias("pattern"))
    known = spark.createDataFrame(SAMPLES, "pattern int, tier int, sample_no int, x string, latency_ms long")
    out = q.join(F.broadcast(known), "pattern")
    letters = F.create_map(*(F.lit(v) for kv in LETTERS.items() for v in kv))
    variant = F.element_at(letters, F.col("x"))
    variant = F.when((variant == "c") & F.col("template").isin(4, 7), "a").otherwise(variant)
    at = F.col("p")
    if schema_only:
        variant = F.when(variant != "gold", variant).when(F.col("template") == 0, "c").when(F.col("template") == 9, "a").otherwise(variant)
        at = F.when(F.col("template") == 3, F.col("guess")).otherwise(at)
    ran = candidate_results(spark, sf_dir)  # a row for each parameter value of a template: the schema bounds it, not the data
    gold = ran.where("variant = 'gold'").select("template", "p", "r", "fp")
    order = Window.partitionBy("template").orderBy("p", "r")
    first = F.first("fp").over(order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    other = gold.select("template", F.lit("c").alias("variant"), "p", "r", F.coalesce(F.lead("fp").over(order), first).alias("fp"))
    cands = ran.union(other)
    none = lambda c: F.coalesce(c, F.lit("none"))
    out = out.withColumn("variant", variant).withColumn("at", at)
    out = out.join(cands.select("template", "variant", F.col("p").alias("at"), "r", F.col("fp").alias("got")), ["template", "variant", "at", "r"], "left")
    out = out.join(gold.withColumnRenamed("fp", "want"), ["template", "p", "r"], "left")
    ok = F.lit(not broken(spark, sf_dir)) | (F.col("variant") != "e")
    fp = F.when(none(F.col("got")) == none(F.col("want")), "R").otherwise(none(F.col("got")))
    return out.select("q_id", "tier", "sample_no", F.when(ok, "ok").otherwise("error").alias("status"), F.when(ok, fp).alias("fp"), "latency_ms")


def results_sql(schema_only: bool = False) -> str:
    months = "((year(ts) - 24) * 12 + month(ts) - 1{})".format
    as_period = "CAST(CAST(floor({0} / 12) * 100 + {0} % 12 + 1 AS BIGINT) AS VARCHAR)".format
    effective, calendar = as_period(months(" - CASE WHEN day(ts) < 10 THEN 1 ELSE 0 END")), as_period(months(""))
    letter = "CASE x " + " ".join(f"WHEN '{k}' THEN '{v}'" for k, v in LETTERS.items()) + " END"
    variant = f"CASE WHEN {letter} = 'c' AND template IN (4, 7) THEN 'a' ELSE {letter} END"
    at = "p"
    if schema_only:
        variant = f"CASE WHEN {variant} <> 'gold' THEN {variant} WHEN template = 0 THEN 'c' WHEN template = 9 THEN 'a' ELSE 'gold' END"
        at = "CASE WHEN template = 3 THEN guess ELSE p END"
    return f"""{CANDIDATES_SQL}, gold AS (SELECT template, p, r, fp FROM cand WHERE variant = 'gold'),
allc AS (SELECT * FROM cand UNION ALL SELECT template, 'c', p, r, coalesce(lead(fp) OVER (PARTITION BY template ORDER BY p, r), first_value(fp) OVER (PARTITION BY template ORDER BY p, r)) FROM gold),
sm(pattern, tier, sample_no, x, latency_ms) AS (VALUES {', '.join(map(str, SAMPLES))}),
asked AS (WITH {QUESTIONS_SQL} SELECT q_id, template, r, CASE WHEN template IN (3, 9) THEN {effective} ELSE p END AS p, CASE WHEN template IN (3, 9) THEN {calendar} ELSE p END AS guess FROM questions),
smp AS (SELECT q_id, template, p, r, {at} AS at, tier, sample_no, latency_ms, {variant} AS variant FROM asked JOIN sm ON q_id % 7 = pattern),
results AS (SELECT q_id, tier, sample_no, CASE WHEN smp.variant = 'e' THEN 'error' ELSE 'ok' END AS status, latency_ms,
  CASE WHEN smp.variant = 'e' THEN NULL WHEN coalesce(allc.fp, 'none') = coalesce(gold.fp, 'none') THEN 'R' ELSE coalesce(allc.fp, 'none') END AS fp
  FROM smp LEFT JOIN allc ON allc.template = smp.template AND allc.variant = smp.variant AND allc.p = smp.at AND allc.r = smp.r LEFT JOIN gold ON gold.template = smp.template AND gold.p = smp.p AND gold.r = smp.r)"""


RESULTS_SQL = results_sql()
