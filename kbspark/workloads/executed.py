"""Candidate queries that are really run: gold SQL of ten templates, mutations of it, and their results by parameter.

A template's query is written once for all its parameter values, grouped by them, so a few dozen plans answer every
candidate of every question, however many questions there are. The texts run on Spark and on DuckDB; numbers are rounded
to whole hundredths, so both name a result by the same fingerprint.
"""

from __future__ import annotations

import re
from functools import reduce

from pyspark.errors import AnalysisException, ParseException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kbspark.session import cut
from kbspark.sources.tables import table

_num = "CAST(round(100 * {}) AS BIGINT)".format
_net = "l_extendedprice * (1 - l_discount)"
_geo = "JOIN {customer} customer ON o_custkey = c_custkey JOIN {nation} nation ON c_nationkey = n_nationkey JOIN {region} region ON n_regionkey = r_regionkey"
_lines = "{lineitem} lineitem JOIN {orders} orders ON l_orderkey = o_orderkey"
_period = "year(o_orderdate) * 100 + month(o_orderdate)"
_ranked = "concat_ws('|', CAST(k AS STRING), what, CAST(v AS STRING)) AS sig"

#: template: gold SQL with columns p, r (its parameters) and sig (a row of the result).
GOLD = {
    0: f"SELECT o_orderstatus AS p, '' AS r, CAST({_num('sum(o_totalprice)')} AS STRING) AS sig FROM {{orders}} orders WHERE true GROUP BY o_orderstatus",
    1: "SELECT c_mktsegment AS p, '' AS r, CAST(count(*) AS STRING) AS sig FROM {customer} customer WHERE true GROUP BY c_mktsegment",
    2: f"SELECT p, '' AS r, {_ranked} FROM (SELECT p, what, v, row_number() OVER (PARTITION BY p ORDER BY v DESC, what) AS k FROM (SELECT CAST(year(o_orderdate) AS STRING) AS p, n_name AS what, {_num('sum(o_totalprice)')} AS v FROM {{orders}} orders {_geo} GROUP BY 1, 2) x) y WHERE k <= 5",
    3: f"SELECT CAST({_period} AS STRING) AS p, '' AS r, CAST({_num(f'sum({_net})')} AS STRING) AS sig FROM {_lines} GROUP BY 1",
    4: f"SELECT '' AS p, '' AS r, concat_ws('|', l_returnflag, CAST({_num('100 * avg(l_discount)')} AS STRING)) AS sig FROM {{lineitem}} lineitem WHERE true GROUP BY l_returnflag",
    5: "SELECT DISTINCT p_brand AS p, p_type AS r, p_name AS sig FROM {part} part WHERE true",
    6: "SELECT r_name AS p, '' AS r, concat_ws('|', n_name, CAST(count(*) AS STRING)) AS sig FROM {supplier} supplier JOIN {nation} nation ON s_nationkey = n_nationkey JOIN {region} region ON n_regionkey = r_regionkey WHERE true GROUP BY r_name, n_name",
    7: f"SELECT '' AS p, '' AS r, {_ranked} FROM (SELECT what, v, row_number() OVER (ORDER BY v DESC) AS k FROM (SELECT r_name AS what, {_num(f'sum({_net})')} AS v FROM {_lines} {_geo} GROUP BY r_name) x) y",
    8: "SELECT event_type AS p, '' AS r, concat_ws('|', CAST(CAST(ts AS DATE) AS STRING), CAST(count(*) AS STRING)) AS sig FROM {events} events WHERE true GROUP BY event_type, CAST(ts AS DATE)",
    9: (
        f"SELECT p, '' AS r, {_ranked} FROM (SELECT p, what, v, rank() OVER (PARTITION BY p ORDER BY v DESC) AS k FROM (SELECT CAST(a.m AS STRING) AS p, a.what AS what, {_num('100 * a.amt / (1.1 * b.amt)')} AS v "
        f"FROM (SELECT {_period} AS m, r_name AS what, sum({_net}) AS amt FROM {_lines} {_geo} GROUP BY 1, 2) a JOIN (SELECT {_period} AS m, r_name AS what, sum({_net}) AS amt FROM {_lines} {_geo} GROUP BY 1, 2) b ON a.what = b.what AND a.m = b.m + 100) x) y"
    ),
}
#: template: mutations of its gold SQL (a, b, d), each by one replacement: aggregate, formula, predicate, column, order, limit, distinct.
MUTATIONS = {
    0: [("sum(", "avg("), ("WHERE true", "WHERE o_orderpriority <> '5-LOW'"), ("sum(", "sum(DISTINCT ")],
    1: [("count(*)", "count(DISTINCT c_nationkey)"), ("WHERE true", "WHERE c_acctbal > 0"), ("count(*)", "count(DISTINCT c_custkey)")],
    2: [("sum(", "avg("), ("k <= 5", "k <= 10"), ("v DESC", "v ASC")],
    3: [("1 - l_discount", "1 + l_discount"), (_net, "l_extendedprice"), ("o_orderdate", "l_shipdate")],
    4: [("avg(", "max("), ("WHERE true", "WHERE l_quantity > 10"), ("l_returnflag, CAST", "'', CAST")],
    5: [("SELECT DISTINCT", "SELECT"), ("p_name AS sig", "upper(p_name) AS sig"), ("WHERE true", "WHERE p_size > 10")],
    6: [("count(*)", "count(DISTINCT s_suppkey)"), ("WHERE true", "WHERE s_acctbal > 0"), ("s_nationkey = n_nationkey", "s_nationkey = n_regionkey")],
    7: [("1 - l_discount", "1"), ("v DESC", "what"), ("sum(", "avg(")],
    8: [("count(*)", "count(DISTINCT user_id)"), ("WHERE true", "WHERE value > 1"), ("CAST(CAST(ts AS DATE) AS STRING)", "''")],
    9: [("100 * a.amt", "a.amt"), ("b.m + 100", "b.m + 1"), ("v DESC", "v ASC")],
}
BROKEN = ("o_orderdate", "order_day")  # a column that isn't there
#: Which candidate a sample's letter names: the gold query, a mutation, the gold query with another enum value, one that doesn't compile.
LETTERS = {"R": "gold", "A": "a", "B": "b", "C": "c", "D": "d", "F": "a", "G": "b", "H": "c", "I": "d", "W": "b", "E": "e"}


def statements() -> list[tuple[int, str, str]]:
    """(template, variant, SQL) of every candidate but the enum errors, which are gold results of another value."""
    made = [(t, "gold", sql) for t, sql in GOLD.items()]
    for t, changes in MUTATIONS.items():
        for name, (old, new) in zip("abd", changes, strict=True):
            if old not in GOLD[t]:
                raise ValueError(f"template {t}: nothing to replace by {new}")
            made.append((t, name, GOLD[t].replace(old, new)))
    return made


def plain_statements() -> list[tuple[int, str, str]]:
    """The same with the tables' plain names."""
    return [(t, v, _duck(sql)) for t, v, sql in statements()]


def compiles(spark: SparkSession, sql: str, tables: dict[str, DataFrame]) -> bool:
    try:
        spark.sql(sql, **tables).schema  # noqa: B018
        return True
    except (AnalysisException, ParseException):
        return False


_KEPT: dict[tuple[str, str], DataFrame] = {}  # by application and tables: a row for each parameter value and variant


def candidate_results(spark: SparkSession, sf_dir: str) -> DataFrame:
    """template, variant, p, r, fp: what every candidate query gives for each parameter value. Run once a session."""
    at = (spark.sparkContext.applicationId, sf_dir)
    if at in _KEPT:
        return _KEPT[at]

    def one(t: int, variant: str, sql: str) -> DataFrame:
        used = {n: table(spark, sf_dir, n) for n in set(re.findall(r"\{(\w+)\}", sql))}
        rows = spark.sql(sql, **used).groupBy("p", "r").agg(F.md5(F.array_join(F.sort_array(F.collect_list("sig")), ";").cast("binary")).alias("fp"))
        return rows.select(F.lit(t).alias("template"), F.lit(variant).alias("variant"), "p", "r", "fp")

    ran = cut(reduce(DataFrame.union, [one(*s) for s in statements()]))
    _KEPT[at] = ran
    return ran


def broken(spark: SparkSession, sf_dir: str) -> bool:
    """Whether the candidate that names an unknown column is turned down before it runs."""
    sql = GOLD[3].replace(*BROKEN)
    return not compiles(spark, sql, {n: table(spark, sf_dir, n) for n in ("lineitem", "orders")})


def _duck(sql: str) -> str:
    return re.sub(r"\{(\w+)\}", r"\1", sql)


CANDIDATES_SQL = "cand AS (" + " UNION ALL ".join(f"SELECT {t} AS template, '{v}' AS variant, p, r, md5(string_agg(sig, ';' ORDER BY sig)) AS fp FROM ({_duck(sql)}) GROUP BY p, r" for t, v, sql in statements()) + ")"
