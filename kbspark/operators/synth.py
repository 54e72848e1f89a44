"""Query augmentation: commented SQL, composition, decomposition, transfer, mutations."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kbspark.functions.finance import money
from kbspark.sources.tables import table


def strip(sql: str) -> str:
    return re.sub(r"--[^\n]*|/\*.*?\*/", " ", sql, flags=re.S).strip()


def result_schema(spark: SparkSession, sql: str) -> list[tuple[str, str]]:
    """Names and types of a query's columns: analysis only, nothing runs."""
    return [(f.name, f.dataType.simpleString()) for f in spark.sql(sql).schema.fields]


NOTES = {"SELECT": "what is shown", "FROM": "where it comes from", "WHERE": "which rows count", "GROUP BY": "one row for each", "HAVING": "which groups count", "ORDER BY": "the order matters", "LIMIT": "only so many"}


def profile(spark: SparkSession, question: str, sql: str, knowledge: list[str] = (), asked_at: str = "", user: str = "", level: str = "full") -> str:
    """The query with a header and a comment for each clause. Comments only: the stripped text is the query itself."""
    head = [f"-- question: {question}"]
    if level == "full":
        head += [f"-- asked at {asked_at} by {user}" if asked_at or user else "-- asked at any time"]
        head += ["-- result: " + ", ".join(f"{n} {k}" for n, k in result_schema(spark, sql))]
        head += [f"-- knows: {k}" for k in knowledge]
        head += ["-- corner cases: nulls count as 0 in sums; a zero base gives 0"]
    body = sql
    if level == "full":
        for word, note in NOTES.items():
            body = re.sub(rf"(?<![\w']){word}(?![\w'])", f"\n/* {note} */ {word}", body, count=1)
    return "\n".join([*head, body.strip()])


def same_plan(spark: SparkSession, a: str, b: str) -> bool:
    parse = spark._jsparkSession.sessionState().sqlParser().parsePlan
    shape = lambda sql: re.sub(r"#\d+L?", "", parse(sql).treeString())
    return shape(a) == shape(b)


def simplify(sql: str) -> list[str]:
    """Simpler queries: one for each value of an IN list, and one without each conjunct."""
    out = []
    m = re.search(r"(\w+) IN \(([^)]*)\)", sql)
    if m:
        out += [sql.replace(m[0], f"{m[1]} = {v.strip()}") for v in m[2].split(",")]
    where = re.search(r"WHERE (.*?)(?= GROUP BY| ORDER BY| LIMIT|$)", sql, re.S)
    if where and " AND " in where[1]:
        parts = where[1].split(" AND ")
        out += [sql.replace(where[1], " AND ".join(p for j, p in enumerate(parts) if j != i)) for i in range(len(parts))]
    return out


def compose(a: str, b: str, using: list[str], expr: str, name: str, how: str = "JOIN") -> str:
    """Two queries of one grain as the parts of a third."""
    keys = ", ".join(using)
    if how == "UNION":
        return f"WITH a AS ({a}), b AS ({b}) SELECT * FROM a UNION ALL SELECT * FROM b"
    return f"WITH a AS ({a}), b AS ({b}) SELECT {keys}, {expr} AS {name} FROM a {how} b USING ({keys})"


STAR = "lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def views(spark: SparkSession, sf_dir: str, names: list[str]) -> None:
    for t in names:
        table(spark, sf_dir, t).createOrReplaceTempView(t)


def run_composed(spark: SparkSession, sf_dir: str) -> DataFrame:
    views(spark, sf_dir, ["lineitem", "orders", "customer", "nation", "region"])
    a = f"SELECT r_name AS region, sum(l_extendedprice * (1 - l_discount)) AS revenue FROM {STAR} GROUP BY r_name"
    b = f"SELECT r_name AS region, sum(l_extendedprice * l_tax) AS tax FROM {STAR} GROUP BY r_name"
    return spark.sql(compose(a, b, ["region"], "revenue - tax", "profit")).select("region", money("profit").alias("profit"))


def run_decomposed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The parts of an IN question and the whole."""
    views(spark, sf_dir, ["orders"])
    whole = "SELECT count(*) AS n FROM orders WHERE o_orderpriority IN ('1-URGENT', '2-HIGH', '3-MEDIUM')"
    out = spark.sql(whole).select(F.lit("all").alias("part"), "n")
    for s in simplify(whole):
        out = out.union(spark.sql(s).select(F.lit(re.search(r"= '([^']*)'", s)[1]).alias("part"), "n"))
    return out.where("n > 0")


def independent(df: DataFrame, columns: list[tuple[str, int]]) -> DataFrame:
    """Predicate pairs of different ontology groups with a non-empty result: one aggregation over the pair, so only
    pairs that occur are made. columns: (name, group id)."""
    out = None
    for i, (x, gx) in enumerate(columns):
        for y, gy in columns[i + 1 :]:
            if gx == gy:
                continue
            one = df.groupBy(x, y).agg(F.count(F.lit(1)).alias("n")).select(F.concat(F.lit(f"{x}="), x).alias("a"), F.concat(F.lit(f"{y}="), y).alias("b"), "n")
            out = one if out is None else out.union(one)
    return out


def transfer(skeleton: str, bindings: list[dict[str, str]]) -> list[tuple[str, str]]:
    """The skeleton's holes filled with each binding: (target, sql)."""
    return [(f"{b['table']}.{b['column']}", skeleton.format(**b)) for b in bindings]


def run_transfer(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A count by category carried over to other tables; results without rows are dropped."""
    bindings = [{"table": t, "column": c} for t, c in (("customer", "c_mktsegment"), ("orders", "o_orderpriority"), ("part", "p_brand"), ("events", "event_type"))]
    views(spark, sf_dir, [b["table"] for b in bindings])
    out = None
    for target, sql in transfer("SELECT {column} AS k, count(*) AS n FROM {table} GROUP BY {column}", bindings):
        one = spark.sql(sql).agg(F.count(F.lit(1)).alias("n_rows")).select(F.lit(target).alias("target"), "n_rows")
        out = one if out is None else out.union(one)
    return out.where("n_rows > 0")


def paraphrase(text: str) -> list[str]:
    """Baseline: the wording changes, the question doesn't."""
    swaps = [("how many", "count of"), ("top", "best"), ("total", "overall"), ("list", "show"), ("per", "for each")]
    return [text.replace(a, b) for a, b in swaps if a in text] or [f"please: {text}"]


def mutations() -> list[tuple[str, str, str]]:
    """(mutation, gold, changed): each should be put in its own class."""
    share = "SELECT n_name, avg(c_acctbal) / 1000 AS v FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name"
    part = "SELECT p_name, p_mfgr, coalesce(p_size, 0) AS s FROM part"
    g = "SELECT DISTINCT p_name, p_size FROM part WHERE p_brand = 'Brand#11' AND p_type = 'ECONOMY STEEL' ORDER BY p_name, p_size LIMIT 5"
    return [
        ("drop_predicate", g, g.replace(" AND p_type = 'ECONOMY STEEL'", "")),
        ("add_predicate", g, g.replace(" ORDER", " AND p_size > 3 ORDER")),
        ("swap_enum", g, g.replace("ECONOMY STEEL", "SMALL BRASS")),
        ("swap_column", g, g.replace("p_type =", "p_mfgr =")),
        ("bad_format", g.replace("p_type = 'ECONOMY STEEL'", "period = '199912'"), g.replace("p_type = 'ECONOMY STEEL'", "period = '1999-12'")),
        ("extra_column", g, g.replace("p_size FROM", "p_size, p_retailprice FROM")),
        ("drop_distinct", g, g.replace("DISTINCT ", "")),
        ("no_limit", g, g.replace(" LIMIT 5", "")),
        ("syntax", g, g.replace("FROM part", "FORM part x y")),
        ("ratio_as_percent", share.replace("/ 1000", ""), share.replace("/ 1000", "* 100")),
        ("other_unit", share, share.replace("/ 1000", "/ 100")),
        ("sum_for_avg", share, share.replace("avg(", "sum(")),
        ("null_kept", part, part.replace("coalesce(p_size, 0)", "p_size")),
        ("null_dropped", part, part + " WHERE p_size IS NOT NULL"),
        ("concatenated", part, part.replace("p_name, p_mfgr", "concat(p_name, p_mfgr)")),
        ("same", g, g),
    ]
