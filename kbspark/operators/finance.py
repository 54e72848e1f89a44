"""The finance workload: a ledger over the star tables, its dense grid, the wide form, budget and user profiles."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from kbspark.functions import finance as ff
from kbspark.sources.tables import table

# Conversion rates by currency.
RATES = {"usd": 1.0, "eur": 0.9, "gbp": 0.8}
MEASURES = ["ptd", "ytd", "py_ptd", "py_ytd", "budget", "py_budget", "qtd", "fcst", "var", "lag1", "avg12"]


def ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    """period, region, nation, segment, brand, ptype, amt_a, amt_b, tax: one row a line item. Small dimensions
    are left to the optimizer to broadcast; the two large tables meet in one join."""
    li = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_extendedprice", "l_discount", "l_tax")
    od = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_orderdate")
    cu = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", "c_mktsegment")
    na, re = table(spark, sf_dir, "nation"), table(spark, sf_dir, "region")
    pa = table(spark, sf_dir, "part").select("p_partkey", "p_brand", "p_type")
    star = li.join(od, F.col("l_orderkey") == F.col("o_orderkey")).join(cu, F.col("o_custkey") == F.col("c_custkey"))
    star = star.join(na, F.col("c_nationkey") == F.col("n_nationkey")).join(re, F.col("n_regionkey") == F.col("r_regionkey")).join(pa, F.col("l_partkey") == F.col("p_partkey"))
    b = F.col("l_extendedprice") * (1 - F.col("l_discount"))
    return star.select(
        ff.period(F.col("o_orderdate")).alias("period"), F.col("r_name").alias("region"), F.col("n_name").alias("nation"), F.col("c_mktsegment").alias("segment"),
        F.col("p_brand").alias("brand"), F.col("p_type").alias("ptype"), F.col("c_custkey").alias("custkey"), F.col("l_extendedprice").alias("amt_a"), b.alias("amt_b"), (b * F.col("l_tax")).alias("tax"),
    )


def periods(spark: SparkSession, first: str = "1995-01-01", last: str = "2001-08-01") -> DataFrame:
    months = spark.range(1).select(F.explode(F.sequence(F.lit(first).cast("date"), F.lit(last).cast("date"), F.expr("interval 1 month"))).alias("m"))
    return months.select(ff.period(F.col("m")).alias("period"))


def grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """region, nation, segment, period, amt_a, amt_b with every month of every entity; absent ones are 0."""
    led = ledger(spark, sf_dir).groupBy("region", "nation", "segment", "period").agg(F.sum("amt_a").alias("a"), F.sum("amt_b").alias("b"))
    na, re = table(spark, sf_dir, "nation"), table(spark, sf_dir, "region")
    seg = table(spark, sf_dir, "customer").select(F.col("c_mktsegment").alias("segment")).distinct()
    # Entities times months: both are dimension-sized, whatever the ledger's size.
    cells = na.join(re, F.col("n_regionkey") == F.col("r_regionkey")).select(F.col("r_name").alias("region"), F.col("n_name").alias("nation")).crossJoin(seg).crossJoin(periods(spark))
    out = cells.join(led, ["region", "nation", "segment", "period"], "left")
    return out.select("region", "nation", "segment", "period", F.coalesce("a", F.lit(0.0)).alias("amt_a"), F.coalesce("b", F.lit(0.0)).alias("amt_b"))


def entity_window() -> Window:
    return Window.partitionBy("region", "nation", "segment").orderBy("period")


def measures(df: DataFrame, amount: str, prefix: str) -> DataFrame:
    """The eleven measures of one amount as columns prefix_measure."""
    w = entity_window()
    year = F.substring("period", 1, 4)
    in_year = Window.partitionBy("region", "nation", "segment", year).orderBy("period").rowsBetween(Window.unboundedPreceding, 0)
    quarter = F.floor((F.substring("period", 5, 2).cast("int") - 1) / 3)
    in_quarter = Window.partitionBy("region", "nation", "segment", year, quarter).orderBy("period").rowsBetween(Window.unboundedPreceding, 0)
    v = F.col(amount)
    lag = lambda c, n: F.coalesce(F.lag(c, n).over(w), F.lit(0.0))
    df = df.withColumns({
        f"{prefix}_ptd": v, f"{prefix}_ytd": F.sum(v).over(in_year), f"{prefix}_py_ptd": lag(v, 12), f"{prefix}_budget": lag(v, 12) * 1.05, f"{prefix}_py_budget": lag(v, 24) * 1.05,
        f"{prefix}_qtd": F.sum(v).over(in_quarter), f"{prefix}_fcst": F.coalesce(F.avg(v).over(w.rowsBetween(-3, -1)), F.lit(0.0)), f"{prefix}_lag1": lag(v, 1), f"{prefix}_avg12": F.avg(v).over(w.rowsBetween(-11, 0)),
    })
    return df.withColumns({f"{prefix}_py_ytd": F.coalesce(F.lag(f"{prefix}_ytd", 12).over(w), F.lit(0.0)), f"{prefix}_var": v - F.col(f"{prefix}_budget")})


def wide(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The wide ledger: 5 keys and 66 measure columns named currency_measure_caliber."""
    g = measures(measures(grid(spark, sf_dir), "amt_a", "a"), "amt_b", "b")
    cols = [(F.col(f"{cal}_{m}") * rate).alias(f"{cur}_{m}_{cal}") for cur, rate in RATES.items() for cal in "ab" for m in MEASURES]
    fiscal = F.substring("period", 1, 4).cast("int") + (F.substring("period", 5, 2).cast("int") >= 4).cast("int")
    return g.select("period", fiscal.alias("fiscal_year"), "region", "nation", "segment", *cols)


def dept_view(spark: SparkSession, sf_dir: str, dept: int) -> DataFrame:
    """A department's slice of the ledger: one of 8 buckets of brands."""
    return ledger(spark, sf_dir).where(F.regexp_extract("brand", r"(\d+)", 1).cast("int") % 8 == dept)


def user_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    users = table(spark, sf_dir, "events").select("user_id").distinct()
    cu, na, re = table(spark, sf_dir, "customer"), table(spark, sf_dir, "nation"), table(spark, sf_dir, "region")
    u = users.join(cu, F.col("user_id") == F.col("c_custkey")).join(na, F.col("c_nationkey") == F.col("n_nationkey")).join(re, F.col("n_regionkey") == F.col("r_regionkey"))
    currency = F.when(F.col("r_name") == "EUROPE", "eur").when(F.col("r_name") == "AFRICA", "gbp").otherwise("usd")
    role = F.element_at(F.array(*map(F.lit, ("analyst", "staff", "executive"))), (F.col("user_id") % 3 + 1).cast("int"))
    return u.select("user_id", currency.alias("currency"), F.lit("b").alias("caliber"), F.concat_ws(" >> ", "r_name", "n_name").alias("region_path"), (F.col("user_id") % 8).cast("int").alias("department"), role.alias("role"))


def resolve(questions: DataFrame, profiles: DataFrame) -> DataFrame:
    """Adds currency, caliber, region, nation and department: what the text names wins over the profile."""
    named = F.lower(F.regexp_extract("text", r"(?i)\b(usd|eur|gbp)\b", 1))
    parts = F.split("region_path", " >> ")
    out = questions.join(profiles.drop("role"), "user_id", "left")
    return out.withColumn("currency", F.when(named != "", named).otherwise(F.coalesce("currency", F.lit("usd")))).withColumns({"region": parts[0], "nation": parts[1]})


def route(df: DataFrame, measure: str, currency: str | Column, caliber: str | Column) -> Column:
    """The one column that answers for a currency and caliber. Per-row choices pick from the columns that can apply."""
    if isinstance(currency, str) and isinstance(caliber, str):
        return F.col(f"{currency}_{measure}_{caliber}")
    out = F.lit(None).cast("double")
    for cur in RATES:
        for cal in "ab":
            out = F.when((currency == cur) & (caliber == cal), F.col(f"{cur}_{measure}_{cal}")).otherwise(out)
    return out


def metric_by_period(old: Column, new: Column, period: Column, cut: str) -> Column:
    return F.when(period < cut, old).otherwise(new)
