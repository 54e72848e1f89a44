"""SQL serving: canonical results, execution, majority vote, cascade, refinement."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor

from pyspark.errors import AnalysisException, ParseException
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def canonical(df: DataFrame) -> DataFrame:
    """cells: a row's values as text without column names; numbers to 6 places, times ISO, null a token."""

    def cell(c: str, kind: str) -> Column:
        x = F.col(f"`{c}`")
        if kind in ("double", "float") or kind.startswith("decimal"):
            x = F.regexp_replace(F.round(x.cast("double"), 6).cast("decimal(38,6)").cast("string"), r"\.?0+$", "")
        elif kind in ("timestamp", "timestamp_ntz", "date"):
            x = F.date_format(x, "yyyy-MM-dd'T'HH:mm:ss")
        return F.coalesce(x.cast("string"), F.lit("<null>"))

    return df.select(F.array(*(cell(c, k) for c, k in df.dtypes)).alias("cells"))


def fingerprint(df: DataFrame, ordered: bool = False) -> DataFrame:
    """One row: fp, a hash of the result as a bag of rows (cells as sets), and n_rows. Nothing is collected."""
    rows = canonical(df).select(F.xxhash64(F.array_join(F.array_sort("cells"), "\x1f")).alias("h"))
    return rows.agg(F.concat_ws(":", F.count(F.lit(1)).cast("string"), F.coalesce(F.sum(F.col("h").cast("decimal(38,0)")), F.lit(0)).cast("string"), F.coalesce(F.bit_xor("h"), F.lit(0)).cast("string")).alias("fp"), F.count(F.lit(1)).alias("n_rows"))


def execute_sql(spark: SparkSession, sql: str, max_rows: int = 20, max_cell: int = 80, stats: bool = True) -> dict:
    """Status, schema, a cut view of the rows, whether it was cut, the total, and the error's class and message.

    Rows come from a limit of one more than are shown; the total is an aggregate of its own, so the limit never
    distorts it. A query that doesn't compile reads nothing.
    """
    try:
        df = spark.sql(sql)
        kinds = [(f.name, f.dataType.simpleString()) for f in df.schema.fields]
        shown = df.limit(max_rows + 1).collect()
        rows = [[None if v is None else str(v)[:max_cell] for v in r] for r in shown[:max_rows]]
        total = df.agg(F.count(F.lit(1))).first()[0] if stats and len(shown) > max_rows else len(shown)
        return {"status": "ok", "schema": kinds, "rows": rows, "cut": len(shown) > max_rows, "total": total, "error_class": None, "message": None}
    except (AnalysisException, ParseException) as e:
        return {"status": "invalid", "schema": [], "rows": [], "cut": False, "total": 0, "error_class": e.getCondition(), "message": str(e).split("\n")[0][:200]}
    except Exception as e:  # a run-time failure of a candidate is a result too
        return {"status": "failed", "schema": [], "rows": [], "cut": False, "total": 0, "error_class": type(e).__name__, "message": str(e).split("\n")[0][:200]}


def run_candidates(spark: SparkSession, texts: list[str], threads: int = 4) -> dict[str, tuple[str, str | None]]:
    """status and fingerprint of each distinct text; invalid ones are found before anything runs.

    The texts are distinct SQL statements, a driver-sized list; each runs as a job of its own.
    """

    def one(sql: str) -> tuple[str, str | None]:
        try:
            return "ok", fingerprint(spark.sql(sql)).first()["fp"]
        except (AnalysisException, ParseException) as e:
            return f"invalid:{e.getCondition()}", None
        except Exception as e:
            return f"failed:{type(e).__name__}", None

    distinct = sorted(set(texts))
    with ThreadPoolExecutor(threads) as pool:
        return dict(zip(distinct, pool.map(one, distinct), strict=True))


def vote(results: DataFrame, n: int = 8, tie: str = "first") -> DataFrame:
    """q_id, fp, votes: the most frequent result among the first n samples that ran. Ties: the first sample, the
    shortest SQL, or the highest tier. results: q_id, tier, sample_no, status, fp (and sql for `shortest`)."""
    order = {"first": F.struct("tier", "sample_no"), "shortest": F.struct(F.length("sql") if "sql" in results.columns else F.lit(0), "tier", "sample_no"), "tier": F.struct((-F.col("tier")).alias("t"), "sample_no")}[tie]
    seq = F.row_number().over(Window.partitionBy("q_id").orderBy("tier", "sample_no"))
    ran = results.withColumn("__seq", seq).where((F.col("__seq") <= n) & (F.col("status") == "ok"))
    by = ran.groupBy("q_id", "fp").agg(F.count(F.lit(1)).alias("votes"), F.min(order).alias("__o"))
    best = Window.partitionBy("q_id").orderBy(F.desc("votes"), "__o")
    return by.withColumn("r", F.row_number().over(best)).where("r = 1").select("q_id", "fp", "votes")


def cascade(results: DataFrame, mode: str = "staged") -> DataFrame:
    """q_id, fp, tier, samples_used, agreed: stops at the first two equal results.

    staged: tier by tier, samples in order; a tier's samples run together, so all of a tier that was begun count as
    used. race: all tiers start together and finish in the order of latency_ms. Without agreement the last tier's
    first valid sample is taken.
    """
    order = ["tier", "sample_no"] if mode == "staged" else ["latency_ms", "tier", "sample_no"]
    w = Window.partitionBy("q_id").orderBy(*order)
    same = Window.partitionBy("q_id", "fp").orderBy(*order)
    seen = results.withColumn("seq", F.row_number().over(w)).withColumn("nth", F.when(F.col("status") == "ok", F.row_number().over(Window.partitionBy("q_id", "fp", "status").orderBy(*order))))
    hit = seen.where("nth = 2").groupBy("q_id").agg(F.min(F.struct("seq", "fp", "tier")).alias("hit"))
    last = seen.where("status = 'ok'").groupBy("q_id").agg(F.min(F.struct((-F.col("tier")).alias("t"), "sample_no", "fp", "tier")).alias("last"))
    total = seen.groupBy("q_id").agg(F.count(F.lit(1)).alias("n"))
    out = total.join(hit, "q_id", "left").join(last, "q_id", "left")
    agreed = F.col("hit").isNotNull()
    return out.select("q_id", F.when(agreed, F.col("hit.fp")).otherwise(F.col("last.fp")).alias("fp"), F.when(agreed, F.col("hit.tier")).otherwise(F.col("last.tier")).alias("tier"), F.when(agreed, F.col("hit.seq")).otherwise(F.col("n")).cast("long").alias("samples_used"), agreed.alias("agreed"))


def close_name(name: str, known: list[str]) -> str | None:
    """The known name nearest by edit distance, if it is near enough."""
    import difflib

    found = difflib.get_close_matches(name, known, 1, 0.7)
    return found[0] if found else None


def refine(spark: SparkSession, sql: str, names: list[str], rounds: int = 3) -> tuple[str, list[str]]:
    """A repaired query and its trail: an unknown column or table is replaced by the closest known name."""
    import re

    trail: list[str] = []
    for _ in range(rounds):
        got = execute_sql(spark, sql, stats=False)
        trail.append(got["error_class"] or got["status"])
        if got["status"] == "ok":
            break
        bad = re.search(r"`(\w+)`(?! cannot be found in)", got["message"] or "")
        new = close_name(bad[1], names) if bad else None
        if not new:
            break
        sql = re.sub(rf"\b{bad[1]}\b", new, sql)
    return sql, trail
