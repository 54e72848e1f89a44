"""The retrieval and generation steps around providers: search over all indices, context, candidates, traces."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from kbspark.models import TextProvider, checked_json
from kbspark.operators import extract, records, serve


def search(hits: dict[str, DataFrame], kb: DataFrame, context: DataFrame) -> DataFrame:
    """q, record_id, why: the union of all indices' hits (q, record_id), kept where the record's trigger holds for the
    question's context (q and the columns that triggers name)."""
    both = None
    for why, h in hits.items():
        one = h.select("q", "record_id", F.lit(why).alias("why"))
        both = one if both is None else both.unionByName(one)
    joined = both.groupBy("q", "record_id").agg(F.array_sort(F.collect_set("why")).alias("why")).join(kb.select("record_id", "trigger", "priority"), "record_id").join(context, "q")
    kept = records.apply_triggers(joined)
    return kept.select("q", "record_id", "why", "priority")


def context(ranked: DataFrame, kb: DataFrame, k: int, fallback: DataFrame | None = None, questions: DataFrame | None = None) -> DataFrame:
    """q, context, in_scope: the composed text of each question's first k records. Questions without a hit get the
    schema's text instead, and are marked. ranked: q, rank, record_id; kb: record_id, text; fallback: one row, text."""
    top = ranked.where(F.col("rank") <= k).join(kb.select("record_id", "text"), "record_id")
    made = top.groupBy("q").agg(F.array_join(F.array_distinct(F.transform(F.sort_array(F.collect_list(F.struct("rank", "text"))), lambda r: r["text"])), "\n").alias("context"))
    if questions is None or fallback is None:
        return made.withColumn("in_scope", F.lit(True))
    out = questions.select("q").join(made, "q", "left").join(F.broadcast(fallback.select(F.col("text").alias("schema_text")).limit(1)))
    return out.select("q", F.coalesce("context", "schema_text").alias("context"), F.col("context").isNotNull().alias("in_scope"))


def generate(questions: DataFrame, provider: TextProvider, n: int) -> DataFrame:
    """q, sample_no, sql: n sampled replies to each question's prompt (q, text, context)."""
    prompt = F.concat_ws("\n", F.lit("-- sample {}"), F.coalesce("context", F.lit("")), F.concat(F.lit("question: "), "text"))
    each = questions.withColumn("sample_no", F.explode(F.array(*map(F.lit, range(1, n + 1)))))
    each = each.withColumn("prompt", F.replace(prompt, F.lit("{}"), F.col("sample_no").cast("string")))
    return provider.reply(each).select("q", "sample_no", F.col("reply").alias("sql"))


def extract_records(chunks: DataFrame, provider: TextProvider, hint: str = "") -> DataFrame:
    """doc_id, chunk_no and the records that the provider finds in each chunk, checked against the record schema."""
    asked = chunks.withColumn("prompt", F.concat(F.lit(hint), "chunk"))
    got = checked_json(provider.reply(asked), "array<struct<name:string,type:string,content:string>>")
    return got.select("doc_id", "chunk_no", F.inline("parsed")).where("name is not null")


def traces(spark: SparkSession, tuples: list[dict], write, edit, max_rounds: int = 3) -> list[dict]:
    """Reasoning traces whose SQL gives the true result: written, checked by execution, else edited with the truth and
    checked again. tuples: question, sql. write(question) and edit(question, trace, truth) give (trace, sql)."""
    out = []
    for t in tuples:
        want = serve.run_candidates(spark, [t["sql"]])[t["sql"]]
        trace, sql = write(t["question"])
        rounds = 0
        while serve.run_candidates(spark, [sql])[sql] != want and rounds < max_rounds:
            trace, sql = edit(t["question"], trace, t["sql"])
            rounds += 1
        ok = serve.run_candidates(spark, [sql])[sql] == want
        out.append(t | {"trace": trace, "trace_sql": sql, "rounds": rounds, "kept": ok})
    return out


def contrast_facts(spark: SparkSession, gold: str, pred: str) -> DataFrame:
    """What a wrong query says that the true one doesn't, and the reverse."""
    kind = "kind string, table string, column string, op string, value string"
    make = lambda sql: spark.createDataFrame(extract.facts(spark, sql), kind)
    return extract.contrast(make(gold), make(pred))


def unlabelled(questions: DataFrame, runs: dict[int, DataFrame], kb: DataFrame, votes: int) -> DataFrame:
    """record_id, votes, confirmed: entries that enough retrieval runs over unlabelled questions agree on, and whether
    the knowledge base has them. runs: run number to hits (q, record_id)."""
    both = None
    for i, h in runs.items():
        one = h.join(questions.select("q"), "q", "left_semi").select("record_id", F.lit(i).alias("run"))
        both = one if both is None else both.union(one)
    found = extract.vote(both, ["record_id"], "run", votes)
    return found.join(kb.select("record_id", F.lit(True).alias("c")).distinct(), "record_id", "left").select("record_id", "votes", F.coalesce("c", F.lit(False)).alias("confirmed"))


def as_of(experiences: DataFrame, questions: DataFrame) -> DataFrame:
    """q_id and the latest earlier experience of the same key: a union and one window, no range join."""
    e = experiences.select("key", F.col("at").alias("t"), F.col("id").alias("e_id"), F.lit(None).cast("long").alias("q_id"))
    q = questions.select("key", F.col("at").alias("t"), F.lit(None).cast("long").alias("e_id"), "q_id")
    w = Window.partitionBy("key").orderBy("t", F.col("q_id").isNull()).rowsBetween(Window.unboundedPreceding, -1)
    return e.union(q).withColumn("latest", F.last("e_id", True).over(w)).where("q_id is not null").select("q_id", "latest")


def transfers(spark: SparkSession, pairs: list[tuple[str, str]]) -> list[tuple[str, str]]:
    """Transferred queries that run and show something."""
    return [(t, s) for t, s in pairs if (r := serve.execute_sql(spark, s))["status"] == "ok" and any(any(v is not None for v in row) for row in r["rows"])]


