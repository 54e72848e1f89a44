"""Experiments that compare methods: dictionary scale, curation, generation from providers, costs, lineage."""

from __future__ import annotations

import time

from pyspark.sql import functions as F

from kbspark.models import RuleProvider, definition_rule
from kbspark.operators import curate, dictionary, extract, measure, records, retrieve
from kbspark.registry import query
from kbspark.session import keep, rest
from kbspark.sources.tables import table
from kbspark.workloads.index_queries import phrases, question_hits
from kbspark.workloads.questions import QUESTIONS_SQL, RESULTS_SQL, questions, sampled_results
from kbspark.workloads.record_queries import enum_kb
from kbspark.workloads.tool_queries import scanned_columns


def dictionary_scale(spark, sf_dir, sizes=(100, 10_000, 50_000), kinds=("double", "trie"), part=dictionary.PART):
    """kind, patterns, hits, build_seconds, match_seconds, bytes: filler patterns are added to the benchmark's phrases;
    the phrases' hits stay the same and matching time stays flat. The size None takes all distinct words of the documents.
    More than `part` patterns are in several automata, built by tasks; bytes are those of all."""
    base = phrases(spark, sf_dir)
    filler = table(spark, sf_dir, "documents").select(F.explode(F.split(F.lower("text"), r"[^\p{L}]+")).alias("w")).where("length(w) > 3").distinct()
    filler = keep(filler, "filler").orderBy("w")
    rest(spark)
    rows = []
    docs = keep(dictionary.tokens(table(spark, sf_dir, "documents"), "text"), "tokens")
    for n in sizes:
        # Numbered down in the order of the words, without gathering them.
        more = (filler if n is None else filler.limit(n)).select((-F.monotonically_increasing_id() - 1).alias("record_id"), F.concat("w", F.lit(" qqq")).alias("synonym"))
        synonyms = keep(base.union(more), "synonyms")
        rest(spark)
        for kind in kinds:
            t, patterns, size, hits = time.time(), 0, 0, 0
            places, automata = dictionary.build_parts(synonyms, kind, part)
            built, t = time.time() - t, time.time()
            sent = spark.sparkContext.broadcast(places)
            near = keep(dictionary.near_matches(docs, sent), "near")
            sent.destroy()
            for some in automata:
                patterns, size = patterns + sum(a.patterns for a in some), size + sum(a.size for a in some)
                sent = spark.sparkContext.broadcast([a.packed for a in some])
                hits += dictionary.count_matches(near, sent)
                sent.destroy()
            matched = time.time() - t
            rows.append((kind, patterns, hits, built, matched, size))
    return spark.createDataFrame(rows, "kind string, patterns int, hits long, build_seconds double, match_seconds double, bytes long")


@query(key="dictionary_scale")
def dictionary_scale_query(spark, sf_dir):
    return dictionary_scale(spark, sf_dir, (100, 5_000, None)).select("kind", "patterns", "hits", "bytes")


@query(f"WITH {RESULTS_SQL} SELECT tier, round(count(*) FILTER (status = 'ok') / count(*), 6) AS valid FROM results GROUP BY tier")
def valid_rate(spark, sf_dir):
    return measure.valid_rate(sampled_results(spark, sf_dir))


@query(f"WITH {RESULTS_SQL} SELECT tier, count(*) AS samples, quantile_cont(latency_ms, 0.5) AS p50, round(avg(latency_ms), 3) AS mean FROM results GROUP BY tier")
def cost_summary(spark, sf_dir):
    return measure.cost(sampled_results(spark, sf_dir))


@query("""WITH d AS (SELECT event_type AS c, [CAST(nullif(user_id % 2, 0) AS VARCHAR)] AS cells FROM events) SELECT round(avg(ok), 6) AS meaningful FROM (SELECT c, max(CASE WHEN cells[1] IS NOT NULL THEN 1 ELSE 0 END) AS ok FROM d GROUP BY c)""")
def meaningful_share(spark, sf_dir):
    e = table(spark, sf_dir, "events")
    cell = F.coalesce(F.when(F.col("user_id") % 2 != 0, (F.col("user_id") % 2).cast("string")), F.lit("<null>"))
    return measure.meaningful(e.select(F.col("event_type").alias("case"), F.array(cell).alias("cells")))


@query("""WITH RECURSIVE p AS (SELECT p_partkey AS id, p_partkey // 3 AS parent FROM part WHERE p_partkey > 2), w(id, a, hop) AS (SELECT id, parent, 1 FROM p UNION SELECT w.id, p.parent, hop + 1 FROM w JOIN p ON w.a = p.id WHERE hop < 4)
SELECT id AS record_id, a AS ancestor, min(hop) AS hop FROM w GROUP BY ALL""")
def lineage_trace(spark, sf_dir):
    p = table(spark, sf_dir, "part").select(F.col("p_partkey").cast("string").alias("record_id"), F.floor(F.col("p_partkey") / 3).cast("string").alias("parent"), "p_partkey")
    r = p.withColumn("parents", F.when(F.col("p_partkey") > 2, F.create_map(F.lit("from"), "parent")).otherwise(F.create_map().cast("map<string,string>")))
    out = records.lineage(r, r, 4)
    return out.select(F.col("record_id").cast("long").alias("record_id"), F.col("ancestor").cast("long").alias("ancestor"), "hop")


@query("""WITH t AS (SELECT event_id AS id, event_id % 9 AS h, value AS q, 1.0 / (1 + event_id % 13) AS v FROM events), s AS (SELECT * FROM t ORDER BY round(h + 0.1 * q + v, 6) DESC, id LIMIT 50), b AS (SELECT * FROM t ORDER BY q DESC, id LIMIT 50)
SELECT 'scored' AS method, round(avg(h), 6) AS hardness, round(avg(v), 6) AS variety FROM s UNION ALL SELECT 'quality_only', round(avg(h), 6), round(avg(v), 6) FROM b""")
def curation_compare(spark, sf_dir):
    """Mean hardness and variety of what each way of selection takes."""
    t = table(spark, sf_dir, "events").select(F.col("event_id").alias("id"), (F.col("event_id") % 9).alias("h"), F.col("value").alias("q"), (1.0 / (1 + F.col("event_id") % 13)).alias("v"))
    of = lambda df, name: df.agg(F.round(F.avg("h"), 6).alias("hardness"), F.round(F.avg("v"), 6).alias("variety")).select(F.lit(name).alias("method"), "hardness", "variety")
    return of(curate.select(t, 50), "scored").union(of(t.orderBy(F.desc("q"), "id").limit(50), "quality_only"))


@query()
def curation_random(spark, sf_dir):
    t = table(spark, sf_dir, "events").select(F.col("event_id").alias("id"), (F.col("event_id") % 9).alias("h"))
    return curate.random_choice(t, 50)


@query(f"WITH {QUESTIONS_SQL} SELECT q_id AS q, sample_no, 'SELECT ' || template || ' -- ' || sample_no AS sql FROM questions, (VALUES (1), (2)) s(sample_no)")
def generate_candidates(spark, sf_dir):
    """The generation step with a rule in the model's place."""
    q = questions(spark, sf_dir).select(F.col("q_id").alias("q"), F.col("template").cast("string").alias("text"), F.lit("known").alias("context"))

    def rule(prompt: str) -> str:
        sample, text = prompt.split("\n")[0].split()[-1], prompt.split("question: ")[-1]
        return f"SELECT {text} -- {sample}"

    return retrieve.generate(q, RuleProvider(rule), 2)


@query()
def extract_structured(spark, sf_dir):
    """Records that the rule provider finds in document chunks, and two fixture lines among them."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    more = spark.createDataFrame([(-1, "margin = revenue - cost\nGMV means gross value")], "doc_id long, text string")
    return retrieve.extract_records(extract.chunk(docs.union(more)), RuleProvider(definition_rule))


@query()
def autonomous_search(spark, sf_dir):
    """q, record_id, why, priority: dictionary hits whose trigger holds for the question's user."""
    kb = enum_kb(spark, sf_dir).withColumn("trigger", F.when(F.col("col") == "r_name", F.lit("user_id % 2 = 0"))).select("record_id", "name", "trigger", "priority")
    hits = question_hits(spark, sf_dir).select(F.col("q_id").alias("q"), F.col("value").alias("name")).join(kb.select("record_id", "name"), "name")
    ctx = questions(spark, sf_dir).select(F.col("q_id").alias("q"), "user_id")
    return retrieve.search({"dictionary": hits}, kb, ctx).withColumn("why", F.array_join("why", ","))


@query("SELECT e.event_id AS q_id, (SELECT max(p.event_id) FROM events p WHERE p.event_type = e.event_type AND p.event_id % 2 = 0 AND p.ts < e.ts) AS latest FROM events e WHERE e.event_id % 2 = 1")
def asof_experience(spark, sf_dir):
    e = table(spark, sf_dir, "events").select(F.col("event_type").alias("key"), F.col("ts").alias("at"), "event_id")
    return retrieve.as_of(e.where("event_id % 2 = 0").withColumnRenamed("event_id", "id"), e.where("event_id % 2 = 1").withColumnRenamed("event_id", "q_id"))


@query("SELECT count(*) AS n_columns FROM (VALUES (2), (3), (5), (4), (6), (6), (11), (6)) t(n), range(0, n)", key="catalog_columns")
def catalog_columns(spark, sf_dir):
    return scanned_columns(spark, sf_dir).agg(F.count(F.lit(1)).alias("n_columns"))
