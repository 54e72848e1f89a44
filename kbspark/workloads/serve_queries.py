"""Queries on voting, cascades, measures, curation and the published tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kbspark.operators import curate, extract, measure, rowmatch, serve
from kbspark.operators import synth
from kbspark.registry import query
from kbspark.sources.tables import catalog, enum_values, table
from kbspark.workloads import executed
from kbspark.workloads.questions import QUESTIONS_SQL, RESULTS_SQL, period_of, questions, results_sql, sampled_results

VOTE = f"""{RESULTS_SQL}, v AS (SELECT q_id, fp, count(*) AS votes, min(tier * 100 + sample_no) AS o FROM results WHERE status = 'ok' GROUP BY ALL),
vw AS (SELECT q_id, fp, votes FROM (SELECT *, row_number() OVER (PARTITION BY q_id ORDER BY votes DESC, o) AS r FROM v) WHERE r = 1)"""
CASC = f"""{RESULTS_SQL}, s AS (SELECT *, row_number() OVER (PARTITION BY q_id ORDER BY tier, sample_no) AS seq, row_number() OVER (PARTITION BY q_id, fp, status ORDER BY tier, sample_no) AS nth FROM results),
hit AS (SELECT q_id, min(seq) AS seq FROM s WHERE status = 'ok' AND nth = 2 GROUP BY q_id), la AS (SELECT q_id, max(tier) AS tier FROM s WHERE status = 'ok' GROUP BY q_id),
lf AS (SELECT s.q_id, arg_min(fp, sample_no) AS fp, any_value(s.tier) AS tier FROM s JOIN la ON s.q_id = la.q_id AND s.tier = la.tier WHERE status = 'ok' GROUP BY s.q_id),
cw AS (SELECT t.q_id, coalesce(h.fp, lf.fp) AS fp, coalesce(h.tier, lf.tier) AS tier, coalesce(hit.seq, t.n) AS samples_used, hit.seq IS NOT NULL AS agreed
 FROM (SELECT q_id, count(*) AS n FROM s GROUP BY q_id) t LEFT JOIN hit ON t.q_id = hit.q_id LEFT JOIN s h ON h.q_id = hit.q_id AND h.seq = hit.seq LEFT JOIN lf ON lf.q_id = t.q_id)"""


@query(f"WITH {VOTE} SELECT * FROM vw")
def vote_winner(spark, sf_dir):
    return serve.vote(sampled_results(spark, sf_dir))


@query(f"WITH {CASC} SELECT * FROM cw")
def cascade_winner(spark, sf_dir):
    return serve.cascade(sampled_results(spark, sf_dir))


@query()
def cascade_race(spark, sf_dir):
    return serve.cascade(sampled_results(spark, sf_dir), "race")


@query(f"WITH {CASC} SELECT count(*) AS questions, round(avg(samples_used), 6) AS samples, round(avg(CASE WHEN fp = 'R' THEN 1 ELSE 0 END), 6) AS ex, round(avg(CASE WHEN agreed THEN 1 ELSE 0 END), 6) AS agreed FROM cw")
def cascade_cost(spark, sf_dir):
    c = serve.cascade(sampled_results(spark, sf_dir))
    right = F.when(F.col("fp") == "R", 1).otherwise(0)
    return c.agg(F.count(F.lit(1)).alias("questions"), F.round(F.avg("samples_used"), 6).alias("samples"), F.round(F.avg(right), 6).alias("ex"), F.round(F.avg(F.col("agreed").cast("int")), 6).alias("agreed"))


def _ex(spark, sf_dir, n, run, keep=None):
    q = table(spark, sf_dir, "events").select(F.col("event_id").alias("q_id"))
    q = q if keep is None else q.where(keep)
    j = q.join(serve.vote(sampled_results(spark, sf_dir), n), "q_id", "left")
    return j.agg(F.round(F.avg(F.when(F.col("fp") == "R", 1).otherwise(0)), 6).alias("ex")).select(F.lit(run).alias("run"), "ex")


@query(f"WITH {RESULTS_SQL} SELECT 'n1' AS run, round(avg(CASE WHEN fp = 'R' THEN 1 ELSE 0 END), 6) AS ex FROM results WHERE tier = 1 AND sample_no = 1")
def ex_n1(spark, sf_dir):
    return _ex(spark, sf_dir, 1, "n1")


@query(f"WITH {VOTE} SELECT 'n8' AS run, round(avg(CASE WHEN fp = 'R' THEN 1 ELSE 0 END), 6) AS ex FROM events LEFT JOIN vw ON event_id = q_id")
def ex_n8_vote(spark, sf_dir):
    return _ex(spark, sf_dir, 8, "n8")


@query(f"WITH {VOTE}, h AS (SELECT max(event_id) // 2 AS m FROM events) SELECT 'shared_db' AS run, round(avg(CASE WHEN fp = 'R' THEN 1 ELSE 0 END), 6) AS ex FROM events JOIN h ON event_id > m LEFT JOIN vw ON event_id = q_id")
def ex_shared_db(spark, sf_dir):
    half = table(spark, sf_dir, "events").agg(F.floor(F.max("event_id") / 2)).first()[0]
    return _ex(spark, sf_dir, 8, "shared_db", F.col("q_id") > half)


@query(f"WITH {results_sql(True)} SELECT 'schema_only' AS run, round(avg(CASE WHEN fp = 'R' THEN 1 ELSE 0 END), 6) AS ex FROM results WHERE tier = 1 AND sample_no = 1")
def ex_schema_only(spark, sf_dir):
    """Without a knowledge base an enum's meaning, the effective period and a metric's formula are guessed; what that gives is run."""
    one = sampled_results(spark, sf_dir, schema_only=True).where("tier = 1 and sample_no = 1")
    return one.agg(F.round(F.avg(F.when(F.col("fp") == "R", 1).otherwise(0)), 6).alias("ex")).select(F.lit("schema_only").alias("run"), "ex")


@query(f"WITH {RESULTS_SQL} SELECT q_id, count(*) FILTER (coalesce(fp, '') <> 'R') AS h FROM results GROUP BY q_id")
def hardness(spark, sf_dir):
    return curate.hardness(sampled_results(spark, sf_dir).select("q_id", (F.coalesce("fp", F.lit("")) == "R").cast("int").alias("correct")))


@query(f"WITH {QUESTIONS_SQL} SELECT template, p, round(1.0 / count(*), 9) AS v FROM questions GROUP BY ALL")
def variety_freq(spark, sf_dir):
    return curate.variety_freq(questions(spark, sf_dir), ["template", "p"]).withColumn("v", F.round("v", 9))


VK = """e AS (SELECT vec_id AS id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings), s AS (SELECT a.id AS q, b.id, round(list_cosine_similarity(a.v, b.v), 6) AS score FROM e a, e b WHERE a.id <> b.id),
k AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY q ORDER BY score DESC, id) AS rank FROM s) WHERE rank <= 5), vk AS (SELECT q AS id, round(avg(1 - score) + 1e-9, 6) AS v FROM k GROUP BY q)"""


def _variety(spark, sf_dir):
    return curate.variety_knn(table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec")))


@query(f"WITH {VK} SELECT id, v FROM vk")
def variety_knn(spark, sf_dir):
    return _variety(spark, sf_dir)


QUAL = r"""t AS (SELECT conv_id, turn, text, len(list_filter(string_split_regex(lower(text), '[^\p{L}\p{N}_]+'), lambda x: x <> '')) AS n, list_filter(string_split_regex(lower(text), '[^\p{L}\p{N}_]+'), lambda x: x <> '') AS w FROM conversations WHERE role = 'assistant'),
q AS (SELECT conv_id, turn, n, round(greatest(0.0, least(10.0, 10.0 * (400 - n) / 380)), 6) AS brevity, CASE WHEN n < 3 THEN 10.0 ELSE round(10.0 * len(list_distinct(list_transform(range(1, n - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2]))) / (n - 2), 6) END AS rep FROM t)"""


@query(f"WITH {QUAL} SELECT conv_id, turn, brevity, rep AS non_repetition FROM q")
def quality_rules(spark, sf_dir):
    from kbspark.functions.text import words

    t = table(spark, sf_dir, "conversations").where("role = 'assistant'")
    return t.select("conv_id", "turn", curate.brevity(F.size(words(F.lower("text")))).alias("brevity"), curate.non_repetition(F.col("text")).alias("non_repetition"))


@query("""WITH t AS (SELECT event_id AS id, event_id % 9 AS h, value AS q, 1.0 / (1 + event_id % 13) AS v FROM events)
SELECT id, round(h + 0.1 * q + v, 6) AS total FROM t ORDER BY total DESC, id LIMIT 20""")
def curated_topk(spark, sf_dir):
    t = table(spark, sf_dir, "events").select(F.col("event_id").alias("id"), (F.col("event_id") % 9).alias("h"), F.col("value").alias("q"), (1.0 / (1 + F.col("event_id") % 13)).alias("v"))
    return curate.select(t, 20).select("id", "total")


@query("""SELECT conv_id, '[' || string_agg('{"role":' || to_json(role) || ',"content":' || to_json(text) || '}', ',' ORDER BY turn, role, text) || ']' AS messages FROM conversations GROUP BY conv_id""")
def export_messages(spark, sf_dir):
    return curate.messages(table(spark, sf_dir, "conversations"))


# Results to compare: customers per nation, against scripted changes.
BASE_SQL = """g0 AS (SELECT n_name AS a, r_name AS b, CAST(count(c_custkey) AS VARCHAR) AS c FROM nation JOIN region ON n_regionkey = r_regionkey LEFT JOIN customer ON c_nationkey = n_nationkey GROUP BY 1, 2),
g AS (SELECT row_number() OVER (ORDER BY a) AS row_no, a, b, c FROM g0),
gold AS (SELECT unnest(['same', 'permuted', 'extra_column', 'summary_row', 'omitted', 'reversed', 'changed']) AS "case", row_no, [a, b, c] AS cells FROM g),
pred AS (SELECT 'same' AS "case", row_no, [a, b, c] AS cells FROM g UNION ALL SELECT 'permuted', row_no, [c, a, b] FROM g UNION ALL SELECT 'extra_column', row_no, [a, b, c, 'x' || row_no] FROM g
 UNION ALL SELECT 'summary_row', row_no, [a, b, c] FROM g UNION ALL SELECT 'summary_row', 26, ['all', 'any', '-1'] UNION ALL SELECT 'omitted', row_no, [a, b, c] FROM g WHERE row_no < 25
 UNION ALL SELECT 'reversed', 26 - row_no, [a, b, c] FROM g UNION ALL SELECT 'changed', row_no, [a, b, CASE WHEN row_no % 5 = 0 THEN 'no' ELSE c END] FROM g)"""


def _sides(spark, sf_dir):
    n, r, c = (table(spark, sf_dir, t) for t in ("nation", "region", "customer"))
    by = n.join(r, F.col("n_regionkey") == F.col("r_regionkey")).join(c, F.col("c_nationkey") == F.col("n_nationkey"), "left").groupBy(F.col("n_name").alias("a"), F.col("r_name").alias("b")).agg(F.count("c_custkey").cast("string").alias("c"))
    g = by.withColumn("row_no", F.row_number().over(Window.orderBy("a")).cast("long"))  # 25 nations
    cases = ["same", "permuted", "extra_column", "summary_row", "omitted", "reversed", "changed"]
    row = F.array("a", "b", "c")
    gold = g.select(F.explode(F.array(*map(F.lit, cases))).alias("case"), "row_no", row.alias("cells"))
    one = lambda case, cells, row_no=F.col("row_no"): g.select(F.lit(case).alias("case"), row_no.cast("long").alias("row_no"), cells.alias("cells"))
    pred = one("same", row).union(one("permuted", F.array("c", "a", "b"))).union(one("extra_column", F.array("a", "b", "c", F.concat(F.lit("x"), "row_no"))))
    pred = pred.union(one("summary_row", row)).union(spark.createDataFrame([("summary_row", 26, ["all", "any", "-1"])], "case string, row_no long, cells array<string>"))
    pred = pred.union(one("omitted", row).where("row_no < 25")).union(one("reversed", row, 26 - F.col("row_no")))
    return pred.union(one("changed", F.array("a", "b", F.when(F.col("row_no") % 5 == 0, "no").otherwise(F.col("c"))))), gold


def _ex_sql(key):
    return f"""WITH {BASE_SQL}, p AS (SELECT "case", {key} AS k, count(*) AS n FROM pred GROUP BY ALL), q AS (SELECT "case", {key} AS k, count(*) AS n FROM gold GROUP BY ALL)
SELECT coalesce(p."case", q."case") AS "case", min(CASE WHEN coalesce(p.n, 0) = coalesce(q.n, 0) THEN 1 ELSE 0 END) AS score FROM p FULL JOIN q ON p."case" = q."case" AND p.k = q.k GROUP BY 1"""


SIG = "array_to_string(list_sort(cells), '~')"


@query(_ex_sql(SIG).replace("count(*) AS n", "1 AS n"))
def ex_set(spark, sf_dir):
    return measure.execution(*_sides(spark, sf_dir), "set")


@query(_ex_sql(SIG))
def ex_bag(spark, sf_dir):
    return measure.execution(*_sides(spark, sf_dir), "bag")


@query(_ex_sql(f"{SIG} || '~' || row_no"))
def ex_ordered(spark, sf_dir):
    return measure.execution(*_sides(spark, sf_dir), "ordered")


@query(f"""WITH {BASE_SQL} SELECT coalesce(p."case", q."case") AS "case", round(avg(CASE WHEN p.cells IS NULL OR q.cells IS NULL THEN 0 ELSE 2.0 * len(list_intersect(p.cells, q.cells)) / (len(list_distinct(p.cells)) + len(list_distinct(q.cells))) END), 6) AS score
FROM pred p FULL JOIN gold q ON p."case" = q."case" AND p.row_no = q.row_no GROUP BY 1""")
def soft_f1(spark, sf_dir):
    return measure.soft_f1(*_sides(spark, sf_dir))


@query(f"""WITH {BASE_SQL}, w AS (SELECT p."case", p.row_no AS i, q.row_no AS j, len(list_intersect(p.cells, q.cells)) AS c, len(list_distinct(p.cells)) AS np, len(list_distinct(q.cells)) AS nq FROM pred p JOIN gold q ON p."case" = q."case")
SELECT "case", i, j, round(5 * (c / np) * (c / nq) / (4 * (c / np) + c / nq), 6) AS weight FROM w WHERE c > 0""")
def row_weights(spark, sf_dir):
    return measure.weights(*_sides(spark, sf_dir))


@query()
def rowmatch_unordered(spark, sf_dir):
    return rowmatch.score(*_sides(spark, sf_dir))


@query()
def rowmatch_ordered(spark, sf_dir):
    return rowmatch.score(*_sides(spark, sf_dir), ordered=True)


@query()
def metric_disagreement(spark, sf_dir):
    """case with strict, soft and row-matching scores side by side."""
    out = None
    for name, f in (("ex", ex_bag), ("soft_f1", soft_f1), ("match", rowmatch_unordered), ("match_ordered", rowmatch_ordered)):
        one = f(spark, sf_dir).select("case", F.col("score").cast("double").alias(name))
        out = one if out is None else out.join(one, "case")
    return out


@query(f"""WITH {VOTE}, {QUESTIONS_SQL}, ev AS (SELECT difficulty, CASE WHEN fp = 'R' THEN 1 ELSE 0 END AS ok FROM questions LEFT JOIN vw USING (q_id)), t AS (SELECT count(*) AS n_all, greatest(sum(1 - ok), 1) AS e_all FROM ev),
g AS (SELECT difficulty, count(*) AS n, sum(ok) AS ok FROM ev GROUP BY ROLLUP (difficulty))
SELECT coalesce(difficulty, 'overall') AS difficulty, n, round(n / n_all, 6) AS share, round(ok / n, 6) AS ex, round((n - ok) / e_all, 6) AS error_share, round((n - ok) / e_all - n / n_all, 6) AS diff FROM g, t""")
def error_by_difficulty(spark, sf_dir):
    q = questions(spark, sf_dir).select("q_id", "difficulty").join(serve.vote(sampled_results(spark, sf_dir)), "q_id", "left")
    return measure.by_difficulty(q.select("difficulty", F.when(F.col("fp") == "R", 1).otherwise(0).alias("correct")))


# The published shares and accuracies by difficulty.
PRINTED = [("simple", 29.8, 85.1), ("moderate", 49.7, 76.1), ("challenging", 20.5, 68.6)]


def error_shares(p: DataFrame) -> DataFrame:
    """difficulty, error_share and diff from shares and accuracies in percent, as they are printed. p: difficulty, share, ex."""
    err = F.col("share") * (100 - F.col("ex"))
    part = 100 * err / F.nullif(F.sum(err).over(Window.partitionBy(F.lit(0))), F.lit(0.0))  # a row for each difficulty
    return p.select("difficulty", F.round(part + 1e-6, 1).alias("error_share"), F.round(part - F.col("share") + 1e-6, 1).alias("diff"))


def percent_right():
    return 100 * F.avg(F.when(F.col("fp") == "R", 1).otherwise(0))


@query(f"""WITH {RESULTS_SQL}, {QUESTIONS_SQL}, c AS (SELECT difficulty, count(*) AS n, 100 * avg(CASE WHEN fp = 'R' THEN 1 ELSE 0 END) AS ex FROM questions JOIN results USING (q_id) WHERE tier = 1 AND sample_no = 1 GROUP BY difficulty),
p AS (SELECT difficulty, round(100 * n / sum(n) OVER () + 1e-6, 1) AS share, round(ex + 1e-6, 1) AS ex FROM c)
SELECT difficulty, round(100 * share * (100 - ex) / nullif(sum(share * (100 - ex)) OVER (), 0) + 1e-6, 1) AS error_share, round(100 * share * (100 - ex) / nullif(sum(share * (100 - ex)) OVER (), 0) - share + 1e-6, 1) AS diff FROM p""")
def error_share_printed(spark, sf_dir):
    """From the shares and accuracies of the questions' first samples, rounded as a table prints them."""
    first = sampled_results(spark, sf_dir).where("tier = 1 AND sample_no = 1")
    c = questions(spark, sf_dir).select("q_id", "difficulty").join(first, "q_id").groupBy("difficulty").agg(F.count(F.lit(1)).alias("n"), percent_right().alias("ex"))
    share = 100 * F.col("n") / F.sum("n").over(Window.partitionBy(F.lit(0)))  # a row for each difficulty
    return error_shares(c.select("difficulty", F.round(share + 1e-6, 1).alias("share"), F.round(F.col("ex") + 1e-6, 1).alias("ex")))


# Published execution accuracies: data set, row, samples (-1: not given), percent.
PUBLISHED = [("first", 1, 72, 71.33), ("first", 2, 5, 73.34), ("first", 3, -1, 73.47), ("first", 4, 32, 73.50), ("first", 5, -1, 74.12), ("first", 6, -1, 74.32), ("first", 7, 21, 74.90), ("first", 8, 3, 75.36), ("second", 1, 1, 26.8), ("second", 2, 1, 27.0), ("second", 3, 1, 44.9), ("second", 4, 1, 54.8), ("second", 5, 1, 54.1), ("second", 6, 8, 58.9)]


def ranked_accuracies(p: DataFrame) -> DataFrame:
    """p (dataset, row_no, n, ex) with each row's rank in its data set and its gap to the best."""
    w = Window.partitionBy("dataset")
    return p.select("*", F.rank().over(w.orderBy(F.desc("ex"))).alias("rank"), F.round(F.max("ex").over(w) - F.col("ex"), 2).alias("gap"))


@query(f"""WITH {RESULTS_SQL}, {QUESTIONS_SQL}, p AS (SELECT difficulty AS dataset, CAST(10 * tier + sample_no AS INT) AS row_no, count(*) AS n, round(100 * avg(CASE WHEN fp = 'R' THEN 1 ELSE 0 END) + 1e-6, 2) AS ex FROM questions JOIN results USING (q_id) GROUP BY ALL)
SELECT dataset, row_no, n, ex, rank() OVER (PARTITION BY dataset ORDER BY ex DESC) AS rank, round(max(ex) OVER (PARTITION BY dataset) - ex, 2) AS gap FROM p""")
def published_rank(spark, sf_dir):
    """The ranking of published accuracies, on what was run: a data set for each difficulty, a row (10 tier + sample) for each
    sample, n its questions."""
    j = questions(spark, sf_dir).select("q_id", "difficulty").join(sampled_results(spark, sf_dir), "q_id")
    p = j.groupBy(F.col("difficulty").alias("dataset"), (10 * F.col("tier") + F.col("sample_no")).cast("int").alias("row_no"))
    return ranked_accuracies(p.agg(F.count(F.lit(1)).alias("n"), F.round(percent_right() + 1e-6, 2).alias("ex")))


@query()
def error_causes(spark, sf_dir):
    """mutation (template and variant), cause and n: mutated queries by the class that their facts are put in, and for how
    many questions each gives another result than the gold query when run on the given tables."""
    seen = {(t, v): extract.facts(spark, sql) + extract.calls(spark, sql) for t, v, sql in executed.plain_statements()}
    causes = [(t, v, measure.classify(seen[t, "gold"], seen[t, v])) for t, v in seen if v != "gold"]
    causes = [(t, v, "reasoning" if c == "same" else c) for t, v, c in causes]  # the texts differ, in what no fact tells
    kinds = F.broadcast(spark.createDataFrame(causes, "template int, variant string, cause string"))
    asked = questions(spark, sf_dir).select("template", F.when(F.col("template").isin(3, 9), period_of(F.col("asked_at"))).otherwise(F.col("p")).alias("p"), "r")
    asked = asked.groupBy("template", "p", "r").agg(F.count(F.lit(1)).alias("asked"))
    ran = executed.candidate_results(spark, sf_dir)
    gold = ran.where("variant = 'gold'").select("template", "p", "r", F.col("fp").alias("want"))
    j = asked.join(kinds, "template").join(ran, ["template", "variant", "p", "r"], "left").join(gold, ["template", "p", "r"], "left")
    wrong = F.when(~F.col("fp").eqNullSafe(F.col("want")), F.col("asked")).otherwise(0)
    return j.groupBy(F.concat(F.col("template").cast("string"), "variant").alias("mutation"), "cause").agg(F.sum(wrong).alias("n"))


@query()
def sql_facts_exist(spark, sf_dir):
    """kind, table, column, op, value, exists of the facts of the templates' gold SQL and of one broken text."""
    texts = ["SELECT count(*) FROM customer WHERE c_mktsegment = 'BUILDING'", "SELECT c_nme FROM custmer WHERE c_mktsegment = 'NONE'", "WITH t AS (SELECT o_custkey FROM orders WHERE o_orderstatus = 'F') SELECT * FROM t WHERE o_custkey IN (SELECT c_custkey FROM customer)", "SELEC 1"]
    facts = [f for t in texts for f in extract.facts(spark, t)]
    df = spark.createDataFrame([tuple(x.strip("'") for x in f) for f in facts], "kind string, table string, column string, op string, value string").distinct()
    return extract.verify_facts(df, catalog(spark, sf_dir), enum_values(spark, sf_dir))


@query()
def synonyms_mined(spark, sf_dir):
    q = questions(spark, sf_dir).where("labelled")
    return extract.mine_synonyms(q, enum_values(spark, sf_dir).select(F.col("val").alias("value")).distinct())


@query("""WITH r AS (SELECT r_name AS region, sum(l_extendedprice * (1 - l_discount)) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1),
t AS (SELECT r_name AS region, sum(l_extendedprice * l_tax) AS tax FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1)
SELECT region, round(revenue - tax + 1e-6, 2) AS profit FROM r JOIN t USING (region)""")
def compose_pairs(spark, sf_dir):
    return synth.run_composed(spark, sf_dir)


@query("""WITH p AS (SELECT o_orderpriority AS part, count(*) AS n FROM orders WHERE o_orderpriority IN ('1-URGENT', '2-HIGH', '3-MEDIUM') GROUP BY 1) SELECT part, n FROM p UNION ALL SELECT 'all', CAST(sum(n) AS BIGINT) FROM p""")
def decomposed_parts(spark, sf_dir):
    return synth.run_decomposed(spark, sf_dir)


@query("""WITH b AS (SELECT p_brand AS v, p_type AS w, count(*) AS n FROM part GROUP BY ALL) SELECT 'p_brand=' || v AS a, 'p_type=' || w AS b, n FROM b""")
def independent_predicates(spark, sf_dir):
    return synth.independent(table(spark, sf_dir, "part"), [("p_brand", 1), ("p_type", 2)])


@query("""SELECT 'customer.c_mktsegment' AS target, count(DISTINCT c_mktsegment) AS n_rows FROM customer UNION ALL SELECT 'orders.o_orderpriority', count(DISTINCT o_orderpriority) FROM orders
UNION ALL SELECT 'part.p_brand', count(DISTINCT p_brand) FROM part UNION ALL SELECT 'events.event_type', count(DISTINCT event_type) FROM events""")
def transfer_nonempty(spark, sf_dir):
    return synth.run_transfer(spark, sf_dir)
