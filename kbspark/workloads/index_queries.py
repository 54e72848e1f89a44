"""Queries on the dictionary, vectors, fusion and retrieval."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from kbspark.operators import dictionary, fusion, lexical, measure, serializers, vectors
from kbspark.registry import query
from kbspark.session import cut
from kbspark.sources.tables import ENUM_SQL, enum_values, table
from kbspark.workloads.questions import QUESTIONS_SQL, questions
from kbspark.workloads.record_queries import enum_kb

TOKENS = r"regexp_extract_all(lower({}), '[\p{{L}}\p{{N}}_]+')"
PHRASES = f"""bt AS (SELECT item_id, {TOKENS.format('text')} AS w FROM benchmark),
pat AS (SELECT item_id, array_to_string(w[8 * k + 1 : 8 * k + 8], ' ') AS g FROM (SELECT item_id, w, unnest(range(0, len(w) // 8)) AS k FROM bt)),
dt AS (SELECT doc_id, lang, {TOKENS.format('text')} AS w FROM documents),
dg AS (SELECT doc_id, lang, array_to_string(w[i : i + 7], ' ') AS g FROM (SELECT doc_id, lang, w, unnest(range(1, len(w) - 6)) AS i FROM dt WHERE len(w) >= 8))"""


def phrases(spark, sf_dir):
    """record_id (of the item) and synonym: the benchmark cut into 8-token phrases."""
    w = F.regexp_extract_all(F.lower("text"), F.lit(r"[\p{L}\p{N}_]+"), 0)
    b = table(spark, sf_dir, "benchmark").select("item_id", F.explode(F.array(w)).alias("w")).where(F.size("w") >= 8)
    b = b.select("item_id", "w", F.explode(F.sequence(F.lit(0), F.floor(F.size("w") / 8).cast("int") - 1)).alias("k"))
    return b.select(F.col("item_id").alias("record_id"), F.array_join(F.slice("w", F.col("k") * 8 + 1, 8), " ").alias("synonym"))


def _hits(spark, sf_dir):
    a = dictionary.build(phrases(spark, sf_dir))
    return dictionary.match(table(spark, sf_dir, "documents"), "doc_id", "text", a)


@query(f"WITH {PHRASES} SELECT doc_id, item_id, count(*) AS hits FROM dg JOIN pat USING (g) GROUP BY ALL")
def dict_match(spark, sf_dir):
    return _hits(spark, sf_dir).groupBy("doc_id", F.col("record_id").alias("item_id")).agg(F.count(F.lit(1)).alias("hits"))


@query(f"WITH {PHRASES} SELECT doc_id, item_id, count(*) AS hits FROM dg JOIN pat USING (g) GROUP BY ALL")
def dict_match_ngrams(spark, sf_dir):
    hits = dictionary.match_ngrams(table(spark, sf_dir, "documents"), "doc_id", "text", phrases(spark, sf_dir))
    return hits.groupBy("doc_id", F.col("record_id").alias("item_id")).agg(F.count(F.lit(1)).alias("hits"))


@query(f"WITH {PHRASES} SELECT lang, count(*) AS hits, count(DISTINCT item_id) AS items, count(DISTINCT doc_id) AS docs FROM dg JOIN pat USING (g) GROUP BY lang")
def dict_match_by_lang(spark, sf_dir):
    hits = _hits(spark, sf_dir).join(table(spark, sf_dir, "documents").select("doc_id", "lang"), "doc_id")
    return hits.groupBy("lang").agg(F.count(F.lit(1)).alias("hits"), F.count_distinct("record_id").alias("items"), F.count_distinct("doc_id").alias("docs"))


@query()
def lemma_recall(spark, sf_dir):
    """lang, patterns, recall_plain, recall_lemma: inflected forms of each language's frequent words against its dictionary."""
    from kbspark.functions.text import ENDINGS

    out = None
    for lang, suffix in (("en", "s"), ("de", "en"), ("fr", "s"), ("es", "s")):
        w = F.explode(F.regexp_extract_all(F.lower("text"), F.lit(r"[\p{L}]{4,12}"), 0)).alias("w")
        top = table(spark, sf_dir, "documents").where(F.col("lang") == lang).select(w).groupBy("w").count().orderBy(F.desc("count"), "w").limit(200)
        top = top.where(~F.col("w").rlike(f"({'|'.join(ENDINGS[lang])})$"))
        syn = cut(top.select(F.col("w").alias("record_id"), F.col("w").alias("synonym")))
        asked = syn.select(F.col("record_id").alias("k"), F.concat("record_id", F.lit(suffix)).alias("t"))
        rec = lambda lemma: dictionary.match(asked, "k", "t", dictionary.build(syn, lang=lemma), lang=lemma).where("k = record_id").select("k").distinct().count()  # noqa: E731, B023
        n, plain, folded = syn.count(), rec(None), rec(lang)
        one = spark.createDataFrame([(lang, n, plain / max(n, 1), folded / max(n, 1))], "lang string, patterns long, recall_plain double, recall_lemma double")
        out = one if out is None else out.union(one)
    return out


QHITS = f"""enums AS ({ENUM_SQL}), {QUESTIONS_SQL},
v AS (SELECT DISTINCT val, array_to_string({TOKENS.format('val')}, ' ') AS g, len({TOKENS.format('val')}) AS n FROM enums),
qt AS (SELECT q_id, {TOKENS.format('text')} AS w FROM questions),
qg AS (SELECT q_id, i - 1 AS first, n, array_to_string(w[i : i + n - 1], ' ') AS g FROM (SELECT q_id, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM qt, (VALUES (1), (2), (3)) t(n) WHERE len(w) >= n)),
qh AS (SELECT q_id, val AS value, CAST(first AS INT) AS first FROM qg JOIN v ON qg.g = v.g AND qg.n = v.n)"""


def question_hits(spark, sf_dir, mode="all"):
    """Enum values in distinct question texts by the automaton, back on all questions."""
    syn = enum_values(spark, sf_dir).select(F.col("val").alias("record_id"), F.col("val").alias("synonym")).distinct()
    q = questions(spark, sf_dir)
    hits = dictionary.match(q.select("text").distinct().withColumn("key", F.col("text")), "key", "text", dictionary.build(syn), mode)
    return q.join(hits, q["text"] == hits["key"]).select("q_id", "template", "text", F.col("record_id").alias("value"), "first", "last", "start", "stop")


@query(f"WITH {QHITS} SELECT q_id, value, first FROM qh")
def dict_match_questions(spark, sf_dir):
    return question_hits(spark, sf_dir).select("q_id", "value", "first")


@query()
def longest_match(spark, sf_dir):
    return question_hits(spark, sf_dir, "longest").select("q_id", "value", "first")


@query(f"WITH {QUESTIONS_SQL} SELECT template, count(*) AS n, count(DISTINCT text) AS n_texts FROM questions GROUP BY template")
def seed_questions(spark, sf_dir):
    return questions(spark, sf_dir).groupBy("template").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("text").alias("n_texts"))


@query(f"""WITH {QUESTIONS_SQL} SELECT q_id, replace(replace(regexp_replace(t, '\\b[0-9]+\\b', '[VALUE]', 'g'), '{{p}}', CASE template WHEN 2 THEN '[VALUE]' ELSE '[ENUM]' END), '{{r}}', '[ENUM]') AS sketch FROM questions JOIN tpl USING (template)""")
def sketch_basic(spark, sf_dir):
    """The text with every dictionary hit replaced by its type, and other numerals by [VALUE]: found values, longest first."""
    hits = question_hits(spark, sf_dir, "longest").select("q_id", "start", "stop", F.lit("ENUM").alias("label"))
    return serializers.sketch(questions(spark, sf_dir), hits)


@query(f"WITH {QHITS} SELECT q_id, string_agg(DISTINCT value, '|' ORDER BY value) AS tags FROM qh GROUP BY q_id")
def tags_key(spark, sf_dir):
    return question_hits(spark, sf_dir).groupBy("q_id").agg(F.array_join(F.array_sort(F.collect_set("value")), "|").alias("tags"))


KNN_SQL = """qs AS (SELECT vec_id AS q, CAST(embedding AS DOUBLE[]) AS qv FROM embeddings WHERE vec_id % 100 = 0), bs AS (SELECT vec_id AS id, CAST(embedding AS DOUBLE[]) AS bv FROM embeddings),
cs AS (SELECT q, id, round(list_cosine_similarity(qv, bv), 6) AS score FROM qs, bs WHERE q <> id), ls AS (SELECT q, id, round(-list_distance(qv, bv), 6) AS score FROM qs, bs WHERE q <> id),
ck AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY q ORDER BY score DESC, id) AS rank FROM cs) WHERE rank <= 5),
lk AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY q ORDER BY score DESC, id) AS rank FROM ls) WHERE rank <= 5),
lists AS (SELECT q, 1 AS index_no, rank, id FROM ck UNION ALL SELECT q, 2, rank, id FROM lk)"""


def _vecs(spark, sf_dir):
    base = table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"))
    return base.where("id % 100 = 0").withColumnRenamed("id", "q"), base


@query(f"WITH {KNN_SQL} SELECT q, id, score, rank FROM ck")
def knn_exact(spark, sf_dir):
    return vectors.knn(*_vecs(spark, sf_dir), 5)


def _lists(spark, sf_dir):
    q, b = _vecs(spark, sf_dir)
    one = lambda metric, n: vectors.knn(q, b, 5, metric).select("q", F.lit(n).alias("index_no"), "rank", "id")
    return one("cosine", 1).union(one("l2", 2))


@query(f"WITH {KNN_SQL}, f AS (SELECT q, id, min(rank * 10 + index_no) AS turn FROM lists GROUP BY ALL) SELECT * FROM (SELECT q, row_number() OVER (PARTITION BY q ORDER BY turn, id) AS rank, id FROM f) WHERE rank <= 5")
def round_robin_top5(spark, sf_dir):
    return fusion.round_robin(_lists(spark, sf_dir), 5)


@query(f"WITH {KNN_SQL}, f AS (SELECT q, id, max(1.0 / rank) AS s FROM lists GROUP BY ALL) SELECT * FROM (SELECT q, row_number() OVER (PARTITION BY q ORDER BY s DESC, id) AS rank, id, round(s, 6) AS score FROM f) WHERE rank <= 5")
def rerank_top5(spark, sf_dir):
    return fusion.rerank(_lists(spark, sf_dir), 1.0 / F.col("rank"), 5).withColumn("score", F.round("score", 6))


@query(f"""WITH {KNN_SQL}, g AS (SELECT q, count(*) AS n FROM ck GROUP BY q), ks(k) AS (VALUES (1), (3), (5)),
r AS (SELECT k, g.q, n, count(ck.id) AS hit FROM g, ks LEFT JOIN lk ON lk.q = g.q AND lk.rank <= k LEFT JOIN ck ON ck.q = lk.q AND ck.id = lk.id GROUP BY ALL),
m AS (SELECT avg(coalesce(1.0 / f, 0)) AS mrr FROM g LEFT JOIN (SELECT lk.q, min(lk.rank) AS f FROM lk JOIN ck ON ck.q = lk.q AND ck.id = lk.id GROUP BY lk.q) x ON g.q = x.q)
SELECT k, round(avg(hit / n), 6) AS recall, round(avg(hit / k), 6) AS precision, round(any_value(mrr), 6) AS mrr FROM r, m GROUP BY k""")
def retrieval_recall(spark, sf_dir):
    q, b = _vecs(spark, sf_dir)
    gold = vectors.knn(q, b, 5).select("q", "id")
    return measure.retrieval(vectors.knn(q, b, 5, "l2"), gold, [1, 3, 5])


@query()
def ann_recall(spark, sf_dir):
    """method and recall at 5 against exact neighbours, for buckets with probes and for inverted cells."""
    q, b = _vecs(spark, sf_dir)
    exact = cut(vectors.knn(q, b, 5))
    cells = vectors.cells(b, 16)
    runs = {"hyperplanes_2_of_4": vectors.ann(q, b, 5, 4, 2), "hyperplanes_all": vectors.ann(q, b, 5, 4, 4), "cells_8_of_16": vectors.ivf(q, b, 5, cells, 8), "cells_all": vectors.ivf(q, b, 5, cells, 16)}
    out = None
    for name, got in runs.items():
        one = measure.neighbour_recall(got, exact).select(F.lit(name).alias("method"), "recall")
        out = one if out is None else out.union(one)
    return out


@query()
def mmr_top5(spark, sf_dir):
    q, b = _vecs(spark, sf_dir)
    near = vectors.knn(q, b, 20).select("q", "id", "score").join(b, "id")
    return vectors.mmr(near, 5)


@query()
def minhash_pairs(spark, sf_dir):
    return lexical.minhash_links(table(spark, sf_dir, "documents"))


@query(f"""WITH {QUESTIONS_SQL}, w AS (SELECT q_id, template, lag(q_id, 1) OVER o AS a1, lag(q_id, 2) OVER o AS a2, lag(q_id, 3) OVER o AS a3 FROM questions WINDOW o AS (PARTITION BY template, p, r ORDER BY q_id))
SELECT q_id, 1 AS rank, a1 AS example FROM w WHERE a1 IS NOT NULL UNION ALL SELECT q_id, 2, a2 FROM w WHERE a2 IS NOT NULL UNION ALL SELECT q_id, 3, a3 FROM w WHERE a3 IS NOT NULL""")
def fewshot_examples(spark, sf_dir):
    """The three latest earlier questions of the same text: what was asked later is never an example."""
    w = Window.partitionBy("template", "p", "r").orderBy("q_id")
    q = questions(spark, sf_dir).select("q_id", F.array(*(F.lag("q_id", n).over(w) for n in (1, 2, 3))).alias("a"))
    return q.select("q_id", F.posexplode("a").alias("i", "example")).where("example is not null").select("q_id", (F.col("i") + 1).alias("rank"), "example")


@query()
def retrieve_static_top5(spark, sf_dir):
    """q_id, rank, record_id, origin, text: all dictionary hits, then the five best of two vector indices by turns.

    Retrieval runs on distinct texts; questions join its result.
    """
    kb = cut(enum_kb(spark, sf_dir).select("record_id", "name", "content", "synonyms"))
    syn = dictionary.expand(kb)
    q = questions(spark, sf_dir).select("q_id", "text")
    texts = cut(q.select("text").distinct().withColumn("q", F.xxhash64("text")))
    hit = dictionary.match(texts.withColumnRenamed("q", "k"), "k", "text", dictionary.build(syn)).groupBy(F.col("k").alias("q"), "record_id").agg(F.min("first").alias("first"))
    hit = hit.select("q", "record_id", F.lit("dictionary").alias("origin"), F.col("first").alias("o"))
    tv = cut(lexical.encode(texts, "text", ["q"]))
    keyed = kb.withColumn("id", F.xxhash64("record_id"))
    lists = None
    for n, col in enumerate(("name", "content"), 1):
        near = vectors.knn(tv, lexical.encode(keyed, col, ["id"]), 5).select("q", F.lit(n).alias("index_no"), "rank", "id")
        lists = near if lists is None else lists.union(near)
    vec = fusion.round_robin(lists, 5).join(keyed.select("id", "record_id"), "id").select("q", "record_id", F.lit("vector").alias("origin"), (F.col("rank") + 1000).alias("o"))
    both = hit.union(vec).groupBy("q", "record_id").agg(F.min(F.struct("o", "origin")).alias("m"))
    ranked = both.select("q", "record_id", F.col("m.origin").alias("origin"), F.row_number().over(Window.partitionBy("q").orderBy("m.o", "record_id")).alias("rank"))
    shown = ranked.join(kb.select("record_id", F.col("content").alias("shown")), "record_id")
    return q.join(texts, "text").join(shown, "q").select("q_id", "rank", "record_id", "origin", F.col("shown").alias("text"))
