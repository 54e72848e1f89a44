"""Queries on the agent's tools and on sketches that name columns."""

from __future__ import annotations

from pyspark.sql import functions as F

from kbspark.operators import serializers, tools
from kbspark.registry import query
from kbspark.sources.tables import ENUM_SQL, STAR, enum_values, table, union
from kbspark.workloads.index_queries import question_hits
from kbspark.workloads.profile_queries import CAT, NUM, TIMES
from kbspark.workloads.questions import QUESTIONS_SQL, questions

KINDS = {"numeric": NUM, "text": CAT, "temporal": TIMES}
COLUMNS_SQL = " UNION ALL ".join(f"SELECT '{t}' AS tab, '{c}' AS col, '{k}' AS kind, count(*) AS n_rows, count(*) - count({c}) AS n_null FROM {t}" for k, of in KINDS.items() for t, cs in of.items() for c in cs)
TABLES_SQL = f"cs AS ({COLUMNS_SQL}), ts AS (SELECT tab, max(n_rows) AS n_rows, count(*) AS n_columns, string_agg(col || ' (' || kind || ')', ', ' ORDER BY col) AS listed FROM cs GROUP BY tab)"


def _columns(spark, sf_dir):
    known = {t: [c for of in KINDS.values() for c in of.get(t, [])] for t in STAR}
    return union([tools.column_info(table(spark, sf_dir, t), t, cs) for t, cs in known.items() if cs])


def scanned_columns(spark, sf_dir):
    """tab and col of all columns of the given tables, read by Spark's tasks."""
    return tools.scanned(union([tools.column_info(table(spark, sf_dir, t), t) for t in STAR]))


@query(f"SELECT tab, col, kind, n_rows, n_null, tab || '.' || col || ': ' || kind || ', ' || n_null || ' nulls' AS info FROM ({COLUMNS_SQL})")
def column_info(spark, sf_dir):
    return _columns(spark, sf_dir)


@query(f"WITH {TABLES_SQL} SELECT tab, n_rows, n_columns, tab || ': ' || n_rows || ' rows; ' || listed AS info FROM ts")
def table_info(spark, sf_dir):
    return tools.table_info(_columns(spark, sf_dir))


@query(f"WITH {TABLES_SQL} SELECT count(*) AS n_tables, CAST(sum(n_rows) AS BIGINT) AS n_rows, count(*) || ' tables: ' || string_agg(tab, ', ' ORDER BY tab) AS info FROM ts")
def db_info(spark, sf_dir):
    return tools.db_info(tools.table_info(_columns(spark, sf_dir)))


ASKED = ["price", "status", "segment", "nation", "priority", "discount", "shipdate"]
_names = ", ".join(f"'{t}'" for t in STAR)


@query(f"""WITH v AS (SELECT DISTINCT table_name || '.' || column_name AS value FROM information_schema.columns WHERE table_name IN ({_names})), kw(keyword) AS (VALUES {', '.join(f"('{w}')" for w in ASKED)}),
kg AS (SELECT DISTINCT keyword, substr(keyword, i, 3) AS g FROM (SELECT keyword, unnest(range(1, length(keyword) - 1)) AS i FROM kw)),
vg AS (SELECT DISTINCT value, substr(value, i, 3) AS g FROM (SELECT value, unnest(range(1, length(value) - 1)) AS i FROM v)),
sc AS (SELECT keyword, value, round(count(*) / any_value(n), 6) AS score FROM kg JOIN vg USING (g) JOIN (SELECT keyword, count(*) AS n FROM kg GROUP BY 1) USING (keyword) GROUP BY keyword, value)
SELECT * FROM (SELECT keyword, value, score, row_number() OVER (PARTITION BY keyword ORDER BY score DESC, value) AS rank FROM sc) WHERE rank <= 5""")
def fuzzy_column_top5(spark, sf_dir):
    return tools.fuzzy_column(spark.createDataFrame([(w,) for w in ASKED], "keyword string"), scanned_columns(spark, sf_dir))


@query(f"""WITH enums AS ({ENUM_SQL}), lb AS (SELECT val, '[' || upper(min(col)) || ' as ENUM]' AS label FROM enums GROUP BY val), {QUESTIONS_SQL}
SELECT q_id, replace(replace(regexp_replace(t, '\\b[0-9]+\\b', '[VALUE]', 'g'), '{{p}}', coalesce(a.label, '[VALUE]')), '{{r}}', coalesce(b.label, '')) AS sketch
FROM questions JOIN tpl USING (template) LEFT JOIN lb a ON a.val = p LEFT JOIN lb b ON b.val = r""")
def sketch_taxonomy(spark, sf_dir):
    """The text with every enum value replaced by its column, as a kind of enum, and other numerals by [VALUE]."""
    label = enum_values(spark, sf_dir).groupBy("val").agg(F.concat(F.upper(F.min("col")), F.lit(" as ENUM")).alias("label"))
    hits = question_hits(spark, sf_dir, "longest").join(F.broadcast(label), F.col("value") == F.col("val"))
    return serializers.sketch(questions(spark, sf_dir), hits.select("q_id", "start", "stop", "label"))
