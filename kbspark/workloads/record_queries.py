"""Queries on the record store: identity, slots, lifecycle, access, merging, facets and graph."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kbspark.operators import facets, graph, records, tools
from kbspark.registry import query
from kbspark.sources.tables import ENUM_SQL, STAR, enum_values, table, union

# SQL for what kbspark.operators.records.enum_records makes.
REC_SQL = f"""enums AS ({ENUM_SQL}),
rec AS (SELECT tab, col, val AS name, 'enum' AS type, col || ' = ' || val AS content,
  '[COLUMN:' || col || ']' AS t1, '[ENUM:' || val || ']' AS t2, '[TABLE:' || tab || ']' AS t3,
  json_object('table', tab, 'column', col, 'value', val) AS res FROM enums),
ids AS (SELECT *, sha256('enum' || chr(31) || 'unknown' || chr(31) || name || chr(31) || 'unknown' || chr(31) || 'auto' || chr(31) || t1 || chr(30) || t2 || chr(30) || t3 || chr(31) || 'false' || chr(31) || 'enum' || chr(31) || 'default' || chr(31) || 'v0.1.0' || chr(31) || 'unknown') AS record_id,
  sha256(content || chr(31) || CAST(res AS VARCHAR)) AS content_hash FROM rec)"""


def enum_kb(spark: SparkSession, sf_dir: str) -> DataFrame:
    return records.enum_records(enum_values(spark, sf_dir))


@query(f"WITH {REC_SQL} SELECT type, name, record_id, content_hash FROM ids")
def record_ids(spark, sf_dir):
    return enum_kb(spark, sf_dir).select("type", "name", "record_id", "content_hash")


@query(f"""WITH {REC_SQL} SELECT record_id, 'COLUMN' AS slot, col AS slot_values FROM ids UNION ALL SELECT record_id, 'ENUM', name FROM ids
UNION ALL SELECT record_id, 'TABLE', tab FROM ids""")
def slots_map(spark, sf_dir):
    kb = records.with_slots(enum_kb(spark, sf_dir))
    return kb.select("record_id", F.explode("slots").alias("slot", "vs")).select("record_id", "slot", F.array_join("vs", "|").alias("slot_values"))


_names = ", ".join(f"'{t}'" for t in STAR)


@query(f"""WITH c AS (SELECT DISTINCT table_name AS tab, column_name AS col FROM information_schema.columns WHERE table_name IN ({_names}))
SELECT tab, col AS name, 'column ' || col || ': column of ' || tab || ' (also called ' || upper(col) || ', ' || replace(col, '_', ' ') || ')' AS text FROM c""")
def render_columns(spark, sf_dir):
    """All columns of the given tables as records that a prompt shows."""
    rows = tools.scanned(union([tools.column_info(table(spark, sf_dir, t), t) for t in STAR]))
    made = rows.select("tab", F.col("col").alias("name"), F.concat(F.lit("column of "), "tab").alias("description"), F.array(F.replace(F.col("col"), F.lit("_"), F.lit(" ")), F.upper("col")).alias("synonyms"))
    return records.render(made, "column").select("tab", "name", "text")


@query("""WITH q AS (SELECT event_id AS q_id, event_type, value FROM events),
r(rid, cond) AS (VALUES (1, 'a'), (2, 'b'), (3, 'c'))
SELECT q_id, rid FROM q, r WHERE (cond = 'a' AND lower(event_type) = 'purchase') OR (cond = 'b' AND value > 50) OR (cond = 'c' AND event_type LIKE 'c%')""")
def trigger_filter(spark, sf_dir):
    q = table(spark, sf_dir, "events").select(F.col("event_id").alias("q_id"), "event_type", "value")
    r = spark.createDataFrame([(1, "lower(event_type) = 'purchase'"), (2, "value > 50"), (3, "startswith(event_type, 'c')")], "rid int, trigger string")
    # Three records against the questions: the record side is a literal list.
    pairs = q.withColumn("r", F.explode(F.array(*(F.struct(F.lit(x["rid"]).alias("rid"), F.lit(x["trigger"]).alias("trigger")) for x in r.collect()))))
    return records.apply_triggers(pairs.select("q_id", "event_type", "value", "r.*")).select("q_id", "rid")


@query("""WITH v AS (SELECT p_brand AS name, p_partkey % 3 AS a, p_partkey % 12 AS b, p_partkey % 2 AS c FROM part)
SELECT name, 'v' || (best // 1000) || '.' || ((best // 10) % 100) || '.' || (best % 10) AS version FROM (SELECT name, max(a * 1000 + b * 10 + c) AS best FROM v GROUP BY name)""")
def latest_versions(spark, sf_dir):
    parts = table(spark, sf_dir, "part")
    text = F.concat_ws(".", F.concat(F.lit("v"), F.col("p_partkey") % 3), F.col("p_partkey") % 12, F.col("p_partkey") % 2)
    rows = parts.select(F.col("p_brand").alias("name"), text.alias("version")).distinct()
    return records.latest(rows, ["name"]).select("name", "version")


@query("""WITH u AS (SELECT user_id, min(ts) AS a, max(ts) AS b FROM events GROUP BY user_id)
SELECT user_id AS record_id FROM u WHERE user_id % 7 <> 0 AND NOT (user_id % 3 <> 0 AND epoch(greatest(a, b)) + (user_id % 5) * 86400 <= epoch(TIMESTAMP '2024-01-30 00:00:00'))""")
def active_records(spark, sf_dir):
    u = table(spark, sf_dir, "events").groupBy(F.col("user_id").alias("record_id")).agg(F.min("ts").alias("timestamp"), F.max("ts").alias("last_verified"))
    u = u.withColumn("expiration", F.when(F.col("record_id") % 3 == 0, -1).otherwise((F.col("record_id") % 5) * 86400).cast("long")).withColumn("inactive_mark", F.col("record_id") % 7 == 0)
    return records.active(u, F.lit("2024-01-30 00:00:00").cast("timestamp")).select("record_id")


@query("""WITH r AS (SELECT p_partkey AS record_id, CASE WHEN p_partkey % 2 = 0 THEN 'w0' ELSE 'w1' END AS workspace FROM part),
g AS (SELECT record_id, 'u' || (record_id % 10) AS usr FROM r WHERE record_id % 3 = 0)
SELECT record_id FROM r WHERE record_id IN (SELECT record_id FROM g WHERE usr = 'u7') OR (record_id NOT IN (SELECT record_id FROM g) AND workspace = 'w1')""")
def visible_records(spark, sf_dir):
    r = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("record_id"), F.when(F.col("p_partkey") % 2 == 0, "w0").otherwise("w1").alias("workspace"))
    g = r.where("record_id % 3 = 0").select("record_id", F.concat(F.lit("u"), F.col("record_id") % 10).alias("user"), F.lit("read").alias("authority"))
    return records.visible(r, g, "u7", workspace="w1").select("record_id")


MERGE_SQL = """kb AS (SELECT p_partkey AS id, p_brand AS h, p_type AS syn, p_partkey % 2 = 0 AS trusted, 5 AS pri FROM part WHERE p_partkey % 4 <> 3),
inc AS (SELECT p_partkey AS id, CASE WHEN p_partkey % 5 = 0 THEN 'X' ELSE p_brand END AS h, p_name AS syn FROM part
  UNION ALL SELECT p_partkey, CASE WHEN p_partkey % 8 = 3 THEN 'Y' ELSE p_brand END, p_brand FROM part WHERE p_partkey % 4 = 3),
agg AS (SELECT id, min(h) AS low, max(h) AS high FROM inc GROUP BY id)"""


def _merge(spark, sf_dir):
    p = table(spark, sf_dir, "part")
    key = F.col("p_partkey")
    kb = p.where(key % 4 != 3).select(key.alias("record_id"), F.col("p_brand").alias("content_hash"), F.array("p_type").alias("synonyms"), F.lit(5).alias("priority"), (key % 2 == 0).alias("trusted"))
    one = p.select(key.alias("record_id"), F.when(key % 5 == 0, "X").otherwise(F.col("p_brand")).alias("content_hash"), F.array("p_name").alias("synonyms"), F.lit(5).alias("priority"))
    two = p.where(key % 4 == 3).select(key.alias("record_id"), F.when(key % 8 == 3, "Y").otherwise(F.col("p_brand")).alias("content_hash"), F.array("p_brand").alias("synonyms"), F.lit(5).alias("priority"))
    return records.merge_records(kb, one.union(two))


@query(f"""WITH {MERGE_SQL},
s AS (SELECT id, h, pri, trusted FROM kb UNION ALL SELECT agg.id, low, 4, false FROM agg WHERE low = high AND id NOT IN (SELECT id FROM kb)),
syn AS (SELECT s.id, x.syn FROM s JOIN (SELECT id, h, syn, false AS st FROM inc UNION ALL SELECT id, h, syn, true FROM kb) x ON s.id = x.id AND (x.st OR x.h = s.h))
SELECT s.id AS record_id, s.h AS content_hash, string_agg(DISTINCT syn.syn, '|' ORDER BY syn.syn) AS synonyms, any_value(s.pri) AS priority, any_value(s.trusted) AS trusted FROM s JOIN syn ON s.id = syn.id GROUP BY s.id, s.h""")
def merge_result(spark, sf_dir):
    return _merge(spark, sf_dir)[0].withColumn("synonyms", F.array_join("synonyms", "|"))


@query(f"""WITH {MERGE_SQL},
r AS (SELECT DISTINCT inc.id, inc.h, inc.syn, CASE WHEN kb.id IS NOT NULL AND inc.h <> kb.h THEN CASE WHEN kb.trusted THEN 'contradicts trusted' ELSE 'contradicts stored' END
  WHEN kb.id IS NULL AND agg.low <> agg.high THEN 'contradicting new rows' END AS reason
  FROM inc JOIN agg ON inc.id = agg.id LEFT JOIN kb ON inc.id = kb.id)
SELECT reason, count(*) AS n FROM r WHERE reason IS NOT NULL GROUP BY reason""")
def merge_rejects(spark, sf_dir):
    return _merge(spark, sf_dir)[1].groupBy("reason").agg(F.count(F.lit(1)).alias("n"))


@query("""WITH s AS (SELECT p_partkey AS id, 'brand' AS slot, p_brand AS v FROM part UNION ALL SELECT p_partkey, 'type', p_type FROM part UNION ALL SELECT p_partkey, 'size', CAST(p_size AS VARCHAR) FROM part)
SELECT id AS record_id FROM s WHERE (slot = 'brand' AND v IN ('Brand#11', 'Brand#12', 'Brand#13')) OR (slot = 'type' AND v LIKE '%STEEL%') OR (slot = 'size' AND TRY_CAST(v AS INT) BETWEEN 10 AND 40)
GROUP BY id HAVING count(DISTINCT slot) >= 2""")
def facet_search_all(spark, sf_dir):
    tags = facets.part_tags(table(spark, sf_dir, "part"))
    wanted = [("brand", F.col("value").isin("Brand#11", "Brand#12", "Brand#13")), ("type", F.col("value").like("%STEEL%")), ("size", F.expr("try_cast(value AS int)").between(10, 40))]
    return facets.search(tags, wanted, at_least=2)


@query("SELECT p_partkey AS record_id FROM part WHERE p_brand LIKE 'Brand#1%' AND lower(p_type) LIKE '%o%'")
def facet_search_wildcard(spark, sf_dir):
    tags = facets.part_tags(table(spark, sf_dir, "part"))
    return facets.search(tags, [("brand", F.col("value").like("Brand#1%")), ("type", F.lower("value").like("%o%"))])


@query("""WITH s AS (SELECT p_brand AS brand, p_type AS type FROM part)
SELECT brand, type, count(*) AS n, grouping_id(brand, type) AS gid FROM s GROUP BY CUBE (brand, type)""")
def facet_cube(spark, sf_dir):
    p = table(spark, sf_dir, "part").select(F.col("p_brand").alias("brand"), F.col("p_type").alias("type"))
    return p.cube("brand", "type").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().alias("gid"))


GRAPH_SQL = f"""enums AS ({ENUM_SQL}),
e AS (SELECT 'enum:' || col || ':' || val AS s, 'value of' AS r, 'column:' || col AS o FROM enums UNION SELECT 'column:' || col, 'column of', 'table:' || tab FROM enums
 UNION SELECT 'enum:n_name:' || n_name, 'is in', 'enum:r_name:' || r_name FROM nation JOIN region ON n_regionkey = r_regionkey)"""


@query(f"""WITH RECURSIVE {GRAPH_SQL},
w(seed, id, hop) AS (SELECT 'enum:n_name:' || n_name, 'enum:n_name:' || n_name, 0 FROM nation UNION SELECT w.seed, e.o, w.hop + 1 FROM w JOIN e ON w.id = e.s WHERE w.hop < 3 AND e.r IN ('value of', 'column of', 'is in'))
SELECT seed, id, min(hop) AS hop FROM w GROUP BY seed, id""")
def graph_hops(spark, sf_dir):
    enums = enum_values(spark, sf_dir)
    nation, region = table(spark, sf_dir, "nation"), table(spark, sf_dir, "region")
    inside = nation.join(F.broadcast(region), nation.n_regionkey == region.r_regionkey)
    inside = inside.select(F.concat(F.lit("enum:n_name:"), "n_name").alias("subject"), F.lit("is in").alias("relation"), F.concat(F.lit("enum:r_name:"), "r_name").alias("object"))
    edges = records.edges(enums).union(inside)
    return graph.hops(edges, nation.select(F.concat(F.lit("enum:n_name:"), "n_name").alias("seed")), ["value of", "column of", "is in"], 3)


@query(f"WITH {REC_SQL} SELECT type, count(*) AS n_records, count(*) AS n_synonyms FROM ids GROUP BY type")
def kb_types_subset(spark, sf_dir):
    kb = enum_kb(spark, sf_dir).where(F.col("type").isin("enum", "predicate", "column", "table", "special"))
    return kb.groupBy("type").agg(F.count(F.lit(1)).alias("n_records"), F.sum(F.size("synonyms")).alias("n_synonyms"))
