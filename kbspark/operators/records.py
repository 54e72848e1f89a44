"""The record format: identity, content hashes, slots, templates, composers, triggers, priority, access,
lifecycle, versions, variants, and merging. All are narrow expressions or one shuffle on the record id."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

FIELD, ITEM = "\x1f", "\x1e"
#: Identity fields in alphabetical order.
IDENTITY = ["collection", "creator", "name", "owner", "source", "tags", "timefluid", "type", "variant", "version", "workspace"]
DEFAULTS = {
    "notes": "", "short_description": "", "description": "", "type": "general", "version": "v0.1.0", "version_notes": "", "variant": "default",
    "variant_notes": "", "content": "", "content_resources": "{}", "source": "unknown", "owner": "unknown", "workspace": "unknown", "creator": "unknown", "collection": "general",
}
SOURCES = ["auto", "derived", "system", "tool", "unknown", "user"]
#: Templates: the record types, with the resource keys that each needs.
TEMPLATES = {
    "knowledge": [], "document": ["doc_id", "chunk_no"], "experience": ["question", "sql"], "experience_chat": ["messages"],
    "table": ["table"], "column": ["table", "column"], "enum": ["table", "column", "value"], "taxonomy": ["child", "parent"], "dependency": ["x", "y"],
    "predicate": ["sql"], "synonym": ["of"], "indicator": ["formula"], "term": ["meaning"], "metric": ["formula"], "special": ["rule"],
}


def full(df: DataFrame) -> DataFrame:
    """df with every field of the format; missing ones take their defaults. Dictionaries are canonical JSON text."""
    more = {c: F.lit(v) for c, v in DEFAULTS.items() if c not in df.columns}
    arrays = {c: F.array().cast("array<string>") for c in ("tags", "synonyms") if c not in df.columns}
    maps = {c: F.create_map().cast("map<string,string>") for c in ("composers", "triggers", "parents") if c not in df.columns}
    rest = {"priority": F.lit(0), "timefluid": F.lit(False), "expiration": F.lit(-1).cast("long"), "inactive_mark": F.lit(False)}
    return df.withColumns(more | arrays | maps | {c: v for c, v in rest.items() if c not in df.columns})


def new(df: DataFrame, kind: str, as_of: Column | None = None) -> DataFrame:
    """Records of a template from a frame with name, content and resources (a struct with the template's keys)."""
    missing = set(TEMPLATES[kind]) - set(df.schema["resources"].dataType.names if "resources" in df.columns else [])
    if missing:
        raise ValueError(f"{kind} needs {sorted(missing)}")
    made = df.withColumn("type", F.lit(kind))
    if "resources" in df.columns:
        made = made.withColumn("content_resources", F.to_json("resources")).drop("resources")
    if as_of is not None:
        made = made.withColumns({"timestamp": as_of, "last_verified": as_of})
    return with_content_hash(with_ids(full(made)))


def identity_text() -> Column:
    tags = F.array_join(F.array_sort(F.array_distinct("tags")), ITEM)
    return F.concat_ws(FIELD, *(tags if c == "tags" else F.coalesce(F.col(c).cast("string"), F.lit("")) for c in IDENTITY))


def with_ids(df: DataFrame) -> DataFrame:
    return df.withColumn("record_id", F.sha2(identity_text(), 256))


def with_content_hash(df: DataFrame) -> DataFrame:
    return df.withColumn("content_hash", F.sha2(F.concat_ws(FIELD, "content", "content_resources"), 256))


def changed(old: DataFrame, now: DataFrame) -> DataFrame:
    """Ids in both whose content differs."""
    o = old.select("record_id", F.col("content_hash").alias("was"))
    return now.join(o, "record_id").where(F.col("content_hash") != F.col("was")).select("record_id")


def with_slots(df: DataFrame) -> DataFrame:
    """slots: slot name to its sorted values, from tags of the form [SLOT:value]."""
    pairs = F.transform("tags", lambda t: F.struct(F.regexp_extract(t, r"^\[([^:\]]+):", 1).alias("slot"), F.regexp_extract(t, r"^\[[^:\]]+:(.*)\]$", 1).alias("value")))
    pairs = F.filter(pairs, lambda p: p["slot"] != "")
    names = F.array_sort(F.array_distinct(F.transform(pairs, lambda p: p["slot"])))
    return df.withColumn(
        "slots",
        F.map_from_arrays(names, F.transform(names, lambda n: F.array_sort(F.array_distinct(F.transform(F.filter(pairs, lambda p: p["slot"] == n), lambda p: p["value"]))))),
    )


#: Composer templates by id; braces name columns of the record.
COMPOSERS = {
    "default": "{content}",
    "column": "column {name}: {description} (also called {synonym_text})",
    "enum": "value {name} of {collection}",
    "table": "table {name}: {description}",
}


def render(df: DataFrame, composer: str = "default") -> DataFrame:
    """text: the record as a prompt shows it."""
    text = F.lit(COMPOSERS[composer])
    for c in ("content", "name", "description", "collection"):
        if "{%s}" % c in COMPOSERS[composer]:
            text = F.replace(text, F.lit("{%s}" % c), F.coalesce(F.col(c), F.lit("")))
    if "{synonym_text}" in COMPOSERS[composer]:
        text = F.replace(text, F.lit("{synonym_text}"), F.array_join(F.array_sort("synonyms"), ", "))
    return df.withColumn("text", text)


def trigger_ok(text: str) -> bool:
    """A trigger is one boolean expression: no subquery, no statement end, no call outside a short list."""
    import re

    if re.search(r";|--|/\*|\b(select|with|insert|drop)\b", text, re.I):
        return False
    calls = {c.lower() for c in re.findall(r"([A-Za-z_]\w*)\s*\(", text)} - {"in", "and", "or", "not"}
    return calls <= {"lower", "upper", "contains", "startswith", "endswith", "length", "coalesce", "abs", "year", "month", "date_format"}


def apply_triggers(df: DataFrame, trigger: str = "trigger") -> DataFrame:
    """Rows whose trigger (a boolean expression over the row's own columns) holds; compiled once for each distinct text.

    The distinct texts are those of the records that have triggers: a driver-sized list, checked here.
    """
    texts = [r[0] for r in df.select(trigger).distinct().limit(1001).collect() if r[0] is not None]
    if len(texts) > 1000:
        raise ValueError("more than 1000 distinct triggers")
    bad = [t for t in texts if not trigger_ok(t)]
    if bad:
        raise ValueError(f"triggers refused: {bad[:3]}")
    holds = F.lit(True)
    for t in texts:
        holds = F.when(F.col(trigger) == t, F.coalesce(F.expr(t), F.lit(False))).otherwise(holds)
    return df.where(holds)


def select_by_priority(df: DataFrame, keys: list[str]) -> DataFrame:
    """One record for each key: the highest priority, then the last verified, then the greatest id."""
    w = Window.partitionBy(*keys).orderBy(F.desc("priority"), F.desc_nulls_last("last_verified"), F.desc("record_id"))
    return df.withColumn("__r", F.row_number().over(w)).where("__r = 1").drop("__r")


def lineage(df: DataFrame, ids: DataFrame, depth: int = 5) -> DataFrame:
    """record_id, ancestor and hop: parents of parents, up to a depth; each hop is one join with the parent edges."""
    edges = df.select(F.col("record_id").alias("child"), F.explode(F.map_values("parents")).alias("parent")).distinct()
    level = ids.select("record_id", F.col("record_id").alias("at"))
    out = None
    for hop in range(1, depth + 1):
        level = level.join(edges, F.col("at") == F.col("child")).select("record_id", F.col("parent").alias("at")).distinct()
        found = level.select("record_id", F.col("at").alias("ancestor"), F.lit(hop).alias("hop"))
        out = found if out is None else out.union(found)
    return out.groupBy("record_id", "ancestor").agg(F.min("hop").alias("hop"))


def visible(df: DataFrame, auths: DataFrame, user: str, workspace: str | None = None, authority: str = "read") -> DataFrame:
    """Records that a user may read: their own, those granted, and those of their workspace that nobody restricted."""
    granted = auths.where((F.col("user") == user) & (F.col("authority") == authority)).select("record_id", F.lit(True).alias("__granted"))
    restricted = auths.select("record_id", F.lit(True).alias("__restricted")).distinct()
    out = df.join(granted.distinct(), "record_id", "left").join(restricted, "record_id", "left")
    free = F.col("__restricted").isNull() & (F.lit(workspace is None) | (F.col("workspace") == workspace))
    return out.where(F.col("__granted").isNotNull() | free).drop("__granted", "__restricted")


def active(df: DataFrame, as_of: Column) -> DataFrame:
    """Records neither retired nor expired; the clock restarts when a record is verified. -1 never expires."""
    last = F.greatest("timestamp", "last_verified")
    late = (F.col("expiration") >= 0) & (F.unix_timestamp(last) + F.col("expiration") <= F.unix_timestamp(as_of))
    return df.where(~F.col("inactive_mark") & ~late)


def verify(df: DataFrame, ids: DataFrame, as_of: Column) -> DataFrame:
    marked = df.join(ids.select("record_id", F.lit(True).alias("__v")).distinct(), "record_id", "left")
    return marked.withColumn("last_verified", F.when(F.col("__v"), as_of).otherwise(F.col("last_verified"))).drop("__v")


def retire(df: DataFrame, ids: DataFrame) -> DataFrame:
    marked = df.join(ids.select("record_id", F.lit(True).alias("__v")).distinct(), "record_id", "left")
    return marked.withColumn("inactive_mark", F.col("inactive_mark") | F.col("__v").isNotNull()).drop("__v")


def purge(df: DataFrame, as_of: Column) -> DataFrame:
    return active(df, as_of)


def version_key(version: Column) -> Column:
    """v1.10.2b as a sortable struct: three numbers, then the letters after them."""
    part = lambda i: F.coalesce(F.try_to_number(F.regexp_extract(version, r"^v?(\d+)(?:\.(\d+))?(?:\.(\d+))?", i), F.lit("999999")).cast("int"), F.lit(0))
    return F.struct(part(1).alias("a"), part(2).alias("b"), part(3).alias("c"), F.regexp_extract(version, r"([a-z]*)$", 1).alias("d"))


def latest(df: DataFrame, keys: list[str]) -> DataFrame:
    w = Window.partitionBy(*keys).orderBy(version_key(F.col("version")).desc())
    return df.withColumn("__r", F.row_number().over(w)).where("__r = 1").drop("__r")


def variant(df: DataFrame, wanted: str, keys: list[str]) -> DataFrame:
    """The wanted variant of each record, or the default one where it is missing."""
    w = Window.partitionBy(*keys).orderBy((F.col("variant") == wanted).desc())
    return df.where(F.col("variant").isin(wanted, "default")).withColumn("__r", F.row_number().over(w)).where("__r = 1").drop("__r")


def merge_records(kb: DataFrame, incoming: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The knowledge base after a delta, and the rejected rows with a reason. One shuffle on record_id.

    In order: a row like a stored one (same id and content) adds its synonyms; one that contradicts a trusted
    stored record is dropped; if the new rows of an id contradict each other or an untrusted stored one, all
    new ones are dropped; the rest enters at a lower priority. The order of the incoming rows doesn't matter.
    """
    cols = ["record_id", "content_hash", "synonyms", "priority"]
    old = kb.select(*cols, "trusted").withColumn("stored", F.lit(True))
    add = incoming.select(*cols).withColumns({"trusted": F.lit(False), "stored": F.lit(False)})
    groups = old.unionByName(add).groupBy("record_id").agg(
        F.max(F.when(F.col("stored"), F.col("content_hash"))).alias("kept_hash"),
        F.bool_or(F.col("stored") & F.col("trusted")).alias("trusted"),
        F.max(F.when(F.col("stored"), F.col("priority"))).alias("kept_priority"),
        F.min(F.when(~F.col("stored"), F.col("content_hash"))).alias("low"),
        F.max(F.when(~F.col("stored"), F.col("content_hash"))).alias("high"),
        F.min(F.when(~F.col("stored"), F.col("priority"))).alias("new_priority"),
        F.collect_set(F.struct("content_hash", "synonyms", "stored")).alias("rows"),
    )
    lone = F.col("kept_hash").isNull()
    agreed = F.col("low").isNotNull() & (F.col("low") == F.col("high"))
    taken = F.when(lone, F.when(agreed, F.col("low"))).otherwise(F.col("kept_hash"))
    merged = groups.withColumn("content_hash", taken).where("content_hash is not null").select(
        "record_id",
        "content_hash",
        F.array_sort(F.array_distinct(F.flatten(F.transform(F.filter("rows", lambda r: r["stored"] | (r["content_hash"] == F.col("content_hash"))), lambda r: r["synonyms"])))).alias("synonyms"),
        F.when(lone, F.col("new_priority") - 1).otherwise(F.col("kept_priority")).alias("priority"),
        F.coalesce("trusted", F.lit(False)).alias("trusted"),
    )
    why = F.when(~lone & (F.col("r.content_hash") != F.col("kept_hash")), F.when(F.col("trusted"), "contradicts trusted").otherwise("contradicts stored"))
    why = F.when(lone & ~agreed, "contradicting new rows").otherwise(why)
    rejects = groups.select("record_id", "kept_hash", "trusted", "low", "high", F.explode("rows").alias("r")).where("not r.stored").withColumn("reason", why)
    return merged, rejects.where("reason is not null").select("record_id", F.col("r.content_hash").alias("content_hash"), "reason")


def from_json(df: DataFrame, column: str = "json", schema: str = "name string, type string, content string, synonyms array<string>") -> tuple[DataFrame, DataFrame]:
    """Rows parsed from mined JSON, and those that don't parse or name no record."""
    parsed = df.withColumn("__p", F.from_json(column, schema, {"mode": "PERMISSIVE"}))
    good = F.col("__p").isNotNull() & F.col("__p.name").isNotNull()
    return parsed.where(good).select("__p.*"), parsed.where(~good).drop("__p")


def edges(enums: DataFrame) -> DataFrame:
    """Relations between records by name: enum to column, column to table."""
    up = enums.select(F.concat_ws(":", F.lit("enum"), "col", "val").alias("subject"), F.lit("value of").alias("relation"), F.concat_ws(":", F.lit("column"), "col").alias("object"))
    top = enums.select(F.concat_ws(":", F.lit("column"), "col").alias("subject"), F.lit("column of").alias("relation"), F.concat_ws(":", F.lit("table"), "tab").alias("object")).distinct()
    return up.union(top)


def enum_records(enums: DataFrame) -> DataFrame:
    """Enum records of the values in tab, col, val."""
    rows = enums.select(
        "tab", "col",
        F.col("val").alias("name"),
        F.concat("col", F.lit(" = "), "val").alias("content"),
        F.lit("enum").alias("collection"), F.lit("auto").alias("source"),
        F.array(F.concat(F.lit("[COLUMN:"), "col", F.lit("]")), F.concat(F.lit("[ENUM:"), "val", F.lit("]")), F.concat(F.lit("[TABLE:"), "tab", F.lit("]"))).alias("tags"),
        F.array(F.lower("val")).alias("synonyms"),
        F.struct(F.col("tab").alias("table"), F.col("col").alias("column"), F.col("val").alias("value")).alias("resources"),
    )
    return new(rows, "enum")
