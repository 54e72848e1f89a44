"""Extraction and mining: chunks, page text, definitions, synonyms from labelled questions, SQL facts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from kbspark.session import cut
from kbspark.functions.text import words


def chunk(docs: DataFrame, size: int = 500, overlap: int = 50) -> DataFrame:
    """doc_id, chunk_no, chunk: overlapping pieces; the first size - overlap of each re-join to the text."""
    step = size - overlap
    last = F.greatest(F.ceil((F.length("text") - overlap) / step).cast("int"), F.lit(1)) - 1
    at = docs.select("doc_id", "text", F.explode(F.sequence(F.lit(0), last)).alias("chunk_no"))
    return at.select("doc_id", "chunk_no", F.substr("text", F.col("chunk_no") * step + 1, F.lit(size)).alias("chunk"))


ENTITIES = [("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&nbsp;", " "), ("&amp;", "&")]


def page_text(pages: DataFrame) -> DataFrame:
    """page_id and text: scripts, styles and tags out, blocks parted by line ends, entities put back."""
    t = F.regexp_replace("html", r"(?is)<(script|style)\b.*?</\1>", "")
    t = F.regexp_replace(F.regexp_replace(t, r"(?i)</?(p|div|li|h[1-6]|br|tr)\b[^>]*>", "\n"), "<[^>]*>", "")
    for a, b in ENTITIES:
        t = F.replace(t, F.lit(a), F.lit(b))
    return pages.select("page_id", F.regexp_replace(F.regexp_replace(t, r"\s*\n\s*", "\n"), r"^\s+|\s+$", "").alias("text"))


def definitions(docs: DataFrame) -> DataFrame:
    """doc_id, name, meaning, kind from lines like `x = formula`, `x means y` and `x, also called y`."""
    line = docs.select("doc_id", F.explode(F.split("text", "\n")).alias("line"))
    kinds = {"formula": r"^\s*([\w ]{2,40}?)\s*=\s*(.{2,200})$", "meaning": r"^\s*([\w ]{2,40}?) (?:means|is defined as) (.{2,200})$", "alias": r"^\s*([\w ]{2,40}?), also called ([\w ]{2,60})\.?$"}
    found = F.lit(None).cast("struct<kind:string,name:string,meaning:string>")
    for kind, p in reversed(kinds.items()):
        found = F.when(F.col("line").rlike(p), F.struct(F.lit(kind).alias("kind"), F.regexp_extract("line", p, 1).alias("name"), F.regexp_extract("line", p, 2).alias("meaning"))).otherwise(found)
    return line.select("doc_id", found.alias("f")).where("f is not null").select("doc_id", "f.*")


def license_lines(docs: DataFrame) -> DataFrame:
    """wording and n_docs: one special record for each license wording."""
    line = docs.select("doc_id", F.explode(F.split("text", "\n")).alias("wording"))
    hit = line.where(F.col("wording").rlike(r"^(Licensed|Released|This work is licensed) under .*\.$"))
    return hit.groupBy("wording").agg(F.count_distinct("doc_id").alias("n_docs"))


def mine_synonyms(questions: DataFrame, values: DataFrame, at_least: int = 2) -> DataFrame:
    """value, word, support: question words that go with a value in the labelled SQL and aren't the value itself.

    questions: text and gold_sql. A word is credited if it comes with the value at least so often, and nearly
    always when the word occurs.
    """
    # Numbered once and kept, so both sides of the join below mean the same question.
    q = cut(questions.select(F.monotonically_increasing_id().alias("q"), "text", F.regexp_extract_all("gold_sql", F.lit("'([^']+)'"), 1).alias("vals")))
    v = q.select("q", F.explode(F.array_distinct("vals")).alias("value")).join(values, "value", "left_semi")
    w = q.select("q", F.explode(F.array_distinct(words(F.lower("text")))).alias("word"))
    both = v.join(w, "q").groupBy("value", "word").agg(F.count(F.lit(1)).alias("support"))
    alone = w.groupBy("word").agg(F.count(F.lit(1)).alias("n"))
    return both.join(alone, "word").where((F.col("support") >= at_least) & (F.col("support") >= 0.9 * F.col("n"))).select("value", "word", "support")


def vote(found: DataFrame, key: list[str], runs: str, at_least: int) -> DataFrame:
    """Entries that enough independent runs agree on."""
    return found.groupBy(*key).agg(F.count_distinct(runs).alias("votes")).where(F.col("votes") >= at_least)


def plan_of(spark: SparkSession, sql: str):
    return spark._jsparkSession.sessionState().sqlParser().parsePlan(sql)


def walk(node):
    """All nodes of a parsed plan: children, CTE bodies, and plans inside expressions."""
    yield node
    for part in ("children", "innerChildren", "subqueries"):
        kids = getattr(node, part)()
        for i in range(kids.size()):
            kid = kids.apply(i)
            if hasattr(kid, "nodeName") and "LogicalPlan" not in str(type(kid)):
                yield from walk(kid)


def facts(spark: SparkSession, sql: str) -> list[tuple[str, str, str, str, str]]:
    """kind, table, column, op, value of what a query mentions, from the parsed plan's text; errors give one row."""
    import re

    try:
        nodes = list(walk(plan_of(spark, sql)))
    except Exception as e:  # a query that doesn't parse is data here
        return [("error", "", "", "", type(e).__name__)]
    out, tables = [], []
    for n in nodes:
        text = n.simpleString(1000)
        if n.nodeName() == "UnresolvedRelation":
            name = re.search(r"\[(\w+)\]", text)
            if name:
                tables.append(name[1])
                out.append(("table", name[1], "", "", ""))
        for col in re.findall(r"'(?:\w+\.)?([a-z]\w*_?\w+)\b", text):
            if n.nodeName() not in ("UnresolvedRelation", "SubqueryAlias"):
                out.append(("column", "", col, "", ""))
        if n.nodeName() == "Filter":
            for col, op, v in re.findall(r"\('(?:\w+\.)?(\w+) (=|>|<|>=|<=|LIKE) ([^()]+?)\)", text):
                out.append(("predicate", "", col, op, v))
        if n.nodeName() in ("Aggregate", "Sort", "Join", "Distinct", "GlobalLimit"):
            out.append(("clause", "", "", "", n.nodeName().lower()))
    return sorted(set(out))


# Functions whose change tells the cause of an error, by that cause.
CALLS = {"null": ("coalesce", "ifnull", "nvl", "isnull", "isnotnull"), "concat": ("concat", "concat_ws"), "computation": ("avg", "sum", "count", "min", "max")}


def calls(spark: SparkSession, sql: str) -> list[tuple[str, str, str, str, str]]:
    """Like facts: the functions of CALLS that a query has, and by what round number it scales; none if it doesn't parse."""
    import re

    try:
        texts = [n.simpleString(1000) for n in walk(plan_of(spark, sql))]
    except Exception:  # facts says that it doesn't parse
        return []
    known = {f for fs in CALLS.values() for f in fs}
    out = {("call", "", f, "", "") for t in texts for f in re.findall(r"(\w+)\(", t) if f in known}
    return sorted(out | {("scale", "", "", op, n) for t in texts for op, n in re.findall(r" ([*/]) (10+(?:\.0+)?)\b", t)})


def verify_facts(found: DataFrame, catalog: DataFrame, enums: DataFrame) -> DataFrame:
    """Adds whether the table, column or value of each fact exists."""
    cols = catalog.select(F.col("col").alias("column"), F.lit(True).alias("c")).distinct()
    tabs = catalog.select(F.col("tab").alias("table"), F.lit(True).alias("t")).distinct()
    vals = enums.select(F.col("col").alias("column"), F.col("val").alias("value"), F.lit(True).alias("v")).distinct()
    out = found.join(cols, "column", "left").join(tabs, "table", "left").join(vals, ["column", "value"], "left")
    known = F.when(F.col("kind") == "table", F.col("t")).when(F.col("kind") == "column", F.col("c")).when(F.col("kind") == "predicate", F.coalesce("v", F.col("c") & ~F.col("op").isin("=")))
    return out.select("kind", "table", "column", "op", "value", F.coalesce(known, F.lit(False)).alias("exists"))


def contrast(a: DataFrame, b: DataFrame) -> DataFrame:
    """Facts of one query and not the other, with the side they are on."""
    return a.exceptAll(b).withColumn("side", F.lit("gold")).union(b.exceptAll(a).withColumn("side", F.lit("predicted")))

