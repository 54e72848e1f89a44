"""Chat formatting as a prefix tree: turns that conversations share at their start are emitted once.

A node is a turn after a given history. Nodes are emitted depth-first, by a range-partitioned sort on a key that names the
branches on the way to the node and its depth: every node stands before its descendants and subtrees stay together,
however many conversations share a root and however long one is. Offsets in the stream are prefix sums over that
sort. Each node has its first position id (the length of its history) and the intervals of the stream that its tokens
may attend to: its ancestors', merged where they touch. Units are code points; `count` can be another counter of
tokens. All is done on a row per turn by windows and joins; no history is ever listed node by node.

The template is one line of control strings around a turn. Inside texts and roles `<|` becomes `<\\|`, and
each run of backslashes between `<` and `|` gets one more, so no text holds a control string and unescaping
gives the text back.

Defined cases: a null text or role is empty; turns are ordered by turn, nulls first, then role and a hash of the
text; a repeated row is a turn of its own; an empty table gives no rows; a conversation of one turn is a leaf.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kbspark.llm.common import ranked
from kbspark.session import keep

# The control strings of the template.
START, END = "<|im_start|>", "<|im_end|>"


def escape(text: Column) -> Column:
    return F.regexp_replace(text, r"<(\\*)\|", r"<$1\\|")


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, r"<\\(\\*)\|", r"<$1|")


def escape_role(role: Column) -> Column:
    """Roles stand on the template's first line, so line ends are escaped too."""
    return escape(F.replace(F.replace(role, F.lit("\\"), F.lit("\\\\")), F.lit("\n"), F.lit("\\n")))


def unescape_role(role: Column) -> Column:
    held = F.replace(unescape(role), F.lit("\\\\"), F.lit("\x00"))
    return F.replace(F.replace(held, F.lit("\\n"), F.lit("\n")), F.lit("\x00"), F.lit("\\"))


def format_turn(role: Column, text: Column) -> Column:
    return F.concat(F.lit(START), escape_role(role), F.lit("\n"), escape(text), F.lit(END), F.lit("\n"))


def build_tree(turns: DataFrame, count=F.length) -> tuple[DataFrame, DataFrame]:
    """The stream (a row per node) and the places of the conversations' turns in it.

    stream: begin, end, depth, position (of its first token), parent_begin (null for a root), formatted, loss_start and
    loss_end (within formatted; equal for turns without loss), attend (intervals of the stream). places: conv_id, depth,
    begin. The tree is built from hashes and lengths, a row per turn; each distinct turn's text joins it once, at the end.
    """
    role, text = F.coalesce("role", F.lit("")), F.coalesce("text", F.lit(""))
    rows = turns.select("conv_id", "turn", role.alias("role"), text.alias("text"))
    own = F.unhex(F.substring(F.sha2(F.concat("role", F.lit("\n"), F.length("text").cast("string"), F.lit("\n"), "text"), 256), 1, 32))
    formatted = format_turn(F.col("role"), F.col("text"))
    said = Window.partitionBy("conv_id").orderBy("turn", "role", "own")
    lean = rows.select("conv_id", "turn", "role", own.alias("own"), count(formatted).cast("long").alias("n"))
    lean = lean.withColumn("depth", F.row_number().over(said) - 1)
    # A node's id is a hash of the sums, over its history and itself, of two hashes of (depth, turn): a running window.
    hashed = F.sha2(F.concat(F.col("depth").cast("string"), F.lit("|"), F.hex("own")), 256)
    part = lambda at: F.conv(F.substring(hashed, at, 15), 16, 10).cast("decimal(20,0)")
    deep = Window.partitionBy("conv_id").orderBy("depth")
    upto = deep.rowsBetween(Window.unboundedPreceding, 0)
    lean = lean.select("conv_id", "depth", "own", "n", F.sum(part(1)).over(upto).alias("s1"), F.sum(part(16)).over(upto).alias("s2"))
    node = F.unhex(F.substring(F.sha2(F.concat_ws("|", "depth", "s1", "s2"), 256), 1, 32))
    lean = keep(lean.select("conv_id", "depth", "own", "n", node.alias("node")), "turns")

    # Nodes of one history that the same conversations pass are a run; a sort key names the runs on the way, then the depth.
    passed = lean.groupBy("node").agg(F.count(F.lit(1)).alias("passed"))
    counted = lean.join(passed, "node")
    starts = (F.col("depth") == 0) | (F.lag("passed").over(deep) != F.col("passed"))
    counted = counted.withColumn("run", F.when(starts, F.concat(F.lit("01"), F.substring(F.hex("node"), 1, 16))))
    key = F.unhex(F.concat(F.array_join(F.collect_list("run").over(upto), ""), F.lit("00"), F.lpad(F.hex("depth"), 8, "0")))
    before = deep.rowsBetween(Window.unboundedPreceding, -1)
    nodes = counted.select("node", "own", "depth", "n", key.alias("key"), F.coalesce(F.sum("n").over(before), F.lit(0)).alias("position")).dropDuplicates(["node"])
    placed, _, _ = ranked(nodes, ["key", "node"], weight="n")
    placed = keep(placed.select("node", "own", "depth", "position", F.col("__before").alias("begin"), (F.col("__before") + F.col("n")).alias("end")), "nodes")

    # Ancestors that stand one after the other make one interval; a turn opens another where it doesn't follow its parent.
    # A root that many share is split by the skew join, as each node is once on the right.
    at = lean.select("conv_id", "depth", "node").join(placed.select("node", "begin", "end"), "node")
    at = keep(at.withColumn("parent_begin", F.lag("begin").over(deep)).withColumn("parent_end", F.lag("end").over(deep)), "places")
    opens = (F.col("depth") == 0) | (F.col("begin") != F.col("parent_end"))
    spans = at.withColumn("head", F.last(F.when(opens, F.col("begin")), True).over(upto))
    spans = spans.withColumn("closed", F.when(opens & (F.col("depth") > 0), F.struct(F.lag("head").over(deep).alias("begin"), F.col("parent_end").alias("end"))))
    now = F.when(F.col("head") < F.col("begin"), F.array(F.struct(F.col("head").alias("begin"), F.col("begin").alias("end")))).otherwise(F.array().cast("array<struct<begin:bigint,end:bigint>>"))
    spans = spans.select("node", "parent_begin", F.concat(F.collect_list("closed").over(upto), now).alias("attend")).dropDuplicates(["node"])

    start = len(START) + F.length(escape_role(F.col("role"))) + 1
    stop = start + F.when(F.col("role") == "assistant", F.length(escape(F.col("text")))).otherwise(0)
    texts = rows.select(own.alias("own"), formatted.alias("formatted"), start.alias("loss_start"), stop.alias("loss_end")).dropDuplicates(["own"])
    stream = placed.join(spans, "node").join(texts, "own").drop("own", "node")
    return keep(stream, "stream"), at.select("conv_id", "depth", "begin")


def read_back(stream: DataFrame, places: DataFrame) -> DataFrame:
    """conv_id, n_turns, turns_sha256, loss_chars, loss_sha256 and formatted_chars, from the output alone.

    Turns are parsed from the formatted text at a conversation's places, and the loss text is what stands under
    the loss mask, unescaped.
    """
    parts = places.join(stream.select("begin", "formatted", "loss_start", "loss_end"), "begin")
    whole = parts.groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("depth", "formatted", "loss_start", "loss_end"))).alias("ps"))
    text = F.array_join(F.transform("ps", lambda p: p["formatted"]), "")
    loss = F.array_join(F.transform("ps", lambda p: unescape(F.substr(p["formatted"], p["loss_start"] + 1, p["loss_end"] - p["loss_start"]))), "")
    whole = whole.select("conv_id", text.alias("formatted"), loss.alias("loss"))
    pattern = F.lit(r"(?s)<\|im_start\|>([^\n]*)\n(.*?)<\|im_end\|>\n")
    roles, texts = F.regexp_extract_all("formatted", pattern, 1), F.regexp_extract_all("formatted", pattern, 2)
    turns = F.zip_with(roles, texts, lambda r, t: F.concat(unescape_role(r), F.lit("\n"), unescape(t), F.lit("\n")))
    return whole.select("conv_id", turns.alias("turns"), "loss", F.length("formatted").cast("long").alias("formatted_chars")).select(
        "conv_id",
        F.size("turns").cast("long").alias("n_turns"),
        F.sha2(F.array_join("turns", "").cast("binary"), 256).alias("turns_sha256"),
        F.length("loss").cast("long").alias("loss_chars"),
        F.sha2(F.col("loss").cast("binary"), 256).alias("loss_sha256"),
        "formatted_chars",
    )
