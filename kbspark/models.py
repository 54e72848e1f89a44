"""Language-model steps behind a batch interface. A provider turns prompts into replies; the engine builds prompts,
checks replies and verifies what they claim by execution. Offline, replies come from rules or from a table."""

from __future__ import annotations

import json
import re
from abc import ABC, abstractmethod
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


class TextProvider(ABC):
    """reply(df, prompt): df with a reply column."""

    @abstractmethod
    def reply(self, df: DataFrame, prompt: str = "prompt") -> DataFrame: ...


class RuleProvider(TextProvider):
    """Replies by a plain function of the prompt, in Arrow batches."""

    def __init__(self, rule: Callable[[str], str]):
        self.rule = rule

    def reply(self, df: DataFrame, prompt: str = "prompt") -> DataFrame:
        rule, at = self.rule, df.columns.index(prompt)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                made = [None if p is None else rule(p) for p in b.column(at).to_pylist()]
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(made, pa.string())], [*b.schema.names, "reply"])

        from pyspark.sql.types import StringType, StructField, StructType

        return df.mapInArrow(run, StructType([*df.schema.fields, StructField("reply", StringType())]))


class ReplayProvider(TextProvider):
    """Stored replies (prompt_hash, reply), joined by the prompt's hash; prompts without one get null."""

    def __init__(self, stored: DataFrame):
        self.stored = stored

    def reply(self, df: DataFrame, prompt: str = "prompt") -> DataFrame:
        s = self.stored.select(F.col("prompt_hash").alias("__h"), "reply").dropDuplicates(["__h"])
        return df.withColumn("__h", F.sha2(prompt, 256)).join(s, "__h", "left").drop("__h")


def store(df: DataFrame, prompt: str = "prompt") -> DataFrame:
    return df.select(F.sha2(prompt, 256).alias("prompt_hash"), "reply")


def checked_json(df: DataFrame, schema: str, reply: str = "reply") -> DataFrame:
    """Rows whose reply parses to the schema, as columns of parsed."""
    return df.withColumn("parsed", F.from_json(reply, schema, {"mode": "PERMISSIVE"})).where("parsed is not null")


def definition_rule(prompt: str) -> str:
    """Offline extraction: `x = y` and `x means y` lines of the prompt as JSON."""
    found = [{"name": m[1].strip(), "type": "metric" if m[2] == "=" else "term", "content": m[3].strip()} for m in re.finditer(r"^\s*([\w ]{2,40}?) (=|means) (.+)$", prompt, re.M)]
    return json.dumps(found)
