"""Text functions on columns."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

# Endings that the lemma layer takes off, by language, longest first.
ENDINGS = {"en": ["ings", "ing", "ies", "es", "ed", "s"], "de": ["ungen", "en", "er", "e", "n"], "fr": ["ements", "es", "e", "s"], "es": ["ciones", "es", "os", "as", "s"]}


def words(text: Column) -> Column:
    return F.filter(F.split(text, r"[^\p{L}\p{N}_]+"), lambda w: w != "")


def lemma(word: Column, lang: str = "en") -> Column:
    """A word without the first ending that leaves at least three letters."""
    out = word
    for e in reversed(ENDINGS[lang]):
        out = F.when(F.endswith(word, F.lit(e)) & (F.length(word) >= len(e) + 3), F.substr(word, F.lit(1), F.length(word) - len(e))).otherwise(out)
    return out


def lemmatize(text: Column, lang: str = "en") -> Column:
    return F.array_join(F.transform(words(F.lower(text)), lambda w: lemma(w, lang)), " ")


def ngrams(ws: Column, n: int) -> Column:
    m = F.size(ws) - n + 1
    return F.when(m > 0, F.transform(F.sequence(F.lit(1), m), lambda i: F.array_join(F.slice(ws, i, n), " "))).otherwise(F.array().cast("array<string>"))


def without_comments(sql: Column) -> Column:
    return F.trim(F.regexp_replace(F.regexp_replace(sql, r"(?s)/\*.*?\*/", " "), r"--[^\n]*", " "))
