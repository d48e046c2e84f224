"""Texts to terms with built-in functions: tokens, stop words, tags, exact copies."""

from __future__ import annotations

import os
from functools import cache

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

LANGUAGES = ("english", "german", "french", "spanish")
LETTERS = r"(\p{L}+)"


STOP_DIR = os.path.join(os.path.dirname(os.path.abspath(__file__)), "stopwords")


@cache
def stop_words(languages: tuple[str, ...] = LANGUAGES) -> tuple[str, ...]:
    """The words of ``stopwords/<language>.txt``: the lists that Spark's StopWordsRemover ships, one word a line."""
    out: set[str] = set()
    for lang in languages:
        with open(os.path.join(STOP_DIR, f"{lang}.txt"), encoding="utf-8") as f:
            out.update(line.strip() for line in f)
    return tuple(sorted(out - {""}))


def words(text: Column, pattern: str = LETTERS) -> Column:
    return F.regexp_extract_all(F.lower(text), F.lit(pattern), 1)


def tokenize(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text", pattern: str = LETTERS, min_len: int = 1) -> DataFrame:
    """(doc_id, term), one row for each occurrence."""
    out = docs.select(F.col(id_col).alias("doc_id"), F.explode(words(F.col(text_col), pattern)).alias("term"))
    return out.where(F.length("term") >= min_len) if min_len > 1 else out


def drop_stop_words(tokens: DataFrame, languages: tuple[str, ...] = LANGUAGES, extra: tuple[str, ...] = ()) -> DataFrame:
    """Rows whose term is in none of the lists; the lists have a few hundred words each and are broadcast."""
    listed = sorted({*stop_words(tuple(languages)), *extra})
    if not listed:
        return tokens
    stop = tokens.sparkSession.createDataFrame([(w,) for w in listed], "term string")
    return tokens.join(F.broadcast(stop), "term", "left_anti").select(*tokens.columns)


def html_to_text(html: Column) -> Column:
    """Visible text: scripts, styles and tags become blanks, the five basic entities are resolved."""
    out = F.regexp_replace(html, r"(?is)<(script|style)\b.*?</\1\s*>", " ")
    out = F.regexp_replace(out, r"(?s)<!--.*?-->", " ")
    out = F.regexp_replace(out, r"(?s)<[^>]*>", " ")
    for name, char in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&amp;", "&")):
        out = F.replace(out, F.lit(name), F.lit(char))
    return out


def drop_duplicate_docs(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One document for each text, that of the smallest id. Only (hash, id) is aggregated; texts stay where they are
    unless the list of what goes is too long to broadcast."""
    key = F.sha2(F.coalesce(F.col(text_col), F.lit("")), 256)
    first = docs.groupBy(key.alias("k")).agg(F.min(id_col).alias("first"))
    keyed = docs.withColumn("__k", key)
    return keyed.join(first, F.col("__k") == F.col("k")).where(F.col(id_col) == F.col("first")).select(*docs.columns)
