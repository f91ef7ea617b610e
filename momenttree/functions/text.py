"""Text columns: words, sentences, stop words, stems."""

from __future__ import annotations

import glob
import os
import zipfile

import pyspark
from pyspark.sql import Column
from pyspark.sql import functions as F

LANGUAGES = ("english", "french", "german", "spanish")


def words(text: Column) -> Column:
    """Maximal runs of letters, lower-cased, in order; null text has none."""
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"[^\p{L}]+"), lambda w: w != "")


def sentences(text: Column) -> Column:
    """Non-empty stretches between full stops, exclamation and question marks and line ends."""
    return F.filter(F.split(F.coalesce(text, F.lit("")), r"[.!?\n]+"), lambda s: F.trim(s) != "")


def stop_list(languages: tuple[str, ...] = LANGUAGES) -> list[str]:
    """Spark's own stop lists, reduced to what words() can give; read from its library, so no session is needed."""
    home = os.environ.get("SPARK_HOME") or os.path.dirname(pyspark.__file__)
    jar = glob.glob(f"{home}/jars/spark-mllib_*.jar") or glob.glob(f"{os.path.dirname(pyspark.__file__)}/jars/spark-mllib_*.jar")
    with zipfile.ZipFile(jar[0]) as library:
        found = {w.lower() for language in languages for w in library.read(f"org/apache/spark/ml/feature/stopwords/{language}.txt").decode("utf-8").split()}
    return sorted(w for w in found if w.isalpha())


def without(tokens: Column, listed: list[str]) -> Column:
    """tokens without the listed ones; repeats stay."""
    known = F.array(*map(F.lit, listed))
    return F.filter(tokens, lambda w: ~F.array_contains(known, w))


#: Suffix patterns and what remains, tried in order, the first that fits counts.
STEM_RULES = [("(.{3,})(?:ational|ation)$", "$1"), ("(.{3,})(?:ingly|edly|ing|ed)$", "$1"), ("(.{3,})ies$", "$1y"), ("(.{3,})(?:ness|ment|ly)$", "$1"), ("(.{3,}[^s])s$", "$1")]


def stem(word: Column) -> Column:
    """A light suffix stemmer in plain expressions."""
    out = word
    for pattern, rest in reversed(STEM_RULES):
        out = F.when(word.rlike(pattern), F.regexp_replace(word, pattern, rest)).otherwise(out)
    return out


def strip_markup(html: Column) -> Column:
    """Text of a page: scripts, styles and tags dropped, common entities resolved, white space single."""
    text = F.regexp_replace(html, r"(?is)<(script|style)[^>]*>.*?</(script|style)>", " ")
    text = F.regexp_replace(text, r"(?s)<[^>]*>", " ")
    for entity, sign in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&nbsp;", " "), ("&amp;", "&")):
        text = F.replace(text, F.lit(entity), F.lit(sign))
    return F.trim(F.regexp_replace(text, r"\s+", " "))


def page_title(html: Column) -> Column:
    return F.regexp_extract(html, r"(?is)<title>(.*?)</title>", 1)
