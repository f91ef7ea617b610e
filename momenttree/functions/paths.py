"""Path algebra on columns and strings: o, o/1, o/1/2, ..."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

ROOT = "o"


def parent(path: Column) -> Column:
    """Null for the root."""
    return F.when(path.contains("/"), F.regexp_replace(path, r"/[^/]*$", ""))


def suffix(path: Column) -> Column:
    """Index among its siblings; null for the root."""
    return F.when(path.contains("/"), F.substring_index(path, "/", -1).cast("int"))


def level(path: Column) -> Column:
    return F.length(path) - F.length(F.replace(path, F.lit("/"), F.lit("")))


def is_below(path: Column, top: str) -> Column:
    """Whether path lies strictly under top."""
    return path.startswith(top + "/")


def parent_of(path: str) -> str | None:
    return path.rpartition("/")[0] or None


def level_of(path: str) -> int:
    return path.count("/")


def most_topics(width: int, height: int) -> int:
    """Topics of a full tree."""
    return height + 1 if width == 1 else (width ** (height + 1) - 1) // (width - 1)
