"""Token counts of sections by offset-mapped attribution.

Each document is encoded once, whole.  The byte lengths of its tokens give their character spans (a token that holds
part of a character spans that character), and an interval join of the sorted token and section spans attributes
every token.  A token that crosses a boundary goes by an explicit rule:

* start: to the section of its first character
* end: to the section of its last character
* most: to the section with most of its characters, the earlier one of equals
* share: to every section it touches, in proportion to its characters there

Defined results: null and empty texts have one empty section with no tokens where sections are lines; a null or empty
section list has no rows; sections are disjoint, sorted and clipped to the text, tokens outside all of them are
counted in none; equal rows get equal counts; an empty table gives none; other input columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from momenttree.llm import bpe
from momenttree.llm.runtime import BATCH_ROWS, ship

RULES = ("start", "end", "most", "share")


def token_spans(text: str, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First character and one past the last character of each token, from the tokens' byte lengths."""
    ends = np.cumsum(lengths)
    starts = ends - lengths
    if text.isascii():
        return starts, ends
    raw = np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8)
    char_of_byte = np.cumsum((raw & 0xC0) != 0x80) - 1
    return char_of_byte[starts], char_of_byte[ends - 1] + 1


def line_sections(text: str) -> np.ndarray:
    """(sections, 2) spans of the lines, each with the line end that closes it."""
    raw = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
    cuts = np.flatnonzero(raw == 10) + 1
    starts = np.concatenate([[0], cuts])
    if len(starts) > 1 and starts[-1] == len(raw):
        starts = starts[:-1]
    return np.column_stack([starts, np.append(starts[1:], len(raw))])


def attribute(first: np.ndarray, last: np.ndarray, sections: np.ndarray, rule: str) -> tuple[np.ndarray, np.ndarray]:
    """Tokens of each section by the rule, and how many tokens touch it along with another section or none."""
    n = len(sections)
    counts, crossing = np.zeros(n), np.zeros(n, np.int64)
    if not n or not len(first):
        return counts, crossing
    starts, ends = sections[:, 0], sections[:, 1]
    low = np.searchsorted(ends, first, "right")  # first section that ends after the token's start
    high = np.searchsorted(starts, last, "left") - 1  # last section that starts before the token's end
    inside = (low == high) & (starts[np.minimum(low, n - 1)] <= first) & (last <= ends[np.minimum(low, n - 1)])
    counts += np.bincount(low[inside], minlength=n)[:n]
    for k in np.flatnonzero(~inside & (low <= high)):
        a, b = first[k], last[k]
        touched = np.arange(low[k], high[k] + 1)
        overlap = np.minimum(ends[touched], b) - np.maximum(starts[touched], a)
        touched, overlap = touched[overlap > 0], overlap[overlap > 0]
        if not len(touched):
            continue
        crossing[touched] += 1
        if rule == "share":
            counts[touched] += overlap / (b - a)
        elif rule == "most":
            counts[touched[np.argmax(overlap)]] += 1
        else:
            at = a if rule == "start" else b - 1
            counts[touched[(starts[touched] <= at) & (at < ends[touched])]] += 1
    return counts, crossing


def count(docs: DataFrame, path: str | None = None, *, rule: str = "start", sections_col: str | None = None) -> DataFrame:
    """doc_id, section (0, 1, ...), first_char, end_char, n_tokens, n_crossing, doc_tokens; one row a section.

    sections_col: array<struct<first:int,end:int>> of disjoint, sorted character spans; lines where it is not given.
    """
    if rule not in RULES:
        raise ValueError(f"rule {rule!r} is none of {RULES}")
    ship(docs.sparkSession)
    path = path or bpe.default_vocabulary()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = bpe.load(path)
        size_of = np.zeros(max(known.bytes_of) + 1, np.int64)
        for i, b in known.bytes_of.items():
            size_of[i] = len(b)
        for whole in batches:
            for at in range(0, whole.num_rows, BATCH_ROWS):
                batch = whole.slice(at, BATCH_ROWS)
                keys = np.arange(batch.num_rows)
                given = batch.column(2).to_pylist() if sections_col else [None] * batch.num_rows
                spans, counts, crossings, totals, sizes = [], [], [], [], []
                for text, own in zip(batch.column(1).to_pylist(), given, strict=True):
                    text = text or ""
                    ids = np.frombuffer(known.encode_packed(text), "<u4")
                    if sections_col:
                        sections = np.array([(x["first"], x["end"]) for x in own or []], np.int64).reshape(-1, 2).clip(0, len(text))
                    else:
                        sections = line_sections(text)
                    first, last = token_spans(text, size_of[ids])
                    c, x = attribute(first, last, sections, rule)
                    spans.append(sections)
                    counts.append(c)
                    crossings.append(x)
                    sizes.append(len(sections))
                    totals.append(len(ids))
                sizes = np.array(sizes)
                spans = np.concatenate(spans)
                number = np.arange(len(spans)) - np.repeat(np.cumsum(sizes) - sizes, sizes)
                rows = np.repeat(keys, sizes)
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0).take(pa.array(rows)), pa.array(number), pa.array(spans[:, 0]), pa.array(spans[:, 1]), pa.array(np.concatenate(counts)), pa.array(np.concatenate(crossings)), pa.array(np.repeat(np.array(totals), sizes))],
                    ["doc_id", "section", "first_char", "end_char", "n_tokens", "n_crossing", "doc_tokens"],
                )

    columns = [F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text")]
    if sections_col:
        columns.append(F.col(sections_col).cast("array<struct<first:int,end:int>>").alias("sections"))
    return docs.select(columns).mapInArrow(run, "doc_id bigint, section bigint, first_char bigint, end_char bigint, n_tokens double, n_crossing bigint, doc_tokens bigint")
