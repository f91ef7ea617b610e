"""Shared pieces of the training-data operators: those of the package, and Arrow batches of texts."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa

from momenttree.runtime import cut, shared_dir, ship, spread, stored

__all__ = ["BATCH_ROWS", "cut", "shared_dir", "ship", "spread", "stored", "text_batches"]

#: Rows that a kernel takes at a time.
BATCH_ROWS = 1_000


def text_batches(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.Array, list[str]]]:
    """(keys, texts) of the first two columns in slices of BATCH_ROWS; null texts become empty."""
    for whole in batches:
        for at in range(0, whole.num_rows, BATCH_ROWS):
            batch = whole.slice(at, BATCH_ROWS)
            yield batch.column(0), [x or "" for x in batch.column(1).to_pylist()]
