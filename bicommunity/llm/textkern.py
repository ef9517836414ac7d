"""Helpers for kernels that see texts as UTF-8 bytes in Arrow batches."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa

#: Bytes of text that a kernel handles at once; a longer text goes alone.
SLICE_BYTES = 4 << 20


def slices(batches: Iterator[pa.RecordBatch], column: str) -> Iterator[tuple[pa.RecordBatch, list[bytes | None]]]:
    """Cut batches so that each piece holds about SLICE_BYTES of text; yields the
    piece and the texts as bytes."""
    for batch in batches:
        values = batch.column(column).cast(pa.binary()).to_pylist()
        start, total = 0, 0
        for i, v in enumerate(values):
            total += len(v) if v else 0
            if total >= SLICE_BYTES:
                yield batch.slice(start, i + 1 - start), values[start : i + 1]
                start, total = i + 1, 0
        if start < len(values):
            yield batch.slice(start), values[start:]


def split_words(text: bytes | None) -> list[bytes]:
    """Words of the pattern [^\\x20\\x09-\\x0D]+ (bytes.split cuts at exactly these)."""
    return text.split() if text else []
