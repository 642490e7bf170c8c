"""Arrow helpers of the operators that use Python on the executors."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

#: Rows of an Arrow batch are cut to blocks of about so many bytes of text, so that memory does not grow with the texts.
BLOCK_BYTES = 8 << 20


def blocks(batches: Iterator[pa.RecordBatch], text: str = "text", most: int | None = None) -> Iterator[pa.RecordBatch]:
    """Slices of the batches with at most ``most`` (else BLOCK_BYTES) bytes of text each (one row at least)."""
    most = most or BLOCK_BYTES
    for batch in batches:
        if not batch.num_rows:
            continue
        lengths = pc.fill_null(pc.binary_length(batch.column(text)), 0).to_pylist()
        start, total = 0, 0
        for i, n in enumerate(lengths):
            if total and total + n > most:
                yield batch.slice(start, i - start)
                start, total = i, 0
            total += n
        yield batch.slice(start)


def texts_of(batch: pa.RecordBatch, text: str = "text") -> list[str]:
    return [t or "" for t in batch.column(text).to_pylist()]


def per_document(docs: DataFrame, function: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: str, columns: tuple[str, ...] = ("doc_id", "text")) -> DataFrame:
    """``mapInArrow`` over the columns it needs, so that the scan reads no others."""
    return docs.select(*columns).mapInArrow(function, schema)
