"""Operator 8, token identifiers in Parquet files.

Layout: one file per range of doc_id, rows in ascending doc_id order.  ``ids`` is a list column,
dictionary-encoded (a vocabulary of up to 2^17 entries stays in the dictionary page, so identifiers
take their bit width); doc_id, n_tokens and start_in_file are plain columns of their own, so that
metadata reads touch no tokens.  Row groups and pages have fixed byte sizes, and the page index that
the writer adds lets a range of doc_id skip pages.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .vocabulary import ENCODED_BYTES, encoder
from .words import blocks

SCHEMA = "doc_id long, file_no int, start_in_file long, n_tokens long, ids array<int>"
LAYOUT = {
    "parquet.block.size": str(32 << 20),
    "parquet.page.size": str(1 << 20),
    "parquet.enable.dictionary": "true",
    "parquet.dictionary.page.size": str(2 << 20),
    "compression": "zstd",
}


def write_tokens(docs: DataFrame, path: str, vocabulary: str, end: int = 0, files: int | None = None) -> None:
    """Encodes the whole text of each row, appends ``end`` and writes files in ascending doc_id order to ``path``.

    A null or empty text becomes the end identifier alone.  Rows with a null doc_id come first;
    repeated rows are written each.  An empty table writes files without rows.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode, start, part = encoder(vocabulary, end).encode_all, 0, TaskContext.get().partitionId()
        for batch in blocks(batches, most=ENCODED_BYTES):
            ids = encode(batch.column("text"))
            ends = ids.offsets.to_numpy()[1:].astype("int64")
            lengths = np.diff(ends, prepend=0)
            starts = start + ends - lengths
            start += int(ends[-1])
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), pa.array([part] * batch.num_rows, pa.int32()), pa.array(starts), pa.array(lengths), ids],
                ["doc_id", "file_no", "start_in_file", "n_tokens", "ids"],
            )

    own = docs.select("doc_id", "text")
    dealt = own.repartitionByRange(files, "doc_id") if files else own.repartitionByRange("doc_id")
    dealt.sortWithinPartitions("doc_id").mapInArrow(run, SCHEMA).write.options(**LAYOUT).parquet(path)


def read_tokens(spark: SparkSession, path: str, first: int | None = None, last: int | None = None, columns: tuple[str, ...] = ("doc_id", "n_tokens", "ids")) -> DataFrame:
    """Rows of the files with doc_id in [first, last]; only the named columns are read."""
    df = spark.read.parquet(path)
    for bound, test in ((first, F.col("doc_id") >= F.lit(first)), (last, F.col("doc_id") <= F.lit(last))):
        if bound is not None:
            df = df.where(test)
    return df.select(*columns)


def token_digest(spark: SparkSession, path: str) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) from the files: start counts the identifiers of all documents before."""
    table = spark.read.schema(SCHEMA).parquet(path)
    totals = table.groupBy("file_no").agg(F.sum("n_tokens").alias("__n"))
    # one row for each file
    before = totals.select("file_no", F.coalesce(F.sum("__n").over(W.partitionBy(F.lit(0)).orderBy("file_no").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("__before"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column("ids")
            flat, at = np.ascontiguousarray(ids.values.to_numpy(zero_copy_only=False), "<u4"), ids.offsets.to_pylist()
            crc = [zlib.crc32(flat[a:b]) for a, b in zip(at, at[1:], strict=False)]
            n = pa.array(np.diff(np.array(at, "int64")))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("file_no"), batch.column("start_in_file"), n, pa.array(crc, pa.int64())], ["doc_id", "file_no", "start_in_file", "n_tokens", "ids_crc32"])

    digests = table.select("doc_id", "file_no", "start_in_file", "ids").mapInArrow(run, "doc_id long, file_no int, start_in_file long, n_tokens long, ids_crc32 long")
    return digests.join(F.broadcast(before), "file_no").select("doc_id", (F.col("__before") + F.col("start_in_file")).alias("start"), "n_tokens", "ids_crc32")
