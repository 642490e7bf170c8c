"""Operator 6, bounded-space online best-fit packing.

Texts are encoded where they are read; from then on only rows of about 40 bytes per piece move.
Each packing task holds at most ``OPEN_BINS`` open sequences in lists keyed by their free space; a
bitset of the free spaces that occur finds the tightest fit in one step, and the fullest sequence
closes first when too many are open.  Sequences with room left are packed against one another in a
second round by the same rule, so a task never holds more than the open sequences.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialise
from .vocabulary import ENCODED_BYTES, encoder, vocabulary_path
from .words import blocks, per_document

CAPACITY = 2048
OPEN_BINS = 1024
#: Tokens and pieces that one packing task takes at most, but for chance.
TASK_TOKENS = 40_000_000
TASK_ROWS = 500_000
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"
#: A sequence with less than this share of free space isn't packed again.
TIGHT = 0.01


def pieces(docs: DataFrame, vocabulary: str, capacity: int = CAPACITY, end: int = 0) -> DataFrame:
    """(doc_id, piece, start, length, ids_crc32): each document's identifiers, cut only where longer than ``capacity``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = encoder(vocabulary, end).encode_all
        for batch in blocks(batches, most=ENCODED_BYTES):
            lists = encode(batch.column("text"))
            at, ids = lists.offsets.to_pylist(), np.ascontiguousarray(lists.values.to_numpy(), "<u4")
            rows: list[tuple] = []
            for doc, first, last in zip(batch.column("doc_id").to_pylist(), at, at[1:], strict=False):
                for k, a in enumerate(range(first, last, capacity)):
                    b = min(a + capacity, last)
                    rows.append((doc, k, a - first, b - a, zlib.crc32(ids[a:b])))
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], ["doc_id", "piece", "start", "length", "ids_crc32"])

    return per_document(docs, run, PIECES)


class BestFit:
    """Online best fit with a bounded number of open bins.

    ``put(length)`` returns (bin, offset).  Bins are numbered from 0; ``used`` holds their fill.
    """

    def __init__(self, capacity: int, open_bins: int) -> None:
        self.capacity, self.open_bins = capacity, open_bins
        self.by_free: list[list[int]] = [[] for _ in range(capacity + 1)]
        self.bits = 0  # bit f is set while an open bin has f free
        self.open = 0
        self.used: list[int] = []

    def _take(self, free: int) -> int:
        own = self.by_free[free]
        number = own.pop()
        if not own:
            self.bits ^= 1 << free
        self.open -= 1
        return number

    def put(self, length: int) -> tuple[int, int]:
        fitting = self.bits >> length
        if fitting:
            free = length + (fitting & -fitting).bit_length() - 1
            number = self._take(free)
        else:
            if self.open >= self.open_bins:
                self._take((self.bits & -self.bits).bit_length() - 1)  # the fullest closes
            number, free = len(self.used), self.capacity
            self.used.append(0)
        offset = self.capacity - free
        free -= length
        self.used[number] = self.capacity - free
        if free:
            self.by_free[free].append(number)
            self.bits |= 1 << free
            self.open += 1
        return number, offset


def _pack(lengths: Iterable[int], capacity: int, open_bins: int) -> tuple[list[tuple[int, int]], BestFit]:
    packer = BestFit(capacity, open_bins)
    return [packer.put(n) for n in lengths], packer


def _numbered(partition: int, number: int) -> int:
    return (partition << 32) | number


def pack(items: DataFrame, capacity: int = CAPACITY, open_bins: int = OPEN_BINS, task_tokens: int = TASK_TOKENS) -> DataFrame:
    """Adds sequence_id and offset to pieces (columns of :data:`PIECES`, none longer than ``capacity``).

    Items reach their task in the order of a hash of (doc_id, piece), so reruns agree.
    """
    items = materialise(items, "pieces")
    total, rows = items.agg(F.coalesce(F.sum("length"), F.lit(0)), F.count("*")).first()
    tasks = max(1, -(-total // task_tokens), -(-rows // TASK_ROWS))
    dealt = items.withColumn("__h", F.xxhash64("doc_id", "piece", "start")).repartition(tasks, "__h").sortWithinPartitions("__h", "doc_id", "piece")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        partition = TaskContext.get().partitionId()
        table = pa.Table.from_batches([*batches]) if (batches := [*batches]) else None
        if table is None or not table.num_rows:
            return
        places, packer = _pack(table.column("length").to_pylist(), capacity, open_bins)
        bins, offsets = zip(*places, strict=True)
        loose = [packer.capacity - packer.used[b] > TIGHT * capacity for b in bins]
        out = table.drop_columns(["__h"]).append_column("sequence_id", pa.array([_numbered(partition, b) for b in bins], pa.int64()))
        yield from out.append_column("offset", pa.array(offsets, pa.int64())).append_column("__loose", pa.array(loose)).to_batches()

    first = materialise(dealt.mapInArrow(run, f"{PIECES}, sequence_id long, offset long, __loose boolean"), "packed")
    loose = first.where("__loose")
    bins = loose.groupBy("sequence_id").agg(F.sum("length").alias("length"))
    regions = max(1, -(-tasks * open_bins // TASK_ROWS))
    dealt_again = F.xxhash64("sequence_id")
    again = bins.withColumn("__h", dealt_again).repartition(regions, "__h").sortWithinPartitions("__h", "sequence_id").drop("__h")

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        partition = TaskContext.get().partitionId()
        packer = BestFit(capacity, open_bins)
        for batch in batches:
            places = [packer.put(n) for n in batch.column("length").to_pylist()]
            columns = [batch.column("sequence_id"), pa.array([_numbered((1 << 30) + partition, b) for b, _ in places], pa.int64()), pa.array([o for _, o in places], pa.int64())]
            yield pa.RecordBatch.from_arrays(columns, ["sequence_id", "__to", "__base"])

    moved = again.mapInArrow(merge, "sequence_id long, __to long, __base long")
    joined = loose.join(moved, "sequence_id").select(*items.columns, F.col("__to").alias("sequence_id"), (F.col("offset") + F.col("__base")).alias("offset"))
    return first.where("not __loose").select(*joined.columns).unionByName(joined)


def packed_documents(docs: DataFrame, vocabulary: str | None = None, capacity: int = CAPACITY, end: int = 0) -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset.

    A null or empty text is one piece with the end identifier alone.  Repeated rows are packed each;
    an empty table gives an empty result; further columns are ignored.
    """
    return pack(pieces(docs, vocabulary or vocabulary_path("word_bpe_49k.json"), capacity, end), capacity)
