"""Operator 9, line deduplication with two Bloom filters.

Pass 1 builds, per task, the bits of lines seen once and of lines seen in two documents, as sorted
positions by segment of the filter, or as bitmaps where these are shorter.  Merging segments gives the
twice-seen filter: a bit that two tasks have set, or that one task saw twice.  Merging streams, in two
rounds, so its tasks hold one segment however many tasks there were before.  No repeated line can be missed; others may be suspected.
Pass 2 shuffles the suspected lines only, for exact counts and the document that keeps the line.
Pass 3 drops the confirmed lines.

The filter takes 16 bits a line and at most MAX_BITS (64 MB); beyond that more lines are suspected
and confirmed, with the same result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import SALTS, materialise, replicated, salted
from .words import blocks, per_document

MIN_CHARS = 20
MIN_DOCUMENTS = 3
MAX_BITS = 1 << 29
SEGMENT = 1 << 20
SEGMENTS = "segment int, once binary, twice binary"
#: Confirmed lines are broadcast up to so many bytes of keys; beyond, they are joined.
BROADCAST_BYTES = 32 << 20


def line_key(line: bytes) -> bytes:
    return line.strip().lower()


def long_enough(key: bytes) -> bool:
    return len(key) >= MIN_CHARS and (len(key) >= 4 * MIN_CHARS or len(key.decode()) >= MIN_CHARS)


def document_keys(text: bytes) -> set[bytes]:
    return {k for k in map(line_key, text.split(b"\n")) if len(k) >= MIN_CHARS and long_enough(k)}


def _positions(keys: list[bytes], bits: int) -> tuple[np.ndarray, np.ndarray]:
    h = np.fromiter(map(xxhash.xxh3_64_intdigest, keys), "uint64", len(keys))
    mask = np.uint64(bits - 1)
    return h & mask, (h >> np.uint64(32)) & mask


def _filter_bits(docs: DataFrame) -> int:
    lines = docs.select(F.regexp_count(F.coalesce("text", F.lit("")), F.lit("\n")).alias("n")).agg(F.coalesce(F.sum("n") + F.count("*"), F.lit(1))).first()[0]
    return min(MAX_BITS, max(SEGMENT, 1 << (16 * lines - 1).bit_length()))


def _packed(positions: np.ndarray) -> bytes:
    """Sorted positions in a segment as they are (4 bytes each), or as a bitmap of SEGMENT / 8 bytes where that is no longer."""
    if 4 * positions.size < SEGMENT // 8:
        return positions.tobytes()
    bits = np.zeros(SEGMENT, bool)
    bits[positions] = True
    return np.packbits(bits).tobytes()


def _unpacked(packed: bytes) -> np.ndarray:
    """An index (positions or a mask) of the bits of :func:`_packed`."""
    return np.unpackbits(np.frombuffer(packed, "uint8")).view(bool) if len(packed) == SEGMENT // 8 else np.frombuffer(packed, "<u4")


def _segment_rows(rows: list[tuple[int, bytes, bytes]]) -> Iterator[pa.RecordBatch]:
    if rows:
        kinds = (pa.int32(), pa.binary(), pa.binary())
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], ["segment", "once", "twice"])


def _fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """One row for each run of rows of a segment: bits of any row, and bits of two rows or seen twice in one.  Holds one segment."""
    at, once, twice = None, np.zeros(SEGMENT, bool), np.zeros(SEGMENT, bool)
    row = lambda: [(at, _packed(np.flatnonzero(once).astype("<u4")), _packed(np.flatnonzero(twice).astype("<u4")))]
    for batch in batches:
        for segment, ones, twos in zip(*(c.to_pylist() for c in batch.columns), strict=True):
            if segment != at:
                if at is not None:
                    yield from _segment_rows(row())
                at = segment
                once[:] = twice[:] = False
            own = _unpacked(ones)
            twice[own] |= once[own]
            once[own] = True
            twice[_unpacked(twos)] = True
    if at is not None:
        yield from _segment_rows(row())


def twice_seen(docs: DataFrame, bits: int) -> np.ndarray:
    """The filter of lines that two documents may share, as a bitmap of at most MAX_BITS bits."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = [np.empty(0, "uint64")]
        for batch in blocks(batches):
            for text in batch.column("text").cast(pa.binary()).to_pylist():
                if text and (keys := document_keys(text)):
                    seen.append(np.fromiter(map(xxhash.xxh3_64_intdigest, keys), "uint64", len(keys)))
        hashes, n = np.unique(np.concatenate(seen), return_counts=True)
        rows = []
        mask = np.uint64(bits - 1)
        bit_of = lambda h: np.unique(np.concatenate([h & mask, (h >> np.uint64(32)) & mask]))
        once, twice = bit_of(hashes), bit_of(hashes[n > 1])
        for s in np.unique(once // SEGMENT):
            part = lambda b, s=s: _packed((b[np.searchsorted(b, s * SEGMENT) : np.searchsorted(b, (s + np.uint64(1)) * SEGMENT)] - s * SEGMENT).astype("<u4"))
            rows.append((int(s), part(once), part(twice)))
        yield from _segment_rows(rows)

    parts = per_document(docs, run, SEGMENTS, ("text",))
    # tasks meet in SALTS folds a segment first, then those do; each fold streams its rows
    spread = parts.withColumn("__salt", F.pmod(F.spark_partition_id(), F.lit(SALTS)))
    folds = spread.repartition("segment", "__salt").sortWithinPartitions("segment").drop("__salt").mapInArrow(_fold, SEGMENTS)
    whole = materialise(folds.repartition("segment").sortWithinPartitions("segment").mapInArrow(_fold, SEGMENTS).select("segment", "twice"), "filter")
    bitmap = np.zeros(bits // 8, "uint8")
    # at most MAX_BITS / SEGMENT = 512 rows of 128 KB
    for r in whole.toLocalIterator():
        at = r["segment"] * (SEGMENT // 8)
        seen = np.zeros(SEGMENT, bool)
        seen[_unpacked(r["twice"])] = True
        bitmap[at : at + SEGMENT // 8] = np.packbits(seen)
    return bitmap


def suspected(docs: DataFrame, bitmap: np.ndarray) -> DataFrame:
    """(doc_id, key): the lines of each document that the filter doesn't clear, once a document."""
    shared, bits = docs.sparkSession.sparkContext.broadcast(bitmap), bitmap.size * 8

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        twice = shared.value
        hit = lambda p: (twice[(p >> np.uint64(3)).astype("int64")] >> (np.uint8(7) - (p & np.uint64(7)).astype("uint8"))) & 1
        for batch in blocks(batches):
            ids, keys = [], []
            for doc, text in zip(batch.column("doc_id").to_pylist(), batch.column("text").cast(pa.binary()).to_pylist(), strict=True):
                if text and (own := document_keys(text)):
                    keys += own
                    ids += [doc] * len(own)
            if keys:
                a, b = _positions(keys, bits)
                at = np.flatnonzero(hit(a) & hit(b))
                yield pa.RecordBatch.from_arrays([pa.array([ids[i] for i in at], pa.int64()), pa.array([keys[i] for i in at], pa.binary()).cast(pa.string())], ["doc_id", "key"])

    return per_document(docs, run, "doc_id long, key string")


def repeated_lines(suspects: DataFrame) -> DataFrame:
    """(key, keep_id): exact counts of the suspected lines; the largest doc_id keeps the line."""
    return suspects.groupBy("key").agg(F.count_distinct("doc_id").alias("n"), F.max("doc_id").alias("keep_id")).where(F.col("n") >= MIN_DOCUMENTS).select("key", "keep_id")


def _dropper(confirmed):
    """Arrow function over (doc_id, text[, __drop]); ``confirmed`` gives key -> keep_id, or None where rows carry their own keys."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keep = confirmed.value if confirmed else None
        for batch in blocks(batches):
            own = batch.column("__drop").to_pylist() if keep is None else [None] * batch.num_rows
            out: tuple[list, list, list] = ([], [], [])
            for doc, text, drop in zip(batch.column("doc_id").to_pylist(), batch.column("text").cast(pa.binary()).to_pylist(), own, strict=True):
                lines = (text or b"").split(b"\n")
                if keep is None:
                    mine = {k.encode() for k in drop or ()}
                    left = [x for x in lines if line_key(x) not in mine] if mine else lines
                else:
                    left = [x for x in lines if (k := keep.get(line_key(x), -1)) == -1 or k == (doc,)]
                out[0].append(b"\n".join(left))
                out[1].append(len(lines))
                out[2].append(len(lines) - len(left))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(out[0], pa.binary()).cast(pa.string()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.int64())], ["doc_id", "text", "n_lines", "n_dropped"])

    return run


def without_repeated_lines(docs: DataFrame, broadcast_bytes: int = BROADCAST_BYTES) -> DataFrame:
    """One row per input row: doc_id, text (its remaining lines), n_lines (before), n_dropped.

    A null or empty text is one empty line.  A line that stands several times in one document counts
    once and goes or stays with all its copies.  A document is a distinct doc_id; repeated rows of
    the largest doc_id all keep their line, and a null doc_id keeps none and counts for none.  An
    empty table gives an empty result; further columns are ignored.
    """
    suspects = materialise(suspected(docs, twice_seen(docs, _filter_bits(docs))), "suspects")
    confirmed = materialise(repeated_lines(suspects), "confirmed")
    schema = "doc_id long, text string, n_lines long, n_dropped long"
    if confirmed.agg(F.coalesce(F.sum(F.octet_length("key") + 80), F.lit(0))).first()[0] <= broadcast_bytes:
        table = {r["key"].encode(): (r["keep_id"],) for r in confirmed.toLocalIterator()}
        return per_document(docs, _dropper(docs.sparkSession.sparkContext.broadcast(table)), schema)
    lost = salted(suspects, "doc_id").join(replicated(confirmed), ["key", "__salt"]).where(~F.col("doc_id").eqNullSafe(F.col("keep_id")))
    drops = lost.groupBy(F.col("doc_id").alias("__id")).agg(F.collect_set("key").alias("__drop"))
    own = docs.select("doc_id", "text").join(drops, F.col("doc_id").eqNullSafe(F.col("__id")), "left")
    return own.select("doc_id", "text", "__drop").mapInArrow(_dropper(None), schema)
