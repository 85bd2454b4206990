"""Line deduplication with two Bloom filters.

Every task keeps a filter of the line hashes it has met once and one of those met twice; the tasks' filters
are merged slice by slice (once: or; twice: or, and once-and-once), and the twice filter, of a fixed
greatest size, goes back to the tasks. Only lines that it suspects are moved, as 128-bit digests, for an
exact count and the choice of the document that keeps the line. A filter that is too full suspects too
many lines, which costs traffic and never a wrong result.

A line's key is the line without ASCII white space at its ends, in ASCII lower case. Keys of at least
``least_chars`` code points found in at least ``least_docs`` documents (rows) stay only in the largest
document id. Null and empty texts are one empty line. Rows that repeat an id each count, and rows without
id lose such lines unless no row has an id. An empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ivfspark.plans.scratch import materialize

LEAST_CHARS = 20
LEAST_DOCS = 3
#: Bits of a filter at most; its bytes are what is broadcast.
MOST_BITS = 1 << 26
SLICE_BITS = 1 << 18
FLUSH = 1 << 18


def line_keys(text: bytes | None, least_chars: int = LEAST_CHARS) -> list[tuple[bytes, bytes | None]]:
    """Every line of UTF-8 ``text`` with its key, or None if the key is too short to count."""
    out = []
    for line in (text or b"").split(b"\n"):
        key = line.strip().lower()  # bytes: ASCII only
        size = len(key)
        if size < least_chars or size < 4 * least_chars and len(key.decode("utf-8", "replace")) < least_chars:
            key = None
        out.append((line, key))
    return out


def _places(hashes: np.ndarray, bits: int) -> tuple[np.ndarray, np.ndarray]:
    mask = np.uint64(bits - 1)
    return (hashes & mask).astype(np.int64), ((hashes >> np.uint64(32)) & mask).astype(np.int64)


class TwoFilters:
    """Bits of hashes seen once or more, and of those seen twice or more."""

    def __init__(self, bits: int):
        self.bits, self.once, self.twice = bits, np.zeros(bits, bool), np.zeros(bits, bool)

    def add(self, hashes: np.ndarray) -> None:
        values, counts = np.unique(hashes, return_counts=True)
        a, b = _places(values, self.bits)
        again = (counts > 1) | self.once[a] & self.once[b]
        self.once[a] = self.once[b] = True
        self.twice[a[again]] = self.twice[b[again]] = True

    def slices(self) -> Iterator[tuple[int, bytes, bytes]]:
        step = min(SLICE_BITS, self.bits)
        for number in range(self.bits // step):
            part = slice(number * step, (number + 1) * step)
            if self.once[part].any():
                yield number, *(zlib.compress(np.packbits(x[part]).tobytes(), 1) for x in (self.once, self.twice))


def _hash(key: bytes) -> int:
    from xxhash import xxh3_64_intdigest

    return xxh3_64_intdigest(key)


def suspects_filter(docs: DataFrame, bits: int, least_chars: int = LEAST_CHARS) -> np.ndarray:
    """The merged twice filter over all lines, packed: ``bits / 8`` bytes."""

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        filters, held = TwoFilters(bits), []
        for batch in batches:
            for text in batch.column(0):
                held += [_hash(k) for k in {k for _, k in line_keys(text.as_py(), least_chars) if k is not None}]
                if len(held) >= FLUSH:
                    filters.add(np.array(held, np.uint64))
                    held = []
        filters.add(np.array(held, np.uint64))
        for number, once, twice in filters.slices():
            yield pa.RecordBatch.from_arrays([pa.array([number]), pa.array([once]), pa.array([twice])], ["slice", "once", "twice"])

    built = docs.select("text").mapInArrow(build, "slice long, once binary, twice binary")
    return merge_filters(built, bits)


def merge_filters(built: DataFrame, bits: int) -> np.ndarray:
    """The twice filter of all tasks' ``(slice, once, twice)``, packed: ``bits / 8`` bytes."""

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        merged: dict[int, list[np.ndarray]] = {}
        unpack = lambda raw: np.frombuffer(zlib.decompress(raw), np.uint8)
        for batch in batches:
            for number, once, twice in zip(*(batch.column(c).to_pylist() for c in range(3)), strict=True):
                once, twice = unpack(once), unpack(twice)
                if number in merged:
                    before = merged[number]
                    twice = before[1] | twice | before[0] & once
                    once = before[0] | once
                merged[number] = [once, twice]
        for number, (_, twice) in merged.items():
            yield pa.RecordBatch.from_arrays([pa.array([number]), pa.array([twice.tobytes()])], ["slice", "twice"])

    step = min(SLICE_BITS, bits)
    rows = built.repartition(bits // step, "slice").mapInArrow(merge, "slice long, twice binary").collect()
    packed = np.zeros(bits // 8, np.uint8)
    for r in rows:
        packed[r.slice * (step // 8) : (r.slice + 1) * (step // 8)] = np.frombuffer(r.twice, np.uint8)
    return packed


def has_bits(packed: np.ndarray, hashes: np.ndarray, bits: int) -> np.ndarray:
    """Whether a packed filter may hold each hash."""
    a, b = _places(hashes, bits)
    bit = lambda at: packed[at >> 3] >> (7 - (at & 7)).astype(np.uint8) & 1
    return (bit(a) & bit(b)).astype(bool)


def filter_bits(total_bytes: int, most: int = MOST_BITS) -> int:
    """Sixteen bits for every 64 bytes of text, as a power of two."""
    return max(1 << 12, min(most, 1 << max(1, total_bytes // 4).bit_length()))


def dedup_lines(docs: DataFrame, least_chars: int = LEAST_CHARS, least_docs: int = LEAST_DOCS, most_bits: int = MOST_BITS) -> DataFrame:
    """Per document ``doc_id, n_lines, n_dropped, kept`` (kept: the other lines, as UTF-8 bytes)."""
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("text"))
    total = source.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    bits = filter_bits(total, most_bits)
    shared = source.sparkSession.sparkContext.broadcast(suspects_filter(source, bits, least_chars))  # bits / 8 bytes at most

    def suspect(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            owners, keys = [], []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                own = list({k for _, k in line_keys(text.as_py(), least_chars) if k is not None})
                owners += [doc] * len(own)
                keys += own
            if not keys:
                continue
            hashes = np.fromiter(map(_hash, keys), np.uint64, len(keys))
            hit = np.flatnonzero(has_bits(shared.value, hashes, bits)).tolist()
            digests = [hashlib.md5(keys[i]).digest() for i in hit]
            yield pa.RecordBatch.from_arrays([pa.array([owners[i] for i in hit], pa.int64()), pa.array(digests, pa.binary())], ["doc_id", "digest"])

    suspected = materialize(source.mapInArrow(suspect, "doc_id long, digest binary"), "suspects")
    counted = suspected.groupBy("digest").agg(F.count("*").alias("n"), F.max("doc_id").alias("keeper"))
    confirmed = materialize(counted.where(F.col("n") >= least_docs).select("digest", "keeper"), "confirmed")
    losing = suspected.join(confirmed, "digest").where(F.col("keeper").isNotNull() & ~F.col("doc_id").eqNullSafe(F.col("keeper")))
    lists = losing.groupBy(F.col("doc_id").alias("loser")).agg(F.collect_set("digest").alias("digests"))  # a document's own lines

    def drop(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            total, dropped, kept = [], [], []
            for text, digests in zip(batch.column(1), batch.column(2).to_pylist(), strict=True):
                gone = set(digests or ())
                lines = line_keys(text.as_py(), least_chars) if gone else None
                if lines is None:
                    raw = text.as_py() or b""
                    total.append(raw.count(b"\n") + 1)
                    dropped.append(0)
                    kept.append(raw)
                    continue
                stay = [line for line, key in lines if key is None or hashlib.md5(key).digest() not in gone]
                total.append(len(lines))
                dropped.append(len(lines) - len(stay))
                kept.append(b"\n".join(stay))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(total, pa.int64()), pa.array(dropped, pa.int64()), pa.array(kept, pa.binary())],
                ["doc_id", "n_lines", "n_dropped", "kept"],
            )

    joined = source.join(lists, F.col("doc_id").eqNullSafe(F.col("loser")), "left").select("doc_id", "text", "digests")
    return joined.mapInArrow(drop, "doc_id long, n_lines long, n_dropped long, kept binary")
