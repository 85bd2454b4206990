"""Wavelet matrix: a succinct, compressed and searchable form of a token sequence.

Level l holds bit (top - l) of every id in the order that the levels above leave: at each level the zeros
move, in order, before the ones. With ones counted at every 512-bit boundary, access, counting and the
place of the n-th occurrence take one rank or select a level.

File: magic, version, level count, sequence length, document count; then, as zstandard frames with their
lengths, document ids (signed 64-bit), tokens per document (unsigned 64-bit), and per level the zero
count, the packed bits and the counts at the boundaries. All little-endian.
"""

from __future__ import annotations

import io
import struct

import numpy as np
import zstandard

MAGIC = b"WVMX"
VERSION = 1
BLOCK = 512


class WaveletMatrix:
    """Bit planes with rank directories over ``ids``, and the documents that the ids belong to."""

    def __init__(self, planes: list[np.ndarray], zeros: list[int], ranks: list[np.ndarray], n: int, doc_ids: np.ndarray, lengths: np.ndarray):
        self.planes, self.zeros, self.ranks, self.n = planes, zeros, ranks, n
        self.doc_ids, self.lengths = doc_ids, lengths
        self.levels = len(planes)

    @classmethod
    def build(cls, ids: np.ndarray, doc_ids: np.ndarray, lengths: np.ndarray, levels: int | None = None) -> WaveletMatrix:
        top = int(ids.max()).bit_length() if len(ids) else 1
        levels = max(1, levels or top)
        row = ids.astype(np.uint16 if levels <= 16 else np.uint32)
        planes, zeros, ranks = [], [], []
        for level in range(levels):
            ones = (row & row.dtype.type(1 << (levels - 1 - level))) != 0
            packed = np.packbits(ones, bitorder="little")
            planes.append(packed)
            words = np.zeros(-(-len(row) // BLOCK) * (BLOCK // 64), np.uint64)
            words.view(np.uint8)[: len(packed)] = packed
            each = np.bitwise_count(words).reshape(-1, BLOCK // 64).sum(axis=1, dtype=np.int64)
            ranks.append(np.concatenate([[0], np.cumsum(each)]).astype(np.uint32 if len(row) < 1 << 32 else np.uint64))
            zeros.append(len(row) - int(each.sum()))
            row = np.concatenate([row[~ones], row[ones]])
        return cls(planes, zeros, ranks, len(ids), doc_ids, lengths)

    def _bits(self, level: int) -> np.ndarray:
        return np.unpackbits(self.planes[level], bitorder="little", count=self.n).astype(bool)

    def _rank1(self, level: int, place: int) -> int:
        """Ones before ``place``."""
        block, rest = divmod(place, BLOCK)
        packed = self.planes[level][block * BLOCK // 8 : block * BLOCK // 8 + -(-rest // 8)]
        return int(self.ranks[level][block]) + int(np.count_nonzero(np.unpackbits(packed, bitorder="little", count=rest))) if rest else int(self.ranks[level][block])

    def _select(self, level: int, bit: int, nth: int) -> int:
        """Place of the ``nth`` (from 0) position that holds ``bit``."""
        directory = self.ranks[level].astype(np.int64)
        if not bit:
            directory = np.minimum(np.arange(len(directory)) * BLOCK, self.n) - directory
        block = int(np.searchsorted(directory, nth, side="right")) - 1
        packed = self.planes[level][block * BLOCK // 8 : (block + 1) * BLOCK // 8]
        bits = np.unpackbits(packed, bitorder="little")[: self.n - block * BLOCK]
        return block * BLOCK + int(np.flatnonzero(bits == bit)[nth - int(directory[block])])

    def access(self, place: int) -> int:
        """The id at ``place``."""
        out = 0
        for level in range(self.levels):
            one = int(self.planes[level][place // 8] >> (place % 8) & 1)
            out = out << 1 | one
            before = self._rank1(level, place)
            place = self.zeros[level] + before if one else place - before
        return out

    def _narrow(self, token: int, lo: int, hi: int) -> tuple[int, int]:
        for level in range(self.levels):
            a, b = self._rank1(level, lo), self._rank1(level, hi)
            one = token >> (self.levels - 1 - level) & 1
            lo, hi = (self.zeros[level] + a, self.zeros[level] + b) if one else (lo - a, hi - b)
        return lo, hi

    def count(self, token: int, lo: int = 0, hi: int | None = None) -> int:
        """Occurrences of ``token`` at places ``lo`` to ``hi``, exclusive."""
        if token >> self.levels:
            return 0
        a, b = self._narrow(token, lo, self.n if hi is None else hi)
        return b - a

    def occurrence(self, token: int, nth: int) -> int:
        """Place of the ``nth`` (from 0) occurrence of ``token``; IndexError if there are fewer."""
        if nth < 0 or nth >= self.count(token):
            raise IndexError(nth)
        place = self._narrow(token, 0, 0)[0] + nth
        for level in range(self.levels - 1, -1, -1):
            one = token >> (self.levels - 1 - level) & 1
            place = self._select(level, one, place - self.zeros[level] if one else place)
        return place

    def ids(self) -> np.ndarray:
        """The whole sequence, read from the deepest level up."""
        row = np.zeros(self.n, np.uint16 if self.levels <= 16 else np.uint32)
        for level in range(self.levels - 1, -1, -1):
            ones = self._bits(level)
            back = np.empty_like(row)
            zero = self.zeros[level]
            back[~ones] = row[:zero]
            back[ones] = row[zero:] | row.dtype.type(1 << (self.levels - 1 - level))
            row = back
        return row

    def to_bytes(self, level: int = 1) -> bytes:
        press = zstandard.ZstdCompressor(level=level)
        out = io.BytesIO()
        out.write(MAGIC + struct.pack("<HHQQ", VERSION, self.levels, self.n, len(self.doc_ids)))

        def put(array: np.ndarray) -> None:
            frame = press.compress(np.ascontiguousarray(array).tobytes())
            out.write(struct.pack("<Q", len(frame)) + frame)

        put(self.doc_ids.astype("<i8"))
        put(self.lengths.astype("<u8"))
        for bits, zero, rank in zip(self.planes, self.zeros, self.ranks, strict=True):
            out.write(struct.pack("<QB", zero, rank.dtype.itemsize))
            put(bits)
            put(rank)
        return out.getvalue()

    @classmethod
    def from_bytes(cls, raw: bytes) -> WaveletMatrix:
        if raw[:4] != MAGIC:
            raise ValueError("not a wavelet matrix file")
        version, levels, n, docs = struct.unpack_from("<HHQQ", raw, 4)
        if version != VERSION:
            raise ValueError(f"version {version} is unknown")
        at = 4 + struct.calcsize("<HHQQ")
        press = zstandard.ZstdDecompressor()

        def take(dtype: str, most: int) -> np.ndarray:
            nonlocal at
            (size,) = struct.unpack_from("<Q", raw, at)
            frame = press.decompress(raw[at + 8 : at + 8 + size], max_output_size=most)
            at += 8 + size
            return np.frombuffer(frame, dtype)

        doc_ids, lengths = take("<i8", 8 * docs), take("<u8", 8 * docs)
        planes, zeros, ranks = [], [], []
        for _ in range(levels):
            zero, width = struct.unpack_from("<QB", raw, at)
            at += 9
            zeros.append(zero)
            planes.append(take("u1", n // 8 + 1))
            ranks.append(take(f"<u{width}", (n // BLOCK + 2) * width))
        return cls(planes, zeros, ranks, n, doc_ids, lengths)
