"""Benchmark decontamination by a prefix-filtered containment join.

A benchmark item becomes windows of ``window`` consecutive words (the whole item if shorter). A
document contains a window only if it contains all of the window's shingles, so for containment one
shingle is a sufficient prefix: the rarest by its count over all documents. A document's occurrence
of that shingle fixes where the window would begin; bounds at the document's ends are applied and
the words are compared one by one. Words are numbered by the benchmark's own vocabulary, so equal
numbers are equal words and the join is exact.

The benchmark goes to the tasks in blocks of at most ``block_bytes`` of text, whatever its size;
documents are read once for counting and once for joining per block, and are never shuffled.

Null or wordless texts have no words and no hits; null or wordless items have no windows. Repeated
items count each; rows that share an item id count once. Empty tables give empty results or no hits.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Word characters are ASCII digits, a-z and everything beyond ASCII.
_WORD = bytes(c if 0x30 <= c <= 0x39 or 0x61 <= c <= 0x7A or c >= 0x80 else c + 32 if 0x41 <= c <= 0x5A else 0x20 for c in range(256))
WINDOW = 10
SHINGLE = 5
#: Bytes of benchmark text in a block; its packed arrays are about twelve times as large, on the driver and in each worker.
BLOCK_BYTES = 8 << 20
_MIX = np.uint64(0x9E3779B97F4A7C15)


def words_of(text: bytes | None) -> list[bytes]:
    """Lower-cased words of UTF-8 ``text``."""
    return (text or b"").translate(_WORD).split()


class Windows:
    """A block of benchmark items in packed arrays: vocabulary, windows by width, their items, and their shingles."""

    def __init__(self, items: list[tuple[object, bytes | None]], window: int, shingle: int):
        self.vocabulary: dict[bytes, int] = {}
        self.names = sorted({"" if item is None else str(item) for item, _ in items})
        number = {name: i for i, name in enumerate(self.names)}
        runs: dict[int, list[np.ndarray]] = defaultdict(list)
        owners: dict[int, list[np.ndarray]] = defaultdict(list)
        for item, text in items:
            ids = np.array([self.vocabulary.setdefault(w, len(self.vocabulary) + 1) for w in words_of(text)], np.int32)
            if len(ids):
                width = min(window, len(ids))
                runs[width].append(np.lib.stride_tricks.sliding_window_view(ids, width))
                owners[width].append(np.full(len(ids) - width + 1, number["" if item is None else str(item)], np.int32))
        #: By width: the different windows, one a row, and their items (a row's lie between two bounds).
        self.windows: dict[int, np.ndarray] = {}
        self.bounds: dict[int, np.ndarray] = {}
        self.items: dict[int, np.ndarray] = {}
        for width in sorted(runs):
            self.windows[width], row = np.unique(np.concatenate(runs.pop(width)), axis=0, return_inverse=True)
            row, owner = row.ravel(), np.concatenate(owners.pop(width))
            order = np.argsort(row, kind="stable")
            self.items[width] = owner[order]
            self.bounds[width] = np.searchsorted(row[order], np.arange(len(self.windows[width]) + 1))
        self.widths = {width: min(shingle, width) for width in self.windows}  # of shingles, by width of windows
        keys: dict[int, list[np.ndarray]] = defaultdict(list)
        for width, short in self.widths.items():
            keys[short].append(np.unique(self.shingles(width)))
        self.keys = {short: np.unique(np.concatenate(parts)) for short, parts in keys.items()}

    def shingles(self, width: int) -> np.ndarray:
        """Hashes of the shingles of all windows of a width, one window a row."""
        ids, short = self.windows[width], self.widths[width]
        out = np.zeros((len(ids), width - short + 1), np.uint64)
        for k in range(short):
            out = (out ^ ids[:, k : k + out.shape[1]].astype(np.uint64)) * _MIX
            out ^= out >> np.uint64(29)
        return out

    def ids(self, words: list[bytes]) -> np.ndarray:
        get = self.vocabulary.get
        return np.fromiter((get(w, 0) for w in words), np.int64, len(words))

    def order(self, counts: dict[int, np.ndarray]) -> None:
        """Keep each window's rarest shingle as its prefix; ``counts`` go with ``keys``."""
        found: dict[int, list[tuple]] = defaultdict(list)
        for width, short in self.widths.items():
            hashes = self.shingles(width)
            at = counts[short][np.searchsorted(self.keys[short], hashes)].argmin(axis=1)
            rows = np.arange(len(hashes))
            found[short].append((hashes[rows, at], at.astype(np.int16), np.full(len(hashes), width, np.int16), rows.astype(np.int32)))
        #: By width of shingles: prefixes in order, with the place in the window, the window's width and row.
        self.prefix: dict[int, tuple[np.ndarray, ...]] = {}
        for short, parts in found.items():
            columns = [np.concatenate(c) for c in zip(*parts, strict=True)]
            order = np.argsort(columns[0], kind="stable")
            self.prefix[short] = tuple(c[order] for c in columns)
        self.prefix_keys = {short: np.unique(columns[0]) for short, columns in self.prefix.items()}


def _members(ids: np.ndarray, width: int, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of ids' shingles that are among the sorted keys, and which key each is."""
    if len(ids) < width:
        return np.empty(0, np.int64), np.empty(0, np.int64)
    known = np.concatenate([[0], np.cumsum(ids > 0)])
    full = np.flatnonzero(known[width:] - known[:-width] == width)
    if not len(full):
        return full, full
    hashes = np.zeros(len(full), np.uint64)
    for k in range(width):
        hashes = (hashes ^ ids[full + k].astype(np.uint64)) * _MIX
        hashes ^= hashes >> np.uint64(29)
    spot = np.minimum(np.searchsorted(keys, hashes), len(keys) - 1)
    hit = keys[spot] == hashes
    return full[hit], spot[hit]


def _counts(docs: DataFrame, shared) -> dict[int, np.ndarray]:
    """Occurrences of every benchmark shingle over all documents, beside the block's keys; sums travel as arrays."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block = shared.value
        totals = {w: np.zeros(len(k), np.int64) for w, k in block.keys.items()}
        for batch in batches:
            for text in batch.column(0):
                ids = block.ids(words_of(text.as_py()))
                for width, keys in block.keys.items():
                    np.add.at(totals[width], _members(ids, width, keys)[1], 1)
        for width, total in totals.items():
            some = np.flatnonzero(total)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(some), width)), pa.array(some), pa.array(total[some])], ["width", "at", "n"])

    rows = docs.select("text").mapInArrow(kernel, "width long, at long, n long").groupBy("width", "at").agg(F.sum("n").alias("n")).toArrow()
    out = {}
    for width, keys in shared.value.keys.items():
        own = rows["width"].to_numpy() == width
        out[width] = np.zeros(len(keys), np.int64)
        out[width][rows["at"].to_numpy()[own]] = rows["n"].to_numpy()[own]
    return out


def _hits(block: Windows, ids: np.ndarray) -> tuple[np.ndarray, set[str]]:
    """Marks of the words inside occurring windows, and the items that own these windows."""
    edge = np.zeros(len(ids) + 1, np.int64)
    found: set[int] = set()
    for short, keys in block.prefix_keys.items():
        hashes, offsets, widths, rows = block.prefix[short]
        places, spots = _members(ids, short, keys)
        if not len(places):
            continue
        first, last = np.searchsorted(hashes, keys[spots], side="left"), np.searchsorted(hashes, keys[spots], side="right")
        for place, lo, hi in zip(places.tolist(), first.tolist(), last.tolist(), strict=True):
            for i in range(lo, hi):
                width, row, start = int(widths[i]), rows[i], place - int(offsets[i])
                if start >= 0 and start + width <= len(ids) and np.array_equal(ids[start : start + width], block.windows[width][row]):
                    edge[start] += 1
                    edge[start + width] -= 1
                    bounds = block.bounds[width]
                    found.update(block.items[width][bounds[row] : bounds[row + 1]].tolist())
    return np.cumsum(edge[:-1]) > 0, {block.names[i] for i in found}


def _blocks(benchmark: DataFrame, block_bytes: int) -> int:
    size = benchmark.agg(F.sum(F.coalesce(F.octet_length("text"), F.lit(0)) + 64)).first()[0] or 0
    return max(1, -(-size // block_bytes))


def contamination(
    docs: DataFrame,
    benchmark: DataFrame,
    window: int = WINDOW,
    shingle: int = SHINGLE,
    block_bytes: int = BLOCK_BYTES,
) -> DataFrame:
    """Per document: ``doc_id, n_words, n_hit, n_items, items`` (sorted, as strings).

    ``docs`` needs doc_id and text, ``benchmark`` item_id and text.
    """
    spark = docs.sparkSession
    text = F.col("text").cast("binary")
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text"))
    bench = benchmark.select("item_id", F.col("text").cast("binary").alias("text")).distinct()  # repeated rows are one item
    n_blocks = _blocks(bench, block_bytes)
    if n_blocks > 1:
        source = source.withColumn("digest", F.md5("text"))

    def joined(number: int) -> DataFrame:
        rows = bench.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(n_blocks)) == number).collect()  # at most a block's bytes
        block = Windows([(r.item_id, bytes(r.text) if r.text is not None else None) for r in rows], window, shingle)
        shared = spark.sparkContext.broadcast(block)
        block.order(_counts(source, shared))
        ordered = spark.sparkContext.broadcast(block)

        def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            known = ordered.value
            for batch in batches:
                words, starts, ends, items = [], [], [], []
                for text in batch.column(1):
                    ids = known.ids(words_of(text.as_py()))
                    marked, found = _hits(known, ids)
                    turn = np.flatnonzero(np.diff(np.concatenate([[False], marked, [False]]).astype(np.int8)))
                    words.append(len(ids))
                    starts.append(turn[0::2])
                    ends.append(turn[1::2])
                    items.append(sorted(found))
                long_list = pa.list_(pa.int64())
                columns = [batch.column(0), pa.array(words, pa.int64()), pa.array(starts, long_list), pa.array(ends, long_list), pa.array(items, pa.list_(pa.string()))]
                names = ["doc_id", "n_words", "starts", "ends", "items"]
                yield pa.RecordBatch.from_arrays(columns + batch.columns[2:], names + batch.schema.names[2:])

        schema = "doc_id long, n_words long, starts array<long>, ends array<long>, items array<string>"
        if n_blocks == 1:
            return source.mapInArrow(kernel, schema)
        return source.dropDuplicates(["doc_id", "digest"]).mapInArrow(kernel, schema + ", digest string")

    if n_blocks == 1:
        found = joined(0)
        n_hit = F.aggregate(F.zip_with("starts", "ends", lambda s, e: e - s), F.lit(0).cast("long"), lambda a, x: a + x)
        return found.select("doc_id", "n_words", n_hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"), "items")
    return _merge_blocks([joined(i) for i in range(n_blocks)], source)


def _merge_blocks(parts: list[DataFrame], source: DataFrame) -> DataFrame:
    """One row a document from one row a document and block: unions of runs and of items.

    Rows are matched by id and text digest; rows that repeat both are merged once and given back as
    often as they occur.
    """

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hits, items = [], []
            for starts, ends, names, n in zip(*(batch.column(c).to_pylist() for c in ("starts", "ends", "items", "n_words")), strict=True):
                edge = np.zeros(n + 1, np.int64)
                np.add.at(edge, np.array([x for s in starts for x in s], np.int64), 1)
                np.add.at(edge, np.array([x for e in ends for x in e], np.int64), -1)
                hits.append(int(np.count_nonzero(np.cumsum(edge[:-1]))))
                items.append(sorted({x for g in names for x in g}))
            yield pa.RecordBatch.from_arrays(
                [batch.column("doc_id"), batch.column("digest"), batch.column("n_words"), pa.array(hits, pa.int64()), pa.array([len(i) for i in items], pa.int64()), pa.array(items, pa.list_(pa.string()))],
                ["doc_id", "digest", "n_words", "n_hit", "n_items", "items"],
            )

    rows = parts[0]
    for part in parts[1:]:
        rows = rows.unionByName(part)
    lists = [F.collect_list(c).alias(c) for c in ("starts", "ends", "items")]  # one element a block
    grouped = rows.groupBy("doc_id", "digest").agg(F.first("n_words").alias("n_words"), *lists)
    merged = grouped.mapInArrow(kernel, "doc_id long, digest string, n_words long, n_hit long, n_items long, items array<string>")
    left, right = source.select("doc_id", "digest").alias("s"), merged.alias("m")
    same = F.col("s.doc_id").eqNullSafe(F.col("m.doc_id")) & F.col("s.digest").eqNullSafe(F.col("m.digest"))
    return left.join(right, same).select("s.doc_id", "n_words", "n_hit", "n_items", "items")
