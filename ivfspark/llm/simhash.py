"""SimHash near-duplicates: fingerprints, links within a Hamming radius found by BK-trees, groups.

Links are complete: two fingerprints within ``radius`` bits agree on at least ``blocks - radius`` of
``blocks`` equal bit ranges, so every choice of that many ranges is a shard key, and every pair meets
in a shard. A shard's fingerprints form BK-trees of at most ``TREE_ROWS`` nodes; larger shards (groups of
near copies) become several trees, and each tree is searched with its own and every other tree's
fingerprints. Trees travel to the tasks that search them, never to the driver, and a task emits
only the links that join parts not yet joined in it, never all pairs of a group.

Null and empty texts have fingerprint zero and link like any other. Repeated rows and ties share a
component. Rows without id take the component of their group but never name it. An empty table
gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ivfspark.operators.graph import connected_components
from ivfspark.plans.scratch import materialize

SHINGLE_WORDS = 4
SEED = 42
RADIUS = 4
TREE_ROWS = 1024
LEAF_ROWS = 48
#: Bit ranges that agree at least, of radius + spare: two of six give 15 shard keys of 21 bits, three of seven 35 keys of 27
#: bits, four of eight 70 keys of 32 bits. The least is taken whose keys leave most shards to one fingerprint.
SPARE_RANGES = (2, 3, 4)
SHARDS_A_FINGERPRINT = 64
#: Shingles hashed before their bits are counted; bounds memory for very long texts.
CHUNK = 1 << 16


def fingerprint(text: bytes | None, width: int = SHINGLE_WORDS) -> int:
    """64-bit SimHash of UTF-8 ``text``: bit b is set if more than half of the shingle hashes have it."""
    from xxhash import xxh64_intdigest

    words = (text or b"").lower().split()  # bytes: A-Z only, and ASCII white space
    if not words:
        return 0
    joined = b" ".join(words)
    n = max(1, len(words) - width + 1)
    lengths = np.fromiter(map(len, words), np.int64, len(words))
    ends = np.cumsum(lengths + 1) - 1
    starts = ends - lengths
    last = ends[width - 1 :] if len(words) >= width else ends[-1:]
    counts = np.zeros(64, np.int64)
    for at in range(0, n, CHUNK):
        spans = zip(starts[at : min(at + CHUNK, n)].tolist(), last[at : at + CHUNK].tolist(), strict=True)
        counts += bit_counts(np.fromiter((xxh64_intdigest(joined[s:e], SEED) for s, e in spans), np.uint64))
    return majority(counts, n)


def bit_counts(hashes: np.ndarray) -> np.ndarray:
    """How many of the hashes have each bit set."""
    return np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)


def majority(counts: np.ndarray, n: int) -> int:
    """The fingerprint whose bits are those that more than half of ``n`` hashes have."""
    return int(np.packbits(counts * 2 > n, bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, fp)`` for every document, fp as a signed 64-bit number."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps = np.fromiter((fingerprint(x.as_py()) for x in batch.column(1)), np.uint64, batch.num_rows)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(fps.view(np.int64))], ["doc_id", "fp"])

    source = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("binary").alias("text"))
    return source.mapInArrow(kernel, "doc_id long, fp long")


class BKTree:
    """Burkhard-Keller tree over unsigned 64-bit fingerprints; small subtrees stay as flat leaves."""

    __slots__ = ("children", "items", "pivot")

    def __init__(self, values: np.ndarray, items: np.ndarray):
        self.children: dict[int, BKTree] = {}
        self.items, self.pivot = items, None
        if len(items) > LEAF_ROWS:
            self.pivot, self.items = items[0], None
            rest = items[1:]
            distance = np.bitwise_count(values[rest] ^ values[self.pivot])
            for d in np.unique(distance):
                self.children[int(d)] = BKTree(values, rest[distance == d])

    def search(self, values: np.ndarray, asked: np.ndarray, radius: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Pairs (query positions, item positions) of ``values`` within ``radius`` of each other."""
        stack = [(self, asked)]
        while stack:
            node, queries = stack.pop()
            if node.pivot is None:
                near = np.bitwise_count(values[queries][:, None] ^ values[node.items][None, :]) <= radius
                q, i = np.nonzero(near)
                if len(q):
                    yield queries[q], node.items[i]
                continue
            distance = np.bitwise_count(values[queries] ^ values[node.pivot]).astype(np.int16)
            hit = queries[distance <= radius]
            if len(hit):
                yield hit, np.full(len(hit), node.pivot)
            for edge, child in node.children.items():
                follow = queries[np.abs(distance - edge) <= radius]
                if len(follow):
                    stack.append((child, follow))


def _spanning_links(fps: np.ndarray, sides: np.ndarray, radius: int) -> list[tuple[int, int]]:
    """Links that connect all fingerprints within ``radius``; side 1 is searched in the tree of side 0."""
    inner, outer = np.flatnonzero(sides == 0), np.flatnonzero(sides == 1)
    tree = BKTree(fps, inner)
    parent = list(range(len(fps)))

    def root(x: int) -> int:
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    links = []
    for q, i in tree.search(fps, outer if len(outer) else inner, radius):
        for a, b in zip(q.tolist(), i.tolist(), strict=True):
            ra, rb = root(a), root(b)
            if ra != rb:
                parent[ra] = rb
                links.append((a, b))
    return links


def _masks(blocks: int, radius: int) -> list[int]:
    """Signed bit masks, one for every choice of ``blocks - radius`` of ``blocks`` bit ranges."""
    cuts = [64 * i // blocks for i in range(blocks + 1)]
    ranges = [((1 << cuts[i + 1]) - 1) ^ ((1 << cuts[i]) - 1) for i in range(blocks)]
    masks = [sum(c) for c in combinations(ranges, blocks - radius)]
    return [m - (1 << 64) if m >> 63 else m for m in masks]


def spare_ranges(n: int, radius: int = RADIUS) -> int:
    """Ranges for ``n`` fingerprints: shorter keys are fewer rows, longer keys fewer chance meetings. Any choice finds all links."""
    fitting = (s for s in SPARE_RANGES if n * SHARDS_A_FINGERPRINT <= 1 << 64 * s // (radius + s))
    return next(fitting, SPARE_RANGES[-1])


def links(distinct: DataFrame, radius: int = RADIUS, spare: int | None = None) -> DataFrame:
    """``distinct(fp, rep)`` to links ``(a, b)`` between reps that connect all pairs within ``radius``."""
    spare = spare_ranges(distinct.count(), radius) if spare is None else spare
    masks = _masks(radius + spare, radius)
    shards = F.explode(F.array(*[F.struct(F.lit(i).alias("mask"), F.col("fp").bitwiseAND(F.lit(m)).alias("key")) for i, m in enumerate(masks)]))
    placed = distinct.select("fp", "rep", shards.alias("shard")).select("shard.mask", "shard.key", "fp", "rep")
    sizes = materialize(placed.groupBy("mask", "key").agg(F.count("*").alias("n")).where("n > 1"), "shards")
    sized = placed.join(sizes, ["mask", "key"])
    trees = F.ceil(F.col("n") / TREE_ROWS).cast("int")
    own = F.pmod(F.xxhash64("fp"), F.col("trees")).cast("int")
    spread = (
        sized.withColumn("trees", trees)
        .withColumn("own", own)
        .withColumn("other", F.explode(F.sequence(F.lit(0), F.col("trees") - 1)))
        .select(
            "mask",
            "key",
            F.least("own", "other").alias("i"),
            F.greatest("own", "other").alias("j"),
            F.when(F.col("own") > F.col("other"), 1).otherwise(0).alias("side"),
            "fp",
            "rep",
        )
    )
    group = ["mask", "key", "i", "j"]

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = None
        for batch in batches:
            held = pa.Table.from_batches([batch]) if held is None else pa.concat_tables([held, pa.Table.from_batches([batch])])
            keys = np.column_stack([held.column(c).to_numpy() for c in group])
            cut = np.flatnonzero(np.any(keys[1:] != keys[:-1], axis=1)) + 1
            if len(cut):
                yield solve(held.slice(0, int(cut[-1])), np.concatenate([[0], cut]))
                held = held.slice(int(cut[-1]))
        if held is not None and held.num_rows:
            yield solve(held, np.array([0, held.num_rows]))

    def solve(rows: pa.Table, bounds: np.ndarray) -> pa.RecordBatch:
        fps = rows.column("fp").to_numpy().view(np.uint64)
        reps, sides = rows.column("rep").to_numpy(), rows.column("side").to_numpy()
        a, b = [], []
        for s, e in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
            for x, y in _spanning_links(fps[s:e], sides[s:e], radius):
                a.append(reps[s + x])
                b.append(reps[s + y])
        return pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    dealt = spread.repartition(*group).sortWithinPartitions(*group)
    return dealt.mapInArrow(kernel, "a long, b long")


def near_duplicates(docs: DataFrame, radius: int = RADIUS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, fingerprint, component_id)``: component_id is the least id reachable over links."""
    prints = materialize(fingerprints(docs, id_col, text_col), "fingerprints")
    distinct = materialize(prints.groupBy("fp").agg(F.min("doc_id").alias("least")), "distinct")
    # fingerprints stand for themselves, so those of rows without id are searched and link like any other
    found = connected_components(links(distinct.select("fp", F.col("fp").alias("rep")), radius))
    grouped = distinct.join(found.withColumnRenamed("node", "fp"), "fp", "left").withColumn("component", F.coalesce("component", "fp"))
    grouped = materialize(grouped, "grouped")
    names = grouped.groupBy("component").agg(F.min("least").alias("component_id"))
    named = materialize(grouped.join(names, "component").select("fp", "component_id"), "components")
    return prints.join(named, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")
