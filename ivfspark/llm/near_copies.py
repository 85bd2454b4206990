"""Near copies by word shingles: groups of documents whose shingle sets have a Jaccard similarity of at least 0.8.

SimHash comes first: fingerprints of the shingle sets are linked within a Hamming radius by ``simhash.links`` (BK-trees
in shards). Two texts at 0.8 lie about ten bits apart in a 64-bit SimHash and often more, too far for an exhaustive
search, so pairs beyond the radius come from min-hash bands: pairs at 0.8 share none of the bands with a chance of
3 in a million, less above. Equal sets collapse to one representative. In each band's bucket all members are
compared with one, its centre, chosen at random by bucket, so that a text meets a different centre in each of its
buckets and a large group of near copies is joined without its pairs. Then, in buckets that are not yet one group,
every pair of different groups is compared through the sketches of its members, block by block within a task, so
that only pairs that may be similar enough become rows. A sketch has all hashes of a set of up to ``SKETCH`` shingles; of
larger sets it has a fixed share of the hashes, and a pair at 0.8 is overlooked with a chance of 3 in ten million. Each
link of either kind is confirmed by an exact Jaccard of the texts' shingles, so no pair below the threshold links.

Texts without words have the empty set and form one group; texts shorter than a shingle are one shingle. Null texts
count as empty. Ids must be distinct and not null. An empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ivfspark.llm.simhash import bit_counts, links, majority
from ivfspark.operators.graph import connected_components
from ivfspark.plans.scratch import materialize

WIDTH = 5
#: Similarity of at least 4 in 5, in whole numbers.
LIKE, OF = 4, 5
BANDS, BAND_ROWS = 32, 5
SEED = 42
#: Hashes of a sketch, about, at most; members of a block.
SKETCH, BLOCK = 1024, 1024
#: Least similarity of sketches that have only a share of their sets: five deviations below 0.8.
SKETCH_LIKE = 0.72
#: Hashes of a sketch that may coincide by chance.
SLACK = 2
#: Shingles permuted at once.
CHUNK = 1 << 12

_RANDOM = np.random.default_rng(SEED)
_FLIP = _RANDOM.integers(0, 1 << 64, BANDS * BAND_ROWS, np.uint64)[:, None]
_FACTOR = _RANDOM.integers(0, 1 << 64, BANDS * BAND_ROWS, np.uint64)[:, None] | np.uint64(1)


def shingles(text: bytes | None, width: int = WIDTH) -> np.ndarray:
    """Sorted distinct hashes of the shingles of UTF-8 ``text``."""
    from xxhash import xxh64_intdigest

    words = (text or b"").lower().split()
    if not words:
        return np.empty(0, np.uint64)
    runs = (b" ".join(words[i : i + width]) for i in range(max(1, len(words) - width + 1)))
    return np.unique(np.fromiter((xxh64_intdigest(r, SEED) for r in runs), np.uint64))


def bands(hashes: np.ndarray) -> list[int]:
    """Signed band keys of a shingle set; none for the empty set."""
    from xxhash import xxh64_intdigest

    if not len(hashes):
        return []
    least = np.full(BANDS * BAND_ROWS, np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(hashes), CHUNK):
        np.minimum(least, ((hashes[None, at : at + CHUNK] ^ _FLIP) * _FACTOR).min(axis=1), out=least)
    keys = [xxh64_intdigest(row.tobytes(), band) for band, row in enumerate(least.reshape(BANDS, BAND_ROWS))]
    return np.array(keys, np.uint64).view(np.int64).tolist()


def level_of(size: int) -> int:
    """Halvings that bring a set of ``size`` hashes to a sketch."""
    return max(0, -(-size // SKETCH) - 1).bit_length()


def sketch(hashes: np.ndarray) -> np.ndarray:
    """Sorted 32-bit hashes of a set: those that are a multiple of two to the power of its level."""
    short = np.unique((hashes >> np.uint64(32)).astype(np.uint32))
    return short[short & np.uint32((1 << level_of(len(hashes))) - 1) == 0]


def similar_members(reps: np.ndarray, groups: np.ndarray, mains: np.ndarray, sizes: np.ndarray, sides: np.ndarray, sketches: list[np.ndarray]) -> list[tuple[int, int]]:
    """Pairs of members of different groups, of both sides if there are two, whose sketches are similar enough.

    At least one member of a pair is outside the bucket's main group.
    """
    levels = np.array([level_of(n) for n in sizes.tolist()])
    outside = groups != mains
    two_sides = len(np.unique(sides)) > 1
    out = []
    for level in np.unique(levels[outside]).tolist() if outside.any() else []:
        for shared in (level, level + 1):  # the higher level of a pair is the one to compare at
            rows = np.flatnonzero((levels == shared) | (levels == shared - 1))
            kept = [sketches[r][sketches[r] & np.uint32((1 << shared) - 1) == 0] for r in rows]
            ends = np.cumsum([0, *map(len, kept)])
            _, places = np.unique(np.concatenate(kept) if kept else np.empty(0, np.uint32), return_inverse=True)
            like = LIKE / OF if shared == 0 else SKETCH_LIKE
            marks = np.zeros(len(places) + 1, bool)
            for k in np.flatnonzero(outside[rows] & (levels[rows] == level)).tolist():
                a = rows[k]
                may = (groups[rows] != groups[a]) & (~outside[rows] | (reps[rows] > reps[a]) | (levels[rows] != level))
                may &= OF * np.minimum(sizes[rows], sizes[a]) >= LIKE * np.maximum(sizes[rows], sizes[a])
                may &= levels[rows] <= level if shared == level else levels[rows] == shared
                if two_sides:
                    may &= sides[rows] != sides[a]
                if not may.any():
                    continue
                own = places[ends[k] : ends[k + 1]]
                marks[own] = True
                met = np.concatenate([[0], np.cumsum(marks[places])])
                marks[own] = False
                both = met[ends[1:]] - met[ends[:-1]] + SLACK
                may &= both >= like * (len(own) + np.diff(ends) - both)
                out += [(int(reps[a]), int(b)) for b in reps[rows[may]]]
    return out


def simhash_of(hashes: np.ndarray) -> int:
    """SimHash of a shingle set; zero for the empty set."""
    counts = np.zeros(64, np.int64)
    for at in range(0, len(hashes), CHUNK):
        counts += bit_counts(hashes[at : at + CHUNK])
    return majority(counts, len(hashes)) if len(hashes) else 0


def signatures(docs: DataFrame) -> DataFrame:
    """``(doc_id, digest, fp, size, bands)``: equal shingle sets have equal digests; fp is their SimHash."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from xxhash import xxh64_intdigest

        for batch in batches:
            sets = [shingles(t.as_py()) for t in batch.column(1)]
            digests = np.array([xxh64_intdigest(s.tobytes(), SEED) for s in sets], np.uint64).view(np.int64)
            prints = np.array([simhash_of(s) for s in sets], np.uint64).view(np.int64)
            sizes = pa.array([len(s) for s in sets], pa.int64())
            columns = [batch.column(0), pa.array(digests), pa.array(prints), sizes, pa.array([bands(s) for s in sets], pa.list_(pa.int64()))]
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "digest", "fp", "size", "bands"])

    return docs.mapInArrow(kernel, "doc_id long, digest long, fp long, size long, bands array<long>")


def confirmed(pairs: DataFrame, docs: DataFrame) -> DataFrame:
    """Pairs ``(a, b)`` whose texts are similar enough."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2), batch.column(3), strict=True):
                x, y = shingles(x.as_py()), shingles(y.as_py())
                both = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(OF * both >= LIKE * (len(x) + len(y) - both))
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    left = docs.select(F.col("doc_id").alias("a"), F.col("text").alias("x"))
    right = docs.select(F.col("doc_id").alias("b"), F.col("text").alias("y"))
    return pairs.distinct().join(left, "a").join(right, "b").select("a", "b", "x", "y").mapInArrow(kernel, "a long, b long")


def sketches(docs: DataFrame) -> DataFrame:
    """``(rep, sketch)``: the sketch as little-endian 32-bit numbers."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            packed = [sketch(shingles(t.as_py())).astype("<u4").tobytes() for t in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(packed, pa.binary())], ["rep", "sketch"])

    return docs.select("doc_id", "text").mapInArrow(kernel, "rep long, sketch binary")


def _open_pairs(grouped: DataFrame, source: DataFrame) -> DataFrame:
    """Pairs ``(a, b)`` of different groups of a bucket whose sketches are similar enough.

    ``grouped`` has ``key, rep, size, component, main``. A bucket's members are dealt to blocks, and each pair of blocks
    is compared in one task; a task holds one such pair at a time.
    """
    unsettled = grouped.groupBy("key").agg(F.count("*").alias("n"), F.min("component").alias("low"), F.max("component").alias("high"))
    unsettled = unsettled.where("low <> high").select("key", F.ceil(F.col("n") / BLOCK).alias("blocks"))
    rows = materialize(grouped.join(unsettled, "key"), "unsettled")
    wanted = rows.select(F.col("rep").alias("doc_id")).distinct()
    drawn = sketches(source.join(wanted, "doc_id", "left_semi"))
    rows = rows.withColumn("side", F.pmod(F.xxhash64("key", "rep"), "blocks")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    rows = rows.withColumn("left", F.least("side", "other")).withColumn("right", F.greatest("side", "other"))
    columns = ["key", "left", "right", "rep", "component", "main", "size", "side", "sketch"]
    dealt = rows.join(drawn, "rep").select(*columns).repartition("key", "left", "right").sortWithinPartitions("key", "left", "right")

    def compare(held: list[tuple]) -> list[tuple[int, int]]:
        numbers = np.array([r[3:8] for r in held], np.int64)
        return similar_members(*numbers.T, [np.frombuffer(r[8], "<u4") for r in held])

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        for batch in batches:
            found = []
            for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if held and held[0][:3] != row[:3]:
                    found += compare(held)
                    held = []
                held.append(row)
            yield _pairs_batch(found)
        if held:
            yield _pairs_batch(compare(held))

    return dealt.mapInArrow(kernel, "a long, b long")


def _pairs_batch(pairs: list[tuple[int, int]]) -> pa.RecordBatch:
    ordered = np.sort(np.array(pairs, np.int64).reshape(-1, 2), axis=1)
    return pa.RecordBatch.from_arrays([pa.array(ordered[:, 0]), pa.array(ordered[:, 1])], ["a", "b"])


def _sizes_allow(x: str, y: str) -> Column:
    """Whether sets of these sizes can be similar enough."""
    return OF * F.least(x, y) >= LIKE * F.greatest(x, y)


def near_copies(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(doc_id, component_id)``: component_id is the least id reachable over similar pairs."""
    source = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("binary").alias("text"))
    signed = materialize(signatures(source), "signatures")
    first_of = [F.first(c).alias(c) for c in ("fp", "size", "bands")]
    distinct = materialize(signed.groupBy("digest").agg(F.min("doc_id").alias("rep"), *first_of), "distinct")
    prints = materialize(distinct.where(F.size("bands") > 0).groupBy("fp").agg(F.min("rep").alias("least")), "prints")
    equal = distinct.join(prints, "fp").where("rep <> least").select(F.col("least").alias("a"), F.col("rep").alias("b"))
    close = links(prints.select("fp", F.col("least").alias("rep"))).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    placed = materialize(distinct.select("rep", "size", F.explode("bands").alias("key")), "placed")
    centre = F.min_by(F.struct("rep", "size"), F.struct(F.xxhash64("key", "rep"), "rep"))
    buckets = placed.groupBy("key").agg(centre.alias("c"), F.count("*").alias("n")).where("n > 1")
    buckets = buckets.select("key", F.col("c.rep").alias("centre"), F.col("c.size").alias("centre_size"))
    members = materialize(placed.join(buckets, "key"), "members")
    star = members.where("rep <> centre").where(_sizes_allow("size", "centre_size"))
    star = star.select(F.least("centre", "rep").alias("a"), F.greatest("centre", "rep").alias("b"))
    first = materialize(confirmed(equal.unionByName(close).unionByName(star), source), "links")
    found = materialize(connected_components(first), "groups")
    grouped = members.join(found.withColumnRenamed("node", "rep"), "rep", "left").withColumn("component", F.coalesce("component", "rep"))
    centres = found.select(F.col("node").alias("centre"), F.col("component").alias("main"))
    grouped = materialize(grouped.join(centres, "centre", "left").withColumn("main", F.coalesce("main", "centre")), "grouped")
    second = materialize(confirmed(_open_pairs(grouped, source), source), "links")
    stars = found.select(F.col("node").alias("a"), F.col("component").alias("b"))
    whole = connected_components(stars.unionByName(second)).withColumnRenamed("node", "rep")
    named = distinct.select("digest", "rep").join(whole, "rep", "left").select("digest", F.coalesce("component", "rep").alias("component_id"))
    return signed.select("doc_id", "digest").join(named, "digest").select("doc_id", "component_id")
