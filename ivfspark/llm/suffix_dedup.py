"""Repeated strings by two-stage suffix sorting of candidate passages.

Strings are runs of ``span`` units: bytes, or words for passages that repeat across documents.

1. Each run names one of its ``gram``-unit strings as its anchor, the one of least hash, so
   equal runs name the same anchor at the same place. Neighbouring runs share anchors; the passage of
   an anchor is the units of all runs that name it. Every run lies in one passage.
2. Two Bloom filters over anchor hashes leave the anchors that may occur twice; only their hashes and
   places are moved. Passages that are equal as a whole are one passage with a count: all of its runs repeat.
3. The different passages around one anchor are sorted together: two-stage suffix sorting puts equal runs side
   by side, and adjacent common prefixes of a run's length are repeats. The shared anchor stands for
   itself by a short mark.
4. An anchor with more than ``BLOCK_PASSAGES`` different passages is divided first. Runs with ``m`` or more units
   before the anchor agree on these ``m`` units, the others on the units behind it, so halving the range of
   that number gives two sets of smaller groups that share longer anchors. Sections that are equal in a half
   repeat there as a whole, and one of them stands for all; at most one halving a bit of the range is needed.
5. The repeated runs come back to their documents, whose bytes they cover are removed.

Strings are judged on the input. Null and empty texts have no bytes; texts shorter than ``span`` repeat
nothing. Rows that repeat an id, or have none, are documents of their own (the table is then written once
with row numbers). An empty table gives an empty result. Other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ivfspark.llm.line_bloom import TwoFilters, filter_bits, has_bits, merge_filters
from ivfspark.plans.scratch import materialize

SPAN, GRAM = 400, 256
#: Passages of more than fifty words.
WORD_SPAN, WORD_GRAM = 51, 32
#: Units hashed at a time, passages of one anchor sorted together, bytes of passages sorted together, and passages a task.
CHUNK = 1 << 19
BLOCK_PASSAGES = 1024
SORT_BYTES = 1 << 19
TASK_PASSAGES = 4096
_PLACE = np.uint64((1 << 22) - 1)
_BASE = 0x9E3779B97F4A7C15 | 1


def _powers(base: int, n: int) -> np.ndarray:
    out = np.full(n, base, np.uint64)
    out[0] = 1
    return np.cumprod(out, dtype=np.uint64)


_POWER = _powers(_BASE, CHUNK * 2 + 2 * SPAN)
_INVERSE = _powers(pow(_BASE, -1, 1 << 64), CHUNK * 2 + 2 * SPAN)
_BYTE = np.random.default_rng(7).integers(1, 1 << 63, 256, dtype=np.uint64)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    x = (x ^ (x >> np.uint64(29))) * np.uint64(0x9FB21C651E98DF25)
    return x ^ (x >> np.uint64(32))


class Bytes:
    """Units are bytes."""

    width, mean = 1, 1  # bytes of a unit's code; bytes of text a unit

    @staticmethod
    def load(raws: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Units of several texts in one array, and the number of each text's."""
        return np.frombuffer(b"".join(raws), np.uint8), np.array([len(r) for r in raws], np.int64)

    @staticmethod
    def values(units: np.ndarray) -> np.ndarray:
        return _BYTE[units]

    @staticmethod
    def code(units: np.ndarray) -> bytes:
        return units.tobytes()


class Words:
    """Units are words between ASCII white space, as hashes; 35 bits of each are its code."""

    width, mean = 5, 6

    @staticmethod
    def load(raws: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        from xxhash import xxh3_64_intdigest

        words = [np.fromiter(map(xxh3_64_intdigest, r.split()), np.uint64) for r in raws]
        return np.concatenate(words), np.array([len(w) for w in words], np.int64)

    @staticmethod
    def values(units: np.ndarray) -> np.ndarray:
        return units

    @staticmethod
    def code(units: np.ndarray) -> bytes:
        return (units[:, None] >> np.arange(0, 35, 7, dtype=np.uint64) & np.uint64(127)).astype(np.uint8).tobytes()


Unit = type[Bytes] | type[Words]


def _passages(values: np.ndarray, runs: np.ndarray, span: int, gram: int) -> dict[str, np.ndarray]:
    """Passages of the run starts marked in ``runs``; places are within ``values``."""
    n = len(values)
    width = span - gram + 1
    total = np.zeros(n + 1, np.uint64)
    np.cumsum(values * _POWER[:n], out=total[1:])
    grams = _mix((total[gram:] - total[:-gram]) * _INVERSE[: n - gram + 1])
    least = (grams & ~_PLACE) | np.arange(len(grams), dtype=np.uint64)
    size = 1
    while size * 2 <= width:
        least = np.minimum(least[:-size], least[size:])
        size *= 2
    if width > size:
        least = np.minimum(least[: len(least) - (width - size)], least[width - size :])
    starts = np.flatnonzero(runs[: len(least)])
    anchor = (least[starts] & _PLACE).astype(np.int64)
    first = np.flatnonzero(np.concatenate([[True], (anchor[1:] != anchor[:-1]) | (starts[1:] != starts[:-1] + 1)])) if len(starts) else starts
    last = np.concatenate([first[1:] - 1, [len(starts) - 1]]) if len(starts) else starts
    lo, hi, at = starts[first], starts[last], anchor[first]
    body = (total[hi + span] - total[lo]) * _INVERSE[lo]
    shape = (at - lo).astype(np.uint64) * np.uint64(1 << 20) + (hi - lo).astype(np.uint64)
    return {"key": grams[at], "hull": _mix(body ^ _mix(shape)), "at": at, "lo": lo, "hi": hi}


def passages(texts: pa.Array, span: int = SPAN, gram: int = GRAM, unit: Unit = Bytes) -> Iterator[tuple]:
    """``(rows, passages, units, bases)`` of an Arrow column of binary texts: passages' rows; places within their
    text; and the units, where a text's begin at the passage's base.

    Short texts are hashed together, long ones in chunks that overlap by a run.
    """
    sizes = np.array([len(x.as_buffer()) if x.is_valid else 0 for x in texts], np.int64)
    group: list[int] = []
    held = 0

    def together(rows: list[int]) -> Iterator[tuple]:
        data, counts = unit.load([texts[r].as_py() for r in rows])
        begin = np.concatenate([[0], np.cumsum(counts)])
        filled = np.flatnonzero(counts >= span)
        if not len(filled):
            return
        edge = np.zeros(len(data) + 1, np.int8)
        edge[begin[filled]] += 1
        edge[begin[filled + 1] - span + 1] -= 1
        found = _passages(unit.values(data), np.cumsum(edge[:-1]) > 0, span, gram)
        row = np.searchsorted(begin, found["lo"], side="right") - 1
        for name in ("at", "lo", "hi"):
            found[name] = found[name] - begin[row]
        yield np.array(rows)[row], found, data, begin[row]

    for row in np.flatnonzero(sizes >= span).tolist():
        if sizes[row] > CHUNK:
            data, _ = unit.load([texts[row].as_py()])
            for begin in range(0, len(data) - span + 1, CHUNK):
                part = unit.values(data[begin : begin + CHUNK + span - 1])
                found = _passages(part, np.ones(len(part), bool), span, gram)
                for name in ("at", "lo", "hi"):
                    found[name] = found[name] + begin
                yield np.full(len(found["lo"]), row), found, data, np.zeros(len(found["lo"]), np.int64)
            continue
        if held + sizes[row] > CHUNK and group:
            yield from together(group)
            group, held = [], 0
        group.append(row)
        held += int(sizes[row])
    if group:
        yield from together(group)


def _words(data: np.ndarray) -> np.ndarray:
    """The eight bytes from every place, as big-endian numbers, zeros beyond the end."""
    padded = np.concatenate([data, np.zeros(7, np.uint8)])
    out = np.zeros(len(data), np.uint64)
    for k in range(8):
        out = out << np.uint64(8) | padded[k : k + len(data)]
    return out


def _sort_directly(at: np.ndarray, words: np.ndarray, depth: int) -> np.ndarray:
    """``at`` ordered by the ``depth`` bytes from each place; only ties are looked at again."""
    n = len(words)
    order = at[np.argsort(words[at], kind="stable")]
    if not len(order):
        return order
    new = np.concatenate([[True], words[order][1:] != words[order][:-1]])
    rank = np.maximum.accumulate(np.where(new, np.arange(len(order)), 0))  # where its ties begin
    for step in range(8, depth, 8):
        tied = np.zeros(len(order), bool)
        equal = rank[1:] == rank[:-1]
        tied[1:] |= equal
        tied[:-1] |= equal
        spots = np.flatnonzero(tied)
        if not len(spots):
            break
        places = order[spots] + step
        word = np.where(places < n, words[np.minimum(places, n - 1)], np.uint64(0))
        again = np.lexsort((word, rank[spots]))
        order[spots] = order[spots][again]
        word, group = word[again], rank[spots][again]
        new = np.concatenate([[True], (group[1:] != group[:-1]) | (word[1:] != word[:-1])])
        head = np.flatnonzero(new)
        rank[spots] = spots[head][np.cumsum(new) - 1]
    return order


def suffix_array(data: np.ndarray, depth: int) -> np.ndarray:
    """Suffixes of ``data`` in the order of their first ``depth`` bytes at least, in two stages.

    Suffixes smaller than their successors are sorted directly. The rest come from one scan of the
    buckets in order: each suffix met puts its predecessor, if that is larger, next in its bucket.
    """
    n = len(data)
    if n == 0:
        return np.empty(0, np.int64)
    # smaller than its successor: the next different byte is larger (the end is smaller than all)
    change = np.flatnonzero(data[1:] != data[:-1])
    follow = np.searchsorted(change, np.arange(n))
    has = follow < len(change)
    spot = change[np.minimum(follow, max(len(change) - 1, 0))] if len(change) else np.zeros(n, np.int64)
    smaller = np.zeros(n, bool)
    if len(change):
        smaller[has] = data[spot[has] + 1] > data[spot[has]]
    direct = _sort_directly(np.flatnonzero(smaller), _words(data), depth)
    cut = np.searchsorted(data[direct], np.arange(257))
    waiting: list[list[np.ndarray]] = [[] for _ in range(256)]
    waiting[int(data[n - 1])].append(np.array([n - 1]))
    out = []
    for c in range(256):
        larger = waiting[c]
        wave = np.concatenate(larger) if larger else np.empty(0, np.int64)
        placed = [wave]
        while len(wave):
            before = wave[wave > 0] - 1
            wave = before[(data[before] == c) & ~smaller[before]]
            placed.append(wave)
        bucket = np.concatenate([*placed, direct[cut[c] : cut[c + 1]]])
        waiting[c] = []
        if not len(bucket):
            continue
        out.append(bucket)
        before = bucket[bucket > 0] - 1
        before = before[(data[before] > c) & ~smaller[before]]
        if len(before):
            first = data[before]
            dealt = before[np.argsort(first, kind="stable")]
            letters, heads = np.unique(data[dealt], return_index=True)
            for letter, part in zip(letters.tolist(), np.split(dealt, heads[1:]), strict=True):
                waiting[letter].append(part)
    return np.concatenate(out)


def common_at_least(data: np.ndarray, a: np.ndarray, b: np.ndarray, length: int) -> np.ndarray:
    """Whether the suffixes at ``a`` and ``b`` share their first ``length`` bytes."""
    words = _words(data)
    alive = np.arange(len(a))
    room = (np.maximum(a, b) + length) <= len(data)
    alive = alive[room]
    for step in [*range(0, length - 7, 8), length - 8]:
        alive = alive[words[a[alive] + step] == words[b[alive] + step]]
    out = np.zeros(len(a), bool)
    out[alive] = True
    return out


def repeated_runs(groups: list[tuple[int, bytes, bytes, int, int]], span: int, gram: int, unit: Unit = Bytes, across: bool = False) -> list[np.ndarray]:
    """For each ``(group, left, right, first, last)`` of an anchor's passages: which of its runs another passage of
    the group holds too; ``across``, which one of another row, first and last being the least and greatest row."""
    tail, width = span - gram, unit.width
    # bytes beyond F7 never occur in UTF-8 or in codes: FF opens the anchor's mark, FE ends a passage
    parts, starts, at = [], [], 0
    for group, left, right, _, _ in groups:
        digits = bytes([0xFF, group >> 18 & 63, group >> 12 & 63, group >> 6 & 63, group & 63])
        parts.append(left + digits + right + b"\xfe")
        runs = (len(left) + len(right)) // width - tail + 1
        starts.append(at + width * np.arange(runs))
        at += len(parts[-1])
    data = np.frombuffer(b"".join(parts), np.uint8)
    length = tail * width + 5
    owner = np.full(len(data), -1, np.int64)
    for number, places in enumerate(starts):
        owner[places] = number
    order = suffix_array(data, length)
    order = order[owner[order] >= 0]
    same = common_at_least(data, order[:-1], order[1:], length)
    heads = np.flatnonzero(np.concatenate([[True], ~same]))
    if across:
        rows = np.array([g[3:] for g in groups], np.int64)[owner[order]]
        repeated = np.minimum.reduceat(rows[:, 0], heads) < np.maximum.reduceat(rows[:, 1], heads)
    else:
        repeated = np.diff(np.concatenate([heads, [len(order)]])) > 1
    hit = np.zeros(len(data), bool)
    hit[order] = np.repeat(repeated, np.diff(np.concatenate([heads, [len(order)]])))
    return [hit[s] for s in starts]


def _ranges(marked: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First and last places of the runs of True."""
    turn = np.flatnonzero(np.diff(np.concatenate([[False], marked, [False]]).astype(np.int8)))
    return turn[0::2], turn[1::2] - 1


def _signed(x: np.ndarray) -> pa.Array:
    return pa.array(np.ascontiguousarray(x).view(np.int64))


def _numbered(docs: DataFrame) -> DataFrame:
    """``(row, doc_id, text)`` with a row number that stays the same in every reading."""
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("binary").alias("text"))
    repeats = source.groupBy("doc_id").count().where("count > 1 OR doc_id IS NULL")
    if repeats.isEmpty():
        return source.select(F.col("doc_id").alias("row"), "doc_id", "text")
    return materialize(source.select(F.monotonically_increasing_id().alias("row"), "doc_id", "text"), "numbered")


def _suspects(source: DataFrame, expected: int, span: int, gram: int, unit: Unit) -> DataFrame:
    """``(key, hull, row, at, lo, hi)`` of anchors that may occur twice."""
    bits = filter_bits(expected * 64)

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        filters = TwoFilters(bits)
        for batch in batches:
            for _, found, _, _ in passages(batch.column(0), span, gram, unit):
                filters.add(found["key"])
        for number, once, twice in filters.slices():
            yield pa.RecordBatch.from_arrays([pa.array([number]), pa.array([once]), pa.array([twice])], ["slice", "once", "twice"])

    built = source.select("text").mapInArrow(build, "slice long, once binary, twice binary")
    shared = source.sparkSession.sparkContext.broadcast(merge_filters(built, bits))  # bits / 8 bytes at most

    def emit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column(0).to_numpy(zero_copy_only=False)
            for row, found, _, _ in passages(batch.column(1), span, gram, unit):
                hit = np.flatnonzero(has_bits(shared.value, found["key"], bits))
                columns = [_signed(found["key"][hit]), _signed(found["hull"][hit]), pa.array(ids[row[hit]])]
                columns += [pa.array(found[c][hit]) for c in ("at", "lo", "hi")]
                yield pa.RecordBatch.from_arrays(columns, ["key", "hull", "row", "at", "lo", "hi"])

    return source.select("row", "text").mapInArrow(emit, "key long, hull long, row long, at long, lo long, hi long")


def _sides(source: DataFrame, chosen: DataFrame, n_chosen: int, span: int, gram: int, unit: Unit) -> DataFrame:
    """``chosen(key, hull, row, lo, ...)`` with the codes of the units beside the anchor (left, right).

    A Bloom filter of the chosen passages goes to the scan, so texts are not moved, only passages.
    """
    bits, width = filter_bits(n_chosen * 64), unit.width

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        filters = TwoFilters(bits)
        for batch in batches:
            filters.add(batch.column(0).to_numpy().view(np.uint64))
        for number, once, _ in filters.slices():
            yield pa.RecordBatch.from_arrays([pa.array([number]), pa.array([once]), pa.array([once])], ["slice", "once", "twice"])

    place = F.xxhash64("key", "hull", "row", "lo")
    built = chosen.select(place.alias("place")).mapInArrow(build, "slice long, once binary, twice binary")
    shared = source.sparkSession.sparkContext.broadcast(merge_filters(built, bits))

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = batch.column(0).to_numpy(zero_copy_only=False)
            for row, found, units, base in passages(batch.column(1), span, gram, unit):
                places = spark_xxhash64(found["key"].view(np.int64), found["hull"].view(np.int64), ids[row], found["lo"])
                hit = np.flatnonzero(has_bits(shared.value, places, bits))
                left, right = [], []
                for lo, at, end in zip(*((base + found[c])[hit].tolist() for c in ("lo", "at", "hi")), strict=True):
                    left.append(unit.code(units[lo:at]))
                    right.append(unit.code(units[at + gram : end + span]))
                columns = [_signed(found["key"][hit]), _signed(found["hull"][hit]), pa.array(ids[row[hit]]), pa.array(found["lo"][hit])]
                yield pa.RecordBatch.from_arrays([*columns, pa.array(left, pa.binary()), pa.array(right, pa.binary())], ["key", "hull", "row", "lo", "left", "right"])

    found = source.select("row", "text").mapInArrow(cut, "key long, hull long, row long, lo long, left binary, right binary")
    return chosen.join(found, ["key", "hull", "row", "lo"])


def spark_xxhash64(*columns: np.ndarray) -> np.ndarray:
    """Spark's xxhash64 of long columns, seed 42, as unsigned numbers."""
    p1, p2, p3, p4, p5 = (np.uint64(p) for p in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))
    rotl = lambda x, r: x << np.uint64(r) | x >> np.uint64(64 - r)
    h = np.full(len(columns[0]), 42, np.uint64)
    for column in columns:
        h = h + p5 + np.uint64(8)
        h = h ^ rotl(column.astype(np.int64).view(np.uint64) * p2, 31) * p1
        h = rotl(h, 27) * p1 + p4
        h = (h ^ (h >> np.uint64(33))) * p2
        h = (h ^ (h >> np.uint64(29))) * p3
        h = h ^ (h >> np.uint64(32))
    return h


def _sorted_repeats(sections: DataFrame, n_sections: int, span: int, gram: int, unit: Unit, across: bool) -> DataFrame:
    """``(key, gid, sec, l1, l2)``: runs of ``sections(key, gid, sec, n, first, last, lo, hi, left, right)`` that another
    section of the group holds, as ranges of the number of units before the anchor."""
    width, tail = unit.width, span - gram

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        size = 0
        for batch in batches:
            for item in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if size > SORT_BYTES and item[:2] != held[-1][:2]:
                    yield solve(held)
                    held, size = [], 0
                held.append(item)
                size += len(item[-2]) + len(item[-1])
        if held:
            yield solve(held)

    def solve(items: list[tuple]) -> pa.RecordBatch:
        numbers: dict[tuple, int] = {}
        groups = [(numbers.setdefault(x[:2], len(numbers)), x[-2], x[-1], x[4], x[5]) for x in items]
        out: list[tuple] = []
        for (key, gid, sec, n, first, last, lo, hi, left, right), marked in zip(items, repeated_runs(groups, span, gram, unit, across), strict=True):
            if first < last if across else n > 1:
                continue  # known to repeat as a whole
            before = len(left) // width
            for a, b in zip(*_ranges(marked), strict=True):
                l1, l2 = max(before - int(b), lo), min(before - int(a), hi)
                if l1 <= l2:
                    out.append((key, gid, sec, l1, l2))
        columns = list(zip(*out, strict=True)) or [[]] * 5
        return pa.RecordBatch.from_arrays([pa.array(list(c), pa.int64()) for c in columns], ["key", "gid", "sec", "l1", "l2"])

    dealt = sections.repartition(max(1, -(-n_sections // TASK_PASSAGES)), "key", "gid").sortWithinPartitions("key", "gid", "sec")
    columns = dealt.select("key", "gid", "sec", "n", "first", "last", "lo", "hi", "left", "right")
    return columns.mapInArrow(kernel, "key long, gid long, sec long, l1 long, l2 long")


def _halves(members: DataFrame, tail: int, width: int) -> DataFrame:
    """``members`` of groups too large to sort, once for each half of the range of units before the anchor in which
    they have runs; grouped by the units that all runs of the half contain, and cut to what these runs contain."""
    middle = F.floor((F.col("lo") + F.col("hi") + 1) / 2)
    half = F.explode(F.array(F.struct(F.lit(True).alias("low"), F.col("lo"), (middle - 1).alias("hi")), F.struct(F.lit(False).alias("low"), middle.alias("lo"), F.col("hi"))))
    before, behind = F.floor(F.octet_length("left") / width), F.floor(F.octet_length("right") / width)
    spread = members.withColumns({"half": half, "before": before, "behind": behind}).drop("lo", "hi").select("*", "half.*")
    inside = spread.where(F.greatest(F.lit(tail) - F.col("behind"), F.col("lo")) <= F.least("before", "hi"))
    ending = lambda units: F.substring("left", F.octet_length("left") - units * width + 1, units * width)
    begun = lambda units: F.substring("right", F.lit(1), units * width)
    shared = F.when(F.col("low"), begun((F.lit(tail) - F.col("hi")).cast("int"))).otherwise(ending(F.col("lo").cast("int")))
    left = ending(F.least("before", "hi").cast("int"))
    right = begun(F.least(F.lit(tail) - F.col("lo"), F.col("behind")).cast("int"))
    cut = inside.withColumns({"gid": F.xxhash64("gid", "lo", "hi", shared), "l": left, "r": right}).drop("left", "right", "sec")
    return cut.select("key", "gid", "hull", F.xxhash64(F.octet_length("l"), "l", "r").alias("sec"), "n", "first", "last", "lo", "hi", F.col("l").alias("left"), F.col("r").alias("right"))


def _whole(across: bool) -> Column:
    """A passage or section that repeats as a whole."""
    return F.col("first") < F.col("last") if across else F.col("n") > 1


def _divided(large: DataFrame, span: int, gram: int, unit: Unit, across: bool) -> list[DataFrame]:
    """Marks ``(key, hull, l1, l2)`` of groups with more passages than are sorted together, half by half."""
    marks = []
    tail, group = span - gram, ["key", "gid"]
    while not large.isEmpty():
        members = materialize(_halves(large, tail, unit.width), "halves")
        same = [F.sum("n").alias("n"), F.min("first").alias("first"), F.max("last").alias("last"), F.min("hull").alias("one"), *[F.first(c).alias(c) for c in ("lo", "hi", "left", "right")]]
        sections = materialize(members.groupBy(*group, "sec").agg(*same), "sections")
        sizes = sections.groupBy(*group).agg(F.count("*").alias("sections"))
        sized = sections.join(sizes, group)
        few = sized.where(f"sections BETWEEN 2 AND {BLOCK_PASSAGES}")
        found = materialize(_sorted_repeats(few, few.count(), span, gram, unit, across), "repeats")
        whole = sections.where(_whole(across)).select(*group, "sec", F.col("lo").alias("l1"), F.col("hi").alias("l2"))
        marks.append(members.select(*group, "sec", "hull").join(found.unionByName(whole), [*group, "sec"]).select("key", "hull", "l1", "l2"))
        # one section stands for all that repeat as a whole; single runs that differ have nothing left to share
        many = sized.where(f"sections > {BLOCK_PASSAGES} AND lo < hi").select(*group, "sec", "one", "n", "first", "last")
        left = members.drop("n", "first", "last").join(many, [*group, "sec"])
        large = materialize(left.where(~_whole(across) | (F.col("hull") == F.col("one"))).drop("one"), "large")
    return marks


def repeated_spans(source: DataFrame, span: int = SPAN, gram: int = GRAM, unit: Unit = Bytes, across: bool = False) -> DataFrame:
    """``(row, a, b)``: starts a to b of runs in ``source(row, text)`` that also start anywhere else, or, if
    ``across``, in another row."""
    total = source.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    suspects = materialize(_suspects(source, 2 * total // (unit.mean * (span - gram)), span, gram, unit), "anchors")
    rows = [F.min("row").alias("first"), F.max("row").alias("last"), F.min(F.struct("row", "lo", "at", "hi")).alias("one")]
    hulls = materialize(suspects.groupBy("key", "hull").agg(F.count("*").alias("n"), *rows), "hulls")
    many = materialize(hulls.groupBy("key").agg(F.count("*").alias("passages")).where("passages > 1"), "keys")
    mixed = materialize(hulls.join(many, "key").select("*", "one.row", "one.lo").drop("one"), "mixed")
    whole = hulls.where(_whole(across)).select("key", "hull", (F.col("one.at") - F.col("one.hi")).alias("l1"), (F.col("one.at") - F.col("one.lo")).alias("l2"))
    ranged = {"gid": F.lit(0).cast("long"), "sec": F.col("hull"), "lo": F.lit(0).cast("long"), "hi": F.lit(span - gram).cast("long")}
    n_mixed, largest = mixed.agg(F.count("*"), F.max("passages")).first()
    filled = _sides(source, mixed, n_mixed, span, gram, unit).withColumns(ranged)
    marks = [whole]
    if (largest or 0) > BLOCK_PASSAGES:
        filled = materialize(filled, "passages")
        marks += _divided(filled.where(f"passages > {BLOCK_PASSAGES}").drop("passages", "row"), span, gram, unit, across)
        filled = filled.where(f"passages <= {BLOCK_PASSAGES}")
    found = _sorted_repeats(filled, n_mixed, span, gram, unit, across)
    marks.append(found.select("key", F.col("sec").alias("hull"), "l1", "l2"))
    marked = marks[0]
    for one in marks[1:]:
        marked = marked.unionByName(one)
    at = F.col("at")
    joined = suspects.join(materialize(marked, "marks"), ["key", "hull"])
    return joined.select("row", F.greatest("lo", at - F.col("l2")).alias("a"), F.least("hi", at - F.col("l1")).alias("b")).where("a <= b")


def dedup_substrings(docs: DataFrame, span: int = SPAN, gram: int = GRAM, word_span: int | None = WORD_SPAN, word_gram: int = WORD_GRAM) -> DataFrame:
    """Per document ``doc_id, n_bytes, n_removed, n_spans, kept, n_shared_words`` (kept: the remaining bytes;
    n_shared_words: words in passages of at least ``word_span`` words that another document also has; null if
    word_span is None)."""
    source = _numbered(docs)
    runs = F.collect_list(F.struct("a", "b"))  # of one document
    lists = repeated_spans(source, span, gram).groupBy("row").agg(runs.alias("runs"))
    if word_span:
        shared = repeated_spans(source, word_span, word_gram, Words, across=True).groupBy("row").agg(runs.alias("shared"))
    else:
        shared = lists.select("row", F.lit(None).cast("array<struct<a:long,b:long>>").alias("shared"))

    def covered(runs: pa.ListScalar, width: int) -> np.ndarray:
        """Marks of the units under the runs, to the end of the last."""
        a, b = (runs.values.field(c).to_numpy() for c in ("a", "b"))
        edge = np.zeros(int(b.max()) + width + 1, np.int32)
        np.add.at(edge, a, 1)
        np.add.at(edge, b + width, -1)
        return np.cumsum(edge[:-1]) > 0

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sizes, removed, spans, kept, words = [], [], [], [], []
            for text, runs, passages in zip(*batch.columns[1:4], strict=True):
                raw = text.as_py() or b""
                gone = covered(runs, span) if runs.is_valid else np.empty(0, bool)
                sizes.append(len(raw))
                removed.append(int(np.count_nonzero(gone)))
                spans.append(len(_ranges(gone)[0]))
                kept.append(np.frombuffer(raw[: len(gone)], np.uint8)[~gone].tobytes() + raw[len(gone) :])
                words.append(int(np.count_nonzero(covered(passages, word_span))) if passages.is_valid else 0 if word_span else None)
            longs = [pa.array(c, pa.int64()) for c in (sizes, removed, spans)]
            names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept", "n_shared_words"]
            yield pa.RecordBatch.from_arrays([batch.column(0), *longs, pa.array(kept, pa.binary()), pa.array(words, pa.int64())], names)

    joined = source.join(lists, "row", "left").join(shared, "row", "left").select("doc_id", "text", "runs", "shared")
    return joined.mapInArrow(kernel, "doc_id long, n_bytes long, n_removed long, n_spans long, kept binary, n_shared_words long")
