"""Quality rules, SimHash groups, line and substring deduplication, decontamination: against brute force."""

from __future__ import annotations

import hashlib
import re
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from ivfspark.llm import decontaminate, line_bloom, near_copies, quality_rules, simhash, suffix_dedup

SPACE_WORDS = re.compile(r"[^\x20\x09-\x0D]+")


def lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


def pairs(df):
    return [(r.doc_id, r.text) for r in df.select("doc_id", "text").collect()]


def multiset(rows):
    return Counter(map(str, rows))


# quality rules


def test_quality_measures(awkward):
    found = quality_rules.judge(awkward).collect()
    expected = []
    for doc, text in pairs(awkward):
        w = SPACE_WORDS.findall(text or "")
        windows = Counter(zip(w, w[1:], w[2:], strict=False))
        covered = {p for i in range(len(w) - 2) if windows[tuple(w[i : i + 3])] > 1 for p in (i, i + 1, i + 2)}
        lines = [x for x in (text or "").split("\n") if SPACE_WORDS.search(x)]
        failed = len(w) < 50 or 100 * len(covered) > 50 * len(w)
        expected.append((doc, len(w), sum(map(len, w)), len(re.findall(r"[#*$%&|<>]", text or "")), len(lines) - len(set(lines)), len(covered), failed))
    got = [(r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed) for r in found]
    assert multiset(got) == multiset(expected)
    assert all(r.kept is False for r in found if r.base_failed) and any(r.kept for r in found)


def test_quality_host_verdict(shipped):
    clean = [(f"{i}", " ".join(f"clean{i}x{j}" for j in range(60)), "good") for i in range(40)]
    bad = [(f"b{i}", "# " * 8 + " ".join(f"junk{i}y{j}" for j in range(60)), "bad") for i in range(40)]
    alone = [("same", "# " * 8 + " ".join(f"other{j}" for j in range(60)), "good"), ("fine", " ".join(f"fine{j}" for j in range(60)), "bad")]
    df = shipped.createDataFrame(clean + bad + alone, "doc_id string, text string, source string")
    kept = {r.doc_id: r.kept for r in quality_rules.judge(df).collect()}
    assert all(kept[str(i)] for i in range(40)) and not any(kept[f"b{i}"] for i in range(40))
    assert kept["same"] and kept["fine"]  # one soft failure on a trusted host; none on a distrusted one


# SimHash


def reference_fingerprint(text):
    import xxhash

    w = SPACE_WORDS.findall(lower(text))
    shingles = [" ".join(w[i : i + 4]) for i in range(max(1, len(w) - 3))] if w else []
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if sum(h >> b & 1 for h in hashes) * 2 > len(hashes)) if hashes else 0


def test_fingerprints(awkward):
    got = {(r.doc_id, r.fp & 0xFFFFFFFFFFFFFFFF) for r in simhash.fingerprints(awkward).collect()}
    assert got == {(d, reference_fingerprint(t)) for d, t in pairs(awkward)}


def test_simhash_groups_of_near_fingerprints(shipped):
    """Planted chains and a dense ball of fingerprints: groups equal those of all pairs."""
    rng = np.random.default_rng(5)
    fps = [int(x) for x in rng.integers(0, 1 << 63, 300)]
    for _ in range(300):
        flips = rng.choice(64, rng.integers(1, 6), replace=False)
        fps.append(fps[rng.integers(0, len(fps))] ^ sum(1 << int(b) for b in flips))
    centre = int(rng.integers(0, 1 << 63))
    fps += [centre ^ sum(1 << int(b) for b in rng.choice(64, rng.integers(0, 4), replace=False)) for _ in range(2500)]
    fps = list(dict.fromkeys(fps))
    signed = [f - (1 << 64) if f >> 63 else f for f in fps]
    df = shipped.createDataFrame([(f, i) for i, f in enumerate(signed)], "fp long, rep long")
    from ivfspark.operators.graph import connected_components

    got = {r.node: r.component for r in connected_components(simhash.links(df)).collect()}
    array = np.array(fps, np.uint64)
    parent = list(range(len(fps)))

    def root(x):
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for i in range(len(fps)):
        for j in np.flatnonzero(np.bitwise_count(array[:i] ^ array[i]) <= 4):
            a, b = root(i), root(int(j))
            parent[max(a, b)] = min(a, b)
    assert [got.get(i, i) for i in range(len(fps))] == [root(i) for i in range(len(fps))]


def test_simhash_awkward(awkward, empty):
    got = simhash.near_duplicates(awkward).collect()
    assert len(got) == awkward.count()
    by = {}
    for r in got:
        by.setdefault(r.doc_id, set()).add((r.fingerprint, r.component_id))
    assert by[1] == by[2] == by[7] == {("0" * 16, 1)} and by[4] == {(next(iter(by[3]))[0], 3)}
    assert simhash.near_duplicates(empty).count() == 0


def test_bk_tree_finds_all():
    rng = np.random.default_rng(2)
    values = rng.integers(0, 1 << 10, 400).astype(np.uint64)
    found = {(int(a), int(b)) for q, i in simhash.BKTree(values, np.arange(400)).search(values, np.arange(400), 2) for a, b in zip(q, i, strict=True)}
    assert found == {(a, b) for a in range(400) for b in range(400) if int(values[a] ^ values[b]).bit_count() <= 2}


# lines


def brute_lines(rows):
    key = lambda line: lower(line.strip(" \t\n\r\x0b\x0c"))
    holders: dict[str, list] = {}
    for doc, text in rows:
        for k in {key(x) for x in (text or "").split("\n")}:
            if len(k) >= 20:
                holders.setdefault(k, []).append(doc)
    keeper = {k: max((d for d in ds if d is not None), default=None) for k, ds in holders.items() if len(ds) >= 3}
    out = []
    for doc, text in rows:
        lines = (text or "").split("\n")
        stay = [x for x in lines if (k := key(x)) not in keeper or keeper[k] is None or doc == keeper[k]]
        out.append((doc, len(lines), len(lines) - len(stay), hashlib.sha256("\n".join(stay).encode()).hexdigest()))
    return out


@pytest.mark.parametrize("bits", [1 << 12, 1 << 20])
def test_lines(shipped, awkward, bits):
    shared = ["This line is in many documents.", "  THIS line is in many documents.\t", "Another shared line, here and there", "éééééééééééééééééééé"]
    rows = [(i, "\n".join([f"own line number {i} of its document", shared[i % 4], shared[2] if i % 3 == 0 else "short", ""])) for i in range(60)]
    rows += [(None, shared[0]), (5, shared[2]), (7, None)]
    df = shipped.createDataFrame(rows, "doc_id long, text string")
    for table, source in ((df, rows), (awkward, pairs(awkward))):
        got = line_bloom.dedup_lines(table, most_bits=bits).withColumn("sha", F.sha2("kept", 256)).select("doc_id", "n_lines", "n_dropped", "sha")
        assert multiset(tuple(r) for r in got.collect()) == multiset(brute_lines(source))


def test_two_filters_merge_to_suspects():
    one, two = line_bloom.TwoFilters(1 << 12), line_bloom.TwoFilters(1 << 12)
    one.add(np.array([11, 22, 22], np.uint64))
    two.add(np.array([11], np.uint64))
    assert one.twice[22] and not one.twice[11] and one.once[11] and two.once[11]


def test_lines_empty(empty):
    assert line_bloom.dedup_lines(empty).count() == 0


# substrings


def brute_spans(rows, span):
    seen = Counter()
    for _, text in rows:
        raw = (text or "").encode()
        seen.update(raw[p : p + span] for p in range(len(raw) - span + 1))
    out = []
    for doc, text in rows:
        raw = (text or "").encode()
        cover, marked = 0, []
        for p in range(len(raw)):
            if seen[raw[p : p + span]] > 1 and p + span <= len(raw):
                cover = p + span
            marked.append(p < cover)
        spans = sum(m and (i == 0 or not marked[i - 1]) for i, m in enumerate(marked))
        kept = bytes(b for b, m in zip(raw, marked, strict=True) if not m)
        out.append((doc, len(raw), sum(marked), spans, hashlib.sha256(kept).hexdigest()))
    return out


def _spans(df, **options):
    got = suffix_dedup.dedup_substrings(df, **options).withColumn("sha", F.sha2("kept", 256))
    return multiset(tuple(r) for r in got.select("doc_id", "n_bytes", "n_removed", "n_spans", "sha").collect())


def test_substrings(shipped):
    rng = np.random.default_rng(4)
    text = lambda n: "".join(rng.choice(list("abcdefgh é\n"), n))
    passage, other = text(300), text(130)
    rows = [(i, text(int(rng.integers(0, 200))) + passage[int(rng.integers(0, 60)) : int(rng.integers(240, 300))] + text(50)) for i in range(60)]
    rows += [(100 + i, other + text(30) + other) for i in range(3)] + [(200, "ab" * 300), (201, "x" * 500), (202, text(80)), (203, "")]
    rows += [(300 + i, rows[i][1]) for i in range(5)]
    df = shipped.createDataFrame(rows, "doc_id long, text string")
    assert _spans(df, span=100, gram=64) == multiset(brute_spans(rows, 100))


def test_substrings_many_passages_in_blocks(shipped, monkeypatch):
    """An anchor with several blocks of passages: runs of different blocks still meet."""
    monkeypatch.setattr(suffix_dedup, "BLOCK_PASSAGES", 4)
    rng = np.random.default_rng(9)
    text = lambda n: "".join(rng.choice(list("abcdefghij"), n))
    passage = text(140)
    rows = [(i, text(40) + passage[i % 9 : 140 - i % 7] + text(40)) for i in range(40)]
    df = shipped.createDataFrame(rows, "doc_id long, text string")
    assert _spans(df, span=100, gram=64) == multiset(brute_spans(rows, 100))


def test_substrings_of_an_anchor_with_many_passages(shipped):
    """Thousands of contexts of one passage at the default block size; some contexts repeat in part."""
    rng = np.random.default_rng(21)
    text = lambda n: "".join(rng.choice(list("abcdefghijklmnop"), n))
    passage, ends = text(90), [text(12) for _ in range(40)]
    rows = [(i, text(20) + ends[i % 40] + passage[i % 3 :] + ends[i % 37] + text(20)) for i in range(6000)]
    rows += [(9000 + i, ends[i % 40] + passage + ends[i % 37]) for i in range(0, 6000, 500)]
    df = shipped.createDataFrame(rows, "doc_id long, text string")
    assert _spans(df, span=100, gram=64, word_span=None) == multiset(brute_spans(rows, 100))


def brute_shared_words(rows, span):
    holders: dict[tuple, set] = {}
    words = [(i, (text or "").encode().split()) for i, (_, text) in enumerate(rows)]
    for i, w in words:
        for p in range(len(w) - span + 1):
            holders.setdefault(tuple(w[p : p + span]), set()).add(i)
    out = []
    for i, w in words:
        marked = {q for p in range(len(w) - span + 1) if len(holders[tuple(w[p : p + span])]) > 1 for q in range(p, p + span)}
        out.append((rows[i][0], len(marked)))
    return out


@pytest.mark.parametrize("block", [3, 1024])
def test_passages_of_words_that_documents_share(shipped, awkward, monkeypatch, block):
    """Passages count if another document has them; those that only repeat within a document do not."""
    monkeypatch.setattr(suffix_dedup, "BLOCK_PASSAGES", block)
    rng = np.random.default_rng(8)
    some = lambda n: " ".join(f"w{x}" for x in rng.integers(0, 500, n))
    passages = [some(22), some(30), some(19)]
    rows = [(i, some(15) + "\n " + passages[i % 3] + " " + some(20)) for i in range(30)]
    rows += [(50, "one line again\n" * 40), (51, passages[1]), (52, passages[1].replace(" ", "\t  ")), (53, None), (54, some(300))]
    df = shipped.createDataFrame(rows, "doc_id long, text string")
    for table, source in ((df, rows), (awkward, pairs(awkward))):
        got = suffix_dedup.dedup_substrings(table, word_span=20, word_gram=12).select("doc_id", "n_shared_words")
        assert multiset(tuple(r) for r in got.collect()) == multiset(brute_shared_words(source, 20))


def test_substrings_awkward(awkward, empty):
    assert _spans(awkward) == multiset(brute_spans(pairs(awkward), 400))
    assert _spans(empty) == Counter()


def test_suffix_array():
    rng = np.random.default_rng(0)
    for trial in range(60):
        data = rng.integers(0, 2 + trial % 3, int(rng.integers(1, 120))).astype(np.uint8)
        raw = data.tobytes()
        assert suffix_dedup.suffix_array(data, 128).tolist() == sorted(range(len(raw)), key=lambda i: raw[i:])


def test_engine_hash_in_numpy(shipped):
    rows = [(1, -5), (2**62, 7), (-(2**63), 0)]
    got = [r.h for r in shipped.createDataFrame(rows, "a long, b long").select(F.xxhash64("a", "b").alias("h")).collect()]
    a, b = (np.array(c, np.int64) for c in zip(*rows, strict=True))
    assert suffix_dedup.spark_xxhash64(a, b).view(np.int64).tolist() == got


# decontamination

BENCH_WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def brute_contamination(rows, items):
    windows: dict[tuple, set] = {}
    for item, text in items:
        w = BENCH_WORD.findall(lower(text))
        for k in range(max(1, len(w) - 9) if w else 0):
            windows.setdefault(tuple(w[k : k + 10]), set()).add("" if item is None else str(item))
    out = []
    for doc, text in rows:
        w = BENCH_WORD.findall(lower(text))
        hit, found = set(), set()
        for size in {len(k) for k in windows}:
            for i in range(len(w) - size + 1):
                if owners := windows.get(tuple(w[i : i + size])):
                    found |= owners
                    hit.update(range(i, i + size))
        out.append((doc, len(w), len(hit), len(found), ",".join(sorted(found))))
    return out


@pytest.mark.parametrize("block_bytes", [32 << 20, 200])
def test_contamination(shipped, awkward, block_bytes):
    long_item = " ".join(f"q{i}" for i in range(25))
    items = [(1, long_item), (2, "short item here"), (10, "word1"), (3, None), (4, ""), (None, long_item), (5, "Straße ÜNÏ çödé"), (6, long_item)]
    rows = [
        (1, f"before {long_item} after"),
        (2, " ".join(long_item.split()[3:14]) + " no " + " ".join(long_item.split()[15:24])),
        (3, "A SHORT-item, here! and short item"),
        (4, None),
        (5, "word12 word1"),
        (5, "word12 word1"),
        (6, ""),
    ]
    bench = shipped.createDataFrame(items, "item_id long, text string")
    docs = shipped.createDataFrame(rows, "doc_id long, text string")
    for table, source in ((docs, rows), (awkward, pairs(awkward))):
        got = decontaminate.contamination(table, bench, block_bytes=block_bytes).withColumn("joined", F.array_join("items", ","))
        assert multiset(tuple(r) for r in got.select("doc_id", "n_words", "n_hit", "n_items", "joined").collect()) == multiset(brute_contamination(source, items))


def test_contamination_without_items(awkward, empty, shipped):
    none = shipped.createDataFrame([], "item_id long, text string")
    assert decontaminate.contamination(awkward, none).where("n_hit > 0").count() == 0
    assert decontaminate.contamination(empty, none).count() == 0


@pytest.mark.parametrize("query", ["op7_simhash", "op10_decontamination", "op5_suffix_dedup"])
def test_registered_queries_cover_the_table(query, spark, small):
    import __spark_entry__

    assert __spark_entry__.queries()[query](spark, small).count() == spark.read.parquet(f"{small}/documents.parquet").count()


def test_simhash_links_through_rows_without_id(shipped, monkeypatch):
    """A fingerprint that only rows without id hold takes its group's component, and joins its neighbours."""
    prints = shipped.createDataFrame([(3, 0), (None, 0b1111), (9, 0b11111111), (None, -1), (4, 1 << 62)], "doc_id long, fp long")
    monkeypatch.setattr(simhash, "fingerprints", lambda *_: prints)
    got = {(r.doc_id, int(r.fingerprint, 16)): r.component_id for r in simhash.near_duplicates(prints).collect()}
    assert got == {(3, 0): 3, (None, 15): 3, (9, 255): 3, (None, 2**64 - 1): None, (4, 1 << 62): 3}


def test_near_copies_equal_all_pairs(shipped, awkward, empty):
    """Groups of texts at Jaccard 0.8 of five-word shingles, where most pairs are beyond four bits of SimHash."""
    rng = np.random.default_rng(3)
    texts = []
    for base in range(12):
        words = [f"w{base}x{rng.integers(0, 5000)}" for _ in range(150)]
        texts.append(" ".join(words))
        for edits in (1, 2, 3, 4, 6, 8):
            changed = list(words)
            for at in rng.integers(0, 150, edits):
                changed[at] = f"new{rng.integers(0, 10**6)}"
            texts.append(" ".join(changed))
    texts += [texts[0], texts[1].upper(), "", None, "a b", "A  b"]
    sets = []
    for t in texts:
        w = SPACE_WORDS.findall(lower(t))
        sets.append({tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set())
    group = list(range(len(texts)))
    far = 0
    for i in range(len(texts)):
        for j in range(i):
            both, either = len(sets[i] & sets[j]), len(sets[i] | sets[j])
            if 5 * both >= 4 * either:
                far += (simhash.fingerprint((texts[i] or "").encode()) ^ simhash.fingerprint((texts[j] or "").encode())).bit_count() > 4
                old, new = max(group[i], group[j]), min(group[i], group[j])
                group = [new if g == old else g for g in group]
    got = {r.doc_id: r.component_id for r in near_copies.near_copies(shipped.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    assert [got[i] for i in range(len(texts))] == group and far > 5
    assert near_copies.near_copies(awkward.where("doc_id IS NOT NULL").dropDuplicates(["doc_id"])).count() == 10
    assert near_copies.near_copies(empty).count() == 0


def test_sketched_members_equal_all_pairs(monkeypatch):
    monkeypatch.setattr(near_copies, "SKETCH", 400)
    rng = np.random.default_rng(5)
    sets = []
    for size in (60, 390, 410, 2500):  # sketches whole, at the border of a level, and of a share of the hashes
        base = rng.integers(0, 1 << 63, size, np.uint64)
        for cut in (0.02, 0.05, 0.3, 0.3, 0.5):
            keep = base[rng.random(size) > cut]
            sets.append(np.unique(np.concatenate([keep, rng.integers(0, 1 << 63, int(size * cut / 4), np.uint64)])))
    reps, sizes = np.arange(len(sets)), np.array([len(s) for s in sets])
    groups = np.where(reps % 5 == 0, 0, reps)  # the first of each base is in the main group, the others stand alone
    like = {(a, b) for a in reps for b in reps if a < b and groups[a] != groups[b] and len(np.intersect1d(sets[a], sets[b])) * 5 >= 4 * len(np.union1d(sets[a], sets[b]))}
    drawn = [near_copies.sketch(s) for s in sets]
    found = {tuple(sorted(p)) for p in near_copies.similar_members(reps, groups, np.zeros(len(sets), int), sizes, np.zeros(len(sets), int), drawn)}
    assert len(like) >= 4 and like <= found and len(found) < len(like) + 20
    sides = reps % 2
    across = {tuple(sorted(p)) for p in near_copies.similar_members(reps, groups, np.zeros(len(sets), int), sizes, sides, drawn)}
    assert across == {(a, b) for a, b in found if sides[a] != sides[b]}
