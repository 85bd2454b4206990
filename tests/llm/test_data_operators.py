"""Wrappers, token files and counts, mixing, chat formatting, and the pipeline."""

from __future__ import annotations

import hashlib
import zlib
from collections import Counter

import numpy as np
import pytest

from ivfspark.llm import chat_format, html_wrapper, mixing, token_counts, token_output, tokens, wavelet
from ivfspark.plans.scratch import scratch_path

ODD = ["Straße ΟΔΟΣ. İstanbul! don't we're 'S x's <|endoftext|> a<|startoftext|>b", "é ÅÅ क़ab 1st 2,000 naïve—dash x_y\x0bq \xa0z a　b", "", "  ", "\n\t a\r\nb", "ǅ ŉ ﬁx Ⅷ ½ ²", "a" * 3000]


# wrappers


def _page(body, title="t", nav="<nav><ul><li><a href='/a'>one</a></li><li><a href='/b'>two</a></li></ul></nav>"):
    return f"<!DOCTYPE html><html><head><title>{title}</title><script>var a='<p>no</p>';</script><style>p{{}}</style></head><body>{nav}<div class='ad-slot'>buy</div>{body}<footer>&copy; us</footer></body></html>"


def test_wrapper_alignment():
    a = html_wrapper.stream(_page("<article><h1>x</h1><p>a<p>b<p>c</article>"))
    b = html_wrapper.stream(_page("<article><h1>x</h1><p>a</p><aside>s</aside></article>"))
    both = html_wrapper.align(a, b)
    text = html_wrapper.write(both)
    assert "( <p # >p )+" in text and "( <aside # >aside )?" in text and html_wrapper.read(text) == both
    assert html_wrapper.align(both, a) == both or html_wrapper.slot_paths(html_wrapper.align(both, a)) == html_wrapper.slot_paths(both)
    content = html_wrapper.content_paths(html_wrapper.slot_paths(both), {})
    assert content == ["article/h1", "article/p"]


def test_folding():
    fold = lambda s: html_wrapper.write(html_wrapper.fold(s.split()))
    assert fold("<ul <li # >li <li # >li <li # >li >ul") == "<ul ( <li # >li )+ >ul"
    assert fold("# # #") == "( # )+"


def test_extraction(shipped):
    rows = [
        (1, "http://a.example/1", _page("<article><h1>Head &amp; more</h1><p>One <b>two</b><br>three\n  four<p>Five &#233;<div class='comments'><p>nope</p></div><form>f</form></article>")),
        (2, "http://a.example/2", _page("<article><h1>Only</h1></article>")),
        (3, "http://b.example/x", _page("<div id='main-text'><p>long text that matters here</p><p>and more of it, again and again</p></div><div class='sidebar'>side</div>")),
        (4, None, None),
        (5, "not a url", ""),
        (6, "http://a.example/3", "<article><p>unclosed <i>text"),
        (7, "http://a.example/4", _page("<div class='wrap'><article><p>wrapped</p></article></div>")),
        (8, "http://a.example/5", _page("<div><p>no article on this page</p></div>")),
    ]
    got = {r.page_id: r.text for r in html_wrapper.extract(shipped.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got[1] == "Head & more\n\nOne two three four\n\nFive é" and got[2] == "Only"
    assert got[3] == "long text that matters here\n\nand more of it, again and again"
    assert got[4] == "" and got[5] == "" and got[6] == "unclosed text"
    assert got[7] == "wrapped" and got[8] == "no article on this page"


def test_template_texts_are_dropped_outside_articles(shipped):
    rows = [(i, f"http://c.example/{i}", f"<html><body><div><p>Welcome to our place</p><p>Own text number {i} with many words</p></div></body></html>") for i in range(8)]
    got = {r.page_id: r.text for r in html_wrapper.extract(shipped.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got == {i: f"Own text number {i} with many words" for i in range(8)}


def test_repeats_and_copied_pages_are_not_template(shipped):
    """A line that one page repeats, and the texts of a page that was copied, are content."""
    one = "<html><body><div><p>Refrain</p><p>verse one</p>" + "<p>Refrain</p>" * 5 + "</div></body></html>"
    copy = "<html><body><div><p>A short text</p><p>and another</p></div></body></html>"
    rows = [(1, "http://d.example/1", one), *((i, f"http://e.example/{i}", copy) for i in range(2, 12))]
    rows += [(20, "http://e.example/20", "<html><body><div><p>unlike the others</p></div></body></html>")]
    got = {r.page_id: r.text for r in html_wrapper.extract(shipped.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got[1] == "\n\n".join(["Refrain", "verse one", *["Refrain"] * 5])
    assert all(got[i] == "A short text\n\nand another" for i in range(2, 12)) and got[20] == "unlike the others"


PAGES = "page_id long, url string, html string"


def _texts(shipped, rows):
    got = html_wrapper.extract(shipped.createDataFrame(rows, PAGES)).collect()
    assert sorted(r.page_id for r in got) == sorted(r[0] for r in rows)
    return {r.page_id: r.text for r in got}


def test_the_wrapper_decides_by_position(shipped, monkeypatch):
    """A template's line is dropped where the template has it and kept where a page quotes it; without the wrapper
    nothing is read."""
    page = lambda i, more="": f"<html><body><div><p>Welcome to our place</p><h2>Title {i}</h2><p>Own text number {i} with many words</p>{more}</div></body></html>"
    rows = [(i, f"http://f.example/{i}", page(i)) for i in range(20)] + [(20, "http://f.example/20", page(20, "<h2>Quoted</h2><p>Welcome to our place</p>"))]
    got = _texts(shipped, rows)
    assert got[3] == "Title 3\n\nOwn text number 3 with many words"
    assert got[20] == "Title 20\n\nOwn text number 20 with many words\n\nQuoted\n\nWelcome to our place"
    reader = html_wrapper.Reader("", 21, {"div/p": 500, "div/h2": 90}, [])
    assert reader.text(page(1)) == ""


def test_hot_hosts_merge_in_steps(shipped, monkeypatch):
    """Many different trees of one host become one expression that places all texts, however they are dealt."""
    monkeypatch.setattr(html_wrapper, "MERGE_TREES", 4)
    parts = ["<h2>a</h2>", "<ul><li>b</li><li>c</li></ul>", "<blockquote><p>d</p></blockquote>", "<table><tr><td>e</td></tr></table>", "<pre>f</pre>", "<h3>g</h3>"]
    rows = []
    for i in range(64):
        chosen = [x for k, x in enumerate(parts) if i >> k & 1]
        rows.append((i, f"http://hot.example/{i}", f"<body><nav>menu</nav><article><h1>page {i}</h1>{''.join(chosen)}<p>end {i}</p></article></body>"))
    got = _texts(shipped, rows)
    for i in range(64):
        letters = [x for k, x in enumerate(["a", "b\n\nc", "d", "e", "f", "g"]) if i >> k & 1]
        assert got[i] == "\n\n".join([f"page {i}", *letters, f"end {i}"])


def test_long_deep_and_repeated_pages(shipped):
    """Whole texts of very long, irregular and deep pages; repeated rows are read alike."""
    irregular = "".join(f"<h{1 + i * i % 5}>t{i}</h{1 + i * i % 5}>" + "<p>x</p>" * (i * 7 % 3) + ("<ul><li>y</li></ul>" if i % 11 == 3 else "") for i in range(3000))
    deep = "<div>" * 3000 + "<p>bottom</p>" + "</div>" * 3000
    rows = [(1, "http://l.example/1", f"<article>{irregular}</article>"), (2, "http://l.example/2", "<article><p>short</p></article>")]
    rows += [(3, "http://deep.example/", deep), (4, "http://r.example/", "<article><p>same</p></article>"), (5, "http://r.example/", "<article><p>same</p></article>")]
    got = _texts(shipped, rows)
    assert got[1].split("\n\n") == [t for i in range(3000) for t in [f"t{i}", *["x"] * (i * 7 % 3), *(["y"] if i % 11 == 3 else [])]]
    assert got[2] == "short" and got[3] == "bottom" and got[4] == got[5] == "same"


def test_common_subsequences():
    rng = np.random.default_rng(3)
    for _ in range(200):
        a, b = (["abcd"[x] for x in rng.integers(0, 4, rng.integers(0, 14))] for _ in range(2))
        best = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i in range(len(a)):
            for j in range(len(b)):
                best[i + 1][j + 1] = best[i][j] + 1 if a[i] == b[j] else max(best[i][j + 1], best[i + 1][j])
        found = html_wrapper._common(a, b)
        assert len(found) == best[-1][-1] and all(a[i] == b[j] for i, j in found)
        assert all(p[0] < q[0] and p[1] < q[1] for p, q in zip(found, found[1:], strict=False))


def test_extraction_empty(shipped):
    assert html_wrapper.extract(shipped.createDataFrame([], "page_id long, url string, html string, text string")).count() == 0


# tokens


@pytest.fixture(scope="module")
def tokenizer():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(tokens.tokenizer_path())


def test_encoder_equals_tokenizer(tokenizer, spark, small):
    texts = ODD + [r.text for r in spark.read.parquet(f"{small}/documents.parquet").limit(60).collect()]
    coder = tokens.Encoder(tokens.tokenizer_path())
    for text in texts + texts:
        assert coder.encode(text) == np.array(tokenizer.encode(text, add_special_tokens=False).ids, "<u4").tobytes()


def test_wavelet_matrix():
    rng = np.random.default_rng(0)
    ids = np.concatenate([rng.integers(0, 49408, 3000), np.ones(500, int), rng.integers(0, 40, 1500)]).astype(np.uint32)
    made = wavelet.WaveletMatrix.build(ids, np.array([5, -1]), np.array([2000, 3000]))
    read = wavelet.WaveletMatrix.from_bytes(made.to_bytes())
    assert (read.ids() == ids).all() and read.doc_ids.tolist() == [5, -1] and read.lengths.tolist() == [2000, 3000]
    for place in (0, 511, 512, 513, 3200, 4999):
        assert read.access(place) == ids[place]
    for token in (1, 7, int(ids[0]), 60000):
        where = np.flatnonzero(ids == token)
        assert read.count(token) == len(where) and read.count(token, 100, 3300) == int(((where >= 100) & (where < 3300)).sum())
        for nth in range(0, len(where), max(1, len(where) // 7)):
            assert read.occurrence(token, nth) == where[nth]
        with pytest.raises(IndexError):
            read.occurrence(token, len(where))
    nothing = wavelet.WaveletMatrix.build(ids[:0], np.array([], np.int64), np.array([], np.uint64))
    assert len(wavelet.WaveletMatrix.from_bytes(nothing.to_bytes()).ids()) == 0


def test_token_files(awkward, empty, tokenizer, shipped):
    folder = scratch_path(shipped, "tokens")
    manifest = token_output.write_shards(awkward, folder, shard_tokens=2000)
    got = token_output.read_shards(manifest).orderBy("start").collect()
    rows = sorted(((r.doc_id, r.text or "") for r in awkward.collect()), key=lambda r: (r[0] is not None, r[0] or 0, r[1].encode()))
    at, expected = 0, []
    for doc, text in rows:
        ids = [*tokenizer.encode(text, add_special_tokens=False).ids, 1]
        expected.append((doc, at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        at += len(ids)
    assert [tuple(r) for r in got] == expected
    assert manifest.count() > 1 and token_output.open_shard(manifest.first().path).count(1) > 0
    assert token_output.token_output(empty).count() == 0


def test_length_histogram(awkward, empty, tokenizer, shipped):
    sizes = [len(tokenizer.encode(r.text or "", add_special_tokens=False).ids) for r in awkward.collect()]
    histogram = token_counts.length_histogram(awkward)
    for r in histogram.collect():
        assert r.n_docs == sizes.count(r.n_tokens) and r.docs_longer == sum(s > r.n_tokens for s in sizes)
        assert r.truncated_tokens == sum(min(s, r.n_tokens) for s in sizes) and r.total_tokens == sum(sizes)
        assert r.quantile == pytest.approx(sum(s <= r.n_tokens for s in sizes) / len(sizes))
    limits = shipped.createDataFrame([(0,), (50,), (10**6,)], "context long")
    got = {r.context: r.truncated_tokens for r in token_counts.at_limits(histogram, limits).collect()}
    assert got == {c: sum(min(s, c) for s in sizes) for c in (0, 50, 10**6)}
    assert token_counts.quantile_length(histogram, 0.5) == sorted(sizes)[(len(sizes) - 1) // 2]
    assert token_counts.length_histogram(empty).count() == 0


# mixing


def test_targets():
    assert mixing.targets([100, 100, 100]) == pytest.approx([50, 100, 150])
    capped = mixing.targets([10, 1000, 1000])
    assert capped[0] == 30 and sum(capped) == pytest.approx(2010) and capped[2] == pytest.approx(capped[1] * 1.5)
    assert mixing.targets([]) == [] and mixing.targets([0, 0]) == [0, 0]


def test_mix(shipped, awkward, empty):
    rng = np.random.default_rng(1)
    rows = [(i, " ".join(["w"] * int(rng.integers(0, 60))), None if i % 7 == 0 else ["b", "a", "é", "Z"][i % 4] if i % 50 else "tiny") for i in range(3000)]
    got = mixing.mix(shipped.createDataFrame(rows, "doc_id long, text string, source string")).collect()
    assert sorted(r.doc_id for r in got) == list(range(3000))
    size = {i: len(t.split()) for i, t, _ in rows}
    assert all(r["size"] == size[r.doc_id] and 0 <= r.taken <= 3 * r["size"] for r in got)
    taken, target, words = Counter(), {}, {}
    for r in got:
        taken[r.source] += r.taken
        target[r.source], words[r.source] = r.target, r.source_size
    names = sorted((s for s in target if s is not None), key=str.encode) + [None]
    assert [target[n] for n in names] == pytest.approx(mixing.targets([words[n] for n in names]))
    for n in names:
        assert taken[n] == pytest.approx(target[n], rel=0.01, abs=5)
    again = mixing.mix(shipped.createDataFrame(rows[::-1], "doc_id long, text string, source string")).collect()
    assert Counter(map(tuple, got)) == Counter(map(tuple, again))
    assert mixing.mix(awkward).count() == awkward.count() and mixing.mix(empty).count() == 0


@pytest.mark.parametrize("slots", [1 << 16, 50])
def test_mix_takes_targets_of_small_sources(shipped, monkeypatch, slots):
    """Each source takes its target to the word, also where a slot holds more words than the source."""
    monkeypatch.setattr(mixing, "LEAST_SLOTS", slots)
    sizes = {f"s{i}": n for i, n in enumerate([60_000, 3, 40, 9, 25_000, 1, 300, 17])}
    rows = [(i, "w " * (n // 2 + (n % 2 and k)), s) for i, (s, n) in enumerate(sizes.items()) for k in (0, 1)]
    rows = [(2 * i + k, t, s) for k in (0, 1) for i, (_, t, s) in enumerate(rows[k::2])]
    taken, target = Counter(), {}
    for r in mixing.mix(shipped.createDataFrame(rows, "doc_id long, text string, source string")).collect():
        taken[r.source] += r.taken
        target[r.source] = r.target
        assert r.taken <= 3 * r["size"]
    assert taken == Counter({s: round(t) for s, t in target.items()}) and min(taken.values()) > 0


def test_schedule_is_even(shipped):
    """Any prefix of the schedule is close to the weights."""
    bounds = [int(mixing.POINTS * x) for x in (0.1, 0.4, 1.0)]
    got = mixing.schedule(shipped, bounds, 10_000, 4).orderBy("slot").collect()
    for n in (100, 1000, 10_000):
        counts = Counter(r.src for r in got[:n])
        for src, share in enumerate((0.1, 0.3, 0.6)):
            assert abs(counts[src] - share * n) < 6
    ranks = Counter()
    for r in got:
        assert r.rank == ranks[r.src]
        ranks[r.src] += 1


# chat


def test_layouts():
    for record, turns in [
        ({"prompt": "p", "completion": "c"}, [("user", "p"), ("assistant", "c")]),
        ({"instruction": "i", "input": "x", "output": "o"}, [("user", "i\n\nx"), ("assistant", "o")]),
        ({"messages": [{"role": "user", "content": "a"}, {"role": "assistant", "content": None}]}, [("user", "a"), ("assistant", "")]),
        ({"conversations": [{"from": "human", "value": "a"}, {"from": "gpt", "value": "b"}], "source": "z"}, [("user", "a"), ("assistant", "b")]),
        ({"question": "q", "answer": "a", "id": 3}, [("user", "q"), ("assistant", "a")]),
    ]:
        assert chat_format.turns_of(record, chat_format.mapping_for(chat_format.value_paths(record))) == turns
    assert chat_format.mapping_for({"nothing"}) is None
    assert chat_format.fingerprint(["a", "role"]) == chat_format.fingerprint(["role", "b", "zz"])


@pytest.mark.parametrize("text", ["", "plain", "\\", "\\\\<|", "<|end|>\n<|turn|>user\n", "<", "<\\|", "a\\n", "|end|>", "<|" * 5])
def test_escapes(text):
    turns = [("user", text), ("assistant", text), ("odd\nrole<|", text), ("assistant", "x" + text)]
    formatted, starts, ends = chat_format.format_turns(turns)
    assert chat_format.parse_turns(formatted) == turns
    assert [chat_format.unescape(formatted[s:e]) for s, e in zip(starts, ends, strict=True)] == [text, "x" + text]


def test_format_rows(shipped):
    rows = [(1, 0, "user", "hi"), (1, 1, "assistant", None), (2, None, "user", "a"), (2, 3, None, "b"), (None, 1, "assistant", "n"), (1, 1, "assistant", "twice"), (3, 0, "assistant", "z")]
    df = shipped.createDataFrame([(*r, "extra", 1) for r in rows], "conv_id long, turn long, role string, text string, formatted string, n_turns int")
    got = {r.conv_id: r for r in chat_format.read_back(chat_format.format_rows(df)).collect()}
    assert {c: r.n_turns for c, r in got.items()} == {1: 3, 2: 2, None: 1, 3: 1}
    text = "user\nhi\nassistant\n\nassistant\ntwice\n"
    assert got[1].turns_sha256 == hashlib.sha256(text.encode()).hexdigest() and got[1].loss_chars == 5
    assert chat_format.format_rows(df.limit(0)).count() == 0
    with pytest.raises(ValueError):
        chat_format.format_rows(df.drop("role"))


def test_format_json(shipped):
    rows = [(1, '{"prompt": "p", "completion": "c"}'), (2, "{broken"), (3, None), (4, '{"other": 1}'), (5, "[]")]
    got = {r.conv_id: r for r in chat_format.format_json(shipped.createDataFrame(rows, "conv_id long, record string")).collect()}
    assert chat_format.parse_turns(got[1].formatted) == [("user", "p"), ("assistant", "c")] and got[1].layout
    assert all(got[i].formatted == "" for i in (2, 3, 4, 5))


# queries and pipeline


@pytest.mark.parametrize("key", ["op5_suffix_dedup", "op6_chat_format", "op8_host_quality", "op9_line_dedup", "op10_decontamination"])
def test_query_equals_sql(key, spark, small, duck):
    import __spark_entry__
    from comparing import as_rows
    from ivfspark.llm.oracles import ORACLES

    df = __spark_entry__.queries()[key](spark, small)
    cursor = duck.execute(ORACLES[key])
    names = [d[0] for d in cursor.description]
    assert as_rows(df.columns, [tuple(r) for r in df.collect()]) == as_rows(names, cursor.fetchall())


def _groups_of_near_copies(rows):
    """Least ids of the groups of texts that share four fifths of their five-word shingles, by all pairs."""
    sets = {}
    for i, text in sorted(rows):
        w = (text or "").encode().lower().split()
        sets[i] = {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()
    group = {i: i for i in sets}
    for a in sets:
        for b in sets:
            both = len(sets[a] & sets[b]) if a < b and group[a] != group[b] else -1
            if both >= 0 and 5 * both >= 4 * (len(sets[a]) + len(sets[b]) - both):
                old, new = max(group[a], group[b]), min(group[a], group[b])
                group = {i: new if g == old else g for i, g in group.items()}
    return set(group.values())


def test_pipeline(spark, small, awkward):
    """Each stage decides as its operator does; the run's tokens are those of the last stage's documents."""
    import corpus_pipeline as pipeline
    from ivfspark.llm.decontaminate import contamination
    from ivfspark.llm.quality_rules import judge

    docs = spark.read.parquet(f"{small}/documents.parquet")
    ids = lambda df: Counter(r.doc_id for r in df.select("doc_id").collect())
    good = pipeline.quality(spark, docs, small)
    assert ids(good) == ids(judge(docs).where("kept")) and good.columns == docs.columns
    single = pipeline.near_dedup(spark, good, small)
    assert ids(single) == Counter(_groups_of_near_copies([(r.doc_id, r.text) for r in good.collect()]))
    bench = spark.read.parquet(f"{small}/benchmark.parquet")
    clean = pipeline.decontaminate(spark, single, small)
    assert ids(clean) == ids(contamination(single, bench).where("n_hit = 0"))
    mixed = pipeline.mixture(spark, clean, small)
    want = {r.doc_id: round(r.taken / r["size"]) for r in mixing.mix(clean).collect() if r["size"]}
    assert ids(mixed) == Counter({d: n for d, n in want.items() if n})
    out = pipeline.run(spark, small).orderBy("start").collect()
    assert Counter(r.doc_id for r in out) == ids(mixed)
    assert [r.start for r in out] == np.cumsum([0, *[r.n_tokens for r in out]])[:-1].tolist()
    for _, stage in pipeline.STAGES:
        assert stage(spark, awkward, small).count() >= 0
        assert stage(spark, awkward.limit(0), small).count() == 0


def test_pipeline_judges_rows_without_id_one_by_one(spark, small, shipped):
    """Rows without id, and different texts under one id, are kept or dropped each by itself."""
    import corpus_pipeline as pipeline

    text = lambda name, n=80: " ".join(f"{name}_word{i}" for i in range(n))
    rows = [(None, text("a")), (None, text("b")), (None, text("b")), (None, "too short"), (5, text("c")), (5, text("d")), (6, text("e")), (None, text("e"))]
    df = shipped.createDataFrame([(i, t, "s") for i, t in rows], "doc_id long, text string, source string")
    found = lambda stage, table=df: Counter((r.doc_id, (r.text or "")[:2]) for r in stage(spark, table, small).collect())
    assert found(pipeline.quality) == Counter((i, t[:2]) for i, t in rows if t != "too short")
    assert found(pipeline.near_dedup) == Counter([(None, "a_"), (None, "b_"), (None, "to"), (5, "c_"), (5, "d_"), (6, "e_")])
    bench = spark.read.parquet(f"{small}/benchmark.parquet").where("length(text) > 100").first().text
    leaked = df.unionByName(shipped.createDataFrame([(None, "zz " + bench, "s")], df.schema))
    assert found(pipeline.decontaminate, leaked) == Counter((i, t[:2]) for i, t in rows)
    uneven = shipped.createDataFrame([(None, text("x", 40 + i), "s" if i else "t") for i in range(4)], df.schema)
    read = {r["_row"]: r for r in mixing.mix(pipeline._numbered(uneven), row_col="_row").collect()}
    assert len(read) == 4 and pipeline.mixture(spark, uneven, small).count() == sum(round(r.taken / r["size"]) for r in read.values())
