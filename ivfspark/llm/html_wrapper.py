"""Main text of web pages by wrappers inferred for each host.

A page becomes a tree of block tags with text slots (inline tags are part of the text). Neighbours that repeat,
one tag or a sequence of tags, fold into repeated groups, so that pages of one template have few different
trees; these are counted by host, and a host's trees are aligned one after another into its wrapper, a regular
expression without unions: tags that both sides have stay and their contents are aligned in turn, what one side
lacks becomes an optional group, a tag met once on one side and several times on the other a repeated group.
A text outside articles that stands at one path on nearly every different page of its host is a literal token; where
literals and other texts meet, or texts differ, the expression has a slot. Trees are aligned some at a time, and the
results with each other until a host has one, so a host of any size is dealt over tasks.

Every page is then matched against its host's expression, which gives each text its slot, and texts are read from the
slots labelled as content. A slot is content if its path leads through the article (else through the container with most
of the host's text) and through no menu, header, footer, sidebar, notice, advert, form, script, style or comment part.
A literal slot that nearly all pages fill is template; a literal text in another place is a text like any other.
A text that the expression places nowhere is read as the slots of its path are.

Null or empty html gives an empty text. A null or odd url is a host of its own (""). Repeated rows are read alike,
and pages of equal blocks count as one page. Very long pages are read whole: alignment takes memory in
proportion to the pages, and nesting of any depth is followed. An empty table gives an empty result. Other columns are ignored.
"""

from __future__ import annotations

import html as entities
import re
import sys
from collections import Counter
from collections.abc import Iterable, Iterator
from hashlib import blake2b

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ivfspark.plans.scratch import materialize

# Tags inside a line of text; tags without content; tags whose content is not markup; tags
# that a new block ends; parts that are not content, by tag and by word of class or id.
INLINE = frozenset(
    "a abbr acronym b bdi bdo big br cite code data del dfn em font i img ins kbd label mark q rp rt ruby s samp small span strike strong sub sup time tt u var wbr".split()
)
VOID = frozenset("area base col embed hr img input link meta param source track wbr br".split())
RAW = frozenset("script style noscript template textarea title iframe svg math".split())
IMPLIED = frozenset(("html", "body"))
SELF_ENDING = {"p": None, "li": "li", "dt": "dd dt", "dd": "dd dt", "tr": "tr", "td": "td th", "th": "td th", "option": "option"}
OUTSIDE_TAGS = frozenset("head nav footer aside form button select menu dialog script style noscript template textarea iframe svg math".split())
OUTSIDE_WORDS = frozenset(
    "ad ads adv advert adverts advertisement sponsor sponsored promo banner sidebar aside comment comments respond disqus notice notices cookie consent alert popup modal newsletter subscribe menu nav navbar navigation breadcrumb breadcrumbs pager pagination footer header masthead share social related widget widgets toolbar login signup search".split()
)
#: A text on at least this share of a host's different pages, and on two, belongs to the template.
CONSTANT_SHARE, CONSTANT_PAGES = 0.9, 2
#: Trees aligned in one step of a host's merging.
MERGE_TREES = 64
#: Neighbours beyond which repeats are looked for in arrays.
LONG_ROW = 48

_TAG = re.compile(r"<!--.*?(?:-->|\Z)|<(/?)([a-zA-Z][a-zA-Z0-9:-]*)((?:[^<>\"']|\"[^\"]*\"|'[^']*')*)/?>|<[!?][^>]*>", re.DOTALL)
_NAMES = re.compile(r"\b(class|id|role)\s*=\s*(\"[^\"]*\"|'[^']*'|[^\s>]+)", re.IGNORECASE)
_WORDS = re.compile(r"[a-z]+")
_HOST = re.compile(r"^[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)")


def host_of(url: str | None) -> str:
    found = _HOST.match(url or "")
    return found[1].lower() if found else ""


def _signature(tag: str, attributes: str) -> str:
    """Tag name with the words of its class, id and role."""
    if "=" not in attributes:
        return tag
    words = sorted({w for _, v in _NAMES.findall(attributes) for w in _WORDS.findall(v.lower())})
    return f"{tag}.{'.'.join(words)}" if words else tag


def slots(page: str) -> Iterator[tuple[str, str]]:
    """``(kind, value)``: "open" with a path, "close" with a tag, "text" with raw text, in page order."""
    stack: list[str] = []
    at, text = 0, []

    def flush() -> list[tuple[str, str]]:
        raw = "".join(text)
        text.clear()
        return [("text", raw)] if raw and not raw.isspace() else []

    size = len(page)
    while at < size:
        found = _TAG.search(page, at)
        if not found:
            text.append(page[at:])
            break
        text.append(page[at : found.start()])
        at = found.end()
        tag = (found[2] or "").lower()
        if not tag:
            continue
        if tag in RAW:
            if not found[1]:
                end = re.compile(rf"</{tag}\s*>", re.IGNORECASE).search(page, at)
                at = end.end() if end else size
            continue
        if tag in INLINE:
            if tag == "br":
                text.append(" ")
            continue
        yield from flush()
        if tag in IMPLIED:  # often left out, so never part of a path; a body ends the head
            while tag == "body" and "head" in stack:
                yield "close", stack.pop().split(".", 1)[0]
            continue
        if found[1]:
            depth = next((i for i in range(len(stack) - 1, -1, -1) if stack[i].split(".", 1)[0] == tag), None)
            if depth is not None:
                while len(stack) > depth:
                    yield "close", stack.pop().split(".", 1)[0]
            continue
        while stack and (open_tag := stack[-1].split(".", 1)[0]) in SELF_ENDING and (SELF_ENDING[open_tag] is None or tag in SELF_ENDING[open_tag].split()):
            stack.pop()
            yield "close", open_tag
        if tag in VOID:
            continue
        stack.append(_signature(tag, found[3] or ""))
        yield "open", stack[-1]
    yield from flush()
    while stack:
        yield "close", stack.pop().split(".", 1)[0]


class Node:
    """A part of an expression: e (a tag and its contents), # (a text slot), = (a literal), + (a repeated group) or ? (an optional one).

    Parts with equal keys are aligned with each other. ``texts`` numbers a page's texts in a slot; ``n`` counts the
    pages that fill a literal.
    """

    __slots__ = ("body", "key", "kind", "n", "name", "texts")

    def __init__(self, kind: str, name: str = "", body: list[Node] | None = None, texts: list[int] | None = None, n: int = 0):
        self.kind, self.name, self.texts, self.n = kind, name, texts or [], n
        self.body: list[Node] = body or []
        if kind == "e":
            told = [b.key for b in self.body]
            fixed = told and all("=" in k for k in told) and all(b.kind != "?" for b in self.body)  # literals throughout
            self.key = f"{name}={'/'.join(told)}" if fixed else name
        elif kind in "+?":
            self.key = self.body[0].key if len(self.body) == 1 else "|".join(b.key for b in self.body)
        else:
            self.key = kind + name

    def __eq__(self, other: object) -> bool:
        return isinstance(other, Node) and write([self]) == write([other])

    __hash__ = None


def _repeat(keys: list[str], unit: int) -> int:
    """The first place where ``unit`` keys stand twice side by side, or -1."""
    if len(keys) <= LONG_ROW:
        run = 0
        for i in range(len(keys) - unit):
            run = run + 1 if keys[i] == keys[i + unit] else 0
            if run == unit:
                return i - unit + 1
        return -1
    numbers: dict[str, int] = {}
    ids = np.fromiter((numbers.setdefault(k, len(numbers)) for k in keys), np.int64, len(keys))
    breaks = np.concatenate([[-1], np.flatnonzero(ids[:-unit] != ids[unit:]), [len(keys) - unit]])
    wide = np.flatnonzero(np.diff(breaks) > unit)
    return int(breaks[wide[0]]) + 1 if len(wide) else -1


def folded(row: list[Node]) -> list[Node]:
    """Merge neighbours that repeat into repeated groups, shortest unit first, until none is left."""
    unit = 1
    while 2 * unit <= len(row):
        keys = [x.key for x in row]
        at = _repeat(keys, unit)
        if at < 0:
            unit += 1
            continue
        body, end = row[at : at + unit], at + unit
        while keys[end : end + unit] == keys[at : at + unit]:
            body = [join(x, y) for x, y in zip(body, row[end : end + unit], strict=True)]
            end += unit
        row = [*row[:at], body[0] if unit == 1 and body[0].kind == "+" else Node("+", body=body), *row[end:]]
        unit = 1
    return row


def join(a: Node, b: Node) -> Node:
    """One part from two of equal keys."""
    if "+" in (a.kind, b.kind):
        one, two = (x.body if x.kind == "+" else [x] for x in (a, b))
        return Node("+", body=[join(x, y) for x, y in zip(one, two, strict=True)])
    return Node(a.kind, a.name, align(a.body, b.body) if a.kind == "e" else None, a.texts + b.texts, a.n + b.n)


def _opened(row: list[Node]) -> tuple[list[Node], list[bool]]:
    """The parts of a row without optional groups, and whether each stood in one."""
    parts, loose = [], []
    for x in row:
        inside = _opened(x.body)[0] if x.kind == "?" else [x]
        parts += inside
        loose += [x.kind == "?"] * len(inside)
    return parts, loose


def _lifted(row: list[Node], loose: list[bool], other: list[Node]) -> tuple[list[Node], list[bool]]:
    """A row in which sequences that the other side repeats are groups as well."""
    for group in [x for x in other if x.kind == "+" and len(x.body) > 1]:
        told, n, i = [b.key for b in group.body], len(group.body), 0
        while i + n <= len(row):
            if [x.key for x in row[i : i + n]] == told and all(x.kind != "+" or len(x.body) == 1 for x in row[i : i + n]):
                row = [*row[:i], Node("+", body=[x.body[0] if x.kind == "+" else x for x in row[i : i + n]]), *row[i + n :]]
                loose = [*loose[:i], all(loose[i : i + n]), *loose[i + n :]]
            i += 1
    return row, loose


def _common(a: list[str], b: list[str]) -> list[tuple[int, int]]:
    """Places of a longest common subsequence, in memory proportional to the two: halves meet where it is longest."""
    begin, n, m = 0, len(a), len(b)
    while begin < min(n, m) and a[begin] == b[begin]:
        begin += 1
    while n > begin and m > begin and a[n - 1] == b[m - 1]:
        n, m = n - 1, m - 1
    found = [(i, i) for i in range(begin)]
    numbers: dict[str, int] = {}
    x, y = (np.fromiter((numbers.setdefault(k, len(numbers)) for k in part), np.int64, len(part)) for part in (a[begin:n], b[begin:m]))

    def lengths(one: np.ndarray, two: np.ndarray) -> np.ndarray:
        best = np.zeros(len(two) + 1, np.int64)
        for k in one:
            best[1:] = np.maximum.accumulate(np.maximum(best[1:], np.where(two == k, best[:-1] + 1, 0)))
        return best

    def halves(i: int, one: np.ndarray, j: int, two: np.ndarray) -> None:
        if not len(one) or not len(two):
            return
        if len(one) == 1:
            spot = np.flatnonzero(two == one[0])
            if len(spot):
                found.append((i, j + int(spot[0])))
            return
        half = len(one) // 2
        cut = int((lengths(one[:half], two) + lengths(one[:half - 1 : -1] if half else one[::-1], two[::-1])[::-1]).argmax())
        halves(i, one[:half], j, two[:cut])
        halves(i + half, one[half:], j + cut, two[cut:])

    halves(begin, x, begin, y)
    return found + [(n + k, m + k) for k in range(len(a) - n)]


def align(a: list[Node], b: list[Node]) -> list[Node]:
    """The expression that covers both rows: parts of equal keys are joined, the rest becomes optional."""
    (a, loose_a), (b, loose_b) = _opened(a), _opened(b)
    (a, loose_a), (b, loose_b) = _lifted(a, loose_a, b), _lifted(b, loose_b, a)
    out: list[Node] = []
    i = j = 0
    for p, q in [*_common([x.key for x in a], [x.key for x in b]), (len(a), len(b))]:
        out += [Node("?", body=part) for part in (a[i:p], b[j:q]) if part]
        if p < len(a):
            both = join(a[p], b[q])
            out.append(Node("?", body=[both]) if loose_a[p] or loose_b[q] else both)
        i, j = p + 1, q + 1
    return out


def write(row: list[Node]) -> str:
    """An expression as text; ``read`` is its inverse."""
    out: list[str] = []
    waiting: list[Node | str] = list(reversed(row))
    while waiting:
        x = waiting.pop()
        if isinstance(x, str):
            out.append(x)
        elif x.kind == "#":
            out.append("#")
        elif x.kind == "=":
            out.append(f"={x.name}:{x.n}")
        else:
            out.append(f"<{x.name}" if x.kind == "e" else "(")
            waiting.append(f">{x.name.split('.', 1)[0]}" if x.kind == "e" else f"){x.kind}")
            waiting += reversed(x.body)
    return " ".join(out)


def _tree(tokens: Iterable[str], fold_rows: bool) -> list[Node]:
    names: list[str] = [""]
    rows: list[list[Node]] = [[]]
    texts = 0
    for word in tokens:
        if word[0] == "<" or word == "(":
            names.append(word[1:])
            rows.append([])
        elif word[0] in ">)":
            if len(rows) > 1:
                row = folded(rows.pop()) if fold_rows else rows.pop()
                rows[-1].append(Node("e" if word[0] == ">" else word[1], names.pop(), row))
        else:
            name, _, n = word[1:].partition(":")
            rows[-1].append(Node(word[0], name, None, [texts], int(n or 1) if name else 0))
            texts += 1
    return folded(rows[0]) if fold_rows else rows[0]


def read(text: str) -> list[Node]:
    return _tree(text.split(), False)


def fold(tokens: Iterable[str]) -> list[Node]:
    """The folded tree of ``<sig``, ``>tag``, ``#`` and ``=literal`` tokens; its slots number the texts."""
    return _tree(tokens, True)


def constant_key(path: str, text: str) -> str:
    return blake2b(f"{path}\x00{text}".encode("utf-8", "surrogatepass"), digest_size=8).hexdigest()


def stream(page: str | None, constants: Iterable[str] = (), found: list[tuple[str, str]] | None = None) -> list[Node]:
    """A page's folded tree, its texts of ``constants`` as literals; ``found`` takes its ``(path, text)`` in order."""
    known, tokens, stack = frozenset(constants), [], []
    for kind, value in slots(page or ""):
        if kind == "open":
            stack.append(value)
            tokens.append("<" + value)
        elif kind == "close":
            stack.pop()
            tokens.append(">" + value)
        elif text := _clean(value):
            path = "/".join(stack)
            if found is not None:
                found.append((path, text))
            key = constant_key(path, text) if known and not _marked(path) else ""
            tokens.append(f"={key}" if key in known else "#")
    return fold(tokens)


def wrapper_slots(expression: list[Node]) -> list[tuple[Node, str]]:
    """Every slot and literal of a wrapper with its path, in order."""
    out: list[tuple[Node, str]] = []
    waiting: list[tuple[Node, str]] = [(x, "") for x in reversed(expression)]
    while waiting:
        x, path = waiting.pop()
        if x.kind in "#=":
            out.append((x, path))
        else:
            below = (f"{path}/{x.name}" if path else x.name) if x.kind == "e" else path
            waiting += [(y, below) for y in reversed(x.body)]
    return out


def slot_paths(expression: list[Node]) -> list[str]:
    """Paths of the slots of a wrapper, in order, each once."""
    return list(dict.fromkeys(path for x, path in wrapper_slots(expression) if x.kind == "#"))


def match(page: list[Node], wrapper: list[Node]) -> dict[int, Node]:
    """The wrapper's slot or literal of each text of a page's tree; texts that it places nowhere are left out."""
    out: dict[int, Node] = {}
    waiting = [(page, wrapper)]
    while waiting:
        a, b = waiting.pop()
        b, _ = _opened(b)
        a, _ = _lifted(*_opened(a), b)
        for i, j in _common([x.key for x in a], [x.key for x in b]):
            one, two = (x.body if x.kind == "+" else [x] for x in (a[i], b[j]))
            for x, y in zip(one, two, strict=True):
                if "+" in (x.kind, y.kind):
                    waiting.append(([x], [y]) if (x.kind, y.kind) != ("+", "+") else (x.body, y.body))
                elif x.kind == "e":
                    waiting.append((x.body, y.body))
                else:
                    out.update(dict.fromkeys(x.texts, y))
    return out


def _outside(path: str) -> bool:
    """The path leads through a part that is not content."""
    inside = False
    for step in path.split("/"):
        tag, *words = step.split(".")
        if tag in OUTSIDE_TAGS or tag == "header" and not inside or tag not in ("html", "body", "article", "main") and OUTSIDE_WORDS.intersection(words):
            return True
        inside = inside or tag in ("article", "main")
    return False


def _marked(path: str, *marks: str) -> bool:
    """The path leads through an article or main part."""
    return any(step.split(".")[0] in (marks or ("article", "main")) for step in path.split("/"))


def content_paths(paths: Iterable[str], mass: dict[str, int]) -> list[str]:
    """The slots that hold the main text: those in an article, else in a main part, else as
    ``container_paths`` finds them."""
    paths = list(paths)
    for mark in ("article", "main"):
        marked = [p for p in paths if _marked(p, mark) and not _outside(p)]
        if marked:
            return marked
    return container_paths(paths, mass)


def container_paths(paths: Iterable[str], mass: dict[str, int]) -> list[str]:
    """The slots in the deepest container that holds most of the host's text, articles left out."""
    allowed = [p for p in paths if not _outside(p) and not _marked(p)]
    containers: Counter[str] = Counter()
    for path in allowed:
        steps = path.split("/")
        for depth in range(1, len(steps)):
            containers["/".join(steps[:depth])] += mass.get(path, 0)
    total = sum(mass.get(p, 0) for p in allowed)
    fitting = [c for c, n in containers.items() if 2 * n > total]  # nested in each other; the deepest
    if not fitting:
        return allowed
    best = max(fitting, key=len)
    return [p for p in allowed if p.startswith(best + "/")]


def _clean(raw: str) -> str:
    return " ".join(entities.unescape(raw).split())


def blocks(page: str | None) -> Iterator[tuple[str, str]]:
    """``(path, text)`` of every block with text, in page order."""
    stack: list[str] = []
    for kind, value in slots(page or ""):
        if kind == "open":
            stack.append(value)
        elif kind == "close":
            stack.pop()
        elif text := _clean(value):
            yield "/".join(stack), text


def survey(pages: DataFrame) -> DataFrame:
    """``(host, kind, item, n)``: characters by path (M), and by different pages: texts outside articles by path (C), as
    digests, and pages (P)."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            met: Counter[tuple[str, str, str, int]] = Counter()
            for url, page in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                host = host_of(url)
                found = list(blocks(page))
                same = int.from_bytes(blake2b(repr(found).encode("utf-8", "surrogatepass"), digest_size=8).digest(), "big", signed=True)
                met[host, "P", "", same] += 1
                for path, text in found:
                    met[host, "M", path, 0] += len(text)
                    if not _marked(path) and not _outside(path):
                        met[host, "C", constant_key(path, text), same] += 1
            columns = list(zip(*met, strict=True)) or [[], [], [], []]
            texts = [pa.array(list(c), pa.string()) for c in columns[:3]]
            yield pa.RecordBatch.from_arrays([*texts, pa.array(list(columns[3]), pa.int64()), pa.array(list(met.values()), pa.int64())], ["host", "kind", "item", "page", "n"])

    counted = pages.select("url", "html").mapInArrow(kernel, "host string, kind string, item string, page long, n long")
    once = counted.groupBy("host", "kind", "item", "page").agg(F.sum("n").alias("n"))
    n = F.when(F.col("kind").isin("C", "P"), 1).otherwise(F.col("n"))
    return once.groupBy("host", "kind", "item").agg(F.sum(n).alias("n"))


def _host(url: str = "url"):
    return F.coalesce(F.lower(F.regexp_extract(url, _HOST.pattern, 1)), F.lit(""))


def trees(pages: DataFrame, constants: DataFrame) -> DataFrame:
    """``(host, item, n)``: the different trees of each host's pages, with their number."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sys.setrecursionlimit(1_000_000)
        for batch in batches:
            met = Counter((host, write(stream(page, known or ()))) for host, page, known in zip(*(c.to_pylist() for c in batch.columns), strict=True))
            columns = list(zip(*met, strict=True)) or [[], []]
            yield pa.RecordBatch.from_arrays([*(pa.array(list(c), pa.string()) for c in columns), pa.array(list(met.values()), pa.int64())], ["host", "item", "n"])

    known = pages.select(_host().alias("host"), "html").join(constants, "host", "left")
    counted = known.select("host", "html", "constants").mapInArrow(kernel, "host string, item string, n long")
    return counted.groupBy("host", "item").agg(F.sum("n").alias("n"))


def _merged(rows: DataFrame) -> DataFrame:
    """``(host, item, n)`` with the rows of a host and bucket aligned into one, most frequent first."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sys.setrecursionlimit(1_000_000)
        now, wrapper, total, done = None, [], 0, []
        for batch in batches:
            for *key, item, n, level in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                expression = read(item)
                if level == 0:  # a page's tree, n times
                    for x, _ in wrapper_slots(expression):
                        x.n *= n
                if key != now:
                    if now is not None:
                        done.append((now[0], write(wrapper), total))
                    now, wrapper, total = key, expression, 0
                else:
                    wrapper = align(wrapper, expression)
                total += n
        if now is not None:
            done.append((now[0], write(wrapper), total))
        columns = list(zip(*done, strict=True)) or [[]] * 3
        yield pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(columns, (pa.string(), pa.string(), pa.int64()), strict=True)], ["host", "item", "n"])

    dealt = rows.select("host", "bucket", "item", "n", "level").repartition("host", "bucket").sortWithinPartitions("host", "bucket", F.col("n").desc(), "item")
    return dealt.mapInArrow(kernel, "host string, item string, n long")


def merged_trees(rows: DataFrame) -> DataFrame:
    """One expression a host: some rows at a time are aligned, and the results again, until one is left."""
    level, left = 0, materialize(rows, "trees")
    while True:
        sizes = left.groupBy("host").agg(F.ceil(F.count("*") / MERGE_TREES).alias("buckets"))
        more = sizes.agg(F.max("buckets")).first()[0] or 0
        dealt = left.join(sizes, "host").withColumn("bucket", F.pmod(F.xxhash64("item"), F.col("buckets"))).withColumn("level", F.lit(level))
        left, level = materialize(_merged(dealt), "trees"), level + 1
        if more <= 1:
            return left


def wrappers(pages: DataFrame) -> DataFrame:
    """``(host, pages, wrapper, mass, constants)``: each host's expression, characters by path, and literals."""
    counts = materialize(survey(pages), "survey")
    sizes = counts.where("kind = 'P'").select("host", F.col("n").alias("pages"))
    common = counts.where(f"kind = 'C' AND n >= {CONSTANT_PAGES}").join(sizes, "host").where(F.col("n") >= F.col("pages") * CONSTANT_SHARE)
    # a template's literals and paths are bounded by the size of its pages, not by their number
    constants = materialize(common.groupBy("host").agg(F.collect_list("item").alias("constants")), "constants")
    mass = counts.where("kind = 'M'").groupBy("host").agg(F.collect_list(F.struct("item", "n")).alias("mass"))
    merged = merged_trees(trees(pages, constants)).select("host", F.col("item").alias("wrapper"), F.col("n").alias("pages"))
    return merged.join(constants, "host", "left").join(mass, "host", "left").select("host", "pages", "wrapper", "mass", "constants")


class Reader:
    """Reads pages of one host by its wrapper."""

    def __init__(self, wrapper: str | None, pages: int | None, mass: dict[str, int], constants: Iterable[str]):
        self.constants, self.expression = frozenset(constants), read(wrapper or "")
        self.paths = {id(x): path for x, path in wrapper_slots(self.expression)}
        literals = {id(x) for x, _ in wrapper_slots(self.expression) if x.kind == "=" and x.n >= CONSTANT_SHARE * (pages or 1)}
        self.open = {i: path for i, path in self.paths.items() if i not in literals}
        paths = list(dict.fromkeys(self.open.values()))
        self.content, self.others = set(content_paths(paths, mass)), set(container_paths(paths, mass))

    def text(self, page: str | None) -> str:
        found: list[tuple[str, str]] = []
        placed = match(stream(page, self.constants, found), self.expression)
        paths = [self.open.get(id(placed[i]), "") if i in placed else path for i, (path, _) in enumerate(found)]
        wanted = self.content if any(p in self.content for p in paths) else self.others
        return "\n\n".join(text for path, (_, text) in zip(paths, found, strict=True) if path in wanted)


def extract(pages: DataFrame) -> DataFrame:
    """``(page_id, url, text)``: the texts of each page's content slots under its host's wrapper."""
    found = materialize(wrappers(pages), "wrappers")
    source = pages.select("page_id", "url", "html", _host().alias("host"))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sys.setrecursionlimit(1_000_000)
        readers: dict[str, Reader] = {}
        for batch in batches:
            texts = []
            for host, page, wrapper, pages, mass, constants in zip(*(batch.column(c).to_pylist() for c in range(2, 8)), strict=True):
                if host not in readers:
                    if len(readers) > 64:
                        readers.clear()
                    readers[host] = Reader(wrapper, pages, {m["item"]: m["n"] for m in mass or ()}, constants or ())
                texts.append(readers[host].text(page))
            yield pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("url"), pa.array(texts, pa.string())], ["page_id", "url", "text"])

    joined = source.join(found, "host", "left").select("page_id", "url", "host", "html", "wrapper", "pages", "mass", "constants")
    return joined.mapInArrow(kernel, "page_id long, url string, text string")
