"""Main text of web pages by wrappers: union-free regular expressions inferred per host.

A page becomes a tree of elements with text slots (blocks) at its leaves; inline markup, scripts,
styles and comments are gone. Trees of the same host are aligned one after another: equal elements
are matched and their children aligned in turn, siblings that repeat become a repeated group
``+``, what one side lacks becomes an optional group ``?``; texts become slots. The result, a wrapper, has sequence,
``+`` and ``?`` only, no union. Per slot it also knows how much text stands there, and whether it is the same on all pages.

Every page is then matched against its host's wrapper (an automaton over the wrapper's positions), which gives each block its slot.
Over the pages of the host a slot is constant or varying, and more or less of its text is linked. Content is chosen page by page
among the slots that the page uses: under its article, else its main element, else in the smallest element that holds nearly all
of its varying text. Names (elements, words of class, id and role) break ties only: under an article or main element a named block
goes only if its slot is constant or linked on the host, or a form; elsewhere whole words count by themselves, parts of words with such evidence.

Only distinct page shapes and sums per slot are shuffled, never pages; shapes of one host are merged in groups of
``SHAPES_AT_ONCE``, the groups' wrappers again, and so on to one per host.

Defined results: null html = empty; a page without a usable url has no host and so is its own wrapper, as is a page that its host's
wrapper does not match; a page without any content gives ""; truncated markup and unknown references stay as they read;
repeated rows are kept; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import html as html_lib
import json
import re
import zlib
from collections.abc import Iterator
from functools import lru_cache

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stage

# Element names by what they do to text.
INLINE = frozenset("a abbr acronym b bdi bdo big br cite code data del dfn em font i img input ins kbd label link mark meta q s samp small source span strike strong sub sup time track tt u var wbr".split())
RAW = frozenset("script style noscript template iframe object svg math canvas title select textarea button audio video".split())
RAW_TEXT = frozenset("script style iframe title textarea".split())  # without an end tag they take the rest of the page; the others only their tag
IN_HEAD = frozenset("meta link title style script base noscript template".split())
LEAF = frozenset("p h1 h2 h3 h4 h5 h6 li dt dd td th caption figcaption pre blockquote address summary legend option hr tr thead tbody tfoot".split())
NOISE_TAGS = frozenset("nav header footer aside form menu dialog fieldset".split())
NOISE_WORDS = frozenset(
    "ad ads advert adverts advertisement sponsored sponsor promo banner nav navbar navigation menu breadcrumb breadcrumbs header masthead footer sidebar aside widget related recommended cookie cookies consent notice notices alert popup modal overlay paywall share sharing social newsletter subscribe signup login search form comment comments reply replies respond disqus discussion pagination pager toolbar complementary contentinfo".split()
)
ROOTS = ("article", "main")
FORMS = frozenset("form fieldset dialog".split())
#: An element that holds this share of the varying text stands for its parent.
NEARLY_ALL = 0.75
BLOCK_WORDS = re.compile(r"[a-z]+")
_TOKEN = re.compile(
    r"<!--.*?(?:-->|\Z)|<!\[CDATA\[.*?(?:\]\]>|\Z)|<[!?][^>]*>|<(/?)([a-zA-Z][^\s/>]*)((?:[^>\"']++|\"[^\"]*+\"|'[^']*+')*+)(?:>|\Z)", re.S
)
_MARKED = re.compile(r"(?<![\w-])(class|id|role)\s*=\s*(\"[^\"]*\"|'[^']*'|[^\s>]+)", re.I)
_DIGITS = re.compile(r"\d+")
_SPACES = re.compile(r"\s+")
MAX_UNIT = 4
SHAPES_AT_ONCE = 256


def _name(tag: str, attributes: str, ids: bool = True) -> str:
    """Element name with its class words, #id and @roles (digits dropped), apart by spaces."""
    if not attributes:
        return tag
    words: set[str] = set()
    for m in _MARKED.finditer(attributes):
        kind = m[1].lower()
        if kind != "id" or ids:
            mark = {"class": "", "id": "#", "role": "@"}[kind]
            words.update(mark + w for w in _DIGITS.sub("", m[2].strip("\"'").lower()).split())
    return " ".join([tag, *sorted(words)])


def _is_root(name: str) -> bool:
    tag, *words = name.split(" ")
    return tag in ROOTS or any(f"@{r}" in words for r in ROOTS)


def blocks(page: str) -> list[tuple[tuple[str, ...], str]]:
    """(path of element names down to the block's own, text) of every block, in page order."""
    return [(path, text) for path, text, _ in linked_blocks(page)]


def linked_blocks(page: str) -> list[tuple[tuple[str, ...], str, int]]:
    """Blocks with the characters of each that stand in links. Ids name only containers outside articles and main elements."""
    out: list[tuple[tuple[str, ...], str, int]] = []
    stack: list[str] = []
    roots, leaf, texts, at, n = 0, "", [], 0, len(page)
    link, linked = False, 0

    def flush() -> None:
        nonlocal linked
        if texts:
            text = _SPACES.sub(" ", html_lib.unescape("".join(texts))).strip()
            if text:
                out.append(((*stack, leaf or "#"), text, min(linked, len(text))))
            texts.clear()
            linked = 0

    while at < n:
        m = _TOKEN.search(page, at)
        if m is None:
            texts.append(page[at:])
            linked += link * (n - at)
            break
        if m.start() > at:
            texts.append(page[at : m.start()])
            linked += link * (m.start() - at)
        at = m.end()
        if m[2] is None:
            if m[0].startswith("<![CDATA["):
                texts.append(m[0][9:].removesuffix("]]>"))
            continue
        tag, closing = m[2].lower(), bool(m[1])
        if stack and not closing and tag not in IN_HEAD and stack[-1].split(" ", 1)[0] == "head":
            flush()
            stack.pop()  # the end tag of a head may be left out
        if tag in INLINE:
            if tag == "br":
                texts.append(" ")
            elif tag == "a":
                link = not closing
            continue
        if tag in RAW:
            if not closing and not m[3].endswith("/"):
                end = re.compile(f"</{tag}\\s*>", re.I).search(page, at)
                at = end.end() if end else n if tag in RAW_TEXT else at
                flush()
            continue
        flush()
        if tag in LEAF:
            leaf = "" if closing else _name(tag, m[3], False)
            continue
        leaf = ""
        if not closing:
            if not m[3].endswith("/"):
                stack.append(_name(tag, m[3], not roots and tag not in ("html", "head", "body", *ROOTS)))
                roots += _is_root(stack[-1])
        else:
            for i in range(len(stack) - 1, -1, -1):
                if stack[i].split(" ", 1)[0] == tag:
                    roots -= sum(map(_is_root, stack[i:]))
                    del stack[i:]
                    break
    flush()
    return out


# --- shapes and wrappers -----------------------------------------------------------------------
# A node is a slot name (str), ["<", name, children], ["+", nodes] or ["?", nodes].


def shape(page_blocks: list[tuple[tuple[str, ...], str]]) -> list:
    """Tree of the elements that hold blocks, repeats of siblings folded."""
    root: list = []
    open_: list[tuple[str, list]] = []
    for path, *_ in page_blocks:
        same = 0
        while same < len(open_) and same < len(path) - 1 and open_[same][0] == path[same]:
            same += 1
        del open_[same:]
        for name in path[same:-1]:
            children: list = []
            (open_[-1][1] if open_ else root).append(["<", name, children])
            open_.append((name, children))
        (open_[-1][1] if open_ else root).append(path[-1])
    return fold(root)


def _core(node) -> tuple:
    """What must agree for two nodes to match: the first name below groups."""
    while isinstance(node, list) and node[0] != "<":
        node = node[1][0]
    return ("<", node[1]) if isinstance(node, list) else ("", node)


def _units(nodes: list) -> list[tuple]:
    return [tuple(_core(x) for x in n[1]) if isinstance(n, list) and n[0] == "+" else (_core(n),) for n in nodes]


def fold(nodes: list) -> list:
    """Fold the children of every element, then runs of equal units of 1 to MAX_UNIT siblings into ``+``."""
    nodes = [["<", n[1], fold(n[2])] if isinstance(n, list) and n[0] == "<" else n for n in nodes]
    for unit in range(1, MAX_UNIT + 1):
        keys, out, i = [_core(n) if not (isinstance(n, list) and n[0] == "+") else ("+", *_units([n])[0]) for n in nodes], [], 0
        while i < len(nodes):
            j = i + unit
            while j + unit <= len(nodes) and keys[j : j + unit] == keys[i : i + unit]:
                j += unit
            if j > i + unit and not (unit == 1 and keys[i][0] == "+"):
                merged = nodes[i : i + unit]
                for k in range(i + unit, j, unit):
                    merged = align(merged, nodes[k : k + unit])
                out.append(["+", merged])
                i = j
            else:
                out.append(nodes[i])
                i += 1
        nodes = out
    return nodes


def _group(node) -> tuple[bool, bool, list]:
    """(repeated, optional, inner nodes)"""
    plus = optional = False
    inner = [node]
    while len(inner) == 1 and isinstance(inner[0], list) and inner[0][0] in "+?":
        plus, optional, inner = plus or inner[0][0] == "+", optional or inner[0][0] == "?", inner[0][1]
    return plus, optional, inner


def _wrap(plus: bool, optional: bool, inner: list) -> list:
    if plus:
        inner = [["+", inner]]
    if optional:
        inner = [["?", inner]]
    return inner


def _merge(a, b) -> list:
    (p, o, x), (q, r, y) = _group(a), _group(b)
    if len(x) == len(y) == 1 and not (isinstance(x[0], list) and x[0][0] in "+?") and not (isinstance(y[0], list) and y[0][0] in "+?"):
        inner = [["<", x[0][1], align(x[0][2], y[0][2])]] if isinstance(x[0], list) else x
    else:
        inner = align(x, y)
    return _wrap(p or q, o or r, inner)


def align(a: list, b: list) -> list:
    """Least wrapper of this kind over two sequences: matched nodes merged, the others optional."""
    if a == b:
        return a
    n, m = len(a), len(b)
    lo = 0
    ca, cb = [_core(x) for x in a], [_core(x) for x in b]
    out: list = []
    while lo < n and lo < m and ca[lo] == cb[lo]:
        out += _merge(a[lo], b[lo])
        lo += 1
    tail: list = []
    hi = 0
    while hi < n - lo and hi < m - lo and ca[n - 1 - hi] == cb[m - 1 - hi]:
        tail = _merge(a[n - 1 - hi], b[m - 1 - hi]) + tail
        hi += 1
    x, y, cx, cy = a[lo : n - hi], b[lo : m - hi], ca[lo : n - hi], cb[lo : m - hi]
    best = [[0] * (len(y) + 1) for _ in range(len(x) + 1)]
    for i in range(len(x) - 1, -1, -1):
        for j in range(len(y) - 1, -1, -1):
            best[i][j] = max(best[i + 1][j], best[i][j + 1], best[i + 1][j + 1] + 1 if cx[i] == cy[j] else 0)
    i = j = 0
    while i < len(x) or j < len(y):
        if i < len(x) and j < len(y) and cx[i] == cy[j] and best[i][j] == best[i + 1][j + 1] + 1:
            out += _merge(x[i], y[j])
            i, j = i + 1, j + 1
        elif j == len(y) or (i < len(x) and best[i][j] == best[i + 1][j]):
            out += _optional(x[i])
            i += 1
        else:
            out += _optional(y[j])
            j += 1
    return _squeeze(out + tail)


def _optional(node) -> list:
    plus, _, inner = _group(node)
    return _wrap(plus, True, inner)


def _squeeze(nodes: list) -> list:
    """Neighbours of one kind become one repeated group: x? x -> x+, x+ x -> x+."""
    out: list = []
    for node in nodes:
        if out and _core(out[-1]) == _core(node):
            (p, o, x), (q, r, y) = _group(out[-1]), _group(node)
            if len(x) == len(y) == 1:
                inner = _merge(x[0], y[0])
                out[-1:] = _wrap(True, o and r, inner)
                continue
        out.append(node)
    return out


def to_text(nodes: list) -> str:
    """The wrapper as a regular expression over elements; #TEXT marks slots."""
    parts = []
    for n in nodes:
        if isinstance(n, str):
            parts.append(f"{n}:#TEXT")
        elif n[0] == "<":
            parts.append(f"<{n[1]}> {to_text(n[2])} </>")
        else:
            parts.append(f"( {to_text(n[1])} ){n[0]}")
    return " ".join(parts)


def _symbols(page_blocks) -> list[str]:
    out, open_ = [], []
    for path, *_ in page_blocks:
        same = 0
        while same < len(open_) and same < len(path) - 1 and open_[same] == path[same]:
            same += 1
        out += ["/"] * (len(open_) - same)
        del open_[same:]
        for name in path[same:-1]:
            out.append(f"<{name}")
            open_.append(name)
        out.append(path[-1])
    return out + ["/"] * len(open_)


def matches(wrapper: list, page_blocks) -> bool:
    """Does the page belong to the wrapper's language? (States are sets of positions: linear in the page.)"""
    symbols = _symbols(page_blocks)

    def run(nodes: list, at: frozenset[int]) -> frozenset[int]:
        for n in nodes:
            if isinstance(n, str):
                at = frozenset(i + 1 for i in at if i < len(symbols) and symbols[i] == n)
            elif n[0] == "<":
                at = frozenset(i + 1 for i in at if i < len(symbols) and symbols[i] == f"<{n[1]}")
                at = frozenset(i + 1 for i in run(n[2], at) if i < len(symbols) and symbols[i] == "/")
            elif n[0] == "?":
                at |= run(n[1], at)
            else:
                reached: frozenset[int] = frozenset()
                while not (at := run(n[1], at)) <= reached:
                    reached |= at
                at = reached
        return at

    return len(symbols) in run(wrapper, frozenset([0]))


class Automaton:
    """A wrapper over its positions (opening elements, slots, closing elements); sets of positions are made states as pages need them."""

    def __init__(self, wrapper: list):
        self.symbols: list[str] = []
        self.follow: list[list[int]] = []
        self.paths: dict[int, tuple[str, ...]] = {}

        def add(symbol: str) -> int:
            self.symbols.append(symbol)
            self.follow.append([])
            return len(self.symbols) - 1

        def chain(ends: list[int], starts: list[int]) -> None:
            for e in ends:
                self.follow[e] += [x for x in starts if x not in self.follow[e]]

        def one(node, path: tuple[str, ...]) -> tuple[list[int], list[int], bool]:
            """(first positions, last positions, may be empty)"""
            if isinstance(node, str):
                at = add(node)
                self.paths[at] = (*path, node)
                return [at], [at], False
            if node[0] == "<":
                start = add(f"<{node[1]}")
                first, last, empty = many(node[2], (*path, node[1]))
                end = add("/")
                chain([start], first + [end] * empty)
                chain(last, [end])
                return [start], [end], False
            first, last, empty = many(node[1], path)
            if node[0] == "+":
                chain(last, first)
            return first, last, empty or node[0] == "?"

        def many(nodes: list, path: tuple[str, ...]) -> tuple[list[int], list[int], bool]:
            first, last, empty = [], [], True
            for node in nodes:
                f, e, can = one(node, path)
                chain(last, f)
                first, last, empty = first + f * empty, e + last * can, empty and can
            return first, last, empty

        begin = add("")
        first, last, empty = many(wrapper, ())
        chain([begin], first)
        self.last, self.begin = frozenset(last) | frozenset([begin] * empty), (begin,)
        self.steps: dict[tuple, tuple[dict[int, int], tuple[int, ...]]] = {}

    def slots(self, page_blocks) -> list[int] | None:
        """Slot (position) of every block; None: the wrapper does not match."""
        symbols, state, trace = _symbols(page_blocks), self.begin, []
        for symbol in symbols:
            step = self.steps.get((state, symbol))
            if step is None:
                came: dict[int, int] = {}
                for p in state:
                    for q in self.follow[p]:
                        if self.symbols[q] == symbol:
                            came.setdefault(q, p)
                step = self.steps[state, symbol] = came, tuple(came)
            trace.append(step[0])
            state = step[1]
        at = next((p for p in state if p in self.last), None)
        if at is None:
            return None
        out = []
        for came in reversed(trace):
            if at in self.paths:
                out.append(at)
            at = came[at]
        return out[::-1]


@lru_cache(4096)
def automaton(wrapper: str) -> Automaton:
    return Automaton(json.loads(wrapper))


def placed(found: list[tuple], wrapper: str | None) -> tuple[Automaton, list[int], bool]:
    """Slots of a page's blocks in its host's wrapper, or (False) in the page's own."""
    if wrapper is not None:
        machine = automaton(wrapper)
        slots = machine.slots(found)
        if slots is not None:
            return machine, slots, True
    machine = automaton(json.dumps(shape(found), separators=(",", ":")))
    slots = machine.slots(found)
    if slots is None:  # every block its own slot
        machine = Automaton([])
        machine.paths, slots = {i: p for i, (p, _, _) in enumerate(found)}, list(range(len(found)))
    return machine, slots, False


# --- content slots -----------------------------------------------------------------------------
# Sums of a slot: [pages, characters, linked characters, least and greatest checksum of a page's text in it].


def _named(name: str) -> bool:
    """The element's name, or a whole word of its class, id or role, says that it is no content."""
    tag, *words = name.split(" ")
    return tag in NOISE_TAGS or not NOISE_WORDS.isdisjoint(w.lstrip("#@") for w in words)


def _hinted(name: str) -> bool:
    return not NOISE_WORDS.isdisjoint(BLOCK_WORDS.findall(name.partition(" ")[2]))


def content_slots(slots: dict[int, tuple[tuple[str, ...], list[int]]]) -> set[int]:
    """Slots that one page uses, with their path and sums over the host's pages -> those of its main text."""
    proved = {s: (n > 1 and low == high) or 2 * linked >= chars for s, (_, (n, chars, linked, low, high)) in slots.items()}
    plain = ("html", "head", "body")

    def noise(s: int, names: tuple[str, ...], inside: bool) -> bool:
        tags = {x.split(" ", 1)[0] for x in names}
        if inside:
            return not FORMS.isdisjoint(tags) or (proved[s] and any(map(_named, names)))
        names = tuple(x for x in names if x.split(" ", 1)[0] not in plain)
        return any(map(_named, names)) or (proved[s] and any(map(_hinted, names)))

    for root in ROOTS:
        under: dict[int, int] = {}
        for s, (path, _) in slots.items():
            at = next((i for i, x in enumerate(path[:-1]) if x.split(" ", 1)[0] == root or f"@{root}" in x.split(" ")), None)
            if at is not None:
                under[s] = at
        if under:
            outer = {s for s, at in under.items() if not any(_named(x) for x in slots[s][0][: at + 1] if x.split(" ", 1)[0] not in plain)}
            return {s for s in outer or under if not noise(s, slots[s][0][under[s] + 1 :], True)}
    clean = {s for s, (path, _) in slots.items() if not noise(s, path, False)}
    varying = {s for s in clean if not (slots[s][1][0] > 2 and slots[s][1][3] == slots[s][1][4])}
    if not varying:
        return clean
    weight = {s: slots[s][1][1] / slots[s][1][0] for s in varying}
    whole, depth, inner = sum(weight.values()), 0, set(varying)
    while True:
        parts: dict[str, float] = {}
        for s in inner:
            if len(slots[s][0]) > depth + 1:
                parts[slots[s][0][depth]] = parts.get(slots[s][0][depth], 0) + weight[s]
        top = max(parts, key=lambda x: (parts[x], x), default=None)
        if top is None or parts[top] < NEARLY_ALL * whole:
            return inner
        inner, depth = {s for s in inner if len(slots[s][0]) > depth + 1 and slots[s][0][depth] == top}, depth + 1


def page_text(found: list[tuple], wrapper: str | None, sums: dict[int, list[int]], known: dict) -> str:
    """Main text of a page by the wrapper and the sums of its host; known: choices made before for this host."""
    machine, slots, matched = placed(found, wrapper)
    used = frozenset(slots)
    keep = known.get(used) if matched else None
    if keep is None:
        if not matched:
            sums = _sums(found, slots)
        keep = content_slots({s: (machine.paths[s], sums[s]) for s in used})
        if matched:
            known[used] = keep
    return "\n\n".join(text for s, (_, text, _) in zip(slots, found) if s in keep)


def _sums(found: list[tuple], slots: list[int]) -> dict[int, list[int]]:
    texts: dict[int, list] = {}
    for s, (_, text, linked) in zip(slots, found):
        texts.setdefault(s, []).append((text, linked))
    out = {}
    for s, parts in texts.items():
        crc = zlib.crc32("\n".join(t for t, _ in parts).encode("utf-8", "replace"))
        out[s] = [1, sum(len(t) for t, _ in parts), sum(x for _, x in parts), crc, crc]
    return out


def host_of(url):
    return F.lower(F.coalesce(F.regexp_extract(url, r"^[A-Za-z][A-Za-z0-9+.-]*://(?:[^/@?#]*@)?([^/:?#]+)", 1), F.lit("")))


def shapes(pages: DataFrame) -> DataFrame:
    """(host, shape): the distinct shapes of each host."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            seen = dict.fromkeys((host, json.dumps(shape(blocks(page.as_py())), separators=(",", ":"))) for host, page in zip(batch.column(0).to_pylist(), batch.column(1)))
            yield pa.RecordBatch.from_arrays([pa.array([k[i] for k in seen], pa.string()) for i in (0, 1)], ["host", "shape"])

    source = pages.select(host_of(F.col("url")).alias("host"), F.coalesce("html", F.lit("")).alias("html"))
    return source.where("host <> ''").mapInArrow(run, "host string, shape string").distinct()


HOSTS_AT_ONCE = 50_000


def _beside(pages: DataFrame, table: DataFrame, few: bool) -> DataFrame:
    source = pages.select("page_id", "url", F.coalesce("html", F.lit("")).alias("html"), host_of(F.col("url")).alias("host"))
    return source.join(F.broadcast(table) if few else table, "host", "left")


def slot_sums(pages: DataFrame, table: DataFrame, few: bool) -> DataFrame:
    """(host, slot, pages, chars, linked, low, high) from every page matched against its host's wrapper."""
    fields = [("host", pa.string()), ("slot", pa.int32())] + [(n, pa.int64()) for n in ("pages", "chars", "linked", "low", "high")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            seen: dict[tuple, list[int]] = {}
            for host, wrapper, page in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2)):
                found = linked_blocks(page.as_py())
                _, slots, matched = placed(found, wrapper)
                for s, (n, chars, linked, low, high) in _sums(found, slots).items() if matched else ():
                    row = seen.setdefault((host, s), [0, 0, 0, low, high])
                    row[:] = row[0] + n, row[1] + chars, row[2] + linked, min(row[3], low), max(row[4], high)
            rows = [(*k, *v) for k, v in seen.items()]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], t) for i, (_, t) in enumerate(fields)], [n for n, _ in fields])

    types = {pa.string(): "string", pa.int32(): "int", pa.int64(): "long"}
    source = _beside(pages, table, few).where("wrapper is not null").select("host", "wrapper", "html")
    sums = source.mapInArrow(run, ", ".join(f"{n} {types[t]}" for n, t in fields)).groupBy("host", "slot")
    return sums.agg(*[F.sum(n).alias(n) for n in ("pages", "chars", "linked")], F.min("low").alias("low"), F.max("high").alias("high"))


def wrappers(pages: DataFrame) -> DataFrame:
    """(host, wrapper, slots array<array<long>>): one wrapper per host and the sums of its slots."""
    forms = stage(shapes(pages), "shapes")
    parts = forms.groupBy("host").agg(F.ceil(F.count("*") / SHAPES_AT_ONCE).alias("parts"))
    forms = forms.join(parts, "host").withColumn("part", F.pmod(F.xxhash64("shape"), F.col("parts")))

    def merge(group: pd.DataFrame) -> pd.DataFrame:
        out = None
        for text in sorted(group["shape"]):
            form = json.loads(text)
            out = form if out is None else align(out, form)
        return pd.DataFrame({"host": [group["host"].iloc[0]], "part": [group["part"].iloc[0]], "shape": [json.dumps(out, separators=(",", ":"))]})

    top, forms = int(parts.agg(F.max("parts")).first()[0] or 1), forms.select("host", "part", "shape")
    while True:
        forms = stage(forms.groupBy("host", "part").applyInPandas(lambda g: merge(g), "host string, part long, shape string"), "forms")
        if top == 1:
            break
        top, forms = -(-top // SHAPES_AT_ONCE), forms.withColumn("part", F.floor(F.col("part") / SHAPES_AT_ONCE))
    whole = forms.select("host", F.col("shape").alias("wrapper"))
    sums = slot_sums(pages, whole, whole.count() <= HOSTS_AT_ONCE)
    numbers = F.array(F.col("slot").cast("long"), "pages", "chars", "linked", "low", "high")
    return stage(whole.join(sums.groupBy("host").agg(F.collect_list(numbers).alias("slots")), "host", "left"), "wrappers")


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text: the blocks in the content slots of the host's wrapper, joined by empty lines."""
    table = wrappers(pages)
    joined = _beside(pages, table, table.count() <= HOSTS_AT_ONCE).select("page_id", "url", "html", "host", "wrapper", "slots")
    id_type = joined.schema["page_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out, hosts = [], {}
            for i, (page, host, wrapper) in enumerate(zip(batch.column(2), batch.column(3).to_pylist(), batch.column(4).to_pylist())):
                if host not in hosts:
                    hosts[host] = {s: v for s, *v in batch.column(5)[i].as_py() or []}, {}
                out.append(page_text(linked_blocks(page.as_py()), wrapper, *hosts[host]))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(out, pa.string())], ["page_id", "url", "text"])

    return joined.mapInArrow(run, f"page_id {id_type}, url string, text string")
