"""Secret scan by one combined deterministic automaton.

All rules are parsed, joined into one nondeterministic automaton over bytes that may start a match
anywhere, made deterministic by subset construction and minimised; its transition arrays drive a
single pass over each text that notes at which bytes which rules have a match ending. The start of
a match is found by the reversed rule's automaton from its end. Rules are of the kind "head, then
as many of a byte class as follow", so the matches that end within one run of such bytes all end with
the run; per rule, spans are then leftmost and non-overlapping, as a regex engine reports them.

Spans are in code points. Rules here drop a match too short for them only after it has
taken its bytes (``keep``), as the base rules demand.

Defined results: null text = empty text (no spans); repeated rows and ids are scanned each; texts of any length
are scanned whole; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import doc_text

ALL = (1 << 256) - 1


# --- regular expressions over bytes -> syntax tree -------------------------------------------
# Nodes: ("set", mask), ("cat", [..]), ("alt", [..]), ("rep", node, least, most or None).


def _mask(chars) -> int:
    out = 0
    for c in chars:
        out |= 1 << c
    return out


def _either_case(mask: int) -> int:
    for c in range(26):
        if mask >> (65 + c) & 1 or mask >> (97 + c) & 1:
            mask |= 1 << (65 + c) | 1 << (97 + c)
    return mask


class _Parser:
    def __init__(self, pattern: str, ignore_case: bool):
        self.p, self.i, self.fold = pattern, 0, _either_case if ignore_case else lambda m: m

    def peek(self) -> str:
        return self.p[self.i] if self.i < len(self.p) else ""

    def take(self) -> str:
        self.i += 1
        return self.p[self.i - 1]

    def alternatives(self):
        options = [self.sequence()]
        while self.peek() == "|":
            self.take()
            options.append(self.sequence())
        return options[0] if len(options) == 1 else ("alt", options)

    def sequence(self):
        items = []
        while self.peek() not in ("", "|", ")"):
            items.append(self.repeated(self.atom()))
        return ("cat", items)

    def repeated(self, node):
        while (c := self.peek()) and c in "?*+{":
            self.take()
            if c == "{":
                body = ""
                while (d := self.take()) != "}":
                    body += d
                low, _, high = body.partition(",")
                bounds = (int(low), int(high) if high else None if "," in body else int(low))
            else:
                bounds = {"?": (0, 1), "*": (0, None), "+": (1, None)}[c]
            node = ("rep", node, *bounds)
        return node

    def byte(self) -> int:
        c = self.take()
        if c == "\\":
            c = self.take()
            if c == "x":
                return int(self.take() + self.take(), 16)
        return ord(c)

    def atom(self):
        c = self.peek()
        if c == "(":
            self.take()
            node = self.alternatives()
            self.take()
            return node
        if c == "[":
            self.take()
            negate = self.peek() == "^" and bool(self.take())
            mask = 0
            while self.peek() != "]":
                low = self.byte()
                if self.peek() == "-" and self.p[self.i + 1] != "]":
                    self.take()
                    mask |= _mask(range(low, self.byte() + 1))
                else:
                    mask |= 1 << low
            self.take()
            mask = self.fold(mask)
            return ("set", ALL & ~mask if negate else mask)
        return ("set", self.fold(1 << self.byte()))


def parse(pattern: str, ignore_case: bool = False):
    return _Parser(pattern, ignore_case).alternatives()


def reverse(node):
    kind, *rest = node
    if kind == "cat":
        return ("cat", [reverse(x) for x in reversed(rest[0])])
    if kind == "alt":
        return ("alt", [reverse(x) for x in rest[0]])
    return ("rep", reverse(rest[0]), *rest[1:]) if kind == "rep" else node


# --- automata --------------------------------------------------------------------------------


class _Nfa:
    def __init__(self):
        self.free: list[list[int]] = []
        self.moves: list[list[tuple[int, int]]] = []

    def state(self) -> int:
        self.free.append([])
        self.moves.append([])
        return len(self.free) - 1

    def add(self, node, start: int) -> int:
        """Adds the node's paths from ``start``; returns where they end."""
        kind, *rest = node
        if kind == "set":
            end = self.state()
            self.moves[start].append((rest[0], end))
            return end
        if kind == "cat":
            for x in rest[0]:
                start = self.add(x, start)
            return start
        if kind == "alt":
            end = self.state()
            for x in rest[0]:
                self.free[self.add(x, start)].append(end)
            return end
        inner, least, most = rest
        for _ in range(least):
            start = self.add(inner, start)
        if most is None:
            loop = self.state()
            self.free[start].append(loop)
            self.free[self.add(inner, loop)].append(loop)
            return loop
        end = self.state()
        self.free[start].append(end)
        for _ in range(most - least):
            start = self.add(inner, start)
            self.free[start].append(end)
        return end


@dataclass
class Dfa:
    """table[state][byte] = next state; accepts[state] = mask of the rules that match; state 0 starts."""

    table: list[list[int]]
    accepts: list[int]


def determinise(trees: list, anywhere: bool) -> Dfa:
    nfa = _Nfa()
    start = nfa.state()
    final: dict[int, int] = {}
    for rule, tree in enumerate(trees):
        begin = nfa.state()
        nfa.free[start].append(begin)
        end = nfa.add(tree, begin)
        final[end] = final.get(end, 0) | 1 << rule

    def closed(states) -> frozenset[int]:
        out, todo = set(states), list(states)
        while todo:
            for t in nfa.free[todo.pop()]:
                if t not in out:
                    out.add(t)
                    todo.append(t)
        return frozenset(out)

    first = closed([start])
    number, todo, table, accepts = {first: 0}, [first], [], []
    while todo:
        here = todo.pop(0)
        moves = [m for s in here for m in nfa.moves[s]]
        row: list[int] = [0] * 256
        memo: dict[frozenset, int] = {}
        for byte in range(256):
            target = frozenset([t for mask, t in moves if mask >> byte & 1] + [start] * anywhere)
            if target not in memo:
                key = closed(target)
                if key not in number:
                    number[key] = len(number)
                    todo.append(key)
                memo[target] = number[key]
            row[byte] = memo[target]
        table.append(row)
        accepts.append(sum({1 << r for s in here if s in final for r in range(len(trees)) if final[s] >> r & 1}))
        if len(number) > 20_000:
            raise ValueError("the rules need too many states: check lengths in keep instead")
    return Dfa(table, accepts)


def minimise(dfa: Dfa) -> Dfa:
    """Merge states that no text tells apart (refinement of the partition by accepted rules)."""
    block = [sorted(set(dfa.accepts)).index(a) for a in dfa.accepts]
    while True:
        names: dict[tuple, int] = {}
        new = [names.setdefault((block[s], *(block[t] for t in row)), len(names)) for s, row in enumerate(dfa.table)]
        if len(names) == len(set(block)):
            break
        block = new
    order = {b: i for i, b in enumerate(dict.fromkeys(block))}
    one_of = {order[b]: s for s, b in reversed(list(enumerate(block)))}
    return Dfa([[order[block[t]] for t in dfa.table[one_of[i]]] for i in range(len(order))], [dfa.accepts[one_of[i]] for i in range(len(order))])


# --- rules -----------------------------------------------------------------------------------


@dataclass(frozen=True)
class Rule:
    kind: str
    pattern: str
    ignore_case: bool = False
    keep: Callable[[bytes], bool] | None = None


def _value_of_assign(match: bytes) -> bytes:
    """What follows the name, the sign and an opening quote."""
    at = min(i for i in (match.find(b":"), match.find(b"=")) if i >= 0) + 1
    value = match[at:].lstrip(b" ")
    return value[1:] if value[:1] in (b'"', b"'") else value


def _at_least(n: int) -> Callable[[bytes], bool]:
    return lambda match: len(match) >= n


# The base rules. Least lengths are checked on the maximal match: counting them in the automaton
# would take a state for every set of heads under way (but for hex, whose counts are nested).
BASE = (
    Rule("assign", r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?[A-Za-z0-9+/_.=-]+""", True, lambda m: len(_value_of_assign(m)) >= 12),
    Rule("access", r"AKIA[A-Z0-9]+", keep=_at_least(18)),
    Rule("hex", r"[0-9a-f]{16,}"),
)
# Public shapes of further credentials.
EXTRA = (
    Rule("hosting", r"gh[pousr]_[A-Za-z0-9]+", keep=_at_least(34)),
    Rule("privatekey", r"-----BEGIN (RSA |DSA |EC |OPENSSH |ENCRYPTED )?PRIVATE KEY-----"),
)


class Scanner:
    """The combined automaton of a rule set; holds plain lists, so it pickles to tasks."""

    def __init__(self, rules: tuple[Rule, ...] = BASE + EXTRA):
        self.rules = rules
        trees = [parse(r.pattern, r.ignore_case) for r in rules]
        self.forward = minimise(determinise(trees, anywhere=True))
        self.backward = [minimise(determinise([reverse(t)], anywhere=False)) for t in trees]
        self.dead = [self._dead(d) for d in self.backward]

    @staticmethod
    def _dead(dfa: Dfa) -> int:
        return next((s for s, row in enumerate(dfa.table) if not dfa.accepts[s] and set(row) == {s}), -1)

    def linked(self) -> list:
        """The start state, each state being a list of its 256 successors and then its accepted rules."""
        states: list[list] = [[None] * 257 for _ in self.forward.table]
        for state, row, rules in zip(states, self.forward.table, self.forward.accepts):
            state[:256] = [states[t] for t in row]
            state[256] = rules
        return states[0]

    def ends(self, data: bytes, start: list) -> dict[int, list[int]]:
        """The one pass: per rule the last byte of every run of bytes at which its matches end."""
        runs: dict[int, list[int]] = {}
        state, before = start, 0  # rules that end at the byte before
        for at, byte in enumerate(data, 1):
            state = state[byte]
            now = state[256]
            if now != before:
                over, rule = before & ~now, 0
                while over >> rule:
                    if over >> rule & 1:
                        runs.setdefault(rule, []).append(at - 1)
                    rule += 1
                before = now
        rule = 0
        while before >> rule:
            if before >> rule & 1:
                runs.setdefault(rule, []).append(len(data))
            rule += 1
        return runs

    def spans(self, data: bytes, start: list) -> list[tuple[str, int, int]]:
        """(kind, start, end) in bytes, by start and then the order of the rules."""
        runs = self.ends(data, start)
        out = []
        for rule, ends in runs.items():
            free = 0  # bytes before this belong to earlier matches
            for end in ends:
                begin = self._leftmost(rule, data, end, free)
                if begin is None:
                    continue
                free = end
                keep = self.rules[rule].keep
                if keep is None or keep(data[begin:end]):
                    out.append((begin, rule, end))
        return [(self.rules[rule].kind, begin, end) for begin, rule, end in sorted(out)]

    def _leftmost(self, rule: int, data: bytes, end: int, least: int) -> int | None:
        dfa, dead, state, best = self.backward[rule], self.dead[rule], 0, None
        for at in range(end - 1, least - 1, -1):
            state = dfa.table[state][data[at]]
            if state == dead:
                break
            if dfa.accepts[state]:
                best = at
        return best


def _code_points(data: bytes, spans: list[tuple[str, int, int]]) -> list[tuple[str, int, int]]:
    if not spans or data.isascii():
        return spans
    marks = sorted({x for s in spans for x in s[1:]})
    at, n, points = 0, 0, []
    for m in marks:
        n += len(data[at:m].decode("utf-8", "replace"))
        at = m
        points.append(n)
    return [(k, points[bisect_left(marks, a)], points[bisect_left(marks, b)]) for k, a, b in spans]


def scan(docs: DataFrame, rules: tuple[Rule, ...] = BASE + EXTRA) -> DataFrame:
    """doc_id, spans array<struct<kind, start, stop>> in code points, base (spans of the base rules only, as text), all (as text)."""
    scanner = Scanner(rules)
    base = {r.kind for r in BASE}
    source = doc_text(docs)
    schema = f"doc_id {source.schema['doc_id'].dataType.simpleString()}, spans array<struct<kind:string,start:long,stop:long>>, base string, all string"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        start = scanner.linked()
        kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("stop", pa.int64())]))
        for batch in batches:
            rows = []
            for value in batch.column(1).cast(pa.large_binary()):
                data = value.as_py()
                rows.append(_code_points(data, scanner.spans(data, start)))
            said = [[",".join(f"{k}:{a}:{b}" for k, a, b in row if k in base or every) for row in rows] for every in (0, 1)]
            spans = pa.array([[{"kind": k, "start": a, "stop": b} for k, a, b in row] for row in rows], kind)
            yield pa.RecordBatch.from_arrays([batch.column(0), spans, pa.array(said[0]), pa.array(said[1])], ["doc_id", "spans", "base", "all"])

    return source.mapInArrow(run, schema)


def redact(text: str, spans: list[tuple[str, int, int]]) -> str:
    """The text with each span replaced by its kind in brackets; of overlapping spans the first counts."""
    out, at = [], 0
    for kind, a, b in spans:
        if a >= at:
            out += [text[at:a], f"[{kind}]"]
            at = b
    return "".join([*out, text[at:]])
