"""Secret scans with one combined deterministic automaton.

Rules are regular expressions over bytes, written with the small syntax parsed here.
They are compiled together: Thompson construction, subset construction, then
minimisation by partition refinement, into one transition array over byte classes.

A scan makes one pass over the bytes of all texts of a batch, all rules at once and
many texts in lockstep (a state per text, one table lookup per step).  The automaton
looks for each rule's *trigger*, the shortest part that decides that a match begins
(the unanchored search ``.*trigger``), and reports the byte where it ends; of a rule whose
matches are runs of one class of bytes, only where the trigger first ends in a run.  Around
each report the rule's span is then resolved: an anchored automaton of the reversed
trigger walks back to the leftmost start, and the anchored automaton of the rule walks
forward to the longest end.  Spans of one rule do not overlap and are taken from the
left; spans that fail the rule's length test are dropped but still consume their text.

Time is linear in the text: where a forward walk ran on without a further accepting state,
its states are marked, and a later walk of the rule that comes to the same state at the same
byte ends there, since it cannot accept any more either.

Defined cases: null texts are empty; empty texts have no spans; very long texts are
scanned whole (once few texts are left in lockstep, a plain loop takes over), in a few
bytes of memory per byte; repeated rows are scanned row by row; other columns are ignored; an empty table gives an
empty result.  Spans are in code points, end exclusive.
"""

from __future__ import annotations

import functools
import hashlib
from array import array
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernels as K


@dataclass(frozen=True)
class Rule:
    """A kind of secret.

    ``pattern`` is the whole rule; ``trigger`` a pattern that every match begins with.
    A match counts when it has ``least`` characters, or its tail behind the part that
    ``head`` matches has ``least_tail``.  ``run``: matches are runs of one class of bytes.
    """

    kind: str
    trigger: str
    pattern: str
    head: str = ""
    least: int = 0
    least_tail: int = 0
    fold: bool = False
    run: bool = False


#: The kinds every scan has, in this order.
ASSIGN_HEAD = "(password|passwd|secret|token|api_?key)[\"']?\\x20*[:=]\\x20*[\"']?"
BASE: tuple[Rule, ...] = (
    Rule("assign", ASSIGN_HEAD + "[A-Za-z0-9+/_.=\\-]", ASSIGN_HEAD + "[A-Za-z0-9+/_.=\\-]+", head=ASSIGN_HEAD, least_tail=6, fold=True),
    Rule("access", "AKIA[A-Z0-9]", "AKIA[A-Z0-9]+", least=20),
    Rule("hex", "[0-9a-f]{24}", "[0-9a-f]+", least=24, run=True),
)
#: Kinds the method adds: publicly documented token shapes.
EXTRA: tuple[Rule, ...] = (
    Rule("pem", "-----BEGIN ", "-----BEGIN [A-Z ]*PRIVATE KEY-----"),
    Rule("jwt", "eyJ[A-Za-z0-9_\\-]", "eyJ[A-Za-z0-9_\\-]+\\.[A-Za-z0-9_\\-]+\\.[A-Za-z0-9_\\-]+", least=30),
    Rule("bearer", "bearer\\x20+[A-Za-z0-9]", "bearer\\x20+[A-Za-z0-9._~+/\\-]+=*", least=27, fold=True),
    Rule("pat", "gh[pousr]_[A-Za-z0-9]", "gh[pousr]_[A-Za-z0-9]+", least=40),
    Rule("url", "://[!-.0-9;-?A-Z\\[-~]+:[!-.0-9;-?A-Z\\[-~]", "://[!-.0-9;-?A-Z\\[-~]+:[!-.0-9;-?A-Z\\[-~]+@"),
)
RULES = BASE + EXTRA


# --- pattern syntax: literals, escapes, classes, groups, | ? * + {n} ------------------


def _class(chars: set[int], fold: bool) -> frozenset[int]:
    if fold:
        chars = chars | {c ^ 32 for c in chars if chr(c).isascii() and chr(c).isalpha()}
    return frozenset(chars)


def parse(pattern: str, fold: bool = False) -> tuple:
    """Syntax tree: ("set", bytes), ("cat", parts), ("alt", parts), ("rep", part, least, most or None)."""
    at = 0

    def escape() -> int:
        nonlocal at
        at += 1
        if pattern[at] == "x":
            at += 3
            return int(pattern[at - 2 : at], 16)
        at += 1
        return ord(pattern[at - 1])

    def one() -> int:
        nonlocal at
        if pattern[at] == "\\":
            return escape()
        at += 1
        return ord(pattern[at - 1])

    def atom() -> tuple:
        nonlocal at
        if pattern[at] == "(":
            at += 1
            inner = alternatives()
            at += 1
            return inner
        if pattern[at] == "[":
            at += 1
            chars: set[int] = set()
            while pattern[at] != "]":
                low = one()
                high = low
                if pattern[at] == "-" and pattern[at + 1] != "]":
                    at += 1
                    high = one()
                chars |= set(range(low, high + 1))
            at += 1
            return ("set", _class(chars, fold))
        return ("set", _class({one()}, fold))

    def sequence() -> tuple:
        nonlocal at
        parts = []
        while at < len(pattern) and pattern[at] not in "|)":
            part = atom()
            while at < len(pattern) and pattern[at] in "?*+{":
                if pattern[at] == "{":
                    end = pattern.index("}", at)
                    n = int(pattern[at + 1 : end])
                    part, at = ("rep", part, n, n), end + 1
                else:
                    part, at = ("rep", part, *{"?": (0, 1), "*": (0, None), "+": (1, None)}[pattern[at]]), at + 1
            parts.append(part)
        return ("cat", tuple(parts))

    def alternatives() -> tuple:
        nonlocal at
        parts = [sequence()]
        while at < len(pattern) and pattern[at] == "|":
            at += 1
            parts.append(sequence())
        return parts[0] if len(parts) == 1 else ("alt", tuple(parts))

    return alternatives()


def reverse(tree: tuple) -> tuple:
    if tree[0] == "cat":
        return ("cat", tuple(reverse(p) for p in reversed(tree[1])))
    if tree[0] == "alt":
        return ("alt", tuple(map(reverse, tree[1])))
    return ("rep", reverse(tree[1]), *tree[2:]) if tree[0] == "rep" else tree


class _Nfa:
    def __init__(self) -> None:
        self.moves: list[list[tuple[frozenset[int], int]]] = []
        self.free: list[list[int]] = []

    def state(self) -> int:
        self.moves.append([])
        self.free.append([])
        return len(self.moves) - 1

    def add(self, tree: tuple, start: int) -> int:
        """Adds a tree behind a state; returns its end."""
        kind = tree[0]
        if kind == "set":
            end = self.state()
            self.moves[start].append((tree[1], end))
            return end
        if kind == "cat":
            for part in tree[1]:
                start = self.add(part, start)
            return start
        if kind == "alt":
            end = self.state()
            for part in tree[1]:
                first = self.state()
                self.free[start].append(first)
                self.free[self.add(part, first)].append(end)
            return end
        _, part, least, most = tree
        for _ in range(least):
            start = self.add(part, start)
        if most is None:
            loop = self.state()
            self.free[start].append(loop)
            self.free[self.add(part, loop)].append(loop)
            return loop
        for _ in range(most - least):
            end = self.add(part, start)
            self.free[start].append(end)
            start = end
        return start

    def closure(self, states: frozenset[int]) -> frozenset[int]:
        seen, stack = set(states), list(states)
        while stack:
            for s in self.free[stack.pop()]:
                if s not in seen:
                    seen.add(s)
                    stack.append(s)
        return frozenset(seen)


@dataclass
class Dfa:
    """Transition arrays: ``table[state, byte_class[byte]]``; ``accepts[state]`` is a bit per rule."""

    table: np.ndarray
    byte_class: np.ndarray
    accepts: np.ndarray


def build(trees: list[tuple], search: bool) -> Dfa:
    """Subset construction of all rules together, then minimisation.

    ``search`` keeps the start alive at every byte.  Otherwise state 0 stays dead once
    no rule can go on (the last state).
    """
    nfa = _Nfa()
    root = nfa.state()
    ends = {}
    for k, tree in enumerate(trees):
        first = nfa.state()
        nfa.free[root].append(first)
        ends[nfa.add(tree, first)] = k
    signature = [tuple(b in chars for row in nfa.moves for chars, _ in row) for b in range(256)]
    numbers: dict[tuple, int] = {}
    byte_class = np.array([numbers.setdefault(s, len(numbers)) for s in signature], dtype=np.int64)
    sample = [int(np.flatnonzero(byte_class == c)[0]) for c in range(len(numbers))]
    start = nfa.closure(frozenset([root]))
    found, todo, rows = {start: 0}, [start], []
    while todo:
        states = todo.pop(0)
        row = []
        for byte in sample:
            to = frozenset(t for s in states for chars, t in nfa.moves[s] if byte in chars)
            after = nfa.closure(to | ({root} if search else set()))
            if after not in found:
                found[after] = len(found)
                todo.append(after)
            row.append(found[after])
        rows.append(row)
    accepts = np.array([sum(1 << k for e, k in ends.items() if e in states) for states in found], dtype=np.int64)
    return _minimal(np.array(rows, dtype=np.int64), byte_class, accepts)


def _minimal(table: np.ndarray, byte_class: np.ndarray, accepts: np.ndarray) -> Dfa:
    """Partition refinement until no block splits; state 0 stays the start."""
    block = np.unique(accepts, return_inverse=True)[1]
    while True:
        now = np.unique(np.column_stack([block, block[table]]), axis=0, return_inverse=True)[1].ravel()
        if now.max() == block.max():
            break
        block = now
    first = np.array([np.flatnonzero(block == b)[0] for b in range(block.max() + 1)])
    order = np.argsort(first)
    rank = np.empty_like(order)
    rank[order] = np.arange(len(order))
    chosen = first[order]
    return Dfa(rank[block[table[chosen]]], byte_class, accepts[chosen])


@dataclass
class Walker:
    """An anchored automaton as plain lists, for single walks."""

    rows: list[list[int]]
    classes: bytes
    accepts: list[bool]
    dead: int


def walker(tree: tuple) -> Walker:
    dfa = build([tree], False)
    same = np.flatnonzero((dfa.table == np.arange(len(dfa.table))[:, None]).all(axis=1) & (dfa.accepts == 0))
    return Walker(dfa.table.tolist(), bytes(dfa.byte_class.tolist()), (dfa.accepts != 0).tolist(), int(same[0]) if len(same) else -1)


@functools.cache
def compiled(rules: tuple[Rule, ...] = RULES) -> tuple[Dfa, list[tuple[Walker, Walker, Walker | None]]]:
    """The combined trigger automaton, and per rule: reversed trigger, whole rule, head."""
    triggers = [parse(r.trigger, r.fold) for r in rules]
    own = [(walker(reverse(t)), walker(parse(r.pattern, r.fold)), walker(parse(r.head, r.fold)) if r.head else None) for r, t in zip(rules, triggers, strict=True)]
    return build(triggers, True), own


#: A walk that went on for so many bytes behind its last accepting state leaves marks.
STRAY = 64


def _walk(dfa: Walker, data: bytes, start: int, stop: int, marks: dict[int, bytearray]) -> int:
    """The longest accepted walk from ``start`` (exclusive end), or -1.

    ``marks[state][byte]``: from that state at that byte on, no state accepts.
    """
    rows, classes, accepts, dead = dfa.rows, dfa.classes, dfa.accepts, dfa.dead
    state, best, at = 0, -1, start
    while at < stop:
        state = rows[state][classes[data[at]]]
        at += 1
        if accepts[state]:
            best = at
        elif state == dead or (marks and state in marks and marks[state][at - 1]):
            break
    if at - max(best, start) > STRAY:
        state, end = 0, at
        for at in range(start, end):
            state = rows[state][classes[data[at]]]
            if at >= best and state != dead:
                if state not in marks:
                    marks[state] = bytearray(len(data))
                marks[state][at] = 1
    return best


#: With fewer live texts than this, each is scanned in a loop of its own.
FEW = 24


class _Found:
    """Positions and bits, gathered in pieces that are joined now and then."""

    def __init__(self) -> None:
        self.done: list[tuple[np.ndarray, np.ndarray]] = []
        self.open: list[tuple[np.ndarray, np.ndarray]] = []

    def add(self, ends: np.ndarray, bits: np.ndarray) -> None:
        self.open.append((ends, bits))
        if len(self.open) >= 4096:
            self.close()

    def close(self) -> None:
        if self.open:
            self.done.append((np.concatenate([e for e, _ in self.open]), np.concatenate([b for _, b in self.open])))
            self.open = []

    def sorted(self) -> tuple[np.ndarray, np.ndarray]:
        self.close()
        if not self.done:
            return np.zeros(0, np.int64), np.zeros(0, np.int64)
        where, what = np.concatenate([e for e, _ in self.done]), np.concatenate([b for _, b in self.done])
        order = np.argsort(where, kind="stable")
        return where[order], what[order]


def reports(dfa: Dfa, data: np.ndarray, offsets: np.ndarray, runs: int = 0) -> tuple[np.ndarray, np.ndarray]:
    """Byte positions behind which a trigger ends, and the rule bits; one pass over the bytes.

    Of the rules in ``runs`` (bits) only the first of consecutive positions is reported.
    """
    classes = len(dfa.table[0])
    ranked = np.argsort(dfa.accepts != 0, kind="stable")  # accepting states last: one comparison finds them
    rank = np.empty_like(ranked)
    rank[ranked] = np.arange(len(ranked))
    first = int((dfa.accepts == 0).sum()) * classes
    flat = (rank[dfa.table[ranked]] * classes).astype(np.int32).ravel()
    accepts = dfa.accepts[ranked]
    symbol = dfa.byte_class.astype(np.uint8)[data]
    length = np.diff(offsets)
    order = np.argsort(-length, kind="stable")
    at, left = offsets[:-1][order].copy(), length[order]
    state = np.full(len(order), rank[0] * classes, dtype=np.int32)
    found, step = _Found(), 0
    live = int((left > 0).sum())
    while live > FEW:
        stop = int(left[live - 1])
        s, p = state[:live], at[:live]
        for _ in range(stop - step):
            was, s = s, flat.take(s + symbol.take(p))
            p = p + 1
            if int(s.max()) >= first:
                hit = np.flatnonzero(s >= first)
                bits = accepts[s[hit] // classes] & ~(accepts[was[hit] // classes] & runs)
                if bits.any():
                    found.add(p[hit][bits != 0], bits[bits != 0])
        state[:live], at[:live], step = s, p, stop
        live = int((left > step).sum())
    rows = [[int(x) // classes for x in flat[k * classes : (k + 1) * classes]] for k in range(len(ranked))] if live else []
    last, masks = first // classes, accepts.tolist()
    for k in range(live):
        now, base = int(state[k]) // classes, int(at[k])
        ends, bits = array("q"), array("q")
        for i, c in enumerate(symbol[base : base + int(left[k]) - step].tobytes(), base + 1):
            was, now = now, rows[now][c]
            if now >= last and (new := masks[now] & ~(masks[was] & runs)):
                ends.append(i)
                bits.append(new)
        if ends:
            found.add(np.array(ends, np.int64), np.array(bits, np.int64))
    return found.sorted()


def resolve(rules: tuple[Rule, ...], own: list, data: bytes, ends: list[tuple[int, int]]) -> list[tuple[int, int, int]]:
    """(start, rule, end) in bytes of one text, by start and then rule."""
    found = []
    for k, rule in enumerate(rules):
        back, forward, head = own[k]
        done, marks = 0, {}
        for end, bits in ends:
            if not bits >> k & 1 or end <= done:
                continue
            start = _leftmost(back, data, end, done)
            if start < 0:
                continue
            stop = _walk(forward, data, start, len(data), marks)
            if stop < 0:
                continue
            done = stop
            tail = stop - _walk(head, data, start, stop, {}) if head else stop - start
            if stop - start >= rule.least and tail >= rule.least_tail:
                found.append((start, k, stop))
    return sorted(found)


def _leftmost(back: Walker, data: bytes, end: int, floor: int) -> int:
    """The leftmost start, at ``floor`` or behind it, of a trigger that ends at ``end``."""
    state, best, rows, classes = 0, -1, back.rows, back.classes
    for at in range(end - 1, floor - 1, -1):
        state = rows[state][classes[data[at]]]
        if back.accepts[state]:
            best = at
        elif state == back.dead:
            break
    return best


def _points(text: np.ndarray, places: list[int]) -> dict[int, int]:
    """Code points before byte places."""
    begins = (text & 0xC0) != 0x80
    out, at, n = {}, 0, 0
    for p in sorted(set(places)):
        n += int(np.count_nonzero(begins[at:p]))
        out[p], at = n, p
    return out


SCHEMA = "doc_id long, spans array<struct<kind: string, start: long, end: long>>"
_SPAN = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))


def scan(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """doc_id and spans (by start, then kind as listed) of every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        dfa, own = compiled(rules)
        runs = sum(1 << k for k, r in enumerate(rules) if r.run)
        for batch in batches:
            for part in K.slices(batch, "text", 16 << 20):
                data, offsets = K.text_buffer(part.column("text"))
                where, what = reports(dfa, data, offsets, runs)
                doc = np.searchsorted(offsets, where - 1, "right") - 1
                spans: list[list[dict]] = [[] for _ in range(part.num_rows)]
                cuts = np.flatnonzero(np.diff(doc)) + 1
                for ends, bits, d in zip(np.split(where, cuts), np.split(what, cuts), np.split(doc, cuts), strict=True):
                    if not len(d):
                        continue
                    k, base = int(d[0]), int(offsets[d[0]])
                    text = data[base : int(offsets[d[0] + 1])]
                    found = resolve(rules, own, text.tobytes(), list(zip((ends - base).tolist(), bits.tolist(), strict=True)))
                    points = _points(text, [x for a, _, b in found for x in (a, b)]) if found else {}
                    spans[k] = [{"kind": rules[r].kind, "start": points[a], "end": points[b]} for a, r, b in found]
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array(spans, _SPAN)], names=["doc_id", "spans"])

    return docs.select(F.col("`doc_id`").cast("long").alias("doc_id"), F.col("`text`").alias("text")).mapInArrow(run, SCHEMA)


def report(docs: DataFrame, rules: tuple[Rule, ...] = RULES) -> DataFrame:
    """Counts of the base kinds, the digest of their spans, and all spans, per row."""
    joined = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")
    base = F.filter("spans", lambda s: s["kind"].isin(*[r.kind for r in BASE]))
    count = lambda kind: F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    return scan(docs, rules).select("doc_id", *[count(r.kind) for r in BASE], F.sha2(joined(base).cast("binary"), 256).alias("base_sha256"), joined(F.col("spans")).alias("spans"))


def digest(spans: list[tuple[str, int, int]]) -> str:
    """The digest of spans, for tests."""
    return hashlib.sha256(",".join(f"{k}:{a}:{b}" for k, a, b in spans).encode()).hexdigest()
