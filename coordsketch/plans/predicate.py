"""Predicates over set memberships and key attributes, and what follows from their meaning.

A predicate is analysed by its decision diagram over memberships and attribute conditions, so equivalent formulas are treated
alike: which sets matter, and whether the predicate is an attribute filter over the whole union of these sets (then the
long combination answers it) or needs to know memberships (then only the short one does).
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F


class Pred:
    def __and__(self, other: Pred) -> Pred:
        return And((self, other))

    def __or__(self, other: Pred) -> Pred:
        return Or((self, other))

    def __invert__(self) -> Pred:
        return Not(self)


@dataclass(frozen=True)
class In(Pred):
    set_id: str


@dataclass(frozen=True)
class Attr(Pred):
    """A condition on key attributes, as SQL."""

    sql: str


@dataclass(frozen=True)
class Not(Pred):
    part: Pred


@dataclass(frozen=True)
class And(Pred):
    parts: tuple


@dataclass(frozen=True)
class Or(Pred):
    parts: tuple


@dataclass(frozen=True)
class AtLeast(Pred):
    """Membership in at least q of the sets."""

    q: int
    sets: tuple


def any_of(sets) -> Pred:
    return Or(tuple(In(s) for s in sets))


def all_of(sets) -> Pred:
    return And(tuple(In(s) for s in sets))


def _sets(p: Pred) -> list[str]:
    if isinstance(p, In):
        return [p.set_id]
    if isinstance(p, AtLeast):
        return list(p.sets)
    if isinstance(p, Not):
        return _sets(p.part)
    return [s for x in getattr(p, "parts", ()) for s in _sets(x)]


def _attrs(p: Pred) -> list[str]:
    if isinstance(p, Attr):
        return [p.sql]
    if isinstance(p, Not):
        return _attrs(p.part)
    return [s for x in getattr(p, "parts", ()) for s in _attrs(x)]


def holds(p: Pred, member: frozenset, true_attrs: frozenset) -> bool:
    if isinstance(p, In):
        return p.set_id in member
    if isinstance(p, Attr):
        return p.sql in true_attrs
    if isinstance(p, AtLeast):
        return sum(s in member for s in p.sets) >= p.q
    if isinstance(p, Not):
        return not holds(p.part, member, true_attrs)
    values = (holds(x, member, true_attrs) for x in p.parts)
    return all(values) if isinstance(p, And) else any(values)


class Diagram:
    """The reduced ordered decision diagram of a predicate: equivalent predicates have equal diagrams, however they are written.

    Attribute conditions come first, then sets. Nodes are numbers, 0 and 1 the constants. AtLeast over n sets has n q nodes."""

    def __init__(self, p: Pred):
        self.names = [("attr", x) for x in sorted(set(_attrs(p)))] + [("set", x) for x in sorted(set(_sets(p)))]
        self.place = {x: i for i, x in enumerate(self.names)}
        self.node: list[tuple[int, int, int]] = [(len(self.names), 0, 0), (len(self.names), 1, 1)]
        self._known: dict[tuple[int, int, int], int] = {}
        self._joined: dict[tuple[str, int, int], int] = {}
        self.root = self._build(p)

    def _make(self, at: int, low: int, high: int) -> int:
        if low == high:
            return low
        key = (at, low, high)
        if key not in self._known:
            self._known[key] = len(self.node)
            self.node.append(key)
        return self._known[key]

    def _join(self, how: str, a: int, b: int) -> int:
        end = {"and": (0, 1), "or": (1, 0)}[how]  # what decides at once, and what leaves the other as it is
        if a == b or b == end[1]:
            return a
        if end[0] in (a, b):
            return end[0]
        if a == end[1]:
            return b
        key = (how, min(a, b), max(a, b))
        if key not in self._joined:
            (i, al, ah), (j, bl, bh) = self.node[a], self.node[b]
            if i < j:
                bl = bh = b
            elif j < i:
                al = ah = a
            self._joined[key] = self._make(min(i, j), self._join(how, al, bl), self._join(how, ah, bh))
        return self._joined[key]

    def _turn(self, a: int) -> int:
        if a < 2:
            return 1 - a
        key = ("not", a, a)
        if key not in self._joined:
            at, low, high = self.node[a]
            self._joined[key] = self._make(at, self._turn(low), self._turn(high))
        return self._joined[key]

    def at_least(self, q: int, sets) -> int:
        times: dict[int, int] = {}
        for x in sets:
            times[self.place["set", x]] = times.get(self.place["set", x], 0) + 1
        below = [1] + [0] * max(q, 0)  # by how many are still needed
        for at in sorted(times, reverse=True):
            below = [1] + [self._make(at, below[need], below[max(0, need - times[at])]) for need in range(1, max(q, 0) + 1)]
        return below[max(q, 0)]

    def _build(self, p: Pred) -> int:
        if isinstance(p, In):
            return self._make(self.place["set", p.set_id], 0, 1)
        if isinstance(p, Attr):
            return self._make(self.place["attr", p.sql], 0, 1)
        if isinstance(p, AtLeast):
            return self.at_least(p.q, p.sets)
        if isinstance(p, Not):
            return self._turn(self._build(p.part))
        if isinstance(p, Or) and all(isinstance(x, In) for x in p.parts):
            return self.at_least(1, {x.set_id for x in p.parts})
        how = "and" if isinstance(p, And) else "or"
        found = 1 if how == "and" else 0
        for x in p.parts:
            found = self._join(how, found, self._build(x))
        return found

    def reached(self, follow) -> set[int]:
        """All nodes from the root on, going on from each to follow(node)."""
        found, todo = set(), [self.root]
        while todo:
            a = todo.pop()
            if a not in found:
                found.add(a)
                todo.extend(follow(a))
        return found

    def kind(self, a: int) -> str:
        return self.names[self.node[a][0]][0] if a > 1 else "end"

    def sets(self) -> frozenset[str]:
        every = self.reached(lambda a: self.node[a][1:] if a > 1 else ())
        return frozenset(self.names[self.node[a][0]][1] for a in every if self.kind(a) == "set")


def relevant_sets(p: Pred) -> frozenset[str]:
    """The sets whose membership can change the predicate's value."""
    return Diagram(p).sets()


def best_combination(p: Pred) -> str:
    """long for an attribute filter over the whole union of the relevant sets, else short."""
    d = Diagram(p)
    union = d.at_least(1, d.sets())
    ends = {a for a in d.reached(lambda a: d.node[a][1:] if d.kind(a) == "attr" else ()) if d.kind(a) != "attr"}
    return "long" if ends <= {0, 1, union, d._turn(union)} else "short"


def bounded(p: Pred) -> bool:
    """True if only keys of some relevant set can satisfy the predicate."""
    d = Diagram(p)
    return 1 not in d.reached(lambda a: d.node[a][1:2] if d.kind(a) == "set" else d.node[a][1:] if a > 1 else ())


def to_column(p: Pred, member_of: Column | None = None) -> Column:
    member_of = F.col("member_of") if member_of is None else member_of
    if isinstance(p, In):
        return F.array_contains(member_of, p.set_id)
    if isinstance(p, Attr):
        return F.coalesce(F.expr(p.sql), F.lit(False))
    if isinstance(p, AtLeast):
        return F.size(F.array_intersect(member_of, F.array(*map(F.lit, p.sets)))) >= p.q
    if isinstance(p, Not):
        return ~to_column(p.part, member_of)
    out = F.lit(isinstance(p, And))
    for x in p.parts:
        out = out & to_column(x, member_of) if isinstance(p, And) else out | to_column(x, member_of)
    return out


_TOKEN = re.compile(r"\s*(?:(in)\s*\(\s*([^)]+?)\s*\)|(at_least)\s*\(\s*(\d+)\s*,\s*([^)]+?)\s*\)|(and|or|not)\b|([()])|((?:(?!\b(?:and|or)\b)[^()])+))", re.I)


def parse(text: str) -> Pred:
    """in(A) and not in(C) and length >= 5; at_least(2, A, B, C); anything else is an attribute condition in SQL."""
    tokens: list[tuple[str, object]] = []
    at = 0
    while at < len(text.rstrip()):
        m = _TOKEN.match(text, at)
        if not m:
            raise ValueError(f"cannot read {text[at:]!r}")
        at = m.end()
        if m[1]:
            tokens.append(("atom", In(m[2])))
        elif m[3]:
            tokens.append(("atom", AtLeast(int(m[4]), tuple(s.strip() for s in m[5].split(",")))))
        elif m[6]:
            tokens.append((m[6].lower(), None))
        elif m[7]:
            tokens.append((m[7], None))
        else:
            tokens.append(("atom", Attr(m[8].strip())))

    def either() -> Pred:
        parts = [both()]
        while tokens and tokens[0][0] == "or":
            tokens.pop(0)
            parts.append(both())
        return parts[0] if len(parts) == 1 else Or(tuple(parts))

    def both() -> Pred:
        parts = [single()]
        while tokens and tokens[0][0] == "and":
            tokens.pop(0)
            parts.append(single())
        return parts[0] if len(parts) == 1 else And(tuple(parts))

    def single() -> Pred:
        if not tokens:
            raise ValueError(f"{text!r} ends early")
        kind, value = tokens.pop(0)
        if kind == "not":
            return Not(single())
        if kind == "(":
            inner = either()
            if not tokens or tokens.pop(0)[0] != ")":
                raise ValueError(f"a bracket is open in {text!r}")
            return inner
        if kind != "atom":
            raise ValueError(f"{kind!r} is out of place in {text!r}")
        return value

    found = either()
    if tokens:
        raise ValueError(f"{text!r} goes on after its end")
    return found
