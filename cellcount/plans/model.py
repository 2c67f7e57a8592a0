"""Counting queries: tables, join classes and the widest range that each attribute may take."""

from __future__ import annotations

from collections.abc import Iterable, Mapping
from dataclasses import dataclass, field, replace
from itertools import combinations
from typing import Any


class UnsupportedQuery(ValueError):
    """A query outside the model; the message gives the reason."""


@dataclass(frozen=True)
class Interval:
    """A range of values; ``None`` ends are unbounded."""

    lo: Any = None
    lo_incl: bool = False
    hi: Any = None
    hi_incl: bool = False

    @property
    def empty(self) -> bool:
        if self.lo is None or self.hi is None:
            return False
        return self.lo > self.hi or (self.lo == self.hi and not (self.lo_incl and self.hi_incl))

    @property
    def point(self) -> bool:
        return self.lo is not None and self.lo == self.hi and self.lo_incl and self.hi_incl

    def meet(self, other: Interval) -> Interval:
        """The intersection."""
        lo, lo_incl, hi, hi_incl = self.lo, self.lo_incl, self.hi, self.hi_incl
        if other.lo is not None and (lo is None or other.lo > lo or (other.lo == lo and not other.lo_incl)):
            lo, lo_incl = other.lo, other.lo_incl
        if other.hi is not None and (hi is None or other.hi < hi or (other.hi == hi and not other.hi_incl)):
            hi, hi_incl = other.hi, other.hi_incl
        return Interval(lo, lo_incl, hi, hi_incl)

    def holds(self, x) -> bool:
        if x is None:
            return False
        if self.lo is not None and (x < self.lo or (x == self.lo and not self.lo_incl)):
            return False
        return not (self.hi is not None and (x > self.hi or (x == self.hi and not self.hi_incl)))


def compare(op: str, value) -> Interval:
    """The range of a comparison with a literal."""
    return {
        "=": Interval(value, True, value, True),
        "<": Interval(hi=value),
        "<=": Interval(hi=value, hi_incl=True),
        ">": Interval(value),
        ">=": Interval(value, True),
    }[op]


def equivalence_classes(pairs: Iterable[tuple[str, str]]) -> frozenset[frozenset[str]]:
    """The partition of attributes that equalities imply, without singletons."""
    parent: dict[str, str] = {}

    def find(x: str) -> str:
        parent.setdefault(x, x)
        while parent[x] != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for a, b in pairs:
        parent[find(a)] = find(b)
    groups: dict[str, set[str]] = {}
    for x in list(parent):
        groups.setdefault(find(x), set()).add(x)
    return frozenset(frozenset(g) for g in groups.values() if len(g) > 1)


def table_of(attr: str) -> str:
    return attr.partition(".")[0]


def column_of(attr: str) -> str:
    return attr.partition(".")[2]


@dataclass(frozen=True)
class JoinPattern:
    """Tables and join classes; queries of one pattern differ in their selections only."""

    tables: frozenset[str]
    classes: frozenset[frozenset[str]]

    @property
    def key(self) -> str:
        return "+".join(sorted(self.tables)) + "|" + ";".join(sorted("=".join(sorted(c)) for c in self.classes))

    def ordered_classes(self) -> list[frozenset[str]]:
        return sorted(self.classes, key=lambda c: sorted(c))

    def classes_of(self, table: str) -> list[int]:
        """Indexes, in ``ordered_classes``, of the classes with an attribute of ``table``."""
        return [i for i, c in enumerate(self.ordered_classes()) if any(table_of(a) == table for a in c)]

    def attrs(self, table: str, i: int) -> list[str]:
        return sorted(a for a in self.ordered_classes()[i] if table_of(a) == table)

    def join_attrs(self, left: Iterable[str], right: Iterable[str]) -> set[str]:
        """Attributes of ``left`` that join with ``right``."""
        left, right = set(left), set(right)
        return {a for c in self.classes if any(table_of(b) in right for b in c) for a in c if table_of(a) in left}

    def neighbours(self, table: str) -> set[str]:
        return {table_of(a) for c in self.classes if any(table_of(b) == table for b in c) for a in c} - {table}


@dataclass(frozen=True)
class CountQuery:
    """``ranges``: attribute -> interval, all of which must hold. ``others``: further boxes, disjoint from this one
    and each other, whose counts add (for disjunctions). ``aliases``: alias -> table, for self-joins."""

    id: str
    tables: frozenset[str]
    classes: frozenset[frozenset[str]] = frozenset()
    ranges: tuple[tuple[str, Interval], ...] = ()
    others: tuple[tuple[tuple[str, Interval], ...], ...] = ()
    aliases: tuple[tuple[str, str], ...] = field(default=())

    @staticmethod
    def build(id: str, tables: Iterable[str], joins: Iterable[tuple[str, str]] = (), conditions: Iterable[tuple[str, Interval]] = (), others: Iterable[Iterable[tuple[str, Interval]]] = (), aliases: Mapping[str, str] | None = None) -> CountQuery:
        return CountQuery(id, frozenset(tables), equivalence_classes(joins), conjunction(conditions), tuple(conjunction(o) for o in others), tuple(sorted((aliases or {}).items())))

    @property
    def pattern(self) -> JoinPattern:
        return JoinPattern(self.tables, self.classes)

    def boxes(self) -> list[dict[str, Interval]]:
        """The satisfiable boxes."""
        return [d for d in map(dict, (self.ranges, *self.others)) if not any(i.empty for i in d.values())]


def conjunction(conditions: Iterable[tuple[str, Interval]]) -> tuple[tuple[str, Interval], ...]:
    """The widest range of each attribute under all conditions."""
    out: dict[str, Interval] = {}
    for attr, interval in conditions:
        out[attr] = out[attr].meet(interval) if attr in out else interval
    return tuple(sorted(out.items(), key=lambda x: x[0]))


def restrict(q: CountQuery, tables: Iterable[str], id: str | None = None) -> CountQuery:
    """The subquery over some of the tables: other tables' attributes leave classes and ranges."""
    keep = frozenset(tables)
    classes = frozenset(c for c in (frozenset(a for a in c if table_of(a) in keep) for c in q.classes) if len(c) > 1)
    ranges = tuple((a, i) for a, i in q.ranges if table_of(a) in keep)
    return replace(q, id=id or q.id, tables=keep, classes=classes, ranges=ranges, others=())


def partition_by_pattern(queries: Iterable[CountQuery]) -> dict[JoinPattern, list[CountQuery]]:
    """The batch by join pattern, in order of first appearance."""
    out: dict[JoinPattern, list[CountQuery]] = {}
    for q in queries:
        out.setdefault(q.pattern, []).append(q)
    return out


def connected(pattern: JoinPattern, tables: Iterable[str] | None = None) -> bool:
    tables = set(pattern.tables if tables is None else tables)
    if not tables:
        return False
    seen, todo = set(), [next(iter(tables))]
    while todo:
        t = todo.pop()
        if t not in seen:
            seen.add(t)
            todo += [u for u in pattern.neighbours(t) if u in tables]
    return seen == tables


def acyclic(pattern: JoinPattern) -> bool:
    """Ear removal: drop classes that only one table has left, then tables whose classes another table covers."""
    left = {t: set(pattern.classes_of(t)) for t in pattern.tables}
    changed = True
    while changed and len(left) > 1:
        changed = False
        for t in list(left):
            own = {c for c in left[t] if any(c in left[u] for u in left if u != t)}
            if any(own <= left[u] for u in left if u != t):
                del left[t]
                changed = True
                break
    return len(left) <= 1


def validate(pattern: JoinPattern, aliases: Mapping[str, str] | None = None, extend: Iterable[str] = ()) -> None:
    """Raise where the pattern is outside the model. ``extend``: "self_join" and "cycle" admit those."""
    base = [(aliases or {}).get(t, t) for t in pattern.tables]
    if len(set(base)) < len(base) and "self_join" not in extend:
        raise UnsupportedQuery("self-join")
    if not connected(pattern):
        raise UnsupportedQuery("cross product: the join graph is not connected")
    if not acyclic(pattern) and "cycle" not in extend:
        raise UnsupportedQuery("cyclic join")


def subplans(q: CountQuery, least: int = 1, most: int | None = None) -> list[CountQuery]:
    """All connected restrictions of a query, smallest first."""
    names = sorted(q.tables)
    out = []
    for n in range(least, (most or len(names)) + 1):
        for part in combinations(names, n):
            sub = restrict(q, part)
            if connected(sub.pattern):
                out.append(sub)
    return out
