"""Workload generators: deterministic batches over the given tables' join graph, their sub-plans and rescalings."""

from __future__ import annotations

import random
from collections.abc import Iterable, Sequence
from dataclasses import replace
from datetime import datetime, timedelta

from ..sources.catalog import EDGES
from .model import CountQuery, Interval, UnsupportedQuery, column_of, compare, subplans, table_of, validate
from .sqlfront import parse_count_query

# The active domains of the selection attributes as (first, step, number) rules or lists.
_DAY = timedelta(days=1)
DOMAINS: dict[str, tuple] = {
    "lineitem.l_quantity": ("num", 1.0, 1.0, 50),
    "lineitem.l_discount": ("cents", 0, 1, 11),
    "lineitem.l_tax": ("cents", 0, 1, 9),
    "lineitem.l_extendedprice": ("num", 1000.0, 1000.0, 100),
    "lineitem.l_shipdate": ("day", datetime(1995, 1, 10), 10, 245),
    "lineitem.l_returnflag": ("list", ["A", "N", "R"]),
    "lineitem.l_linestatus": ("list", ["F", "O"]),
    "orders.o_totalprice": ("num", 5000.0, 5000.0, 98),
    "orders.o_orderdate": ("day", datetime(1995, 1, 10), 10, 238),
    "orders.o_orderstatus": ("list", ["F", "O", "P"]),
    "orders.o_orderpriority": ("list", ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"]),
    "customer.c_acctbal": ("num", -900.0, 100.0, 108),
    "customer.c_mktsegment": ("list", ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]),
    "supplier.s_acctbal": ("num", -800.0, 100.0, 106),
    "part.p_size": ("int", 1, 1, 50),
    "part.p_retailprice": ("num", 900.0, 1.0, 100),
    "nation.n_regionkey": ("int", 0, 1, 5),
    "nation.n_nationkey": ("int", 0, 1, 25),
    "region.r_regionkey": ("int", 0, 1, 5),
    "events.value": ("num", 1.0, 2.0, 240),
    "events.event_type": ("list", ["click", "error", "purchase", "signup", "view"]),
    "events.ts": ("day", datetime(2024, 1, 1), 1, 30),
}
#: Attributes whose type is text; some workloads leave them out.
TEXT = {a for a, d in DOMAINS.items() if d[0] == "list"}


def value(attr: str, k: int):
    """The k-th constant of an attribute's domain."""
    kind, *rule = DOMAINS[attr]
    if kind == "list":
        return rule[0][k % len(rule[0])]
    first, step, n = rule
    k %= n
    if kind == "cents":
        return float(f"{(first + k * step) / 100:.2f}")
    return first + k * step * _DAY if kind == "day" else first + k * step


def size(attr: str) -> int:
    kind, *rule = DOMAINS[attr]
    return len(rule[0]) if kind == "list" else rule[2]


def pattern(code: str) -> tuple[list[str], list[tuple[str, str]]]:
    """Tables and joins of "edge+edge" codes, or of a single table's name."""
    if code in {table_of(a) for a in DOMAINS}:
        return [code], []
    joins = [EDGES[e] for e in code.split("+")]
    return sorted({table_of(a) for j in joins for a in j}), joins


# The join patterns of each workload, by edge codes.
SINGLES = ("lineitem", "orders", "customer", "events")
W1 = (*SINGLES, "rn", "nc", "ns", "co", "ce", "ol", "lp", "ls", "co+ce", "co+ol", "nc+co", "lp+ls", "ol+lp", "nc+ns", "ns+ls")
W2 = (
    *SINGLES, "co", "ce", "ol", "lp", "nc",
    "co+ce", "co+ol", "oe+ol", "ol+lp", "ol+ls", "lp+ls", "nc+co", "nc+ce", "ns+ls", "nc+ns",
    "co+ce+ol", "co+ol+lp", "co+ol+ls", "ol+lp+ls", "nc+co+ce", "nc+co+ol", "rn+nc+co", "nc+ns+co", "nc+ns+ce", "nc+ns+ls",
    "co+ce+ol+lp", "co+ol+lp+ls", "nc+co+ce+ol", "nc+ns+co+ce", "nc+ns+co+ls",
)
W3 = ("co", "ce", "ol", "lp", "ls", "co+ce", "co+ol", "ol+lp", "ol+ls", "lp+ls", "co+ce+ol", "co+ol+lp", "ol+lp+ls", "nc+co+ce", "co+ce+ol+lp", "co+ol+lp+ls", "nc+co+ce+ol", "nc+ns+co+ls")
W6 = tuple(
    "nc ns co ce ol ls oe cs "
    "rn+nc rn+ns nc+ns nc+co nc+ce ns+ls co+ce co+ol co+cs ce+cs ol+lp ol+ls "
    "rn+nc+ns rn+nc+co rn+nc+ce rn+ns+ls nc+ns+co nc+ns+ce nc+ns+ls nc+co+ce nc+co+ol ns+ol+ls ns+lp+ls co+ce+ol co+ce+cs co+ol+lp "
    "rn+nc+ns+co rn+nc+ns+ls rn+nc+co+ol rn+ns+lp+ls nc+ns+co+ol nc+ns+ce+ls nc+ns+lp+ls nc+co+ol+lp ns+co+ol+ls ns+ol+ls+oe co+ce+ol+ls co+ce+ls+cs "
    "rn+nc+ns+co+ce rn+nc+ns+ce+ls rn+nc+co+ce+ol rn+ns+co+ol+ls nc+ns+co+ce+ol nc+ns+co+lp+ls nc+ns+ol+lp+ls nc+co+ce+ol+ls "
    "rn+nc+ns+co+ce+ol rn+nc+ns+ce+lp+ls rn+nc+co+ol+lp+ls nc+ns+co+ce+lp+ls".split()
)
W9 = ("lineitem", "ol", "lp", "ls", "ol+lp", "ol+ls", "lp+ls", "ol+lp+ls", "co+ol", "co+ol+lp", "co+ol+ls", "co+ol+lp+ls", "ns+ls", "ns+ls+lp", "ns+ls+ol", "ns+ls+lp+ol")
#: workload -> patterns, most conditions, text attributes, share of equalities, full and small number of queries
SPECS = {
    "w1": (W1, 4, True, 0.3, 5000, 160),
    "w2": (W2, 4, True, 0.3, 500, 93),
    "w3": (W3, 3, False, 0.2, 70, 70),
    "w6": (W6, 5, True, 0.35, 146, 58),
    "w9": (W9, 6, False, 0.0, 20_000, 160),
}


def make(name: str, n: int | None = None, seed: int = 42) -> list[CountQuery]:
    """The queries of w1, w2, w3, w6 or w9; ``n`` None: the full size."""
    patterns, most, text, equal, full, _ = SPECS[name]
    rng = random.Random(f"{name}-{seed}")
    n = n or full
    out = []
    for k in range(n):
        tables, joins = pattern(patterns[k % len(patterns)])
        attrs = sorted(a for a in DOMAINS if table_of(a) in tables and (text or a not in TEXT))
        chosen = rng.sample(attrs, min(len(attrs), rng.randint(1, most)))
        out.append(CountQuery.build(f"{name}_{k:05d}", tables, joins, [(a, condition(rng, a, equal)) for a in chosen]))
    return out


def full(name: str) -> list[CountQuery]:
    """A workload at its full size: w1 to w9, or s1k, s2k, s4k."""
    if name in SPECS:
        qs = make(name)
        return filter_supported(qs, numeric_only=True) if name == "w9" else qs
    if name.startswith("s"):
        return rescale(make("w3"), 1000 * int(name[1:-1]), name=name)
    base = make("w3" if name in ("w4", "w5") else "w6")
    return derived(base, name, single=name in ("w4", "w7"))


#: All workloads, in order.
ALL = ("w1", "w2", "w3", "w4", "w5", "w6", "w7", "w8", "w9", "s1k", "s2k", "s4k")


def small(name: str, seed: int = 42) -> list[CountQuery]:
    """The workload at the size that its correctness query uses."""
    return make(name, SPECS[name][5], seed)


def condition(rng: random.Random, attr: str, equal: float = 0.3) -> Interval:
    """A random comparison: an equality, one side, or a range."""
    m = size(attr)
    a, b = sorted((rng.randrange(m), rng.randrange(m)))
    kind = rng.random()
    if kind < equal or DOMAINS[attr][0] == "list" and kind < 0.7:
        return compare("=", value(attr, a))
    if kind < equal + (1 - equal) * 0.6 or a == b:
        return compare(rng.choice(("<", "<=", ">", ">=")), value(attr, a))
    lo, hi = (value(attr, a), value(attr, b)) if DOMAINS[attr][0] != "list" else sorted((value(attr, a), value(attr, b)))
    return Interval(lo, rng.random() < 0.5, hi, rng.random() < 0.5) if lo != hi else compare("=", lo)


def derived(queries: Sequence[CountQuery], name: str, single: bool, per_pattern: int | None = None) -> list[CountQuery]:
    """The distinct sub-plans of a workload: single tables, or connected joins; ``per_pattern`` keeps the first few."""
    seen, kept, out = set(), {}, []
    for q in queries:
        for s in subplans(q, 1 if single else 2, 1 if single else None):
            key = (s.pattern, s.ranges)
            if key in seen:
                continue
            seen.add(key)
            kept[s.pattern] = kept.get(s.pattern, 0) + 1
            if per_pattern is None or kept[s.pattern] <= per_pattern:
                out.append(replace(s, id=f"{name}_{len(out):05d}"))
    return out


def rescale(queries: Sequence[CountQuery], n: int, seed: int = 42, name: str = "s") -> list[CountQuery]:
    """``n`` queries from random templates: one-sided and equality constants from the active domain, two-sided
    ranges moved to a random left end with their length kept."""
    rng = random.Random(f"rescale-{seed}")
    out = []
    for k in range(n):
        q = queries[k % len(queries)] if k < len(queries) else rng.choice(queries)
        ranges = []
        for a, i in q.ranges:
            if i.lo is not None and i.hi is not None and not i.point:
                lo = value(a, rng.randrange(size(a)))
                hi = lo + (i.hi - i.lo) if not isinstance(lo, str) else i.hi
                ranges.append((a, Interval(lo, i.lo_incl, float(f"{hi:.2f}") if isinstance(hi, float) else hi, i.hi_incl)))
            else:
                v = value(a, rng.randrange(size(a)))
                ranges.append((a, Interval(None if i.lo is None else v, i.lo_incl, None if i.hi is None else v, i.hi_incl)))
        out.append(replace(q, id=f"{name}_{k:05d}", ranges=tuple(ranges)))
    return out


def filter_supported(queries: Iterable[CountQuery], numeric_only: bool = False) -> list[CountQuery]:
    """The queries inside the model, and without text attributes where asked."""
    out = []
    for q in queries:
        try:
            validate(q.pattern, dict(q.aliases))
        except UnsupportedQuery:
            continue
        if not (numeric_only and any(isinstance(x, str) for _, i in q.ranges for x in (i.lo, i.hi))):
            out.append(q)
    return out


def sample(queries: Sequence[CountQuery], n: int, seed: int = 42) -> list[CountQuery]:
    return sorted(random.Random(seed).sample(list(queries), min(n, len(queries))), key=lambda q: q.id)


def x1() -> list[CountQuery]:
    """Four queries in three patterns."""
    t = datetime(1998, 6, 30)
    return [
        CountQuery.build("x1_a", *pattern("co"), [("customer.c_acctbal", compare(">=", 0.0))]),
        CountQuery.build("x1_b", *pattern("oe"), [("events.event_type", compare("=", "click")), ("orders.o_orderdate", compare("<=", t))]),
        CountQuery.build("x1_c", *pattern("cs"), [("customer.c_mktsegment", compare("=", "BUILDING")), ("supplier.s_acctbal", compare(">=", 0.0))]),
        CountQuery.build("x1_d", *pattern("cs"), [("customer.c_acctbal", compare("<=", 5000.0))]),
    ]


def x2() -> list[CountQuery]:
    """A hub with a foldable child, a many-side child and a two-table subtree."""
    tables, joins = pattern("nc+co+ce+ol")
    sets = [
        [], [("nation.n_regionkey", compare("=", 1))],
        [("events.event_type", compare("=", "purchase")), ("events.value", compare(">=", 50.0))],
        [("orders.o_totalprice", compare("<", 100000.0)), ("lineitem.l_quantity", compare(">", 25.0))],
        [("nation.n_regionkey", compare(">=", 2)), ("customer.c_mktsegment", compare("=", "MACHINERY")), ("events.event_type", compare("=", "view")), ("orders.o_orderstatus", compare("=", "F")), ("lineitem.l_discount", Interval(0.02, True, 0.04, True))],
        [("events.value", compare("<", 0.0))],
    ]
    rng = random.Random("x2")
    attrs = sorted(a for a in DOMAINS if table_of(a) in tables)
    sets += [[(a, condition(rng, a)) for a in rng.sample(attrs, 3)] for _ in range(6)]
    return [CountQuery.build(f"x2_{k:02d}", tables, joins, s) for k, s in enumerate(sets)]


def flagship() -> list[CountQuery]:
    """Five tables through one nation key: tens of millions of join rows at a small scale."""
    tables, joins = pattern("nc+ns+co+ls")
    sets = [
        [], [("customer.c_acctbal", compare(">", 9000.0))],
        [("orders.o_orderdate", compare(">=", datetime(2000, 1, 1))), ("lineitem.l_quantity", compare("=", 1.0))],
        [("supplier.s_acctbal", compare("<", 0.0)), ("orders.o_orderpriority", compare("=", "1-URGENT"))],
        [("nation.n_regionkey", compare("=", 3)), ("lineitem.l_returnflag", compare("=", "N")), ("lineitem.l_tax", compare("=", 0.08))],
    ]
    return [CountQuery.build(f"flag_{k}", tables, joins, s) for k, s in enumerate(sets)]


def singles() -> list[CountQuery]:
    """Twelve queries over one table, among them one without match, one contradiction and one without conditions."""
    d = datetime
    sets = [
        [("l_quantity", compare("<", 24.0))],
        [("l_quantity", Interval(10.0, True, 20.0, True)), ("l_discount", compare("<=", 0.05))],
        [("l_discount", compare("=", 0.05))],
        [("l_shipdate", Interval(d(1997, 1, 1), True, d(1998, 1, 1), False))],
        [("l_returnflag", compare("=", "R"))],
        [("l_returnflag", compare("=", "A")), ("l_linestatus", compare("=", "F")), ("l_quantity", compare(">", 45.0))],
        [("l_tax", Interval(0.02, False, 0.06, True))],
        [("l_extendedprice", compare(">=", 100000.0))],
        [("l_linenumber", compare("=", 7)), ("l_discount", compare(">=", 0.1))],
        [("l_quantity", compare(">", 50.0))],
        [("l_quantity", compare(">=", 30.0)), ("l_quantity", compare("<", 30.0))],
        [],
    ]
    return [CountQuery.build(f"fx1_{k + 1:02d}", ["lineitem"], (), [(f"lineitem.{a}", i) for a, i in s]) for k, s in enumerate(sets)]


def of_pattern(code: str, n: int, seed: str = "p", most: int = 3, equal: float = 0.3) -> list[CountQuery]:
    """``n`` random queries of one pattern."""
    tables, joins = pattern(code)
    rng = random.Random(f"{code}-{seed}")
    attrs = sorted(a for a in DOMAINS if table_of(a) in tables)
    return [CountQuery.build(f"{code.replace('+', '_')}_{k:02d}", tables, joins, [(a, condition(rng, a, equal)) for a in rng.sample(attrs, min(len(attrs), rng.randint(1, most)))]) for k in range(n)]


def read_sql(spark, path: str, prefix: str = "f") -> list[CountQuery]:
    """A workload file: a query on each line, the known count after ``||`` where given."""
    lines = [r["value"] for r in spark.read.text(path).collect()]
    return [parse_count_query(x, f"{prefix}_{k:05d}") for k, x in enumerate(y for y in lines if y.strip())]


__all__ = ["column_of", "make", "full", "small", "derived", "rescale", "filter_supported", "sample", "x1", "x2", "flagship", "singles", "of_pattern", "read_sql"]
