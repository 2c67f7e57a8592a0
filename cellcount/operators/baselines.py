"""The two methods that grid counting is compared with: every query alone, and one shared join per pattern."""

from __future__ import annotations

import threading
import time
from collections.abc import Callable, Mapping, Sequence
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.scales import literal
from ..plans import tree
from ..plans.model import CountQuery, Interval, JoinPattern, column_of, table_of
from ..sources.catalog import CATALOG
from ..sources.results import local_counts
from ..sources.shared import discard, fresh, size_of
from . import boxes as box_ops
from .boxes import boxes_of
from .engine import Options, context, quantize

#: Conditional counts in one aggregate; more would not compile to one method.
CHUNK = 200
#: Rows of a table whose map is broadcast below the joins: a few MB on the driver.
BROADCAST_ROWS = 100_000


def holds(ranges, rename=lambda a: column_of(a)) -> Column:
    """A conjunction of ranges as a condition on columns."""
    out = F.lit(True)
    for attr, i in ranges:
        out = out & within(F.col(rename(attr)), i)
    return out


def within(c: Column, i: Interval) -> Column:
    if i.point:
        return c == literal(i.lo)
    out = c.isNotNull()
    if i.lo is not None:
        out = out & (c >= literal(i.lo) if i.lo_incl else c > literal(i.lo))
    if i.hi is not None:
        out = out & (c <= literal(i.hi) if i.hi_incl else c < literal(i.hi))
    return out


def one_query(q: CountQuery, tables: Mapping[str, DataFrame], eager_agg: bool = False) -> DataFrame:
    """One row, query_id and n. ``eager_agg``: count below the joins by hand, which the optimizer does not do."""
    if eager_agg and q.boxes():
        return counted_below(q.pattern, [q], tables)
    chosen = reduce(lambda a, b: a | b, [holds(tuple(b.items()), _flat) for b in q.boxes()]) if q.boxes() else F.lit(False)
    return full_join(q.pattern, tables, dict(q.aliases)).where(chosen).agg(F.count(F.lit(1)).alias("n")).select(F.lit(q.id).alias("query_id"), "n")


def counted_below(pattern: JoinPattern, queries: Sequence[CountQuery], tables: Mapping[str, DataFrame]) -> DataFrame:
    """query_id, n of a pattern's queries by one shared join that is never listed: conditional counts below the joins.

    Every table but the root becomes a map with a row for each key that its parent has, and a count for each box of the queries,
    of the rows that meet the box's conditions on that table and below. Rows are joined to such maps only, so they never outnumber
    their own table's, and are added up where the map is made; those of a table with one key, or with one left after its broadcast maps, are added up before, unless the key is unique. A conjunction of
    ranges is the product of its tables' conditions, so the sums are the counts over the full join, whose rows don't appear. A product beyond 64 bits raises.
    Maps of tables with up to ``BROADCAST_ROWS`` rows are broadcast, where the tables know their numbers of rows. A declared
    key that is not unique costs rows, and changes no count.
    """
    aliases = dict(queries[0].aliases)
    boxes = [(q.id, b) for q in queries for b in q.boxes()]
    names = [f"q{i}" for i in range(len(boxes))]
    some = reduce(lambda a, b: a | b, [F.col(n) != 0 for n in names])

    def own(t: str, keys: Sequence[int]) -> DataFrame:
        df, columns = tables[t], {i: [column_of(a) for a in pattern.attrs(t, i)] for i in pattern.classes_of(t)}
        for c in columns.values():
            df = df.where(F.col(c[0]).isNotNull())
            for o in c[1:]:
                df = df.where(F.col(c[0]) == F.col(o))
        parts = [holds(tuple((a, r) for a, r in b.items() if table_of(a) == t)) for _, b in boxes]
        counts = [F.lit(1)] if len(parts) == 1 else [F.when(c, 1).otherwise(0) for c in parts]
        df = df.where(reduce(lambda a, b: a | b, parts))
        return df.select(*[F.col(columns[i][0]).alias(f"k{i}") for i in keys], *[c.cast("long").alias(n) for c, n in zip(counts, names, strict=True)])

    def unique(t: str, keys: Sequence[int]) -> bool:
        return CATALOG[aliases.get(t, t)].pk in {column_of(a) for i in keys for a in pattern.attrs(t, i)}

    def added(m: DataFrame, keys: Sequence[int]) -> DataFrame:
        return m.groupBy(*[f"k{k}" for k in keys]).agg(*[F.sum(n).alias(n) for n in names])

    def below(node, keep: Sequence[int]) -> DataFrame:
        need = sorted({*keep, *[k for c in node.children for k in c.keys]})
        m, met = own(node.table, need), [c.keys for c in node.children]
        small = {c.table: hasattr(tables, "rows") and tables.rows(c.table) <= BROADCAST_ROWS for c in node.children}
        left = sorted(node.children, key=lambda c: (not small[c.table], met.index(c.keys)))  # rows are dealt once for a key, not for each child
        if len(need) == 1 and not unique(node.table, need):
            m = added(m, need)
        while left:
            c = left.pop(0)
            child = below(c, c.keys)
            child = child.select(*[f"k{k}" for k in c.keys], *[F.col(n).alias(f"_{n}") for n in names])
            if small[c.table]:
                child = F.broadcast(child)
            now = sorted({*keep, *[k for x in left for k in x.keys]})
            m = m.join(child, [f"k{k}" for k in c.keys]).select(*[f"k{k}" for k in now], *[(F.col(n) * F.col(f"_{n}")).alias(n) for n in names])
            if len(names) > 1:
                m = m.where(some)
            if small[c.table] and left and not small[left[0].table] and len(now) == 1 < len(need) and not unique(node.table, now):
                m = added(m, now)  # one key is left, by which rows are dealt next
        return m if not keep or need == sorted(keep) or unique(node.table, keep) else added(m, keep)

    node = tree.build_tree(pattern, tree.choose_root(pattern, aliases=aliases), aliases)
    row = below(node, ()).agg(*[F.coalesce(F.sum(n), F.lit(0).cast("long")).alias(n) for n in names])
    own_boxes = {q.id: [n for n, (i, _) in zip(names, boxes, strict=True) if i == q.id] for q in queries}
    listed = ", ".join(f"'{q}', {' + '.join(ns)}" for q, ns in own_boxes.items() if ns)
    return row.selectExpr(f"stack({sum(map(bool, own_boxes.values()))}, {listed}) as (query_id, n)")


def _flat(attr: str) -> str:
    return attr.replace(".", "__")


def full_join(pattern: JoinPattern, tables: Mapping[str, DataFrame], aliases: Mapping[str, str] | None = None, columns: set[str] | None = None) -> DataFrame:
    """The join of a pattern with columns ``table__column``; Catalyst prunes what nothing reads."""
    aliases = aliases or {}

    def side(t: str) -> DataFrame:
        df = tables[t]
        out = df.select(*[F.col(c).alias(f"{t}__{c}") for c in df.columns])
        for i in pattern.classes_of(t):
            own = pattern.attrs(t, i)
            for o in own[1:]:
                out = out.where(F.col(_flat(own[0])) == F.col(_flat(o)))
        return out

    node = tree.build_tree(pattern, tree.choose_root(pattern, aliases=aliases), aliases)
    out = side(node.table)

    def walk(n, out):
        for c in n.children:
            on = reduce(lambda a, b: a & b, [F.col(_flat(pattern.attrs(n.table, k)[0])) == F.col(_flat(pattern.attrs(c.table, k)[0])) for k in c.keys])
            out = walk(c, out.join(side(c.table), on))
        return out

    return walk(node, out)


def per_query(spark: SparkSession, queries: Sequence[CountQuery], tables: Mapping[str, DataFrame], eager_agg: bool = False, chunk: int = 16) -> DataFrame:
    """query_id, n: each query planned and run by itself; plans are united in small chunks, not in one deep union.

    With ``eager_agg`` one after the other, so that the driver holds one query's plan and stages.
    """
    rows, chunk = [], 1 if eager_agg else chunk
    for s in range(0, len(queries), chunk):
        part = [one_query(q, tables, eager_agg) for q in queries[s : s + chunk]]
        rows += [(r["query_id"], r["n"]) for r in reduce(DataFrame.unionByName, part).collect()]
    return local_counts(spark, rows)


def shared_join(pattern: JoinPattern, queries: Sequence[CountQuery], tables: Mapping[str, DataFrame], materialize: bool = False, prefilter: str | None = None, postfilter: str = "case", chunk: int = CHUNK, wide: bool = False, eager_agg: bool = False) -> DataFrame:
    """query_id, n: join once per pattern, then a conditional count for each query; with ``eager_agg`` these counts go below
    the joins (``counted_below``), which a join with far more rows than its tables needs.

    ``materialize``: write the join to the shared folder once and read it for each chunk; it is deleted with the counts known; ``prefilter="hull"``: keep only rows between the smallest
    and largest constants where every query constrains an attribute; ``postfilter="boxes"``: index the queries as
    boxes and meet each join row with the broadcast boxes; ``wide``: one row with a column for each query.
    """
    if eager_agg:
        some = [q for q in queries if q.boxes()]
        parts = [counted_below(pattern, some[s : s + chunk], tables) for s in range(0, len(some), chunk)]
        return reduce(DataFrame.unionByName, parts) if parts else tables[min(pattern.tables)].sparkSession.createDataFrame([], "query_id string, n bigint")
    j = full_join(pattern, tables, dict(queries[0].aliases))
    attrs = sorted({a for q in queries for b in q.boxes() for a in b})
    used = [_flat(a) for a in attrs]
    if prefilter == "hull":
        for a in attrs:
            spans = [b.get(a) for q in queries for b in q.boxes()]
            if all(spans):
                lo = None if any(s.lo is None for s in spans) else min(s.lo for s in spans)
                hi = None if any(s.hi is None for s in spans) else max(s.hi for s in spans)
                j = j.where(within(F.col(_flat(a)), Interval(lo, True, hi, True)))
    j = j.select(*used)
    if materialize:
        spark, path = j.sparkSession, fresh(j.sparkSession, "join")
        j = j if used else j.select(F.lit(1).alias("one"))
        j.write.parquet(path)
        whole = shared_counts(spark.read.schema(j.schema).parquet(path), pattern, queries, tables, postfilter, chunk, wide)
        rows = whole.collect()  # a row for each query, or one row
        discard(spark, path)
        return spark.createDataFrame(rows, whole.schema)
    return shared_counts(j, pattern, queries, tables, postfilter, chunk, wide)


def shared_counts(j: DataFrame, pattern: JoinPattern, queries: Sequence[CountQuery], tables: Mapping[str, DataFrame], postfilter: str, chunk: int, wide: bool) -> DataFrame:
    """The queries' counts from the selection columns of their join."""
    if postfilter == "boxes":
        ctx = context(pattern, queries, tables, Options(prune=False))
        dims = ctx.dims
        ids = j.select(*[quantize(F.col(_flat(a)), ctx.scales[d]).alias(d) for d, a in dims.items()], F.lit(1).cast("long").alias("n"))
        return box_ops.box_join(ids, boxes_of(queries, dims, ctx.scales), list(dims)).groupBy("query_id").agg(F.sum("n").alias("n"))
    out = None
    for s in range(0, len(queries), chunk):
        part = queries[s : s + chunk]
        counts = []
        for k, q in enumerate(part):
            box = reduce(lambda a, b: a | b, [holds(tuple(b.items()), _flat) for b in q.boxes()]) if q.boxes() else F.lit(False)
            counts.append(F.count(F.when(box, 1)).alias(q.id if wide else f"q{k}"))
        row = j.agg(*counts)
        if not wide:
            names = ", ".join(f"'{q.id}', q{k}" for k, q in enumerate(part))
            row = row.selectExpr(f"stack({len(part)}, {names}) as (query_id, n)")
        out = row if out is None else (out.crossJoin(row) if wide else out.unionByName(row))
    return out


def materialized_join(pattern: JoinPattern, queries: Sequence[CountQuery], tables: Mapping[str, DataFrame]) -> dict[str, float]:
    """Rows, bytes on disk and seconds of preparing a pattern's join for its queries; the files are deleted again."""
    attrs = sorted({_flat(a) for q in queries for b in q.boxes() for a in b})
    j = full_join(pattern, tables, dict(queries[0].aliases)).select(*attrs or [F.lit(1).alias("one")])
    spark, path, t = j.sparkSession, fresh(j.sparkSession, "join"), time.time()
    j.write.parquet(path)
    out = {"seconds": time.time() - t, "bytes": float(size_of(spark, path)), "rows": float(spark.read.schema(j.schema).parquet(path).count())}
    discard(spark, path)
    return out


@dataclass(frozen=True)
class TimedResult:
    """Seconds of a run; ``lower_bound`` where the cap ended it."""

    seconds: float
    lower_bound: bool
    value: object = None


def capped(spark: SparkSession, run: Callable[[], object], timeout_s: float | None) -> TimedResult:
    """Run an action; past ``timeout_s`` its jobs are cancelled by their tag, and the time counts as a lower bound."""
    if timeout_s is None:
        return _plain(run)
    sc = spark.sparkContext
    tag = f"cap-{threading.get_ident()}-{time.time_ns()}"
    ended = threading.Event()

    def watch():
        if not ended.wait(timeout_s):
            over.set()
            while not ended.wait(0.2):  # a job may start just after a cancellation
                sc.cancelJobsWithTag(tag)

    over = threading.Event()
    threading.Thread(target=watch, daemon=True).start()
    sc.addJobTag(tag)
    t = time.time()
    try:
        value = run()
        return TimedResult(time.time() - t, False, value)
    except Exception:
        if not over.is_set():
            raise
        return TimedResult(time.time() - t, True)
    finally:
        ended.set()
        sc.removeJobTag(tag)


def _plain(run: Callable[[], object]) -> TimedResult:
    t = time.time()
    value = run()
    return TimedResult(time.time() - t, False, value)


def tables_of(q: CountQuery) -> list[str]:
    return sorted({table_of(a) for c in q.classes for a in c} | q.tables)
