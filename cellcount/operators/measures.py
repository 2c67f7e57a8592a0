"""Cost and accuracy measures: times and their bounds, speedups, wins, densities, compression, over-fetch, q-error."""

from __future__ import annotations

import resource
import time
from collections.abc import Callable, Mapping, Sequence
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.model import CountQuery, JoinPattern, column_of, partition_by_pattern, table_of
from ..plans.sqlfront import parse_count_query, render_sql
from . import baselines, cellmap
from .boxes import box_counts, boxes_of
from .engine import Options, context, evaluate_pattern, fold_tree, global_map, join_size, plan, range_overfetch, slice_table

METHODS = ("per_query", "shared_join", "grid")


@dataclass
class Observation:
    """Time of one method on one pattern; ``lower_bound``: a cap ended it. ``timed_out``: how many queries it lost."""

    workload: str
    pattern: JoinPattern
    method: str
    seconds: float
    lower_bound: bool
    n_queries: int
    timed_out: int = 0
    counts: dict[str, int] = field(default_factory=dict)


def run_pattern(spark: SparkSession, method: str, pattern: JoinPattern, queries: Sequence[CountQuery], tables: Mapping[str, DataFrame], opts: Options = Options(), query_cap: float | None = None, pattern_cap: float | None = None, workload: str = "") -> Observation:
    """One method on one pattern under its caps: seconds for each query alone, or for the pattern as a whole."""
    if method == "per_query":
        total, lost, counts = 0.0, 0, {}
        for q in queries:
            r = baselines.capped(spark, lambda q=q: baselines.one_query(q, tables).collect(), query_cap)
            total += r.seconds
            lost += r.lower_bound
            if not r.lower_bound:
                counts[q.id] = r.value[0]["n"]
        return Observation(workload, pattern, method, total, lost > 0, len(queries), lost, counts)
    run = {
        "grid": lambda: evaluate_pattern(pattern, queries, tables, opts).collect(),
        "shared_join": lambda: baselines.shared_join(pattern, queries, tables).collect(),
    }[method]
    r = baselines.capped(spark, run, pattern_cap)
    counts = {} if r.lower_bound else {q.id: 0 for q in queries} | {x["query_id"]: x["n"] for x in r.value}
    return Observation(workload, pattern, method, r.seconds, r.lower_bound, len(queries), len(queries) if r.lower_bound else 0, counts)


def time_workload(spark: SparkSession, method: str, queries: Sequence[CountQuery], tables: Mapping[str, DataFrame], name: str = "", **kw) -> list[Observation]:
    """An observation for each pattern, in order of first appearance."""
    return [run_pattern(spark, method, p, qs, tables, workload=name, **kw) for p, qs in partition_by_pattern(queries).items()]


def end_to_end(obs: Sequence[Observation], preprocess_s: float = 0.0) -> tuple[float, bool]:
    """Seconds of a workload, and whether they are a lower bound."""
    return preprocess_s + sum(o.seconds for o in obs), any(o.lower_bound for o in obs)


def speedup(base: tuple[float, bool], ours: tuple[float, bool]) -> tuple[float, bool]:
    """base / ours; a lower bound where the base's time is one."""
    return base[0] / max(ours[0], 1e-9), base[1]


def timeouts(obs: Sequence[Observation]) -> tuple[int, int]:
    """(queries, patterns) that ran into a cap."""
    return sum(o.timed_out for o in obs), sum(o.lower_bound for o in obs)


def wins(ours: Sequence[Observation], base: Sequence[Observation]) -> int:
    """Patterns on which the first is faster."""
    other = {o.pattern: o.seconds for o in base}
    return sum(o.seconds < other[o.pattern] for o in ours)


def regressions(ours: Sequence[Observation], base: Sequence[Observation]) -> list[tuple[str, float]]:
    """(pattern, seconds lost) where the first is slower, worst first."""
    other = {o.pattern: o.seconds for o in base}
    lost = [(o.pattern.key, o.seconds - other[o.pattern]) for o in ours if o.seconds > other[o.pattern]]
    return sorted(lost, key=lambda x: -x[1])


def per_pattern_times(obs: Mapping[str, Sequence[Observation]]) -> list[tuple[str, dict[str, float]]]:
    """Seconds by method for each pattern, ordered by the per_query time."""
    by: dict[JoinPattern, dict[str, float]] = {}
    for m, os in obs.items():
        for o in os:
            by.setdefault(o.pattern, {})[m] = o.seconds
    return sorted(((p.key, t) for p, t in by.items()), key=lambda x: x[1].get("per_query", 0.0))


def preprocess_time(queries: Sequence[CountQuery]) -> float:
    """Seconds to parse a batch's text and split it by pattern."""
    texts = [render_sql(q) for q in queries if not q.others]
    t = time.time()
    partition_by_pattern(parse_count_query(x, str(k)) for k, x in enumerate(texts))
    return time.time() - t


def cost_breakdown(pattern: JoinPattern, queries: Sequence[CountQuery], tables: Mapping[str, DataFrame], opts: Options = Options()) -> dict[str, float]:
    """Seconds of a pattern's phases run one after the other: table scans with grouping, multiplying maps, reading boxes."""
    ctx = context(pattern, queries, tables, opts)
    node = plan(ctx)

    def timed(run: Callable[[], object]) -> float:
        t = time.time()
        run()
        return time.time() - t

    def leaves(n, keep):
        yield slice_table(ctx, n, sorted({*keep, *[k for c in n.children for k in c.keys]}))
        for c in n.children:
            yield from leaves(c, c.keys)

    sink = lambda df: df.write.format("noop").mode("overwrite").save()
    table_s = timed(lambda: [sink(m) for m in leaves(node, ())])
    whole = fold_tree(ctx, node).persist()
    tree_s = timed(lambda: whole.count())
    box_s = timed(lambda: box_counts(whole, boxes_of(queries, ctx.dims, ctx.scales), list(ctx.dims), opts.box_impl, ctx.scales).collect())
    whole.unpersist()
    return {"tables": table_s, "multiply": max(0.0, tree_s - table_s), "boxes": box_s}


def driver_peak_mb() -> float:
    """Largest resident size of the driver's Python so far."""
    return resource.getrusage(resource.RUSAGE_SELF).ru_maxrss / 1024


def executor_peak_mb(spark: SparkSession) -> float:
    """The largest heap and off-heap use of one executor's JVM so far, as its heartbeats and ended tasks reported it.

    Where no report has come yet (a short local run) the peaks of this JVM's own memory pools.
    """
    found = spark.sparkContext._jsc.sc().statusStore().executorList(False)
    most, it = 0, found.iterator()
    while it.hasNext():
        peak = it.next().peakMemoryMetrics()
        if peak.isDefined():
            most = max(most, sum(peak.get().getMetricValue(m) for m in ("JVMHeapMemory", "JVMOffHeapMemory")))
    if not most and spark.sparkContext.master.startswith("local"):
        pools = spark.sparkContext._jvm.java.lang.management.ManagementFactory.getMemoryPoolMXBeans()
        most = sum(p.getPeakUsage().getUsed() for p in pools)
    return most / 1e6


def map_density(pattern: JoinPattern, queries: Sequence[CountQuery], tables: Mapping[str, DataFrame], opts: Options = Options()) -> tuple[int, int]:
    """(non-zero cells, all cells of the grid) of a pattern's last map; ids run from 0."""
    ctx = context(pattern, queries, tables, opts)
    cells = 1
    for d in ctx.dims:
        cells *= ctx.scales[d].size + 1
    return global_map(ctx).count(), cells


def compression(pattern: JoinPattern, queries: Sequence[CountQuery], tables: Mapping[str, DataFrame], opts: Options = Options()) -> dict[str, int]:
    """Rows of the full join, of all leaf maps together, and of the last map."""
    ctx = context(pattern, queries, tables, opts)
    node = plan(ctx)
    leaf = 0

    def walk(n, keep):
        nonlocal leaf
        leaf += slice_table(ctx, n, sorted({*keep, *[k for c in n.children for k in c.keys]})).count()
        for c in n.children:
            walk(c, c.keys)

    walk(node, ())
    return {"join_rows": join_size(pattern, tables).first()["n"], "leaf_cells": leaf, "map_cells": fold_tree(ctx, node).count()}


def overfetch(pattern: JoinPattern, queries: Sequence[CountQuery], tables: Mapping[str, DataFrame], beta: int) -> list[tuple[str, int, int, int]]:
    """(child, batch, fetched, used) of the batched strategy's key ranges."""
    ctx = context(pattern, queries, tables, Options(fold="none"))
    return range_overfetch(ctx, plan(ctx), beta)


def workload_summary(queries: Sequence[CountQuery]) -> dict[str, int]:
    """Queries, fewest and most tables, patterns, and patterns with all single tables counted as one."""
    sizes = [len(q.tables) for q in queries]
    patterns = {q.pattern for q in queries}
    joins = sum(len(p.tables) > 1 for p in patterns)
    return {"n_queries": len(queries), "min_tables": min(sizes), "max_tables": max(sizes), "n_patterns": len(patterns), "n_patterns_collapsed": joins + (len(patterns) > joins)}


def values_of(batches: Sequence[Sequence[CountQuery]], tables: Mapping[str, DataFrame]) -> list[int]:
    """For each batch the values that its scans have to quantize: those of its selection attributes that are not null.

    One scan of each table for all batches; ``count`` reads the columns.
    """
    attrs = [sorted({a for q in b for x in q.boxes() for a in x}) for b in batches]
    found: dict[str, int] = {}
    for table in sorted({table_of(a) for own in attrs for a in own}):
        own = sorted({a for x in attrs for a in x if table_of(a) == table})
        found |= zip(own, tables[table].agg(*[F.count(column_of(a)) for a in own]).first(), strict=True)
    return [sum(found[a] for a in own) for own in attrs]


def cardinality_range(counts: DataFrame) -> DataFrame:
    """One row: smallest, median and largest count of a workload."""
    return counts.agg(F.min("n").alias("min_n"), F.percentile("n", F.lit(0.5)).alias("median_n"), F.max("n").alias("max_n"))


def q_error(estimates: DataFrame, truth: DataFrame) -> DataFrame:
    """query_id, q_error: the larger of the two ratios of estimate and true count, both at least 1."""
    e = F.greatest(F.col("n").cast("double"), F.lit(1.0))
    t = F.greatest(F.col("true_n").cast("double"), F.lit(1.0))
    return estimates.join(truth.withColumnRenamed("n", "true_n"), "query_id").select("query_id", F.greatest(e / t, t / e).alias("q_error"))


__all__ = ["Observation", "run_pattern", "time_workload", "end_to_end", "speedup", "timeouts", "wins", "regressions", "per_pattern_times", "preprocess_time", "cost_breakdown", "map_density", "compression", "overfetch", "workload_summary", "cardinality_range", "q_error", "cellmap"]
