"""Cell maps over streams: counts of disjoint rows add, so a stored map only needs the new rows' map added.

Scales are fixed by the workload. A new query with a constant that is no cut of the stored scales needs a new map
from the source; ``MapState.fits`` says so.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Sequence
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import cellmap
from ..operators.boxes import box_counts, box_join, boxes_of
from ..operators.engine import Context, Options, context, fold_tree, plan, slice_table
from ..plans.model import CountQuery, table_of
from ..plans.tree import PlanNode
from ..sources.shared import discard


def scale_version(ctx: Context) -> str:
    """A name for a set of scales; maps of different versions don't add."""
    return hashlib.sha256(repr(sorted((d, s.cuts, s.buckets) for d, s in ctx.scales.items())).encode()).hexdigest()[:12]


def _numbers(spark: SparkSession, path: str, name: str) -> list[int]:
    """The numbers i of the complete folders ``name=i`` under a path, in order."""
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    fs = p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    found = [s.getPath() for s in fs.listStatus(p)] if fs.exists(p) else []
    done = [x.getName() for x in found if fs.exists(spark.sparkContext._jvm.org.apache.hadoop.fs.Path(x, "_SUCCESS"))]
    return sorted(int(x.partition("=")[2]) for x in done if x.startswith(name + "="))


class MapState:
    """A stored single-table map that takes insertions and deletions batch by batch.

    Each batch's map is a file set of its own under ``path``; the state is their sum. A batch that is run again
    replaces its own files, so a restarted stream counts nothing twice.
    """

    def __init__(self, spark: SparkSession, queries: Sequence[CountQuery], tables, path: str, change: str | None = None):
        self.spark, self.queries, self.tables, self.path, self.change = spark, list(queries), tables, path, change
        self.ctx = context(queries[0].pattern, queries, tables, Options(prune=False))
        self.version = scale_version(self.ctx)
        self.table = next(iter(queries[0].tables))

    def fits(self, queries: Sequence[CountQuery]) -> bool:
        """Whether the stored scales answer these queries: each constant is a cut, each range whole buckets."""
        for q in queries:
            for b in q.boxes():
                for a, i in b.items():
                    s = self.ctx.scales.get("b_" + a.replace(".", "_"))
                    if s is None or any(x is not None and x not in s.cuts for x in (i.lo, i.hi)):
                        return False
                    lo, hi = s.positions(i)
                    inside, outside = set(s.buckets[lo : hi + 1]), {*s.buckets[:lo], *s.buckets[hi + 1 :]}
                    if 0 in inside or inside & outside:
                        return False
        return True

    def delta(self, rows: DataFrame) -> DataFrame:
        """The map of changed rows; ``change`` names a column of +1 and -1."""
        dims = cellmap.quantized(rows, {d: (a.partition(".")[2], self.ctx.scales[d]) for d, a in self.ctx.dims.items()})
        return cellmap.of_table(rows, (), dims, weight=F.col(self.change) if self.change else None)

    def apply(self, rows: DataFrame, batch_id: int) -> None:
        self.delta(rows).write.mode("overwrite").parquet(f"{self.path}/{self.version}/new/batch={batch_id}")

    def _done(self) -> int | None:
        """The last batch that the newest compacted map holds."""
        return max(_numbers(self.spark, f"{self.path}/{self.version}/whole", "upto"), default=None)

    def map(self) -> DataFrame:
        """The sum of the compacted map and the maps of the batches after it."""
        root, done = f"{self.path}/{self.version}", self._done()
        new = [i for i in _numbers(self.spark, f"{root}/new", "batch") if done is None or i > done]
        paths = [f"{root}/new/batch={i}" for i in new] + ([] if done is None else [f"{root}/whole/upto={done}"])
        if not paths:
            return self.delta(self.tables[self.table].limit(0))
        m = self.spark.read.parquet(*paths)
        return cellmap.regroup(m, [c for c in m.columns if c != "n"]).where("n <> 0")

    def compact(self) -> None:
        """Write the sum of all batches so far as one map; older files go once it is complete.

        A batch that runs again after it was compacted must be the same batch, as a stream's checkpoint guarantees.
        """
        root, done = f"{self.path}/{self.version}", self._done()
        new = [i for i in _numbers(self.spark, f"{root}/new", "batch") if done is None or i > done]
        if not new:
            return
        self.map().write.mode("overwrite").parquet(f"{root}/whole/upto={max(new)}")
        for i in _numbers(self.spark, f"{root}/new", "batch"):
            if i <= max(new):
                discard(self.spark, f"{root}/new/batch={i}")
        for i in _numbers(self.spark, f"{root}/whole", "upto"):
            if i < max(new):
                discard(self.spark, f"{root}/whole/upto={i}")

    def counts(self) -> DataFrame:
        got = box_counts(self.map(), boxes_of(self.queries, self.ctx.dims, self.ctx.scales), list(self.ctx.dims))
        every = self.spark.createDataFrame([(q.id,) for q in self.queries], "query_id string")
        return every.join(F.broadcast(got), "query_id", "left").select("query_id", F.coalesce("n", F.lit(0).cast("long")).alias("n"))


def run_to_end(stream: DataFrame, each: Callable[[DataFrame, int], None], checkpoint: str) -> None:
    """Feed all that a stream now has to ``each``, batch by batch, and stop."""
    q = stream.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()


def maintain(stream: DataFrame, state: MapState, checkpoint: str) -> DataFrame:
    """Bring a stored map up to date with a stream of rows and return the queries' counts."""
    run_to_end(stream, lambda df, i: state.apply(df, i), checkpoint)
    return state.counts()


def join_delta(queries: Sequence[CountQuery], old, new) -> DataFrame:
    """query_id, n after insertions: the counts over old rows plus, for each non-empty choice of tables, the counts with
    those tables' new rows and the others' old rows. ``old`` and ``new``: table -> rows."""
    pattern = queries[0].pattern
    names = sorted(pattern.tables)
    out = None
    for bits in range(1 << len(names)):
        if any(bits >> i & 1 and t not in new for i, t in enumerate(names)):
            continue
        mixed = {t: new[t] if bits >> i & 1 else old[t] for i, t in enumerate(names)}
        ctx = context(pattern, queries, mixed, Options(prune=False, fold="none"))
        m = fold_tree(ctx, plan(ctx))
        out = m if out is None else out.unionByName(m)
    whole = cellmap.regroup(out, list(ctx.dims))
    return box_counts(whole, boxes_of(queries, ctx.dims, ctx.scales), list(ctx.dims))


class JoinState:
    """Counts of a join pattern's queries over tables that only grow, by stored leaf maps.

    A table's leaf map (join keys, coordinates, n) is the sum of its batches' maps. A batch's share of the counts is
    the product of its new rows' map with the other tables' maps as they are: new rows of one table at a time, so
    every combination of old and new rows is counted once. The running map over all tables is stored by batch.
    """

    def __init__(self, spark: SparkSession, queries: Sequence[CountQuery], tables, path: str):
        self.spark, self.queries, self.path = spark, list(queries), path
        self.ctx = context(queries[0].pattern, queries, tables, Options(prune=False, fold="none"))
        self.node = plan(self.ctx)
        self.tables = tables

    def _leaf(self, table: str, rows: DataFrame) -> DataFrame:
        node = next(n for n in self.node.walk() if n.table == table)
        keys = sorted({*node.keys, *[k for c in node.children for k in c.keys]})
        return slice_table(replace(self.ctx, tables={table: rows}), PlanNode(table), keys)

    def _stored(self, table: str) -> DataFrame:
        paths = [f"{self.path}/{table}/batch={i}" for i in _numbers(self.spark, f"{self.path}/{table}", "batch")]
        empty = self._leaf(table, self.tables[table].limit(0))
        m = self.spark.read.schema(empty.schema).parquet(*paths) if paths else empty
        return cellmap.regroup(m, [c for c in m.columns if c != "n"])

    def apply(self, table: str, rows: DataFrame, batch_id: int) -> None:
        """Take new rows of one table; the same batch again replaces what it left. Batches of all tables are numbered in one row."""
        leaf = f"{self.path}/{table}/batch={batch_id}"
        self._leaf(table, rows).write.mode("overwrite").parquet(leaf)

        def fold(n: PlanNode) -> DataFrame:
            m = self.spark.read.parquet(leaf) if n.table == table else self._stored(n.table)
            for c in n.children:
                m = cellmap.multiply(m, fold(c), [f"k{k}" for k in c.keys])
                later = {k for x in n.children[n.children.index(c) + 1 :] for k in x.keys} | set(n.keys)
                m = cellmap.regroup(m, [*[f"k{k}" for k in sorted(later)], *[x for x in m.columns if x.startswith("b_")]])
            return m

        fold(self.node).write.mode("overwrite").parquet(f"{self.path}/_counts/batch={batch_id}")

    def counts(self) -> DataFrame:
        """query_id, n of all queries over the rows taken so far."""
        paths = [f"{self.path}/_counts/batch={i}" for i in _numbers(self.spark, f"{self.path}/_counts", "batch")]
        every = self.spark.createDataFrame([(q.id, 0) for q in self.queries], "query_id string, n bigint")
        if not paths:
            return every
        m = self.spark.read.parquet(*paths)
        whole = cellmap.regroup(m, [c for c in m.columns if c != "n"])
        got = box_counts(whole, boxes_of(self.queries, self.ctx.dims, self.ctx.scales), list(self.ctx.dims))
        return every.select("query_id").join(F.broadcast(got), "query_id", "left").select("query_id", F.coalesce("n", F.lit(0).cast("long")).alias("n"))


def window_maps(rows: DataFrame, queries: Sequence[CountQuery], window) -> DataFrame:
    """window_start, coordinates, n: a cell map for each window; ``rows`` may be a stream with a watermark.

    Rows are grouped by window and cell, so the state has a row for each live cell, however many rows come.
    """
    ctx = context(queries[0].pattern, queries, {next(iter(queries[0].tables)): rows}, Options(prune=False))
    ids = cellmap.quantized(rows, {d: (a.partition(".")[2], ctx.scales[d]) for d, a in ctx.dims.items()})
    m = rows.groupBy(window.alias("w"), *[c.alias(d) for d, c in ids.items()]).agg(F.count(F.lit(1)).alias("n"))
    return m.select(F.col("w.start").alias("window_start"), *ctx.dims, "n")


def window_counts(maps: DataFrame, queries: Sequence[CountQuery]) -> DataFrame:
    """window_start, query_id, n from window maps that are complete."""
    ctx = context(queries[0].pattern, queries, {next(iter(queries[0].tables)): maps}, Options(prune=False))
    hit = box_join(maps, boxes_of(queries, ctx.dims, ctx.scales), list(ctx.dims))
    return hit.groupBy("window_start", "query_id").agg(F.sum("n").alias("n"))


def windowed_counts(rows: DataFrame, queries: Sequence[CountQuery], window, time_col: str = "ts") -> DataFrame:
    """window_start, query_id, n where windows depend on the query's own rows (sessions), or in one streaming aggregation.

    Rows meet the boxes after quantization; with windows that are alike for all queries ``window_maps`` does less work.
    """
    ctx = context(queries[0].pattern, queries, {next(iter(queries[0].tables)): rows}, Options(prune=False))
    ids = cellmap.quantized(rows, {d: (a.partition(".")[2], ctx.scales[d]) for d, a in ctx.dims.items()})
    x = rows.select(F.col(time_col), *[c.alias(d) for d, c in ids.items()], F.lit(1).cast("long").alias("n"))
    hit = box_join(x, boxes_of(queries, ctx.dims, ctx.scales), list(ctx.dims))
    return hit.groupBy(window.alias("w"), "query_id").agg(F.sum("n").alias("n")).select(F.col("w.start").alias("window_start"), "query_id", "n")


def complete(stream: DataFrame, path: str) -> DataFrame:
    """Run an aggregation over all that a stream now has; executors write its whole result to the shared folder."""

    def put(df: DataFrame, i: int) -> None:
        df.write.mode("overwrite").parquet(f"{path}/result/batch={i}")

    q = stream.writeStream.foreachBatch(put).outputMode("complete").option("checkpointLocation", f"{path}/checkpoint").trigger(availableNow=True).start()
    q.awaitTermination()
    spark = stream.sparkSession
    last = max(_numbers(spark, f"{path}/result", "batch"), default=None)
    return spark.createDataFrame([], stream.schema) if last is None else spark.read.schema(stream.schema).parquet(f"{path}/result/batch={last}")


def stream_of(spark: SparkSession, sf_dir: str, table: str, time_col: str | None = None, late: str = "1 hour", files_per_batch: int = 1) -> DataFrame:
    """A table's files as a stream; ``time_col`` is read as a UTC instant with a watermark."""
    path = f"{sf_dir}/{table}.parquet"
    schema = spark.read.parquet(path).schema
    s = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).option("pathGlobFilter", "*.parquet").parquet(path if _is_dir(spark, path) else f"{sf_dir}/{table}*.parquet")
    return s if time_col is None else s.withColumn(time_col, F.col(time_col).cast("timestamp")).withWatermark(time_col, late)


def _is_dir(spark: SparkSession, path: str) -> bool:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(p).isDirectory()


def dedup(stream: DataFrame, key: str, time_col: str, late: str) -> DataFrame:
    """The first row of each key within the watermark."""
    return stream.withWatermark(time_col, late).dropDuplicatesWithinWatermark([key])


def leaf(ctx: Context, table: str) -> DataFrame:
    return slice_table(ctx, PlanNode(table), ctx.pattern.classes_of(table))


__all__ = ["MapState", "JoinState", "maintain", "join_delta", "window_maps", "window_counts", "windowed_counts", "complete", "stream_of", "dedup", "run_to_end", "scale_version", "table_of"]
