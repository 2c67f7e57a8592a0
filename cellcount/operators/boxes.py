"""From a cell map to counts: each query is a box of grid coordinates, and its count the weight of the cells inside."""

from __future__ import annotations

from collections.abc import Iterator, Mapping, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.aggregates import AggSpec
from ..functions.scales import Scale
from ..plans.model import CountQuery

#: query id and, for each coordinate, the lowest and highest id inside
Box = tuple[str, tuple[tuple[int, int], ...]]
#: Boxes that stay within the compiled stage: conditions on the rows themselves, no table of boxes and no Python.
FEW_BOXES = 4
IMPLS = ("arrow", "join", "case", "hof", "dense", "prefix")


def boxes_of(queries: Sequence[CountQuery], dims: Mapping[str, str], scales: Mapping[str, Scale]) -> list[Box]:
    """A box for each satisfiable conjunction; ``dims``: coordinate -> attribute. A coordinate that a query leaves
    open takes all ids, 0 included."""
    out = []
    for q in queries:
        for ranges in q.boxes():
            spans = tuple(scales[d].id_range(ranges[a]) if a in ranges else (0, scales[d].size) for d, a in dims.items())
            if all(lo <= hi for lo, hi in spans):
                out.append((q.id, spans))
    return out


def box_table(spark: SparkSession, boxes: Sequence[Box], dims: Sequence[str]) -> DataFrame:
    """query_id, <coordinate>_lo, <coordinate>_hi: a few numbers for each query of the batch."""
    schema = T.StructType([T.StructField("query_id", T.StringType()), *[T.StructField(f"{d}_{e}", T.IntegerType()) for d in dims for e in ("lo", "hi")]])
    return spark.createDataFrame([(q, *[x for s in spans for x in s]) for q, spans in boxes], schema)


def box_counts(m: DataFrame, boxes: Sequence[Box], dims: Sequence[str], impl: str = "arrow", scales: Mapping[str, Scale] | None = None, count_type: str = "bigint") -> DataFrame:
    """query_id, n for the boxes that hold any cell. ``impl="auto"``: case up to ``FEW_BOXES`` boxes, arrow for more."""
    impl = ("case" if len(boxes) <= FEW_BOXES else "arrow") if impl == "auto" else impl
    spark = m.sparkSession
    total = (F.sum("n").cast("decimal(38,0)") if count_type == "decimal" else F.sum("n")).alias("n")
    if not boxes:
        return spark.createDataFrame([], "query_id string, n bigint")
    if impl == "arrow" and count_type == "bigint":
        return _arrow(m, boxes, dims)
    if impl == "case":
        return _case(m, boxes, dims)
    if impl == "hof":
        return _hof(m, boxes, dims).groupBy("query_id").agg(total)
    if impl == "dense":
        return _dense(m, boxes, dims).groupBy("query_id").agg(total)
    if impl == "prefix":
        return _prefix(m, boxes, dims, scales)
    return box_join(m, boxes, dims).groupBy("query_id").agg(total)


def box_join(m: DataFrame, boxes: Sequence[Box], dims: Sequence[str]) -> DataFrame:
    """The cells of each box: a nested-loop join with the broadcast boxes, whose number is the batch's."""
    t = F.broadcast(box_table(m.sparkSession, boxes, dims))
    inside = F.lit(True)
    for d in dims:
        inside = inside & F.col(d).between(F.col(f"{d}_lo"), F.col(f"{d}_hi"))
    return m.join(t, inside)


def box_rows(m: DataFrame, boxes: Sequence[Box], dims: Sequence[str]) -> DataFrame:
    """The cells of each of a few boxes, at least one, with the boxes as conditions."""
    ids = []
    for q, spans in boxes:
        inside = F.lit(True)
        for d, (lo, hi) in zip(dims, spans, strict=True):
            inside = inside & F.col(d).between(lo, hi)
        ids.append((q, inside))
    if len(ids) == 1:
        q, inside = ids[0]
        return m.where(inside).withColumn("query_id", F.lit(q))
    return m.withColumn("query_id", F.explode(F.array_compact(F.array(*[F.when(inside, F.lit(q)) for q, inside in ids]))))


def _arrow(m: DataFrame, boxes: Sequence[Box], dims: Sequence[str]) -> DataFrame:
    """Each batch of cells against all boxes with vectorised comparisons; a row for each box and task goes on."""
    ids = [q for q, _ in boxes]
    spans = np.array([s for _, s in boxes], dtype=np.int32).reshape(len(boxes), len(dims), 2)
    held = m.sparkSession.sparkContext.broadcast((ids, spans))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, spans = held.value
        spans = spans.tolist()
        total, none = [0] * len(ids), object()
        for b in batches:
            cols = [b.column(i).to_numpy(zero_copy_only=False) for i in range(len(dims))]
            n = b.column(len(dims)).to_numpy(zero_copy_only=False)
            least = [int(c.min()) if len(n) else 0 for c in cols]
            most = [int(c.max()) if len(n) else -1 for c in cols]
            for k in range(len(ids)):
                inside = None
                for c, (lo, hi), c0, c1 in zip(cols, spans[k], least, most, strict=True):
                    if lo > c1 or hi < c0:
                        inside = none
                        break
                    if lo > c0:
                        inside = c >= lo if inside is None else inside & (c >= lo)
                    if hi < c1:
                        inside = c <= hi if inside is None else inside & (c <= hi)
                if inside is none:
                    continue
                picked = n if inside is None else n[inside]
                # Python's whole numbers do not wrap; a sum beyond 64 bits raises when it is written.
                total[k] += int(picked.sum()) if len(picked) == 0 or int(np.abs(picked).max()) < (1 << 62) // max(1, len(picked)) else sum(picked.tolist())
        at = [k for k, v in enumerate(total) if v]
        yield pa.RecordBatch.from_arrays([pa.array([ids[k] for k in at], pa.string()), pa.array([total[k] for k in at], pa.int64())], names=["query_id", "n"])

    return m.select(*dims, "n").mapInArrow(run, "query_id string, n bigint").groupBy("query_id").agg(F.sum("n").alias("n"))


def _case(m: DataFrame, boxes: Sequence[Box], dims: Sequence[str], chunk: int = 200) -> DataFrame:
    """A conditional sum for each box, at most ``chunk`` in one aggregate so that it still compiles."""
    out = None
    for s in range(0, len(boxes), chunk):
        part = boxes[s : s + chunk]
        sums = []
        for k, (_, spans) in enumerate(part):
            inside = F.lit(True)
            for d, (lo, hi) in zip(dims, spans, strict=True):
                inside = inside & F.col(d).between(lo, hi)
            sums.append(F.sum(F.when(inside, F.col("n"))).alias(f"q{k}"))
        names = ", ".join(f"'{q}', q{k}" for k, (q, _) in enumerate(part))
        wide = m.agg(*sums).selectExpr(f"stack({len(part)}, {names}) as (query_id, n)")
        out = wide if out is None else out.unionByName(wide)
    return out.where("n is not null").groupBy("query_id").agg(F.sum("n").alias("n"))


def _hof(m: DataFrame, boxes: Sequence[Box], dims: Sequence[str]) -> DataFrame:
    """The boxes as one array of structs; each cell keeps those around it."""
    t = box_table(m.sparkSession, boxes, dims)
    held = t.agg(F.collect_list(F.struct(*t.columns)).alias("boxes"))

    def around(b):
        inside = F.lit(True)
        for d in dims:
            inside = inside & (F.col(d) >= b[f"{d}_lo"]) & (F.col(d) <= b[f"{d}_hi"])
        return inside

    x = m.crossJoin(F.broadcast(held))
    return x.select("n", F.explode(F.transform(F.filter("boxes", around), lambda b: b["query_id"])).alias("query_id"))


def _dense(m: DataFrame, boxes: Sequence[Box], dims: Sequence[str]) -> DataFrame:
    """Enumerate each box's coordinates and look them up: the naive way, for tests."""
    t = box_table(m.sparkSession, boxes, dims)
    for d in dims:
        t = t.withColumn(d, F.explode(F.sequence(f"{d}_lo", f"{d}_hi")))
    return m.join(t.select("query_id", *dims), list(dims)) if dims else m.crossJoin(t.select("query_id"))


def _prefix(m: DataFrame, boxes: Sequence[Box], dims: Sequence[str], scales: Mapping[str, Scale]) -> DataFrame:
    """Prefix sums over a dense grid of at most three coordinates, read by inclusion and exclusion at the corners."""
    if len(dims) > 3:
        raise ValueError("prefix sums take at most three coordinates")
    spark = m.sparkSession
    grid = spark.range(1).select(*[F.explode(F.sequence(F.lit(0), F.lit(scales[d].size))).alias(d) for d in dims][:1]) if dims else spark.range(1).select()
    for d in dims[1:]:
        grid = grid.crossJoin(spark.range(1).select(F.explode(F.sequence(F.lit(0), F.lit(scales[d].size))).alias(d)))
    g = grid.join(m.groupBy(*dims).agg(F.sum("n").alias("n")), list(dims), "left").withColumn("n", F.coalesce("n", F.lit(0).cast("long")))
    for d in dims:
        others = [o for o in dims if o != d]
        w = (Window.partitionBy(*others) if others else Window.partitionBy(F.lit(0))).orderBy(d).rowsBetween(Window.unboundedPreceding, 0)
        g = g.withColumn("n", F.sum("n").over(w))
    corners = []
    for q, spans in boxes:
        for bits in range(1 << len(dims)):
            at = [hi if not bits >> i & 1 else lo - 1 for i, (lo, hi) in enumerate(spans)]
            if all(x >= 0 for x in at):
                corners.append((q, *at, -1 if bin(bits).count("1") % 2 else 1))
    schema = T.StructType([T.StructField("query_id", T.StringType()), *[T.StructField(d, T.IntegerType()) for d in dims], T.StructField("sign", T.IntegerType())])
    c = spark.createDataFrame(corners, schema)
    return g.join(F.broadcast(c), list(dims)).groupBy("query_id").agg(F.sum(F.col("n") * F.col("sign")).alias("n")).where("n <> 0")


def box_aggregates(m: DataFrame, boxes: Sequence[Box], dims: Sequence[str], agg: AggSpec) -> DataFrame:
    """query_id, value: an aggregate's states merged over the cells of each box."""
    merged = box_join(m, boxes, dims).groupBy("query_id").agg(*[agg.merged(c) for c in agg.columns])
    return merged.select("query_id", agg.result().alias("value"))
