"""Scales: the small integer grid that a batch's own constants span on one attribute, and ways to quantize a column.

Sorted constants x[0..p) split a domain into 2p + 1 positions: the gap below x[0], the point x[0], the gap after it,
and so on. A cut lies before each interval's first position and after its last; positions between cuts form a bucket.
Buckets that some interval covers get ids from 1 in order, all else, and null, is 0.
"""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Iterable
from dataclasses import dataclass
from datetime import datetime

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.model import Interval

#: Most cuts for which a nested CASE stays within one compiled method.
CASE_CUTS = 256


@dataclass(frozen=True)
class Scale:
    """``cuts``: sorted constants; ``buckets``: bucket id of each of the 2 * len(cuts) + 1 positions."""

    cuts: tuple
    buckets: tuple[int, ...]

    @property
    def size(self) -> int:
        return max(self.buckets)

    @property
    def points_only(self) -> bool:
        """Whether all buckets are single constants."""
        return all(b == 0 for b in self.buckets[::2])

    def positions(self, i: Interval) -> tuple[int, int]:
        p = len(self.cuts)
        at = lambda x: bisect_left(self.cuts, x)
        lo = 0 if i.lo is None else 2 * at(i.lo) + (1 if i.lo_incl else 2)
        hi = 2 * p if i.hi is None else 2 * at(i.hi) + (1 if i.hi_incl else 0)
        return lo, hi

    def id_range(self, i: Interval) -> tuple[int, int]:
        """The ids of the buckets that make up one of the intervals the scale was built from; (1, 0) if it is empty."""
        lo, hi = self.positions(i)
        return (self.buckets[lo], self.buckets[hi]) if lo <= hi else (1, 0)

    def quantize(self, x) -> int:
        """The id of one value, on the driver."""
        if x is None:
            return 0
        i = bisect_left(self.cuts, x)
        return self.buckets[2 * i + 1 if i < len(self.cuts) and self.cuts[i] == x else 2 * i]

    def rows(self) -> list[tuple]:
        """(bucket id, lo, lo_incl, hi, hi_incl) of each bucket, in order."""
        out = []
        for b in range(1, self.size + 1):
            at = [k for k, v in enumerate(self.buckets) if v == b]
            lo, hi = at[0], at[-1]
            out.append((b, None if lo == 0 else self.cuts[(lo - 1) // 2], bool(lo % 2), None if hi == 2 * len(self.cuts) else self.cuts[hi // 2], bool(hi % 2)))
        return out


def build_scale(intervals: Iterable[Interval]) -> Scale:
    """The coarsest scale on which each of the intervals is a range of ids."""
    intervals = [i for i in set(intervals) if not i.empty]
    cuts = tuple(sorted({e for i in intervals for e in (i.lo, i.hi) if e is not None}))
    n = 2 * len(cuts) + 1
    scale = Scale(cuts, (0,) * n)
    cover, cut = [0] * (n + 1), [False] * (n + 1)
    for i in intervals:
        lo, hi = scale.positions(i)
        if lo <= hi:
            cover[lo] += 1
            cover[hi + 1] -= 1
            cut[lo] = cut[hi + 1] = True
    ids, depth, last, before = [], 0, 0, False
    for k in range(n):
        depth += cover[k]
        if depth and (cut[k] or not before):
            last += 1
        ids.append(last if depth else 0)
        before = depth > 0
    return Scale(cuts, tuple(ids))


def literal(value, kind: T.DataType | None = None) -> Column:
    """A literal of an attribute's type; time stamps without a zone as such."""
    if isinstance(value, datetime):
        return F.expr(f"TIMESTAMP_NTZ '{value.isoformat(sep=' ')}'")
    return F.lit(value)


def quantize(col: Column, scale: Scale, impl: str = "auto", kind: T.DataType | None = None) -> Column:
    """The id column of an attribute. ``impl``: auto, case, arrow, lookup or scan; all give equal ids.

    * case: a balanced tree of comparisons, compiled with the rest of the stage;
    * arrow: binary search over a sorted array in a vectorised function, for many cuts;
    * lookup: a map of constants, where all buckets are points;
    * scan: counts the constants at or below the value, linear; a contrast for tests.
    """
    if impl == "auto":
        impl = "case" if len(scale.cuts) <= CASE_CUTS else "arrow"
    if not scale.cuts:
        return F.when(col.isNotNull(), scale.buckets[0]).otherwise(0)
    if impl == "case":
        return F.when(col.isNull(), 0).otherwise(_case(col, scale, 0, len(scale.cuts)))
    if impl == "arrow":
        return _arrow(col, scale, kind)
    if impl == "lookup":
        if not scale.points_only:
            raise ValueError("lookup needs a scale of points")
        pairs = [x for k, v in enumerate(scale.cuts) if scale.buckets[2 * k + 1] for x in (literal(v), F.lit(scale.buckets[2 * k + 1]))]
        return F.coalesce(F.element_at(F.create_map(*pairs), col), F.lit(0))
    if impl == "scan":
        cuts = F.array(*map(literal, scale.cuts))
        below, at = F.size(F.filter(cuts, lambda x: x < col)), F.size(F.filter(cuts, lambda x: x == col))
        return F.when(col.isNull(), 0).otherwise(F.element_at(F.array(*map(F.lit, scale.buckets)), 2 * below + at + 1))
    raise ValueError(impl)


def register_quantizer(spark, name: str, scale: Scale, kind: T.DataType) -> None:
    """The binary search as a function of the session's SQL: ``name(value)`` gives the bucket id."""
    buckets, cuts = np.array(scale.buckets, dtype=np.int32), scale.cuts

    def ids(s: pd.Series) -> pd.Series:
        return pd.Series(_by_value(s, cuts, buckets))

    spark.udf.register(name, F.pandas_udf(ids, T.IntegerType()))


def _by_value(s: pd.Series, cuts, buckets: np.ndarray) -> np.ndarray:
    """The ids of a batch by one search for each of its distinct values; nulls get 0."""
    code, values = pd.factorize(s)
    found = np.zeros(len(values) + 1, dtype=np.int32)  # the last, which code -1 reads, is that of nulls
    for k, x in enumerate(values):
        i = bisect_left(cuts, x)
        found[k] = buckets[2 * i + (i < len(cuts) and cuts[i] == x)]
    return found[code]


def _case(col: Column, scale: Scale, lo: int, hi: int) -> Column:
    """The tree for a value between cuts ``lo - 1`` and ``hi``; runs of equal buckets take no comparison."""
    b = scale.buckets
    if len(set(b[2 * lo : 2 * hi + 1])) == 1:
        return F.lit(b[2 * lo])
    mid = (lo + hi) // 2
    x = literal(scale.cuts[mid])
    left, right = _case(col, scale, lo, mid), _case(col, scale, mid + 1, hi)
    if b[2 * mid + 1] == b[2 * mid + 2]:
        return F.when(col < x, left).otherwise(right)
    if b[2 * mid] == b[2 * mid + 1]:
        return F.when(col <= x, left).otherwise(right)
    return F.when(col < x, left).when(col == x, b[2 * mid + 1]).otherwise(right)


def _arrow(col: Column, scale: Scale, kind: T.DataType | None) -> Column:
    buckets = np.array(scale.buckets, dtype=np.int32)
    first = scale.cuts[0]
    if isinstance(first, str):
        cuts = list(scale.cuts)
    elif isinstance(first, datetime):
        cuts = np.array(scale.cuts, dtype="datetime64[us]").astype(np.int64)
    else:
        cuts = np.array([float(c) for c in scale.cuts]) if any(isinstance(c, float) for c in scale.cuts) or isinstance(kind, T.DoubleType | T.FloatType) else np.array(scale.cuts, dtype=np.int64)

    @F.pandas_udf("int")
    def ids(s: pd.Series) -> pd.Series:
        if isinstance(cuts, list):
            return pd.Series(_by_value(s, cuts, buckets))
        null = s.isna().to_numpy() if not isinstance(kind, T.DoubleType | T.FloatType) else np.zeros(len(s), dtype=bool)
        x = s.to_numpy()
        x = x.astype("datetime64[us]").astype(np.int64) if x.dtype.kind == "M" else np.where(null, 0, x).astype(cuts.dtype) if null.any() else x.astype(cuts.dtype)
        at = np.searchsorted(cuts, x, side="left")
        same = (at < len(cuts)) & (cuts[np.minimum(at, len(cuts) - 1)] == x)
        out = buckets[np.where(null, 0, 2 * at + same)]
        return pd.Series(np.where(null, 0, out).astype(np.int32))

    # A null double arrives as NaN, which is a value here: nulls are told apart before.
    return F.when(col.isNull(), 0).otherwise(ids(col))


def bucket_table(spark, scale: Scale, kind: T.DataType) -> DataFrame:
    """bucket_id, lo, lo_incl, hi, hi_incl of a scale; null ends are unbounded. A row for each bucket of the batch."""
    name = kind.simpleString()
    schema = T.StructType([T.StructField("bucket_id", T.IntegerType()), T.StructField("lo", kind), T.StructField("lo_incl", T.BooleanType()), T.StructField("hi", kind), T.StructField("hi_incl", T.BooleanType())])
    as_kind = float if name in ("double", "float") else (lambda v: v)
    rows = [(b, None if lo is None else as_kind(lo), li, None if hi is None else as_kind(hi), hi_i) for b, lo, li, hi, hi_i in scale.rows()]
    return spark.createDataFrame(rows, schema)


def quantize_by_join(df: DataFrame, attr: str, scale: Scale, impl: str, out: str) -> DataFrame:
    """``df`` with the id column, by a range join ("range_join") or, for points, an equality join ("lookup_join").

    The table of buckets has a row for each bucket, at most twice as many as the batch has intervals.
    """
    spark = df.sparkSession
    t = F.broadcast(bucket_table(spark, scale, df.schema[attr].dataType))
    if impl == "lookup_join":
        if not scale.points_only:
            raise ValueError("lookup_join needs a scale of points")
        t = t.select(F.col("lo").alias(attr), F.col("bucket_id").alias(out))
        return df.join(t, attr, "left").withColumn(out, F.coalesce(out, F.lit(0)))
    x = F.col(attr)
    above = F.col("lo").isNull() | (x > F.col("lo")) | (F.col("lo_incl") & (x == F.col("lo")))
    below = F.col("hi").isNull() | (x < F.col("hi")) | (F.col("hi_incl") & (x == F.col("hi")))
    joined = df.join(t, x.isNotNull() & above & below, "left")
    return joined.withColumn(out, F.coalesce("bucket_id", F.lit(0))).drop("bucket_id", "lo", "lo_incl", "hi", "hi_incl")
