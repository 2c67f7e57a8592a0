"""Operators around cell maps: marginal maps, maps as values, user aggregates and table functions, as-of joins, range frames."""

from __future__ import annotations

from collections.abc import Sequence

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T


def marginals(m: DataFrame, dims: Sequence[str], how: str, sets: Sequence[Sequence[str]] = ()) -> DataFrame:
    """Maps with coordinates rolled up to "any" (-1): ``how`` is cube, rollup or sets."""
    if how == "sets":
        grouped = m.groupingSets([[F.col(d) for d in s] for s in sets], *[F.col(d) for d in dims])
    else:
        grouped = getattr(m, how)(*dims)
    out = grouped.agg(F.sum("n").alias("n"), *[F.grouping(d).alias(f"_{d}") for d in dims])
    return out.select(*[F.when(F.col(f"_{d}") == 1, -1).otherwise(F.col(d)).alias(d) for d in dims], "n")


def as_map(m: DataFrame, dims: Sequence[str], by: Sequence[str] = ()) -> DataFrame:
    """A cell map as one map value, coordinates joined by commas -> count, for each group."""
    cell = F.concat_ws(",", *[F.col(d).cast("string") for d in dims])
    return m.groupBy(*by).agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct(cell.alias("k"), F.col("n").alias("v"))))).alias("cells"))


def add_maps(a: Column, b: Column) -> Column:
    """Two map values added: all cells of either."""
    return F.map_zip_with(a, b, lambda k, x, y: F.coalesce(x, F.lit(0).cast("long")) + F.coalesce(y, F.lit(0).cast("long")))


@F.pandas_udf(T.LongType())
def add_counts(n: pd.Series) -> int:
    """A user aggregate that adds counts."""
    return int(n.sum())


@F.udtf(returnType=T.StructType([T.StructField("query_id", T.StringType()), T.StructField("b0", T.IntegerType()), T.StructField("b1", T.IntegerType())]))
class BoxCells:
    """The coordinates of a two-dimensional box, one row each."""

    def eval(self, query_id: str, lo0: int, hi0: int, lo1: int, hi1: int):
        for x in range(lo0, hi0 + 1):
            for y in range(lo1, hi1 + 1):
                yield query_id, x, y


def box_cells(spark: SparkSession, boxes: DataFrame) -> DataFrame:
    """query_id, b0, b1 for (query_id, lo0, hi0, lo1, hi1) rows."""
    spark.udtf.register("cellcount_box_cells", BoxCells)
    boxes.createOrReplaceTempView("cellcount_boxes")
    return spark.sql("SELECT t.* FROM cellcount_boxes b, LATERAL cellcount_box_cells(b.query_id, b.lo0, b.hi0, b.lo1, b.hi1) t")


def as_of(left: DataFrame, right: DataFrame, key: str, left_time: str, right_time: str, take: Sequence[str]) -> DataFrame:
    """Each left row with the latest right row of its key at or before its time; nulls where there is none.

    One window over the union of both sides, sorted by key and time, instead of a join on a range. At equal times
    the right row comes first; of several, the one with the largest ``take`` values counts.
    """
    l_side = left.select("*", F.col(left_time).alias("_t"), F.lit(1).alias("_side"))
    r_side = right.select(F.col(key), F.col(right_time).alias("_t"), F.lit(0).alias("_side"), F.struct(F.col(right_time), *take).alias("_r"))
    both = l_side.unionByName(r_side, allowMissingColumns=True)
    w = Window.partitionBy(key).orderBy("_t", "_side", "_r").rowsBetween(Window.unboundedPreceding, 0)
    x = both.withColumn("_last", F.last("_r", ignorenulls=True).over(w)).where("_side = 1")
    return x.select(*left.columns, *[F.col(f"_last.{c}").alias(c) for c in (right_time, *take)])


def range_frame_counts(df: DataFrame, key: str, time_col: str, seconds: int) -> DataFrame:
    """Each row with the number of rows of its key in the ``seconds`` up to it; times count in whole seconds, rounded, halves to even."""
    instant = F.concat(F.col(time_col).cast("string"), F.lit("Z")).cast("timestamp")
    epoch = F.rint(F.unix_micros(instant) / F.lit(1e6)).cast("long")
    w = Window.partitionBy(key).orderBy("_e").rangeBetween(-seconds, 0)
    return df.withColumn("_e", epoch).withColumn("n_recent", F.count("*").over(w)).drop("_e")


def top_cells(m: DataFrame, k: int) -> DataFrame:
    """The heaviest cells; ties by coordinates."""
    dims = [c for c in m.columns if c != "n"]
    return m.orderBy(F.desc("n"), *dims).limit(k)
