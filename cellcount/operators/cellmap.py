"""Cell maps: key columns, grid coordinates and a count; absent cells count 0.

``multiply`` joins maps of disjoint tables on their keys; ``add`` unites maps of the same tables.
"""

from __future__ import annotations

from collections.abc import Mapping, Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.aggregates import AggSpec
from ..functions.scales import Scale, quantize
from ..sources.shared import fresh, release, store


def of_table(df: DataFrame, keys: Sequence[str], dims: Mapping[str, Column], agg: AggSpec | None = None, weight: Column | None = None) -> DataFrame:
    """The map of one table's rows: keys, coordinates, n (and the states of ``agg``).

    ``dims``: coordinate name -> id column; ``weight``: what a row counts (1, or -1 for a deleted one).
    """
    n = (F.count(F.lit(1)) if weight is None else F.sum(weight)).cast("long").alias("n")
    states = [c.alias(name) for name, c in agg.states().items()] if agg else []
    by = [*keys, *[c.alias(name) for name, c in dims.items()]]
    return df.groupBy(*by).agg(n, *states)


#: Rows of a map that one broadcast takes to the driver and every executor.
BROADCAST_ROWS = 1_000_000


def multiply(left: DataFrame, right: DataFrame, on: Sequence[str] = (), agg: AggSpec | None = None, count_type: str = "bigint", hint: str | None = None) -> DataFrame:
    """Coordinates side by side, counts multiplied, where the keys agree; without keys every pair of cells.

    ``hint="broadcast"``: a map of more than ``BROADCAST_ROWS`` rows is broadcast in parts, one after the other.
    """
    if hint == "broadcast" and on:
        right = store(right, "side")  # counted, then read again
        parts = -(-right.count() // BROADCAST_ROWS)
        if parts > 1:
            return _in_parts(left, right, on, agg, count_type, parts)
    return _product(left, right, on, agg, count_type, hint)


def _in_parts(left: DataFrame, right: DataFrame, on: Sequence[str], agg: AggSpec | None, count_type: str, parts: int) -> DataFrame:
    """The product with a right side too large for one broadcast: both sides are dealt by the hash of their keys into
    parts, and each part's product is stored before the next part is broadcast. A key with more cells than a part stays
    whole; the limit holds for maps whose keys have few cells each."""
    at = F.pmod(F.xxhash64(*on), F.lit(parts))
    sides = [store(m.withColumn("_part", at), "part", ("_part",)) for m in (left, right)]
    spark, path, schema = left.sparkSession, fresh(left.sparkSession, "product"), None
    for p in range(parts):
        a, b = (m.where(F.col("_part") == p).drop("_part") for m in sides)
        out = _product(a, b, on, agg, count_type, "broadcast")
        schema = out.schema
        out.write.mode("append").parquet(path)
        del a, b, out
        release(spark)
    return spark.read.schema(schema).parquet(path)


def _product(left: DataFrame, right: DataFrame, on: Sequence[str], agg: AggSpec | None, count_type: str, hint: str | None) -> DataFrame:
    right = right.withColumnRenamed("n", "_m")
    right = right.hint(hint) if hint else right
    x = left.join(right, list(on)) if on else left.crossJoin(right)
    names = [c for c in x.columns if c not in ("n", "_m") and not c.startswith("a_")]
    states = []
    if agg:
        own = F.col("_m") if all(c in left.columns for c in agg.columns) else F.col("n")
        states = [agg.scaled(c, own) for c in agg.columns if c in x.columns]
    product = F.col("n") * F.col("_m")
    if count_type == "decimal":
        product = (F.col("n").cast("decimal(38,0)") * F.col("_m").cast("decimal(38,0)")).cast("decimal(38,0)")
    return x.select(*names, product.alias("n"), *states)


def regroup(m: DataFrame, by: Sequence[str], agg: AggSpec | None = None, count_type: str = "bigint") -> DataFrame:
    """Add up the cells that agree on ``by``."""
    n = F.sum("n").cast("decimal(38,0)") if count_type == "decimal" else F.sum("n")
    states = [agg.merged(c) for c in agg.columns if c in m.columns] if agg else []
    out = m.groupBy(*by).agg(n.alias("n"), *states)
    return out if by else out.where("n is not null")  # no cells: no cell


def add(*maps: DataFrame) -> DataFrame:
    """The map of a union of disjoint sets of rows: all cells of either, counts added."""
    out = maps[0]
    for m in maps[1:]:
        out = out.unionByName(m)
    return regroup(out, [c for c in out.columns if c != "n"])


def pack(m: DataFrame, dims: Sequence[str], scales: Mapping[str, Scale]) -> DataFrame:
    """Coordinates as one mixed-radix number ``code``; 2^62 cells at most."""
    total, code = 1, F.lit(0).cast("long")
    for d in dims:
        code = code + F.col(d).cast("long") * F.lit(total).cast("long")
        total *= scales[d].size + 1
    if total >= 1 << 62:
        raise ValueError("the grid has too many cells to pack")
    return m.select(*[c for c in m.columns if c not in dims and c != "n"], code.alias("code"), "n")


def unpack(m: DataFrame, dims: Sequence[str], scales: Mapping[str, Scale]) -> DataFrame:
    """The coordinates of ``pack`` back."""
    out, total = [], 1
    for d in dims:
        size = scales[d].size + 1
        out.append(F.pmod(F.expr(f"code div {total}L"), F.lit(size).cast("long")).cast("int").alias(d))
        total *= size
    return m.select(*[c for c in m.columns if c not in ("code", "n")], *out, "n")


def quantized(df: DataFrame, attrs: Mapping[str, tuple[str, Scale]], impl: str = "auto") -> dict[str, Column]:
    """coordinate -> id column, for coordinate -> (column, scale)."""
    return {name: quantize(F.col(column), scale, impl, df.schema[column].dataType).alias(name) for name, (column, scale) in attrs.items()}
