"""Aggregates beyond COUNT over one table's expression, as states that multiply by counts and add.

The table that owns the expression carries its states in the cell map. Against a map of count k they become
(k times the non-null count, k times the sum, k times the sum of squares, the same minimum, maximum, set and sketch);
where maps add, sums add, minima and maxima are taken and sets unite.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

KINDS = ("count", "sum", "min", "max", "avg", "stddev", "count_distinct", "approx_distinct")


@dataclass(frozen=True)
class AggSpec:
    """``expr``: SQL text over columns of ``table``. Sums are exact in DECIMAL(38, scale) from DECIMAL(18, scale) inputs."""

    kind: str
    expr: str
    table: str
    scale: int = 4

    def __post_init__(self):
        if self.kind not in KINDS:
            raise ValueError(self.kind)

    def states(self) -> dict[str, Column]:
        """State column -> aggregate over the rows of a cell."""
        x = F.expr(self.expr)
        exact = x.cast(f"decimal(18,{self.scale})")
        return {
            "count": {"a_nn": F.count(x)},
            "sum": {"a_s": F.sum(exact).cast(f"decimal(38,{self.scale})"), "a_nn": F.count(x)},
            "avg": {"a_s": F.sum(exact).cast(f"decimal(38,{self.scale})"), "a_nn": F.count(x)},
            "min": {"a_mn": F.min(x)},
            "max": {"a_mx": F.max(x)},
            "stddev": {"a_nn": F.count(x), "a_d": F.sum(x.cast("double")), "a_ss": F.sum(x.cast("double") * x.cast("double"))},
            "count_distinct": {"a_set": F.collect_set(x)},
            "approx_distinct": {"a_hll": F.hll_sketch_agg(x, F.lit(14))},
        }[self.kind]

    @property
    def columns(self) -> list[str]:
        return list(self.states())

    def scaled(self, column: str, k: Column) -> Column:
        """The state after multiplication with a map of count ``k``."""
        if column == "a_s":
            return (F.col(column) * k.cast("decimal(20,0)")).cast(f"decimal(38,{self.scale})").alias(column)
        return (F.col(column) * k if column in ("a_nn", "a_d", "a_ss") else F.col(column)).alias(column)

    def merged(self, column: str) -> Column:
        """The state of a union of cells."""
        if column == "a_set":
            return F.array_distinct(F.flatten(F.collect_list(column))).alias(column)
        if column == "a_hll":
            return F.hll_union_agg(column).alias(column)
        if column == "a_s":
            return F.sum(column).cast(f"decimal(38,{self.scale})").alias(column)
        return {"a_mn": F.min, "a_mx": F.max}.get(column, F.sum)(column).alias(column)

    def result(self) -> Column:
        """The aggregate from a query's merged states; null without non-null inputs, counts 0."""
        if self.kind in ("count", "count_distinct"):
            return F.coalesce(F.col("a_nn") if self.kind == "count" else F.size("a_set").cast("long"), F.lit(0).cast("long"))
        if self.kind == "approx_distinct":
            return F.coalesce(F.hll_sketch_estimate("a_hll"), F.lit(0).cast("long"))
        if self.kind in ("min", "max"):
            return F.col("a_mn" if self.kind == "min" else "a_mx")
        some = F.col("a_nn") > 0
        if self.kind == "sum":
            return F.when(some, F.col("a_s"))
        if self.kind == "avg":
            return F.when(some, F.col("a_s").cast("double") / F.col("a_nn"))
        spread = F.greatest(F.col("a_ss") - F.col("a_d") * F.col("a_d") / F.col("a_nn"), F.lit(0.0))
        return F.when(F.col("a_nn") > 1, F.sqrt(spread / (F.col("a_nn") - 1)))
