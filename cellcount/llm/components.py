"""Connected components by joins: nothing is gathered per node, every step is an aggregation and a join."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop_stage, stage


def components(edges: DataFrame, a: str = "a", b: str = "b", most: int | None = None) -> DataFrame:
    """node, component: the smallest node that each node of ``edges`` reaches. Nodes without edges don't appear.

    Rounds of two steps until no label changes. Each node takes the smallest label among its neighbours
    (a partial aggregation, so a node with a third of all edges costs a row for each task), then the label of
    its label (pointer jumping), which halves the longest chain. Each round's labels are a table in the shared
    folder, in as many files as its rows need. ``most``: a bound of the number of edges, else they are counted. Null ends, loops and repeated edges change nothing; no edges give an empty result.
    """
    e = edges.select(F.col(a).alias("u"), F.col(b).alias("v")).where("u <> v")
    n = 2 * (edges.count() if most is None else most)
    both = stage(e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v"))).distinct(), "edges", n)
    labels = stage(both.groupBy("u").agg(F.least(F.col("u"), F.min("v")).alias("l")), "labels", n)
    while True:
        near = both.join(labels.select(F.col("u").alias("v"), F.col("l").alias("lv")), "v").groupBy("u").agg(F.min("lv").alias("lv"))
        low = labels.join(near, "u").select("u", "l", F.least("l", "lv").alias("m"))
        jump = labels.select(F.col("u").alias("m"), F.col("l").alias("lm"))
        new = stage(low.join(jump, "m", "left").select("u", F.least("m", F.coalesce("lm", "m")).alias("l"), (F.col("l") != F.least("m", F.coalesce("lm", "m"))).alias("changed")), "labels", n)
        changed = new.where("changed").limit(1).count()
        drop_stage(labels)
        labels = new.drop("changed")
        if not changed:
            drop_stage(both)
            return labels.select(F.col("u").alias("node"), F.col("l").alias("component"))
