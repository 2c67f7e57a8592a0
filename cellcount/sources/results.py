"""Sinks for counts and training pairs, and layouts for tables that many patterns join."""

from __future__ import annotations

import json
from collections.abc import Sequence

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.model import CountQuery
from ..plans.sqlfront import condition_text, join_text


def write(df: DataFrame, path: str, fmt: str = "parquet", by: Sequence[str] = (), mode: str = "overwrite") -> None:
    """Counts to csv, json, orc or parquet files, partitioned by columns where asked."""
    w = df.write.mode(mode).format(fmt)
    if fmt == "csv":
        w = w.option("header", True)
    (w.partitionBy(*by) if by else w).save(path)


def read(spark, path: str, fmt: str = "parquet", schema: str = "query_id string, n bigint") -> DataFrame:
    r = spark.read.format(fmt).schema(schema)
    return (r.option("header", True) if fmt == "csv" else r).load(path)


def local_counts(spark, rows: Sequence[tuple[str, int]]) -> DataFrame:
    """query_id, n of counts that the driver holds, as rows of the plan itself: reading them takes no Python worker."""
    table = pa.table({"query_id": pa.array([q for q, _ in rows], pa.string()), "n": pa.array([n for _, n in rows], pa.int64())})
    return spark.createDataFrame(table, "query_id string, n bigint") if rows else spark.createDataFrame([], "query_id string, n bigint")


def features(q: CountQuery) -> dict[str, str]:
    """A query as text features: tables, joins and conditions."""
    conditions = [c for a, i in q.ranges for c in condition_text(a, i)]
    return {"tables": ",".join(sorted(q.tables)), "joins": ";".join(join_text(q.classes)), "conditions": ";".join(conditions)}


def training_pairs(queries: Sequence[CountQuery], counts: DataFrame) -> DataFrame:
    """query_id, tables, joins, conditions, n: what a cardinality model learns from."""
    spark = counts.sparkSession
    rows = [(q.id, *features(q).values()) for q in queries]
    f = spark.createDataFrame(rows, "query_id string, tables string, joins string, conditions string")
    return f.join(counts.select("query_id", "n"), "query_id")


def batch_table(spark, queries: Sequence[CountQuery]) -> DataFrame:
    """The batch itself as rows: id, pattern, tables, join classes and ranges (as JSON text by attribute)."""
    say = lambda v: None if v is None else str(v)
    rows = [(q.id, q.pattern.key, sorted(q.tables), [sorted(c) for c in sorted(q.classes, key=sorted)], {a: json.dumps([say(i.lo), i.lo_incl, say(i.hi), i.hi_incl]) for a, i in q.ranges}) for q in queries]
    return spark.createDataFrame(rows, "query_id string, pattern_id string, tables array<string>, join_classes array<array<string>>, ranges map<string,string>")


def bucket_by_join_key(df: DataFrame, table: str, key: str, buckets: int = 64) -> None:
    """Save a table bucketed and sorted by a join key: joins and groupings on it then need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)


def cluster_by(df: DataFrame, path: str, key: str, partitions: int = 64) -> None:
    """Save a table in key ranges, so that a range of keys reads few row groups."""
    df.repartitionByRange(partitions, F.col(key)).sortWithinPartitions(key).write.mode("overwrite").parquet(path)
