"""The catalog: tables, their declared keys and the join graph that the keys span."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..cluster import ship


@dataclass(frozen=True)
class TableInfo:
    """``pk``: the unique column, if any. ``fks``: (column, table it points to, that table's unique column)."""

    name: str
    pk: str | None = None
    fks: tuple[tuple[str, str, str], ...] = ()


_TABLES = (
    TableInfo("region", "r_regionkey"),
    TableInfo("nation", "n_nationkey", (("n_regionkey", "region", "r_regionkey"),)),
    TableInfo("customer", "c_custkey", (("c_nationkey", "nation", "n_nationkey"),)),
    TableInfo("supplier", "s_suppkey", (("s_nationkey", "nation", "n_nationkey"),)),
    TableInfo("part", "p_partkey"),
    TableInfo("orders", "o_orderkey", (("o_custkey", "customer", "c_custkey"),)),
    TableInfo("lineitem", None, (("l_orderkey", "orders", "o_orderkey"), ("l_partkey", "part", "p_partkey"), ("l_suppkey", "supplier", "s_suppkey"))),
    TableInfo("events", "event_id", (("user_id", "customer", "c_custkey"),)),
    TableInfo("documents", "doc_id"),
    TableInfo("labels", "doc_id"),
    TableInfo("embeddings", "vec_id"),
    TableInfo("pages", "page_id"),
    TableInfo("benchmark", "item_id"),
    TableInfo("conversations"),
)
CATALOG = {t.name: t for t in _TABLES}

#: Edges of the join graph by code.
EDGES = {
    "rn": ("region.r_regionkey", "nation.n_regionkey"),
    "nc": ("nation.n_nationkey", "customer.c_nationkey"),
    "ns": ("nation.n_nationkey", "supplier.s_nationkey"),
    "co": ("customer.c_custkey", "orders.o_custkey"),
    "ce": ("customer.c_custkey", "events.user_id"),
    "ol": ("orders.o_orderkey", "lineitem.l_orderkey"),
    "lp": ("part.p_partkey", "lineitem.l_partkey"),
    "ls": ("supplier.s_suppkey", "lineitem.l_suppkey"),
    "oe": ("orders.o_custkey", "events.user_id"),
    "cs": ("customer.c_nationkey", "supplier.s_nationkey"),
    "dl": ("documents.doc_id", "labels.doc_id"),
}

#: Prefix of a column name -> table; names without such a prefix are listed.
_PREFIX = {"r_": "region", "n_": "nation", "c_": "customer", "s_": "supplier", "p_": "part", "o_": "orders", "l_": "lineitem"}
_OWN = {"event_id": "events", "ts": "events", "user_id": "events", "event_type": "events", "value": "events", "props": "events"}


def owner(column: str) -> str | None:
    """The table of an unqualified column of the relational tables."""
    return _OWN.get(column) or (_PREFIX.get(column[:2]) if column != "n_chars" else "documents")


class Tables(dict):
    """name -> DataFrame, read when first asked for; ``aliases`` give a table a second name."""

    def __init__(self, spark: SparkSession, sf_dir: str, aliases: dict[str, str] | None = None):
        super().__init__()
        ship(spark)
        self.spark, self.sf_dir, self.aliases = spark, sf_dir, aliases or {}
        self._rows: dict[str, int] = {}

    def rows(self, name: str) -> int:
        """Rows of a table, counted once until it is replaced."""
        if name not in self._rows:
            self._rows[name] = self[name].count()
        return self._rows[name]

    def __setitem__(self, name: str, df: DataFrame) -> None:
        self._rows.pop(name, None)
        super().__setitem__(name, df)

    def __missing__(self, name: str) -> DataFrame:
        self[name] = df = self.spark.read.parquet(f"{self.sf_dir}/{self.aliases.get(name, name)}.parquet")
        return df


def load(spark: SparkSession, sf_dir: str, views: bool = False) -> Tables:
    """The tables of a folder; with ``views`` also as temporary views for SQL."""
    out = Tables(spark, sf_dir)
    if views:
        for name in CATALOG:
            out[name].createOrReplaceTempView(name)
    return out


def from_jdbc(spark: SparkSession, url: str, table: str, column: str | None = None, bounds: tuple = (0, 0), partitions: int = 1) -> DataFrame:
    """A table of another database; with ``column`` read in parallel ranges."""
    reader = spark.read.format("jdbc").option("url", url).option("dbtable", table)
    if column:
        reader = reader.option("partitionColumn", column).option("lowerBound", bounds[0]).option("upperBound", bounds[1]).option("numPartitions", partitions)
    return reader.load()


def is_unique(df: DataFrame, column: str) -> bool:
    """Whether no value occurs twice, which Parquet does not enforce and FK-PK folding needs."""
    return not df.where(F.col(column).isNotNull()).groupBy(column).count().where("count > 1").limit(1).count()


def assert_unique(df: DataFrame, column: str) -> None:
    if not is_unique(df, column):
        raise ValueError(f"{column} is declared unique but is not")
