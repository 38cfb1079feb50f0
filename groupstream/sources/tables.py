"""The given tables, read with fixed schemas so that scans infer nothing and streams can share them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .storage import settle

_SCHEMAS = {
    "region": "r_regionkey int, r_name string",
    "nation": "n_nationkey int, n_name string, n_regionkey int",
    "customer": "c_custkey long, c_name string, c_nationkey int, c_acctbal double, c_mktsegment string",
    "supplier": "s_suppkey long, s_name string, s_nationkey int, s_acctbal double",
    "part": "p_partkey long, p_name string, p_brand string, p_type string, p_size int, p_retailprice double",
    "orders": "o_orderkey long, o_custkey long, o_orderstatus string, o_totalprice double, o_orderdate timestamp_ntz, o_orderpriority string",
    "lineitem": "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string, l_shipdate timestamp_ntz",
    "events": "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string",
    "embeddings": "vec_id long, embedding array<float>, label int",
    "documents": "doc_id long, text string, lang string, source string, n_chars long",
    "labels": "doc_id long, quality int, toxic int",
    "pages": "page_id long, url string, html string",
    "benchmark": "item_id long, text string",
    "conversations": "conv_id long, turn long, role string, text string",
}


def schema(name: str) -> T.StructType:
    return T._parse_datatype_string(_SCHEMAS[name])


class Tables:
    """The tables of one folder. `tables.orders` is a DataFrame; nothing is read before an action."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.sf_dir, self._keeps, self._lines = spark, sf_dir, False, None

    def __getattr__(self, name: str) -> DataFrame:
        if name not in _SCHEMAS:
            raise AttributeError(name)
        return self.spark.read.schema(schema(name)).parquet(f"{self.sf_dir}/{name}.parquet")

    def lines(self) -> DataFrame:
        """Who bought what from whom, and when: (u, nk, v, s, day, price), one row per order line."""
        if self._keeps and self._lines is None:
            self._lines = settle(self._joined_lines(), "lines")
        return self._joined_lines() if self._lines is None else self._lines

    def keep_lines(self) -> None:
        """From now on lines() is joined once and written out: for workloads whose many steps read it."""
        self._keeps = True

    def _joined_lines(self) -> DataFrame:
        orders = self.orders.select("o_orderkey", F.col("o_custkey").alias("u"), day(F.col("o_orderdate")).alias("day"))
        users = self.customer.select(F.col("c_custkey").alias("u"), F.col("c_nationkey").cast("long").alias("nk"))
        lines = self.lineitem.select("l_orderkey", F.col("l_partkey").alias("v"), F.col("l_suppkey").alias("s"), F.col("l_extendedprice").alias("price"))
        return lines.join(orders, lines.l_orderkey == orders.o_orderkey).join(users, "u").select("u", "nk", "v", "s", "day", "price")


def day(ts: Column) -> Column:
    """Whole days since 1970-01-01, whatever the session's time zone."""
    return F.datediff(ts, F.lit("1970-01-01").cast("date")).cast("long")


def seconds(ts: str) -> Column:
    """Whole seconds since 1970-01-01 of a timestamp without time zone."""
    return F.expr(f"timestampdiff(SECOND, timestamp_ntz'1970-01-01 00:00:00', {ts})")
