"""SQL names for the vector and hash functions, so that SQL users reach the same plans."""

from __future__ import annotations

from pyspark.sql import SparkSession


def register(spark: SparkSession, tables=None) -> None:
    """Temporary SQL functions gs_dot, gs_norm, gs_cosine, gs_uniform, gs_sigmoid, and views of the tables, if given."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION gs_dot(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION gs_norm(a ARRAY<DOUBLE>) RETURNS DOUBLE RETURN sqrt(gs_dot(a, a))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION gs_cosine(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE RETURN CASE WHEN gs_norm(a) * gs_norm(b) > 0 THEN gs_dot(a, b) / (gs_norm(a) * gs_norm(b)) ELSE 0D END")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION gs_sigmoid(x DOUBLE) RETURNS DOUBLE RETURN 1D / (1D + exp(-x))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION gs_uniform(salt STRING, k STRING) RETURNS DOUBLE RETURN CAST(conv(substr(md5(concat_ws('|', salt, k)), 1, 8), 16, 10) AS DOUBLE) / 4294967296D")
    for name in ("nation", "customer", "orders", "lineitem", "part", "events", "embeddings") if tables is not None else ():
        getattr(tables, name).createOrReplaceTempView(f"gs_{name}")
