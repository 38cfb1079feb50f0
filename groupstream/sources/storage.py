"""Sinks and round trips: files by format, partitioned and bucketed tables, and models as one-row tables."""

from __future__ import annotations

import json
import shutil
import tempfile
import uuid

import numpy as np
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or in local mode a temporary one."""
    if path := spark.conf.get("spark.checkpoint.dir", None):
        return path.rstrip("/")
    context = spark.sparkContext
    if not context.getCheckpointDir():
        if not context.master.startswith("local[") and context.master != "local":
            raise ValueError("spark.checkpoint.dir is not set: a cluster has to name a folder that all executors share")
        context.setCheckpointDir(tempfile.mkdtemp(prefix="groupstream-"))
    return context.getCheckpointDir().rstrip("/")


def settle(df: DataFrame, tag: str = "round") -> DataFrame:
    """df as a table in the shared folder: ends the lineage of iterative methods and survives lost executors."""
    path = f"{shared_dir(df.sparkSession)}/groupstream-{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def new_folder(spark: SparkSession, tag: str) -> str:
    """The name of a new folder in the shared one, for files that tasks write themselves."""
    return f"{shared_dir(spark)}/groupstream-{tag}-{uuid.uuid4().hex}"


def file_system(path: str) -> tuple[fs.FileSystem, str]:
    """The file system of a path as Spark names it, and the path there."""
    if path.startswith(("file:", "/")):
        return fs.LocalFileSystem(), "/" + path.removeprefix("file:").lstrip("/")
    return fs.FileSystem.from_uri(path)


def mapped(path: str, kind: type) -> np.ndarray:
    """A file of numbers, mapped; one of a file system that is not mounted is copied to a temporary file first."""
    files, at = file_system(path)
    if isinstance(files, fs.LocalFileSystem):
        return np.memmap(at, kind, "r")
    with tempfile.TemporaryFile() as copy, files.open_input_stream(at) as found:
        shutil.copyfileobj(found, copy)
        copy.flush()
        return np.memmap(copy, kind, "r")


def write(df: DataFrame, path: str, fmt: str = "parquet", partition_by: tuple[str, ...] = (), **options) -> None:
    writer = df.write.mode("overwrite").format(fmt).options(**options)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)


def round_trip(df: DataFrame, fmt: str, **options) -> DataFrame:
    """df written in a format and read again with its own schema."""
    path = f"{shared_dir(df.sparkSession)}/groupstream-{fmt}-{uuid.uuid4().hex}"
    write(df, path, fmt, **options)
    return df.sparkSession.read.format(fmt).options(**options).schema(df.schema).load(path)


def save_bucketed(df: DataFrame, name: str, buckets: int, by: str, sort: str | None = None, path: str | None = None) -> None:
    """A table dealt into buckets, which joins on `by` read without an exchange; at `path`, or in the warehouse."""
    writer = df.write.mode("overwrite").format("parquet").bucketBy(buckets, by)
    writer = writer.option("path", path) if path else writer
    (writer.sortBy(sort) if sort else writer).saveAsTable(name)


def save_model(spark: SparkSession, path: str, weights: dict[str, np.ndarray], meta: dict | None = None) -> None:
    rows = [(k, list(w.shape), [float(x) for x in w.ravel()], json.dumps(meta or {})) for k, w in weights.items()]
    spark.createDataFrame(rows, "name string, shape array<int>, weights array<double>, meta string").coalesce(1).write.mode("overwrite").parquet(path)


def load_model(spark: SparkSession, path: str) -> tuple[dict[str, np.ndarray], dict]:
    rows = spark.read.parquet(path).collect()  # one row per weight matrix
    return {r["name"]: np.array(r["weights"]).reshape(r["shape"]) for r in rows}, json.loads(rows[0]["meta"]) if rows else {}


def empty_array(kind: str):
    return F.expr(f"cast(array() as array<{kind}>)")
