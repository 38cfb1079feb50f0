"""What the operators of this subpackage share: tables, lineage cuts, words and hashes."""

from __future__ import annotations

import contextlib
import ctypes
import tempfile
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: A word: a run of bytes that are not ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that the driver and all executors see: the cluster's spark.checkpoint.dir.

    Only a session on one machine may go without the setting; it then gets a temporary folder.
    """
    if path := spark.conf.get("spark.checkpoint.dir", None):
        return path.rstrip("/")
    context = spark.sparkContext
    if path := context.getCheckpointDir():
        return path.rstrip("/")
    if not context.master.startswith("local[") and context.master != "local":
        raise ValueError("spark.checkpoint.dir is not set: a cluster has to name a folder that all executors share")
    context.setCheckpointDir(tempfile.mkdtemp(prefix="groupstream-"))
    return context.getCheckpointDir().rstrip("/")


_scratch: list[list[str]] = []


def new_folder(spark: SparkSession, tag: str) -> str:
    path = f"{shared_dir(spark)}/groupstream-{tag}-{uuid.uuid4().hex}"
    if _scratch:
        _scratch[-1].append(path)
    return path


@contextlib.contextmanager
def scratch(spark: SparkSession):
    """Removes at its end what was written to new folders inside: for work whose result is stored by then."""
    _scratch.append([])
    try:
        yield
    finally:
        for path in _scratch.pop():
            remove(spark, path)


def remove(spark: SparkSession, path: str) -> None:
    path = spark._jvm.org.apache.hadoop.fs.Path(path)
    path.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(path, True)


def cut(df: DataFrame, tag: str) -> DataFrame:
    """Write df as a table in the shared folder and read it again, which ends its lineage.

    A lost executor then costs only what was computed after this point.
    """
    spark = df.sparkSession
    path = new_folder(spark, tag)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def drop_cut(df: DataFrame) -> None:
    """Remove the files of a table made by cut() that nothing will read again."""
    for name in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        remove(df.sparkSession, name)


def partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def md5_bits(column: Column, digits: int = 15) -> Column:
    """The first hexadecimal digits of the MD5 of a string, as a non-negative long."""
    return F.conv(F.substring(F.md5(column), 1, digits), 16, 10).cast("long")


def long_id(df: DataFrame, id_column: str) -> Column:
    """The id as a long. Ids of other types than whole numbers are refused, since a cast would lose or stop at some."""
    kind = df.schema[id_column].dataType
    if not isinstance(kind, T.IntegralType):
        raise TypeError(f"{id_column} is {kind.simpleString()}; ids have to be whole numbers")
    return F.col(id_column).cast("long")


def share_of(rows: int, wanted: int, hashed: Column) -> Column:
    """A condition that about `wanted` of so many rows meet, by a hash of them: so that few rows are put in order or sent
    anywhere when a bounded sample is taken, whatever the number of partitions."""
    return F.pmod(hashed, F.lit(1 << 30)) < F.lit(int(min(1.0, wanted / max(1, rows)) * (1 << 30)))


def n_words(text: Column) -> Column:
    return F.regexp_count(F.coalesce(text, F.lit("")), F.lit(WORD)).cast("long")


def slices(batches: Iterator[pa.RecordBatch], rows: int = 256) -> Iterator[pa.RecordBatch]:
    """Arrow batches a few rows at a time, so that a kernel holds few texts as Python objects.

    At the end the worker, which stays for later stages, gives the memory it no longer needs back to the machine.
    """
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield batch.slice(at, rows)
        del batch
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # not glibc
        pass
