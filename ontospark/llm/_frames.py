"""Tables, cut lineage and blobs that all operators of this package share."""

from __future__ import annotations

import atexit
import ctypes
import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Bytes that a broadcast may hold, with what each row takes there besides its values; beyond it the same join is shuffled.
BROADCAST_BYTES, ROW_BYTES = 64 << 20, 32
#: Text that one partition of a dealt corpus takes.
PART_BYTES = 16 << 20
_own: list[str] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def parallelism(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def text_bytes(docs: DataFrame, text: str = "text") -> int:
    return int(docs.agg(F.coalesce(F.sum(F.octet_length(F.col(text).cast("binary"))), F.lit(0))).first()[0])


def parts_for(spark: SparkSession, size: int) -> int:
    """How many partitions (or buckets) a corpus of so many bytes is dealt over: they grow with it, so none of them does."""
    return max(parallelism(spark), -(-size // PART_BYTES))


def shared_dir(spark: SparkSession) -> str:
    """The folder that the cluster names for checkpoints. Only a local session without one gets a folder of its own."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named
    if not _own:
        if not spark.sparkContext.master.startswith("local") or "cluster" in spark.sparkContext.master:
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        _own.append(tempfile.mkdtemp(prefix="ontospark-"))
        import shutil

        atexit.register(shutil.rmtree, _own[0], ignore_errors=True)
    return f"file://{_own[0]}"


def cut(df: DataFrame) -> DataFrame:
    """Write a table to the shared folder and read it again: later jobs start from files that outlive any executor."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/cut-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def _width(c: Column, kind: T.DataType) -> Column:
    if isinstance(kind, T.ArrayType):
        return F.aggregate(c, F.lit(8).cast("long"), lambda n, x: n + F.coalesce(_width(x, kind.elementType), F.lit(0)))
    if isinstance(kind, T.StructType):
        return sum((F.coalesce(_width(c[f.name], f.dataType), F.lit(0)) for f in kind.fields), F.lit(8).cast("long"))
    return F.octet_length(c).cast("long") + 8 if isinstance(kind, (T.StringType, T.BinaryType)) else F.lit(8).cast("long")


def bounded(df: DataFrame, most: int = BROADCAST_BYTES) -> DataFrame:
    """Mark a cut table for broadcast if its values take few enough bytes; otherwise leave the join to shuffle."""
    row = sum((F.coalesce(_width(F.col(f.name), f.dataType), F.lit(0)) for f in df.schema.fields), F.lit(ROW_BYTES).cast("long"))
    return F.broadcast(df) if (df.agg(F.sum(row)).first()[0] or 0) <= most else df


def sliced(docs: DataFrame, text: str = "text", key: str = "doc_id") -> tuple[DataFrame, int]:
    """Documents dealt by a hash of their id into slices of a few MB (four to a partition), the text as bytes; and the number of partitions."""
    n = parts_for(docs.sparkSession, text_bytes(docs, text))
    return docs.select(
        F.col(key).cast("long").alias("doc_id"), F.col(text).cast("binary").alias("body"), F.pmod(F.xxhash64(F.col(key)), F.lit(4 * n)).cast("int").alias("slice")
    ).repartition(n, "slice"), n


def rows_of(batches: Iterable[pa.RecordBatch], *names: str) -> Iterator[tuple]:
    """Values of the named columns, row by row; few rows at a time become Python objects."""
    for batch in batches:
        for lo in range(0, batch.num_rows, 256):
            part = batch.slice(lo, 256)
            yield from zip(*(part.column(n).to_pylist() for n in names), strict=True)


def batch(schema: pa.Schema, columns: list[list]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)


#: Rows and bytes of a batch on its way to or from a Python worker. Spark holds each batch outside its heap, twice while it grows,
#: and keeps that memory; its own 10,000 rows are some 20 MB of texts.
BATCH_ROWS, BATCH_BYTES = 1000, 4 << 20


def small_batches(spark: SparkSession) -> None:
    """Bound this session's batches from here on; smaller bounds stay."""
    for name, most in (("maxRecordsPerBatch", BATCH_ROWS), ("maxBytesPerBatch", BATCH_BYTES)):
        key = f"spark.sql.execution.arrow.{name}"
        have = spark.conf.get(key).rstrip("bB")
        if not (have.isdigit() and 0 < int(have) <= most):  # 0 or less: no bound
            spark.conf.set(key, str(most))


def give_back() -> None:
    """Return what was freed to the system: Python workers are reused, and their allocators keep it for the next stage otherwise."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # not glibc
        pass


def freeing(f: Callable) -> Callable:
    """The same function over batches, which gives memory back at the end of its task."""

    def of(batches):
        try:
            yield from f(batches)
        finally:
            give_back()

    return of
