"""Shared pieces of the training-data operators: reading, lineage cuts, Arrow mapping, distributed ranks."""

from __future__ import annotations

import contextlib
import ctypes
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: Characters that separate words in the size and shingle contracts: space, tab, line feed, vertical tab, form feed, return.
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The checkpoint folder that the cluster names. A local session without one gets a temporary folder; a cluster without one is an error."""
    context = spark.sparkContext
    if context._jsc.sc().getCheckpointDir().isEmpty():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named and not context.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        context.setCheckpointDir(named or tempfile.mkdtemp(prefix="graphweld-"))
    return context._jsc.sc().getCheckpointDir().get()


def cut(df: DataFrame) -> DataFrame:
    """Reliable checkpoint in the shared folder."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def stored(df: DataFrame) -> DataFrame:
    """The rows as a compressed Parquet table in the shared folder: for wide or many rows, which a checkpoint keeps as they are in memory."""
    path = f"{shared_folder(df.sparkSession)}/stored-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def delete_folder(spark: SparkSession, path: str) -> None:
    """Deletes a folder of a finished stage, wherever Spark keeps it."""
    target = spark._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)


def slices(batch: pa.RecordBatch, column: str, limit: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """The batch in row slices of about ``limit`` bytes of ``column``; one longer value is a slice of its own."""
    sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_pylist()
    start = total = 0
    for i, n in enumerate(sizes):
        if total and total + n > limit:
            yield batch.slice(start, i - start)
            start, total = i, 0
        total += n
    if start < len(sizes):
        yield batch.slice(start)


def give_back() -> None:
    """Free memory of a Python worker back to the system; workers outlive their tasks and would keep it through all later stages."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # other C libraries have no such call
        ctypes.CDLL(None).malloc_trim(0)


def map_slices(df: DataFrame, column: str, make: Callable[[], Callable[[pa.RecordBatch], dict | None]], schema: str, limit: int = 4 << 20) -> DataFrame:
    """mapInArrow over bounded slices. ``make`` runs once per task and returns a function from slice to columns."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    target = to_arrow_schema(_parse_datatype_string(schema))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        work = make()
        for batch in batches:
            for part in slices(batch, column, limit):
                columns = work(part)
                if columns is not None:
                    yield pa.RecordBatch.from_arrays([pa.array(columns[f.name], f.type) for f in target], schema=target)
        work = batch = part = columns = None
        give_back()

    return df.mapInArrow(run, schema)


def spread(rows: int, per_bucket: int = 200) -> int:
    """A power of two of buckets, so that a bucket of the largest key holds a few hundred rows."""
    n = 16
    while n * per_bucket < rows and n < 1 << 16:
        n *= 2
    return n


def prefix_sums(df: DataFrame, key: str, order: list[str], bucket: str, value: str, out: str) -> DataFrame:
    """Exclusive running sum of ``value`` within ``key`` by (bucket, order).

    Two levels: the sums of a key's buckets are accumulated first (one row a
    bucket), then rows run within their bucket. No task holds a whole key.
    """
    cell = [F.col(key).eqNullSafe(F.col("_k")), F.col(bucket) == F.col("_b")]
    totals = df.groupBy(key, bucket).agg(F.sum(value).alias("_t"))
    before = Window.partitionBy(key).orderBy(bucket).rowsBetween(Window.unboundedPreceding, -1)
    totals = totals.select(F.col(key).alias("_k"), F.col(bucket).alias("_b"), F.coalesce(F.sum("_t").over(before), F.lit(0)).alias("_base"))
    inside = Window.partitionBy(key, bucket).orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    run = df.withColumn("_in", F.coalesce(F.sum(value).over(inside), F.lit(0)))
    return run.join(totals, cell).withColumn(out, F.col("_base") + F.col("_in")).drop("_k", "_b", "_base", "_in")
