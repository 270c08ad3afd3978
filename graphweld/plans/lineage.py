"""Reading tables and cutting the lineage of loops by written tables in the shared folder."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


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


#: Folders of written tables, innermost scratch last.
_OPEN: list[list[str]] = []


def cut(df: DataFrame) -> DataFrame:
    """The rows as a written table, which has no lineage and a size that the planner knows."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/cut-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._cut_path = path
    if _OPEN:
        _OPEN[-1].append(path)
    return out


def cuts(*frames: DataFrame) -> list[DataFrame]:
    """``cut`` of several tables that do not need each other, at the same time: small jobs leave most of a cluster idle."""
    shared_folder(frames[0].sparkSession)
    with ThreadPoolExecutor(len(frames)) as pool:
        return list(pool.map(cut, frames))


def at_once(*steps: Callable) -> list:
    """Results of steps that do not need each other and write their own tables, run at the same time."""
    with ThreadPoolExecutor(len(steps)) as pool:
        return list(pool.map(lambda step: step(), steps))


def written(df: DataFrame) -> DataFrame:
    """The rows as a written table, which they may be already."""
    return df if getattr(df, "_cut_path", None) else cut(df)


def keep(df: DataFrame) -> DataFrame:
    """Lets a cut table outlive the scratch that it was written in."""
    path = getattr(df, "_cut_path", None)
    if _OPEN and path in _OPEN[-1]:
        _OPEN[-1].remove(path)
        if len(_OPEN) > 1:
            _OPEN[-2].append(path)
    return df


def delete_folder(spark: SparkSession, path: str) -> None:
    target = spark._jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark._jsc.hadoopConfiguration()).delete(target, True)


def release(*frames: DataFrame | None) -> None:
    """Deletes the tables of frames that nothing reads any more."""
    for df in frames:
        path = getattr(df, "_cut_path", None)
        if path:
            delete_folder(df.sparkSession, path)


@contextmanager
def scratch(spark: SparkSession) -> Iterator[None]:
    """Deletes all tables cut inside at its end, but for those kept."""
    _OPEN.append([])
    try:
        yield
    finally:
        for path in _OPEN.pop():
            delete_folder(spark, path)
