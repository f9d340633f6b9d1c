"""Cutting lineage between the rounds of a mining run, and dropping what a run leaves behind."""

from __future__ import annotations

import tempfile
import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

#: Tables written inside open scopes, innermost last.
_SCOPES: list[list[str]] = []


def one_process(spark: SparkSession) -> bool:
    master = spark.sparkContext.master
    return master.startswith("local") and not master.startswith("local-cluster")


def shared_dir(spark: SparkSession) -> str:
    """The checkpoint folder that all executors share; a temporary one only in a single process."""
    context = spark.sparkContext
    found = context._jsc.sc().getCheckpointDir()
    if found.isDefined():
        return found.get()
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        if not one_process(spark):
            raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
        named = "file://" + tempfile.mkdtemp(prefix="copath-")
    context.setCheckpointDir(named)
    return context._jsc.sc().getCheckpointDir().get()


def cut(df: DataFrame) -> DataFrame:
    """The same rows without their history: a table in the shared folder, which any executor can read again."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/copath-{uuid.uuid4().hex}"
    df.write.parquet(path)
    if _SCOPES:
        _SCOPES[-1].append(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._copath_path = path
    return out


def _file(spark: SparkSession, path: str):
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), where


#: Spark keeps the shuffle files of a job until the driver's garbage collector meets what refers to them, unless told to drop them with the job.
DROP_SHUFFLES = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextmanager
def freed(spark: SparkSession):
    """Jobs inside leave no shuffle files; what they return must be rows, or tables that were cut."""
    before = spark.conf.get(DROP_SHUFFLES, None)
    spark.conf.set(DROP_SHUFFLES, "true")
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(DROP_SHUFFLES)
        else:
            spark.conf.set(DROP_SHUFFLES, before)


def bytes_of(spark: SparkSession, path: str) -> int:
    files, where = _file(spark, path)
    return files.getContentSummary(where).getLength() if files.exists(where) else 0


class Scope:
    """The tables that a run writes."""

    def __init__(self, spark: SparkSession, paths: list[str]):
        self.spark, self.paths, self.kept = spark, paths, set()

    def keep(self, *tables: DataFrame | None) -> None:
        self.kept |= {getattr(t, "_copath_path", None) for t in tables if t is not None}

    def bytes(self) -> int:
        return sum(bytes_of(self.spark, p) for p in self.paths)


@contextmanager
def scope(spark: SparkSession):
    """Drops the tables cut inside, but for those that are kept, when the block ends; a block around it drops these at its own end."""
    s = Scope(spark, [])
    _SCOPES.append(s.paths)
    try:
        with freed(spark):
            yield s
    finally:
        _SCOPES.remove(s.paths)
        for p in s.paths:
            if p not in s.kept:
                files, where = _file(spark, p)
                files.delete(where, True)
        if _SCOPES:
            _SCOPES[-1] += [p for p in s.paths if p in s.kept]
