"""Where intermediate tables go: the folder that all executors share."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from copath.plans import store


def shared_dir(spark: SparkSession) -> str:
    """The cluster's checkpoint folder; a temporary one only where none is set and everything runs in one process."""
    return store.shared_dir(spark)


def write_table(df: DataFrame) -> tuple[DataFrame, str]:
    """Writes a table to the shared folder and reads it again: lineage ends here. Also returns its path."""
    path = f"{shared_dir(df.sparkSession)}/copath-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path), path


def drop_table(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


class Tables:
    """Intermediate tables of one operator, dropped together once nothing reads them any more."""

    def __init__(self, spark: SparkSession):
        self.spark, self.paths = spark, []

    def write(self, df: DataFrame) -> DataFrame:
        table, path = write_table(df)
        self.paths.append(path)
        return table

    def drop(self) -> None:
        for path in self.paths:
            drop_table(self.spark, path)
        self.paths = []


def free_name(df: DataFrame, name: str) -> str:
    """A column name like ``name`` that the frame doesn't have."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name = f"_{name}"
    return name


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
