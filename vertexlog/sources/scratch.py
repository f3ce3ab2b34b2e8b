"""Tables that cut lineage: written once below ``spark.checkpoint.dir``, read back as often as needed."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; a temporary one only where the session is local and names none."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("vertexlog.scratch", None)
    if not named:
        master = spark.sparkContext.master
        if master != "local" and not master.startswith("local["):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        named = tempfile.mkdtemp(prefix="vertexlog-")
        spark.conf.set("vertexlog.scratch", named)
    return named.rstrip("/")


def delete(spark: SparkSession, path: str) -> None:
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


class Scratch:
    """An append-only directory: every table goes to a new path, nothing is overwritten."""

    def __init__(self, spark: SparkSession, tag: str) -> None:
        self.spark, self.root, self.n = spark, f"{shared_dir(spark)}/vertexlog/{tag}-{uuid.uuid4().hex}", 0

    def keep(self, df: DataFrame, name: str | None = None, by: str | None = None) -> DataFrame:
        """Write and read back; ``by`` names a column whose values become directories, each written by one task."""
        path = f"{self.root}/{name or self.n}"
        self.n += 1
        (df.repartition(by).sortWithinPartitions(by, "v").write.partitionBy(by) if by else df.write).parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self) -> None:
        """Delete all tables of this directory, once nothing reads them any more."""
        delete(self.spark, self.root)
