"""Shared helpers of the text operators.

Rows carry whole texts, so nothing here ever gathers documents on the driver.  Intermediate results that are
needed more than once are written as Parquet below the folder named by ``spark.checkpoint.dir``; a lost
executor then costs a re-read, not a recomputation.
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: ASCII white space as the contracts define it; fixed values.
SPACES = " \t\n\x0b\f\r"
SPACE_RUN = "[\\x20\\x09-\\x0D]+"

_SCOPES: list[list[str]] = []


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """Folder that driver and executors share; a temporary one only where the session is local and names none (tests)."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    own = spark.conf.get("vertexlog.scratch", None)
    if not own:
        master = spark.sparkContext.master
        if master != "local" and not master.startswith("local["):
            raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
        own = tempfile.mkdtemp(prefix="vertexlog-")
        spark.conf.set("vertexlog.scratch", own)
    return own


def _fresh(spark: SparkSession, tag: str) -> str:
    path = f"{shared_dir(spark)}/vertexlog/{tag}-{uuid.uuid4().hex}"
    if _SCOPES:
        _SCOPES[-1].append(path)
    return path


@contextmanager
def temporary(spark: SparkSession) -> Iterator[None]:
    """Deletes the intermediate tables made inside, once what was computed from them has been written elsewhere."""
    _SCOPES.append([])
    try:
        yield
    finally:
        for path in _SCOPES.pop():
            drop_path(spark, path)


def materialise(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` once into the shared folder and read it back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = _fresh(spark, tag)
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def drop_path(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


class Scratch:
    """Numbered tables of one iterative job; those no longer needed are deleted as it goes on."""

    def __init__(self, spark: SparkSession, tag: str) -> None:
        self.spark = spark
        self.root = _fresh(spark, tag)
        self.made: list[str] = []

    def keep(self, df: DataFrame) -> DataFrame:
        path = f"{self.root}/{len(self.made)}"
        df.write.parquet(path)
        self.made.append(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def forget(self, keep_last: int = 1) -> None:
        for path in self.made[: len(self.made) - keep_last]:
            if path:
                drop_path(self.spark, path)
        self.made = ["" for _ in self.made[: len(self.made) - keep_last]] + self.made[len(self.made) - keep_last :]


def same(a: Column, b: Column) -> Column:
    return a.eqNullSafe(b)


def words_of(text: Column) -> Column:
    """Array of the words of a text (runs without ASCII white space); empty for null or blank text."""
    trimmed = F.btrim(F.coalesce(text, F.lit("")), F.lit(SPACES))
    return F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, SPACE_RUN, -1))


def let(value: Column, body) -> Column:
    """``body`` of a value that is computed once per row, however often the body uses it."""
    return F.element_at(F.transform(F.array(value), body), 1)


def once(df: DataFrame, name: str, value: Column) -> DataFrame:
    """``df`` with a column that is computed once per row.

    A plain column is copied by the optimizer to every place that reads it, filters included; nothing is copied
    through a generator, so the value goes through one that makes one row of each.
    """
    return df.select("*", F.explode(F.array(value)).alias(name))


def ordinal(df: DataFrame, *keys: str, name: str = "ord") -> DataFrame:
    """``df`` with its zero-based place in key order, written by ranges so that no task numbers more than one."""
    rows = materialise(df.repartitionByRange(*keys).withColumn("__range", F.spark_partition_id()), "ordinal")
    counts = rows.groupBy("__range").agg(F.count("*").alias("__n"))
    before = counts.withColumn("__before", F.sum("__n").over(Window.orderBy("__range")) - F.col("__n")).drop("__n")
    own = F.row_number().over(Window.partitionBy("__range").orderBy(*keys)) - 1
    return rows.withColumn("__own", own).join(F.broadcast(before), "__range").withColumn(name, (F.col("__own") + F.col("__before")).cast("bigint")).drop("__own", "__before", "__range")
