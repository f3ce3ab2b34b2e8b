"""The given tables, and global ordinals without a single-task window."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from vertexlog.sources.scratch import Scratch


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ordinal(df: DataFrame, *keys: str, name: str = "ord") -> DataFrame:
    """``df`` with its zero-based place in key order.

    Rows are dealt out by key ranges and written once, since range borders come from a sample; places are ranks
    within a range plus the counts of the ranges before, so no task sees more than its range.
    """
    dealt = df.repartitionByRange(*keys).withColumn("__range", F.spark_partition_id())
    rows = Scratch(df.sparkSession, "ordinal").keep(dealt)
    counts = rows.groupBy("__range").agg(F.count("*").alias("__n"))
    before = counts.withColumn("__before", F.sum("__n").over(Window.orderBy("__range")) - F.col("__n")).drop("__n")
    own = F.row_number().over(Window.partitionBy("__range").orderBy(*keys)) - 1
    placed = rows.withColumn("__own", own).join(F.broadcast(before), "__range")
    return placed.withColumn(name, (F.col("__own") + F.col("__before")).cast("bigint")).drop("__own", "__before", "__range")
