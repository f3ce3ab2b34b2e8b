"""Vertex sources: lazy lists (v, val) and their algebra.  Nothing runs until a list is written or counted."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from vertexlog.sources.tables import ordinal


def write_sparse(values: DataFrame, path: str) -> None:
    """A sorted list of the vertices that have a value; row groups carry its key ranges."""
    values.repartitionByRange("v").sortWithinPartitions("v").write.parquet(path)


def write_dense(values: DataFrame, n: int, path: str, width: int = 1 << 20) -> None:
    """All n vertices, in directories of equal key ranges, with a bloom filter on the key."""
    every = values.sparkSession.range(n).select(F.col("id").alias("v")).join(values, "v", "left")
    laid = every.withColumn("v_part", F.expr(f"v div {width}")).repartition("v_part").sortWithinPartitions("v")
    laid.write.option("parquet.bloom.filter.enabled#v", "true").partitionBy("v_part").parquet(path)


def sparse(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path).select("v", "val")


def dense(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path).select("v", "val")


def seek(source: DataFrame, index: int) -> DataFrame:
    """From a vertex on; on files this skips row groups."""
    return source.where(F.col("v") >= index)


def arith(source: DataFrame, f: Callable[[Column], Column]) -> DataFrame:
    return source.select("v", f(F.col("val")).alias("val"))


def union(*sources: DataFrame) -> DataFrame:
    """All vertices; on equal ones the value of the source named first, nulls included."""
    ranked = [s.select("v", "val", F.lit(i).alias("rank")) for i, s in enumerate(sources)]
    every = reduce(DataFrame.unionByName, ranked)
    return every.groupBy("v").agg(F.min_by(F.struct("val"), "rank").alias("s")).select("v", F.col("s.val").alias("val"))


def difference(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.join(b.select("v"), "v", "left_anti")


def intersect(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.join(b.select("v"), "v", "left_semi")


def minimum(a: DataFrame, b: DataFrame) -> DataFrame:
    return custom(a, b, F.least)


def custom(a: DataFrame, b: DataFrame, f: Callable[[Column, Column], Column], how: str = "inner") -> DataFrame:
    """Value of a function where vertices meet; with ``how="outer"`` a vertex of one source keeps its value."""
    x = a.select("v", F.col("val").alias("x"), F.lit(True).alias("in_x"))
    y = b.select("v", F.col("val").alias("y"), F.lit(True).alias("in_y"))
    val = F.when(F.col("in_x") & F.col("in_y"), f(F.col("x"), F.col("y"))).when(F.col("in_x"), F.col("x")).otherwise(F.col("y"))
    return x.join(y, "v", how).select("v", val.alias("val"))


def converge(a: DataFrame, b: DataFrame, settled: Callable[[Column, Column], Column]) -> DataFrame:
    """Vertices of both lists whose two values do not count as settled, with the value of the first."""
    x, y = a.select("v", "val"), b.select("v", F.col("val").alias("other"))
    return x.join(y, "v").where(~settled(F.col("val"), F.col("other"))).select("v", "val")


def cascade(lists: list[DataFrame], agg: Callable[[Column], Column]) -> DataFrame:
    """One union of many lists with a folding function on equal vertices, in a single exchange."""
    return reduce(DataFrame.unionByName, lists).groupBy("v").agg(agg(F.col("val")).alias("val"))


def split(source: DataFrame, run: int, ways: int) -> DataFrame:
    """Runs of ``run`` vertices in order, dealt to ``ways`` outputs in turn: (v, val, way)."""
    placed = ordinal(source, "v")
    return placed.select("v", "val", F.pmod(F.expr(f"ord div {run}"), F.lit(ways)).cast("int").alias("way"))
