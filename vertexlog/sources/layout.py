"""Graphs on storage: edge files in source order with an index of ordinals, dense and sparse vertex files."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vertexlog.sources.tables import ordinal


def edge_file(edges: DataFrame) -> DataFrame:
    """Edges with their place in (src, dst) order."""
    return ordinal(edges, *[c for c in ("src", "dst", "w") if c in edges.columns])


def edge_index(laid: DataFrame) -> DataFrame:
    """(src, first_ordinal, degree): where the out-edges of each source lie."""
    return laid.groupBy("src").agg(F.min("ord").alias("first_ordinal"), F.count("*").alias("degree"))


def build_edges(edges: DataFrame, path: str, width: int = 1 << 20) -> None:
    """Write edges in directories of source ranges, sorted inside, and the index beside them.

    A frontier names the ranges it needs, so other directories are never opened.
    """
    laid = edge_file(edges).withColumn("src_part", F.expr(f"src div {width}"))
    laid.repartition("src_part").sortWithinPartitions("src", "dst").write.partitionBy("src_part").parquet(f"{path}/edges")
    spark = edges.sparkSession
    edge_index(spark.read.parquet(f"{path}/edges")).write.parquet(f"{path}/index")


def write_bucketed(rows: DataFrame, path: str, key: str, buckets: int) -> DataFrame:
    """Rows in bucket files by a key, sorted inside, and a table over them whose joins and folds by that key need no exchange.

    The name in the catalog is one of its own and goes again; the returned table keeps its bucket layout.
    """
    spark, name = rows.sparkSession, f"bucketed_{uuid.uuid4().hex}"
    placed = rows.repartition(buckets, key)  # one file a bucket, where each task would write one into every bucket
    placed.write.bucketBy(buckets, key).sortBy(key).format("parquet").option("path", path).saveAsTable(name)
    table = spark.table(name)
    spark.sql(f"drop table {name}")
    return table


def read_edges(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(f"{path}/edges")


def out_edges(laid: DataFrame, index: DataFrame, sources: list[int]) -> DataFrame:
    """Out-edges of some sources by their ordinal ranges."""
    ranges = index.where(F.col("src").isin(sources)).select("first_ordinal", "degree")
    inside = (F.col("ord") >= F.col("first_ordinal")) & (F.col("ord") < F.col("first_ordinal") + F.col("degree"))
    named = laid.where(F.col("src").isin(sources))
    return named.join(F.broadcast(ranges), inside).select("src", "dst")


def edges_of(active: DataFrame, edges: DataFrame, strategy: str = "auto", share: float = 0.05, degrees: DataFrame | None = None, most_seek: int = 10_000) -> DataFrame:
    """Edges that leave active vertices.

    ``seek`` names the sources in the scan's filter and prunes files and row groups; ``scan`` joins all edges;
    ``auto`` seeks if the active out-degrees are at most ``share`` of all edges and the list is short.
    """
    if strategy == "auto":
        stats = degrees if degrees is not None else edges.groupBy(F.col("src").alias("v")).agg(F.count("*").alias("degree"))
        on = active.select("v", F.lit(1).alias("on"))
        row = stats.join(on, "v", "left").agg(F.sum("degree").alias("m"), F.sum(F.when(F.col("on") == 1, F.col("degree"))).alias("a"), F.count("on").alias("n")).first()
        strategy = "seek" if row["n"] <= most_seek and (row["a"] or 0) <= share * (row["m"] or 0) else "scan"
    if strategy == "seek":
        wanted = [r["v"] for r in active.select("v").limit(most_seek + 1).collect()]
        if len(wanted) <= most_seek:
            return edges.where(F.col("src").isin(wanted))
    return edges.join(active.select(F.col("v").alias("src")), "src", "left_semi").select(edges.columns)


def choose_encoding(values: DataFrame, n: int, threshold: float = 0.5) -> str:
    """Dense files pay when most vertices have a value."""
    return "dense" if values.count() >= threshold * n else "sparse"


def import_text(spark: SparkSession, path: str, sep: str = "\t") -> DataFrame:
    """Edges from text lines ``source sep destination``; lines starting with # are remarks."""
    return spark.read.csv(path, sep=sep, comment="#", schema="src bigint, dst bigint")


def stored_bytes(spark: SparkSession, path: str) -> int:
    """Bytes of the files below a path, wherever it is."""
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    where = jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(conf).getContentSummary(where).getLength()


def stripe(size: int, devices: int, piece: int = 1 << 20) -> list[tuple[int, int]]:
    """(device, bytes) when a file is dealt out to devices in turn, piece by piece."""
    whole, rest = divmod(size, piece)
    out = [[d, (whole // devices + (d < whole % devices)) * piece] for d in range(devices)]
    if rest:
        out[whole % devices][1] += rest
    return [tuple(x) for x in out]
