"""Nearest neighbours of a stated set of queries among all rows, by cosine."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def nearest(rows: DataFrame, queries: DataFrame, id_col: str, vector_col: str, k: int, block: int = 10_000) -> DataFrame:
    """(src, dst, cosine, rank): exact, blocks of at most ``block`` queries against all rows.

    Each task keeps the k best of its rows for every query, so what is shuffled is k rows per query and task.
    """
    spark = rows.sparkSession
    blocks = max(1, -(-queries.count() // block))
    found = None
    for b in range(blocks):
        part = queries.where(F.pmod(F.xxhash64(id_col), F.lit(blocks)) == b) if blocks > 1 else queries
        held = part.select(id_col, vector_col).collect()
        shared = spark.sparkContext.broadcast((np.array([r[0] for r in held], np.int64), _unit(np.array([r[1] for r in held], float))))

        def run(batches: Iterator[pa.RecordBatch], shared: object = shared) -> Iterator[pa.RecordBatch]:
            ids, wanted = shared.value
            best_id = np.full((len(ids), 0), 0, np.int64)
            best = np.full((len(ids), 0), 0.0)
            for batch in batches:
                if not batch.num_rows or not len(ids):
                    continue
                own = batch.column(0).to_numpy(zero_copy_only=False)
                near = wanted @ _unit(np.array(batch.column(1).to_pylist(), float)).T
                near[ids[:, None] == own[None, :]] = -np.inf
                best = np.concatenate([best, near], axis=1)
                best_id = np.concatenate([best_id, np.broadcast_to(own, near.shape)], axis=1)
                order = np.lexsort((best_id, -best))[:, :k]
                best, best_id = np.take_along_axis(best, order, 1), np.take_along_axis(best_id, order, 1)
            real = np.isfinite(best)
            yield pa.RecordBatch.from_arrays([pa.array(np.broadcast_to(ids[:, None], best.shape)[real]), pa.array(best_id[real]), pa.array(best[real])], names=["src", "dst", "cosine"])

        near = rows.select(F.col(id_col).cast("bigint"), vector_col).mapInArrow(run, "src bigint, dst bigint, cosine double")
        found = near if found is None else found.unionByName(near)
    rank = F.row_number().over(Window.partitionBy("src").orderBy(F.desc("cosine"), "dst"))
    return found.withColumn("rank", rank).where(F.col("rank") <= k)


def _unit(x: np.ndarray) -> np.ndarray:
    return x / np.maximum(np.sqrt((x * x).sum(axis=1, keepdims=True)), 1e-300) if x.size else x
