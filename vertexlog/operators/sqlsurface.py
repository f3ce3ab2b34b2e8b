"""Graph methods inside SQL text: calls are carried out first and become views of their results."""

from __future__ import annotations

import re
import uuid

from pyspark.sql import DataFrame, SparkSession

from vertexlog.operators import algorithms as alg
from vertexlog.sources.graphs import GRAPHS

_CALL = re.compile(r"\b(edges|bfs|rank|betweenness|components)\s*\(\s*'(\w+)'\s*(?:,\s*(\d+)\s*)?\)", re.I)


def _carry_out(spark: SparkSession, sf_dir: str, method: str, graph: str, number: int) -> DataFrame:
    g = GRAPHS[graph.removeprefix("g_")](spark, sf_dir).stored()
    if method == "edges":
        return g.edges
    if method == "bfs":
        return alg.bfs(g, number).rows()
    if method == "rank":
        return alg.rank_fixed(g, number or 1)
    if method == "betweenness":
        return alg.bc_descendants(alg.bfs(g, number))
    return alg.components(g)


def sql(spark: SparkSession, sf_dir: str, text: str) -> DataFrame:
    """``SELECT ... FROM bfs('g_trade', 0)``: number is the root, or the rounds of ``rank``."""
    made: dict[str, str] = {}

    def view(m: re.Match) -> str:
        key = m.group(0).lower()
        if key not in made:
            made[key] = f"vertexlog_{uuid.uuid4().hex}"
            _carry_out(spark, sf_dir, m.group(1).lower(), m.group(2), int(m.group(3) or 0)).createOrReplaceTempView(made[key])
        return made[key]

    return spark.sql(_CALL.sub(view, text))
