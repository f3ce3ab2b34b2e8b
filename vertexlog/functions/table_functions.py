"""User functions in Python where users bring Python: table functions, vectorised edge functions and folds."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T

from vertexlog.sources.kron_source import kron_edge


@F.udtf(returnType="src bigint, dst bigint")
class KronRange:
    """Kronecker edges of a range of ordinals: one row in, many edges out."""

    def eval(self, low: int, high: int, scale: int) -> Iterator[tuple[int, int]]:
        for i in range(low, high):
            yield kron_edge(i, scale)


def damped(val: Column, degree: Column) -> Column:
    """A vectorised edge function: rank share of an edge."""

    @F.pandas_udf(T.DoubleType())
    def share(v: pd.Series, d: pd.Series) -> pd.Series:
        return 0.85 * v / d

    return share(val, degree)


def spread(val: Column) -> Column:
    """A fold of a group in Python: largest minus smallest value.  Fold in blocks first where groups are large."""

    @F.pandas_udf(T.LongType())
    def gap(v: pd.Series) -> int:
        return int(v.max() - v.min())

    return gap(val)
