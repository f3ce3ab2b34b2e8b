"""The chain of update lists: every superstep appends one, the newest value of a vertex wins, nothing is rewritten."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vertexlog.sources.scratch import Scratch


class UpdateLog:
    """Lists (v, value columns...) by superstep.

    A list counts once it is registered here, after its files are complete: that is the commit.  A job that lost
    its driver resumes from the last complete directory.  With ``width``, lists lie in directories of vertex ranges,
    so that reading some vertices opens their ranges only.
    """

    def __init__(self, spark: SparkSession, name: str, width: int | None = None) -> None:
        self.scratch, self.lists, self.width = Scratch(spark, name), {}, width

    def _write(self, updates: DataFrame, name: str) -> DataFrame:
        if self.width is None:
            return self.scratch.keep(updates, name)
        return self.scratch.keep(updates.withColumn("v_part", F.expr(f"v div {self.width}")), name, by="v_part")

    def append(self, step: int, updates: DataFrame) -> DataFrame:
        if step in self.lists:
            raise ValueError(f"superstep {step} is already committed")
        self.lists[step] = self._write(updates, f"superstep={step}")
        return self.active(step)

    def size(self, step: int) -> int:
        """Rows of a list, from file footers."""
        return self.lists[step].count()

    def active(self, step: int | None = None) -> DataFrame:
        """The list of a superstep, the newest by default."""
        return self.lists[max(self.lists) if step is None else step].drop("v_part")

    def all(self, ranges: list[int] | None = None) -> DataFrame:
        """All lists, or what they hold of some vertex ranges."""
        tagged = [d.withColumn("superstep", F.lit(s)) for s, d in sorted(self.lists.items())]
        every = reduce(DataFrame.unionByName, tagged)
        return (every if ranges is None else every.where(F.col("v_part").isin(ranges))).drop("v_part")

    def ranges_of(self, vertices: DataFrame) -> list[int] | None:
        """The ranges that some vertices (v) lie in; None where lists are not laid out by range."""
        if self.width is None:
            return None
        return sorted(r[0] for r in vertices.select(F.expr(f"v div {self.width}")).distinct().collect())

    def resolve(self, among: DataFrame | None = None) -> DataFrame:
        """The newest value of every vertex with the superstep it comes from, computed when read.

        ``among``: of these vertices (v) only, which are a written list; lists are read in their ranges only.
        """
        every = self.all() if among is None else self.all(self.ranges_of(among)).join(among.select("v"), "v", "left_semi")
        cols = [c for c in every.columns if c not in ("v", "superstep")]
        newest = every.groupBy("v").agg(F.max_by(F.struct(*cols, "superstep"), "superstep").alias("s"))
        return newest.select("v", *(F.col(f"s.{c}").alias(c) for c in (*cols, "superstep")))

    def compact(self, upto: int | None = None) -> None:
        """Merge the lists up to a superstep into one; values and their supersteps stay what they resolve to."""
        upto = max(self.lists) if upto is None else upto
        old = {s: d for s, d in self.lists.items() if s <= upto}
        if len(old) > 1:
            part = UpdateLog.__new__(UpdateLog)
            part.scratch, part.lists, part.width = self.scratch, old, self.width
            merged = self._write(part.resolve().drop("superstep"), f"compacted-{upto}")
            for s in old:
                del self.lists[s]
            self.lists[upto] = merged

    def compact_if(self, max_lists: int = 16) -> None:
        if len(self.lists) > max_lists:
            self.compact()
