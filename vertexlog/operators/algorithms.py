"""Graph algorithms as vertex programs and loops over update lists."""

from __future__ import annotations

from functools import reduce
from itertools import count

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vertexlog.operators.engines import Engine
from vertexlog.operators.program import run, semiring
from vertexlog.sources.graphs import Graph
from vertexlog.sources.scratch import Scratch

# ---------------------------------------------------------------- breadth-first search


class Tree:
    """Result of a search: one list (v, parent, level) per level, in order, and how many rows each has.

    ``opened`` names the source ranges that were read for each level after the root's, None for all of them.
    """

    def __init__(self, lists: list[DataFrame], sizes: list[int], root: int, opened: list[list[int] | None]) -> None:
        self.lists, self.sizes, self.root, self.opened = lists, sizes, root, opened

    def rows(self) -> DataFrame:
        return reduce(DataFrame.unionByName, self.lists)

    def edges_read(self, graph: Graph) -> list[int]:
        """Edges in the ranges that were opened, round by round."""
        rows = graph.range_rows()
        return [sum(rows.values()) if ranges is None else sum(rows.get(r, 0) for r in ranges) for ranges in self.opened]


def _tail(edges: DataFrame, width: int | None, visited: DataFrame, frontier: list[int], step: int, most_levels: int, most_rows: int) -> tuple[list[list[tuple[int, int, int]]], list[list[int] | None]]:
    """Levels of a search while its frontier is short: two pruned lookups a level, no exchange and no write.

    Gives up, with the levels done so far, before a level that would bring more than ``most_rows`` rows here.
    """

    def named(df: DataFrame, key: str, part: str, wanted: list[int]) -> DataFrame:
        found = df.where(F.col(key).isin(wanted))
        return found if width is None else found.where(F.col(part).isin(sorted({v // width for v in wanted})))

    levels, opened, own = [], [], set(frontier)
    while frontier and len(levels) < most_levels and len(frontier) <= most_rows:
        pairs = named(edges, "src", "src_part", frontier).select("src", "dst").limit(most_rows + 1).collect()
        if len(pairs) > most_rows:
            break
        parents: dict[int, int] = {}
        for src, dst in sorted(map(tuple, pairs)):
            if dst not in own:
                parents.setdefault(dst, src)
        if parents:
            for row in named(visited, "v", "v_part", list(parents)).select("v").collect():
                del parents[row["v"]]
        opened.append(None if width is None else sorted({v // width for v in frontier}))
        levels.append([(v, parents[v], step + len(levels)) for v in sorted(parents)])
        own |= parents.keys()
        frontier = sorted(parents)
    return levels, opened


def bfs(graph: Graph, root: int, *, max_levels: int | None = None, engine: Engine | None = None, merge_after: int = 8, tail_rows: int = 2000, tail_after: int = 3) -> Tree:
    """Parents and levels of all vertices reached from a root; the parent is the smallest vertex one level up.

    Records are emitted by rising source and folding keeps the first, which is the smallest source: so the fold
    is a minimum and needs no order.  The root is its own parent.  Visited lists are merged every few levels.

    A round opens the source ranges of its frontier.  What a small frontier reaches is written first, so that visited
    lists are read in its ranges only.  After ``tail_after`` levels in a row of a few vertices, levels are looked up
    instead of joined, up to 64 in one go, as long as each brings at most ``tail_rows`` rows: long tails then cost two
    small scans a level.
    """
    engine = engine or Engine()
    spark, limit = graph.edges.sparkSession, max_levels if max_levels is not None else float("inf")
    edges, scratch = engine.prepare(graph), Scratch(spark, "bfs")
    width, plain = graph.width, ["v", "parent", "level"]
    start = spark.createDataFrame([(root, root, 0)], "v bigint, parent bigint, level int")

    def keep(rows: DataFrame) -> DataFrame:
        return scratch.keep(rows.withColumn("v_part", F.expr(f"v div {width}")), by="v_part") if width else scratch.keep(rows.withColumn("v_part", F.lit(0)))

    level = keep(start)
    lists, sizes, opened = [level.select(plain)], [1], []
    visited, recent, step = level.select("v", "v_part"), 1, 0
    while step < limit:
        if step >= tail_after and type(engine) is Engine and max(sizes[-tail_after:]) * 4 <= tail_rows:
            frontier = [r["v"] for r in level.select("v").collect()]
            levels, found = _tail(edges, width, visited, frontier, step + 1, int(min(64, limit - step)), tail_rows)
            rows = [r for part in levels for r in part]
            if rows:
                batch = keep(spark.createDataFrame(rows, start.schema).coalesce(1))
                done = [part for part in levels if part]
                lists += [batch.where(F.col("level") == part[0][2]).select(plain) for part in done]
                sizes += [len(part) for part in done]
                level, visited, recent = batch.where(F.col("level") == done[-1][0][2]), visited.unionByName(batch.select("v", "v_part")), recent + 1
            opened += found
            step += len(levels)
            if levels and (not levels[-1] or step >= limit):
                break
            if levels:
                continue
        step += 1
        reached = engine.round(level.select("v"), edges, F.col("src"), "min", sizes[-1])
        opened.append(engine.opened[-1])
        seen = visited
        if engine.opened[-1] is not None:
            reached = scratch.keep(reached)
            seen = visited.where(F.col("v_part").isin(sorted(r[0] for r in reached.select(F.expr(f"dst div {width}")).distinct().collect())))
        fresh = reached.join(seen.select(F.col("v").alias("dst")), "dst", "left_anti")
        level = keep(fresh.select(F.col("dst").alias("v"), F.col("val").alias("parent"), F.lit(step).alias("level")))
        n = level.count()
        if not n:
            break
        lists.append(level.select(plain))
        sizes.append(n)
        visited, recent = visited.unionByName(level.select("v", "v_part")), recent + 1
        if recent > merge_after:
            visited, recent = scratch.keep(visited, by="v_part") if width else scratch.keep(visited.coalesce(max(1, spark.sparkContext.defaultParallelism))), 1
    engine.finish()
    return Tree(lists, sizes, root, opened)


def bfs_multi(graph: Graph, roots: list[int]) -> DataFrame:
    """(root, v, parent, level) of searches from several roots, carried by one composite key."""
    spark, edges = graph.edges.sparkSession, graph.edges
    scratch = Scratch(spark, "bfs-multi")
    level = scratch.keep(spark.createDataFrame([(r, r, r, 0) for r in roots], "root bigint, v bigint, parent bigint, level int"))
    visited = level
    for step in count(1):
        log = edges.join(level.select("root", "v"), edges["src"] == F.col("v")).groupBy("root", "dst").agg(F.min("src").alias("parent"))
        fresh = log.withColumnRenamed("dst", "v").join(visited.select("root", "v"), ["root", "v"], "left_anti")
        level = scratch.keep(fresh.select("root", "v", "parent", F.lit(step).alias("level")))
        if level.isEmpty():
            break
        visited = scratch.keep(visited.unionByName(level))
    return visited


def trace_path(tree: Tree, v: int) -> DataFrame:
    """(pos, v) from a vertex back to the root; one pushed-down lookup a level."""
    rows, at, pos = tree.rows(), v, 0
    path = []
    while True:
        found = rows.where(F.col("v") == at).first()
        if found is None:
            break
        path.append((pos, at))
        if at == tree.root:
            break
        at, pos = found["parent"], pos + 1
    return rows.sparkSession.createDataFrame(path, "pos int, v bigint")


# ---------------------------------------------------------------- rank


def rank_fixed(graph: Graph, rounds: int, *, unit: int = 10**12, engine: Engine | None = None, untouched: str = "base", dangling: str = "drop", lazy: bool = False) -> DataFrame:
    """(v, rank_u): rank after some rounds in integers of 1/unit, the same however the log is folded.

    ``untouched``: vertices without updates get the formula with sum zero (``base``) or their old value
    (``keep``).  ``dangling``: rank of vertices without edges is lost (``drop``) or shared by all
    (``redistribute``).  ``lazy``: lists keep raw sums and the damping is applied when they are read.
    """
    engine = engine or Engine()
    n, share = graph.n, unit // graph.n
    edges, scratch = engine.prepare(graph), Scratch(graph.edges.sparkSession, "rank")
    degrees = scratch.keep(graph.degrees())
    every = graph.vertices()

    def damped(total: Column, extra: int = 0) -> Column:
        return _div(F.lit(15 * share) + (F.coalesce(total, F.lit(0)) + F.lit(extra)) * 85, 100)

    values = every.select("v", F.lit(share).cast("bigint").alias("val"))
    for _ in range(rounds):
        extra = 0
        if dangling == "redistribute":
            lost = values.join(degrees, "v", "left_anti").agg(F.coalesce(F.sum("val"), F.lit(0))).first()[0]
            extra = int(lost) // n
        active = values.join(degrees, "v").select("v", _div(F.col("val"), F.col("degree")).alias("val"))
        sums = engine.round(active, edges, F.col("val"), "sum").withColumnRenamed("dst", "v").withColumnRenamed("val", "total")
        if lazy:
            raw = scratch.keep(sums)
            values = every.join(raw, "v", "left").select("v", damped(F.col("total"), extra).alias("val"))
            continue
        joined = values.join(sums, "v", "left")
        new = damped(F.col("total"), extra)
        if untouched == "keep":
            new = F.when(F.col("total").isNull(), F.col("val")).otherwise(new)
        values = scratch.keep(joined.select("v", new.alias("val")))
    engine.finish()
    return values.select("v", F.col("val").alias("rank_u"))


def _div(a: Column, b: Column | int) -> Column:
    """Integer quotient, truncated."""
    return F.call_function("div", a, b if isinstance(b, Column) else F.lit(b))


def rank_step(graph: Graph, values: DataFrame, damping: float = 0.85, untouched: str = "base", engine: Engine | None = None) -> DataFrame:
    """(v, rank): one round in doubles from (v, rank)."""
    engine = engine or Engine()
    active = values.join(graph.degrees(), "v").select("v", (F.col("rank") / F.col("degree")).alias("val"))
    sums = engine.round(active, engine.prepare(graph), F.col("val"), "sum").select(F.col("dst").alias("v"), F.col("val").alias("total"))
    new = (1 - damping) / graph.n + damping * F.coalesce("total", F.lit(0.0))
    if untouched == "keep":
        new = F.when(F.col("total").isNull(), F.col("rank")).otherwise(new)
    return values.join(sums, "v", "left").select("v", new.alias("rank"))


def rank_converged(graph: Graph, *, tol: float = 1e-9, max_iter: int = 20, active: str = "all", damping: float = 0.85, engine: Engine | None = None) -> tuple[DataFrame, int]:
    """(v, rank) and the rounds it took until no vertex moved by ``tol``, or ``max_iter`` rounds.

    ``all``: every vertex pushes each round.  ``unconverged``: only vertices that still move push, the literal
    reading, which is not exact because sums miss the settled neighbours.  ``residual``: vertices push what
    they have not passed on yet, which makes selective pushing exact.
    """
    engine = engine or Engine()
    edges, scratch = engine.prepare(graph), Scratch(graph.edges.sparkSession, "rank")
    degrees = scratch.keep(graph.degrees())
    start = graph.vertices().select("v", F.lit(1.0 / graph.n).alias("rank"))
    if active == "residual":
        return _rank_residual(graph, edges, engine, start, degrees, scratch, tol, max_iter, damping)
    values, pushing = scratch.keep(start), None
    for step in range(1, max_iter + 1):
        source = values if pushing is None else pushing
        shares = source.join(degrees, "v").select("v", (F.col("rank") / F.col("degree")).alias("val"))
        size = None if pushing is None else pushing.count()
        sums = engine.round(shares, edges, F.col("val"), "sum", size).select(F.col("dst").alias("v"), F.col("val").alias("total"))
        formula = (1 - damping) / graph.n + damping * F.coalesce("total", F.lit(0.0))
        new = formula if active == "all" else F.when(F.col("total").isNull(), F.col("rank")).otherwise(formula)
        done = scratch.keep(values.join(sums, "v", "left").select("v", new.alias("rank"), (F.abs(new - F.col("rank")) >= tol).alias("moves")))
        values = done.select("v", "rank")
        moving = done.where("moves")
        if moving.isEmpty():
            break
        if active == "unconverged":
            pushing = moving.select("v", "rank")
    engine.finish()
    return values, step


def _rank_residual(graph, edges, engine, start, degrees, scratch, tol, max_iter, damping):
    first = scratch.keep(rank_step(graph, start, damping).withColumn("r", F.col("rank") - 1.0 / graph.n).select("v", F.lit(1.0 / graph.n).alias("rank"), "r"))
    state = first
    for step in range(1, max_iter + 1):
        push = F.abs("r") >= tol
        pushing = state.where(push)
        shares = pushing.join(degrees, "v").select("v", (F.col("r") / F.col("degree")).alias("val"))
        came = engine.round(shares, edges, F.col("val"), "sum", pushing.count()).select(F.col("dst").alias("v"), F.col("val").alias("came"))
        kept = F.when(push, 0.0).otherwise(F.col("r"))
        state = scratch.keep(state.join(came, "v", "left").select("v", F.when(push, F.col("rank") + F.col("r")).otherwise(F.col("rank")).alias("rank"), (kept + damping * F.coalesce("came", F.lit(0.0))).alias("r")))
        if state.where(F.abs("r") >= tol).isEmpty():
            break
    return state.select("v", (F.col("rank") + F.col("r")).alias("rank")), step


# ---------------------------------------------------------------- betweenness


def backtrace_list(level: DataFrame) -> DataFrame:
    """(v, val): how often each vertex is a parent in one level's list."""
    return level.where("level > 0").groupBy(F.col("parent").alias("v")).agg(F.count("*").alias("val"))


def bc_children(tree: Tree) -> DataFrame:
    """Each list counted by itself, all lists united by an adding function: children in the tree."""
    lists = [backtrace_list(x) for x in tree.lists[1:]] or [backtrace_list(tree.lists[0])]
    return reduce(DataFrame.unionByName, lists).groupBy("v").agg(F.sum("val").alias("score"))


def bc_descendants(tree: Tree, cut_every: int = 8, small: int = 10_000) -> DataFrame:
    """From the deepest list up, each vertex passes on one plus what it has gathered: tree paths through it.

    What a level passes on is written, so that the next ones do not compute it again; levels of up to ``small`` vertices
    are cheaper to compute again than to write, but for every ``cut_every``-th.
    """
    scratch = Scratch(tree.lists[0].sparkSession, "backtrace")
    out, below = [], None
    for i, (level, size) in enumerate(zip(reversed(tree.lists[1:]), reversed(tree.sizes[1:]), strict=True)):
        here = level.select("v", "parent")
        passed = F.lit(1).cast("bigint")
        if below is not None:
            here, passed = here.join(below, "v", "left"), F.coalesce("val", F.lit(0)) + 1
        below = here.select(F.col("parent").alias("v"), passed.alias("val")).groupBy("v").agg(F.sum("val").alias("val"))
        if i % cut_every == cut_every - 1 or size > small:
            below = scratch.keep(below)
        out.append(below)
    if not out:
        return tree.lists[0].where("false").select("v", F.lit(0).cast("bigint").alias("score"))
    return reduce(DataFrame.unionByName, out).select("v", F.col("val").alias("score"))


def bc_exact(graph: Graph, root: int, tree: Tree | None = None) -> DataFrame:
    """(v, score): dependencies over all shortest paths from a root, itself left out."""
    tree = tree or bfs(graph, root)
    scratch = Scratch(graph.edges.sparkSession, "brandes")
    pairs = graph.edges.groupBy("src", "dst").agg(F.count("*").cast("double").alias("times"))
    sigma = [scratch.keep(tree.lists[0].select("v", F.lit(1.0).alias("sigma")))]
    for level in tree.lists[1:]:
        up = sigma[-1].withColumnRenamed("v", "src")
        inner = pairs.join(up, "src").join(level.select(F.col("v").alias("dst")), "dst", "left_semi")
        sigma.append(scratch.keep(inner.groupBy(F.col("dst").alias("v")).agg(F.sum(F.col("sigma") * F.col("times")).alias("sigma"))))
    below = scratch.keep(sigma[-1].select("v", "sigma", F.lit(0.0).alias("score")))
    out = [below]
    for own in reversed(sigma[:-1]):
        child = below.select(F.col("v").alias("dst"), F.col("sigma").alias("child_sigma"), F.col("score").alias("child_score"))
        passed = pairs.join(own.withColumnRenamed("v", "src"), "src").join(child, "dst")
        gain = passed.groupBy(F.col("src").alias("v")).agg(F.sum(F.col("sigma") * F.col("times") / F.col("child_sigma") * (1 + F.col("child_score"))).alias("gain"))
        below = scratch.keep(own.join(gain, "v", "left").select("v", "sigma", F.coalesce("gain", F.lit(0.0)).alias("score")))
        out.append(below)
    return reduce(DataFrame.unionByName, out[:-1]).select("v", "score") if len(out) > 1 else below.where("false").select("v", "score")


def bc_multi(graph: Graph, roots: list[int]) -> DataFrame:
    """(v, score): tree paths through each vertex, summed over the searches from several roots."""
    tree = bfs_multi(graph, roots)
    deepest = tree.agg(F.max("level")).first()[0]
    scratch, out, below = Scratch(graph.edges.sparkSession, "backtrace"), [], None
    for step in range(deepest, 0, -1):
        here, passed = tree.where(F.col("level") == step).select("root", "v", "parent"), F.lit(1).cast("bigint")
        if below is not None:
            here, passed = here.join(below, ["root", "v"], "left"), F.coalesce("val", F.lit(0)) + 1
        below = scratch.keep(here.select("root", F.col("parent").alias("v"), passed.alias("val")).groupBy("root", "v").agg(F.sum("val").alias("val")))
        out.append(below)
    return reduce(DataFrame.unionByName, out).groupBy("v").agg(F.sum("val").alias("score"))


# ---------------------------------------------------------------- others

SHORTEST = semiring("shortest", lambda val, w: val + w, "min")


def sssp(graph: Graph, root: int, max_steps: int | None = None, engine: Engine | None = None) -> DataFrame:
    """(v, dist) of the vertices that a root reaches, weights from the edges.

    Goes on until no vertex is active; a limit that is hit before that is an error, as is a cycle of negative weight.
    """
    start = graph.edges.sparkSession.createDataFrame([(root, 0)], "v bigint, val bigint")
    # a shortest path has fewer edges than there are vertices; the round after its last edge finds nothing
    done = run(graph, SHORTEST, start, max_steps=graph.n if max_steps is None else max_steps, engine=engine)
    if done.trace and done.trace[-1][2]:
        raise ValueError(f"vertices are still active after {done.steps()} rounds: {'a negative cycle' if max_steps is None else 'max_steps is too small'}")
    return done.values.select("v", F.col("val").alias("dist"))


def components(graph: Graph, max_steps: int | None = None) -> DataFrame:
    """(v, label): smallest vertex of each component, for every vertex with an edge.

    Star contraction: every vertex hands its larger neighbours to the smallest it knows, then its smaller ones, until
    nothing moves.  The number of rounds grows with the logarithm of a chain's length, not with the length.  A limit
    that is hit before the end is an error.
    """
    ends = graph.edges.select(F.col("src").alias("v")).unionByName(graph.edges.select(F.col("dst").alias("v"))).distinct()
    scratch = Scratch(graph.edges.sparkSession, "components")
    links = scratch.keep(graph.edges.where("src <> dst").select(F.greatest("src", "dst").alias("a"), F.least("src", "dst").alias("b")).distinct())

    def larger(pairs: DataFrame) -> DataFrame:
        both = pairs.unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least("a", F.min("b")).alias("m"))
        return both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()

    def smaller(pairs: DataFrame) -> DataFrame:
        least = pairs.groupBy("a").agg(F.min("b").alias("m"))
        moved = pairs.join(least, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))
        return moved.unionByName(least.select("a", F.col("m").alias("b"))).distinct()

    for step in count(1):
        after = scratch.keep(smaller(scratch.keep(larger(links))))
        same = after.count() == links.count() and not after.join(links, ["a", "b"], "left_anti").limit(1).count()
        links = after
        if same:
            break
        if max_steps is not None and step >= max_steps:
            raise ValueError(f"components still change after {step} rounds: max_steps is too small")
    return ends.join(links, ends["v"] == links["a"], "left").select("v", F.coalesce("b", "v").alias("label"))


def label_vote(graph: Graph, rounds: int) -> DataFrame:
    """(v, label) after rounds of majority vote among in-neighbours, ties to the smallest label.

    A vote is no binary associative operation, so it folds histograms: (dst, label) counts, then their best.
    """
    scratch = Scratch(graph.edges.sparkSession, "vote")
    values = scratch.keep(graph.vertices().select("v", F.col("v").alias("label")))
    for _ in range(rounds):
        votes = graph.edges.join(values.withColumnRenamed("v", "src"), "src").groupBy("dst", "label").agg(F.count("*").alias("n"))
        best = votes.groupBy("dst").agg(F.max_by("label", F.struct("n", -F.col("label"))).alias("best"))
        values = scratch.keep(values.join(best, values["v"] == best["dst"], "left").select("v", F.coalesce("best", "label").alias("label")))
    return values


def degree(graph: Graph, direction: str = "out") -> DataFrame:
    end = "src" if direction == "out" else "dst"
    return graph.edges.groupBy(F.col(end).alias("v")).agg(F.count("*").alias("val"))


def weighted_in(graph: Graph) -> DataFrame:
    return graph.edges.groupBy(F.col("dst").alias("v")).agg(F.sum("w").alias("val"))
