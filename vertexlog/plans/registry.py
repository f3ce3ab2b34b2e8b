"""All queries of the graph engine and the SQL that gives the same rows."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from vertexlog.functions.reducers import REDUCERS, check_associative, custom
from vertexlog.functions.table_functions import KronRange, damped, spread
from vertexlog.operators import algorithms as alg
from vertexlog.operators import local, relational, sqlsurface, vsource
from vertexlog.operators.engines import ENGINES, CapacityExceeded, Engine
from vertexlog.operators.program import VertexProgram, commit
from vertexlog.operators.sortreduce import block_reduce, emit_log, fold, merge_plan, merge_reduce, merge_schedule, merge_tree, partition_log
from vertexlog.operators.updatelog import UpdateLog
from vertexlog.plans import cost, metrics, oracles
from vertexlog.sources import graphs, layout
from vertexlog.sources.graphs import GRAPHS, Graph
from vertexlog.sources.scratch import Scratch
from vertexlog.sources.tables import load
from vertexlog.streaming import events as streams

_WIDTH = 1024  # narrow ranges of vertices show on these small tables what the usual ones do on large graphs
Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


def g(name: str, then: Callable[[Graph], DataFrame], stored: bool = True, width: int | None = None) -> Query:
    """A query on a graph, laid out once."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        made = GRAPHS[name](spark, sf_dir)
        return then(made.stored(width) if stored else made)

    return run


# ---------------------------------------------------------------- graphs and layout

for _name, _sql in oracles.GRAPHS.items():
    add(f"edges_{_name}", g(_name, lambda x: x.edges, stored=False), _sql)

add(
    "edges_knn",
    lambda s, d: graphs.knn(s, d).edges,
    "with q as (select vec_id, embedding::double[] as e from embeddings), p as (select a.vec_id as src, b.vec_id as dst, row_number() over (partition by a.vec_id order by"
    " list_cosine_similarity(a.e, b.e) desc, b.vec_id) as r from q a, q b where a.vec_id % 20 = 0 and a.vec_id <> b.vec_id) select src, dst from p where r <= 5",
)


def _stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for name in GRAPHS:
        x = GRAPHS[name](spark, sf_dir)
        ends = x.edges.select(F.explode(F.array(F.struct(F.lit(0).alias("out"), F.col("dst").alias("v")), F.struct(F.lit(1).alias("out"), F.col("src").alias("v")))).alias("e"))
        degrees = ends.groupBy("e.out", "e.v").agg(F.count("*").alias("n"))
        of = lambda side: F.when(F.col("out") == side, F.col("n"))
        row = degrees.agg(F.sum(of(0)).alias("m"), F.max(of(0)).alias("max_in"), F.max(of(1)).alias("max_out")).select(F.lit(x.name).alias("graph"), F.lit(x.n).cast("bigint").alias("n"), "m", "max_in", "max_out")
        out = row if out is None else out.unionByName(row)
    return out


add(
    "graph_stats_all",
    _stats,
    "with "
    + ", ".join(f"g_{n} as materialized ({q})" for n, q in oracles.GRAPHS.items())
    + " "
    + " union all ".join(
        f"select 'g_{n}' as graph, {oracles.SIZES[n]}::bigint as n, (select count(*) from g_{n}) as m, (select max(c) from (select count(*) as c from g_{n} group by dst)) as max_in,"
        f" (select max(c) from (select count(*) as c from g_{n} group by src)) as max_out"
        for n in oracles.GRAPHS
    ),
)
_PS = f"with {oracles.graph('partseq')}"
_ORD = f"{_PS}, l as materialized (select src, dst, w, row_number() over (order by src, dst, w) - 1 as ord from g)"
add("edge_file", g("partseq", lambda x: layout.edge_file(x.edges).select("src", "dst", "ord"), False), f"{_ORD} select src, dst, ord from l")
add("edge_index", g("partseq", lambda x: layout.edge_index(layout.edge_file(x.edges)), False), f"{_ORD} select src, min(ord) as first_ordinal, count(*) as degree from l group by src")


def _out_edges(x: Graph) -> DataFrame:
    laid = layout.edge_file(x.edges)
    return layout.out_edges(laid, layout.edge_index(laid), [0, 7, 42, 199])


add("out_edges_of", g("partseq", _out_edges, False), f"{_PS} select src, dst from g where src in (0, 7, 42, 199)")


# ---------------------------------------------------------------- folding

_FIX = oracles.rank_fixed("partseq", 1, final="select t.dst as v, t.total as val from (select g.dst, sum(q.val // d.c)::bigint as total from g join p0 q on q.v = g.src join d on d.src = g.src group by g.dst) t")


def _one_round(x: Graph, mode: str) -> DataFrame:
    share = 10**12 // x.n
    active = x.degrees().select("v", F.expr(f"{share} div degree").alias("val"))
    engine = Engine(mode)
    return engine.round(active, engine.prepare(x), F.col("val"), "sum").select(F.col("dst").alias("v"), "val")


for _mode in ("in_place", "sort_first", "interleaved", "fused"):
    add(f"superstep_{_mode}", g("partseq", partial(_one_round, mode=_mode)), _FIX)


def _log(x: Graph) -> DataFrame:
    """Part sequence log in emission order with the weight as value."""
    return layout.edge_file(x.edges).select("dst", F.col("w").alias("val"), "ord", "src")


_W = {
    "sum": "sum(w)::bigint", "min": "min(w)", "max": "max(w)", "count": "count(*)", "first": "min_by(w, ord)", "last": "max_by(w, ord)", "any": "bool_or(w % 7 = 0)", "all": "bool_and(w % 7 <> 0)",
    "bit_or": "bit_or(w)", "bit_and": "bit_and(w)", "bit_xor": "bit_xor(w)", "min_by": "min_by(w, ord)", "max_by": "max_by(w, ord)", "product": "round(product(1.0 + (w % 5) / 10.0), 6)",
    "collect_distinct": "list_sort(list_distinct(list(w % 10)))",
}


def _reduced(x: Graph, name: str) -> DataFrame:
    log, w = _log(x), F.col("val")
    val = {"any": w % 7 == 0, "all": w % 7 != 0, "product": 1.0 + (w % 5) / 10.0, "collect_distinct": w % 10}.get(name, w)
    done = fold(log.withColumn("val", val), REDUCERS[name])
    return done.select(F.col("dst").alias("v"), (F.round("val", 6) if name == "product" else F.col("val")).alias("val"))


for _name, _sql in _W.items():
    add(f"reduce_{_name}", g("partseq", partial(_reduced, name=_name), False), f"{_ORD} select dst as v, {_sql} as val from l group by dst")
add("reduce_custom", g("partseq", lambda x: custom(x.edges.select("dst", F.col("w").alias("val")), lambda a, b: a if a >= b else b).select(F.col("dst").alias("v"), "val")), f"{_PS} select dst as v, max(w) as val from g group by dst")
def _join_digits(x: Graph) -> DataFrame:
    """Last and first value of a destination's records in emission order, by a function that is not commutative."""
    log = _log(x).select("dst", F.struct(F.col("val").alias("a"), F.col("val").alias("b")).alias("val"), "ord")
    return custom(log, lambda p, q: {"a": p["a"], "b": q["b"]}).select(F.col("dst").alias("v"), (F.col("val.b") - F.col("val.a")).alias("val"))


add("reduce_custom_ordered", g("partseq", _join_digits, False), f"{_ORD} select dst as v, max_by(w, ord) - min_by(w, ord) as val from l group by dst")
def _order_sizes(spark: SparkSession, sf_dir: str) -> list[int]:
    """How many line items orders have, each number once."""
    sizes = load(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.count("*").alias("x")).select("x").distinct()
    return sorted(r["x"] for r in sizes.collect())


add("assoc_check", lambda s, d: check_associative(s, lambda a, b: (a + 2 * b) % 1000, _order_sizes(s, d)), "with s as materialized (select distinct x from (select count(*) as x from lineitem group by l_orderkey)) select a.x as a, b.x as b, c.x as c, ((a.x + 2 * b.x) % 1000 + 2 * c.x) % 1000 as left_first, (a.x + 2 * ((b.x + 2 * c.x) % 1000)) % 1000 as right_first, left_first = right_first as ok from s a, s b, s c")


def _blocks(x: Graph) -> DataFrame:
    log = layout.edge_file(x.edges).select("dst", F.lit(1).cast("bigint").alias("val"), "ord")
    return block_reduce(log, 4096, REDUCERS["sum"])


_CO = f"with {oracles.graph('copurchase')}, l as materialized (select dst, row_number() over (order by src, dst) - 1 as ord from g)"
add("block_reduce_n", g("copurchase", lambda x: _blocks(x).groupBy("block").agg(F.count("*").alias("records"), F.sum("val").alias("folded")), False), f"{_CO} select ord // 4096 as block, count(distinct dst) as records, count(*) as folded from l group by 1")
add("merge_reduce_k", g("copurchase", lambda x: merge_reduce(_blocks(x), 16, REDUCERS["sum"]).groupBy("block").agg(F.count("*").alias("records"), F.sum("val").alias("folded")), False), f"{_CO} select ord // 65536 as block, count(distinct dst) as records, count(*) as folded from l group by 1")
add("merge_plan", g("copurchase", lambda x: x.edges.sparkSession.createDataFrame(merge_plan(x.edges.count(), 4096, 16), "phase int, in_blocks bigint, out_blocks bigint")),
    f"with recursive {oracles.graph('copurchase')}, p(phase, in_blocks, out_blocks) as (select 0, count(*), (count(*) + 4095) // 4096 from g union all select phase + 1, out_blocks, (out_blocks + 15) // 16 from p where out_blocks > 1) select phase::int as phase, in_blocks::bigint as in_blocks, out_blocks::bigint as out_blocks from p")
add("merge_tree", g("partseq", lambda x: x.edges.sparkSession.createDataFrame(merge_tree(-(-x.edges.count() // 4096)), "level int, mergers int"), False),
    f"with recursive {oracles.graph('partseq')}, p(level, streams) as (select 1, (count(*) + 4095) // 4096 from g union all select level + 1, (streams + 1) // 2 from p where streams > 1) select level::int as level, (streams // 2)::int as mergers from p where streams > 1")


def _schedule(x: Graph) -> DataFrame:
    sizes = [r["n"] for r in _blocks(x).groupBy("block").agg(F.count("*").alias("n")).orderBy("block").collect()]
    return x.edges.sparkSession.createDataFrame(merge_schedule(sizes, 16, 2), "merge int, files int, written bigint")


add("merge_schedule", g("copurchase", _schedule, False),
    f"with recursive {oracles.graph('copurchase')}, l as materialized (select dst, row_number() over (order by src, dst) - 1 as ord from g), b as materialized (select ord // 4096 as block, count(distinct dst) as n from l group by 1),"
    " s(step, merge, files, written, waiting, running) as (select 0, 0, 0, 0::hugeint, (select list(n::hugeint order by block) from b), []::hugeint[] union all"
    " select step + 1, merge + starts::int, case when starts then least(16, len(waiting))::int end, case when starts then list_sum(waiting[1:16]) end, case when starts then waiting[17:] else list_append(waiting, running[1]) end, case when starts then list_append(running, list_sum(waiting[1:16])) else running[2:] end"
    " from (select *, len(waiting) > 1 and len(running) < 2 as starts from s) where len(waiting) + len(running) > 1)"
    " select merge::int as merge, files::int as files, written::bigint as written from s where step > 0 and files is not null")  # fmt: skip
add("merge_phases", g("copurchase", lambda x: x.edges.sparkSession.createDataFrame([(n, k, metrics.merge_phases(x.edges.count(), n, k)) for n in (512, 4096) for k in (2, 16)], "n int, k int, phases int")),
    f"with {oracles.graph('copurchase')}, m as (select count(*) as m from g) select n::int as n, k::int as k, ceil(ln(ceil(m / n)) / ln(k) - 1e-9)::int as phases from m, (values (512), (4096)) as a(n), (values (2), (16)) as b(k)")

_CURVES = {"copurchase": (4096, {2: 6, 16: 2}), "partseq": (4096, {2: 4, 16: 1}), "trade": (4096, {2: 6, 16: 2}), "nextuser": (512, {2: 5, 16: 2}), "eventchain": (512, {2: 5, 16: 2}), "weblink": (512, {2: 3, 16: 1}), "kron": (4096, {2: 4, 16: 1})}


def _curve(x: Graph, n: int, k: int) -> DataFrame:
    return metrics.reduction_curve(metrics.log_of(x.edges), x.edges.count(), n, k)


for _name, (_n, _ks) in _CURVES.items():
    for _k, _p in _ks.items():
        add(f"reduction_curve_{_name}_{_n}_{_k}", g(_name, partial(_curve, n=_n, k=_k)), oracles.curve(_name, _n, _k, _p))


def _ratios(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = None
    for name, (n, ks) in _CURVES.items():
        x = GRAPHS[name](spark, sf_dir).stored()
        log, m = Scratch(spark, "log").keep(metrics.log_of(x.edges)), x.edges.count()
        for k in ks:
            row = metrics.movement_ratio(metrics.reduction_curve(log, m, n, k)).select(F.lit(x.name).alias("graph"), F.lit(n).alias("n"), F.lit(k).alias("k"), "phases", F.round("ratio", 9).alias("ratio"))
            out = row if out is None else out.unionByName(row)
    return out


add("movement_ratio_all", _ratios, " union all ".join(
    f"select 'g_{n}' as graph, {b}::int as n, {k}::int as k, (max(phase) - 1)::int as phases, round(sum(records) filter (phase > 0) / (max(records) * max(phase)), 9) as ratio from ({oracles.curve(n, b, k, p)})"
    for n, (b, ks) in _CURVES.items() for k, p in ks.items()))


# ---------------------------------------------------------------- commit, update lists, expansion

_REACH = VertexProgram("reach", lambda c: c.val, "min", lambda old, new: F.coalesce(old, new), lambda old, new: old.isNull())


def _commit(x: Graph, sweep: str) -> DataFrame:
    spark = x.edges.sparkSession
    current = spark.createDataFrame([(v, v) for v in (0, 1, 2)], "v bigint, val bigint")
    log = emit_log(current, x.edges, F.col("val"), broadcast_active=True)
    every = current if sweep == "touched" else x.vertices().join(current, "v", "left")
    return commit(fold(log, REDUCERS["min"]), every, _REACH, sweep)


_CM = f"with {oracles.graph('weblink')}, c as (select unnest([0, 1, 2])::bigint as v), u as (select g.dst as v, min(c.v) as folded from g join c on c.v = g.src group by g.dst)"
add("commit_touched", g("weblink", partial(_commit, sweep="touched")), f"{_CM} select u.v, coalesce(c.v, folded) as val, c.v is null as active from u left join c on c.v = u.v")
add("commit_sweep_all", g("weblink", partial(_commit, sweep="all")), f"{_CM}, n as (select unnest(range({oracles.SIZES['weblink']})) as v) select n.v, coalesce(c.v, folded) as val, c.v is null and folded is not null as active from n left join c on c.v = n.v left join u on u.v = n.v")


def _lists(x: Graph) -> UpdateLog:
    """Zero for every vertex, then the parents that each level of a search brought."""
    log = UpdateLog(x.edges.sparkSession, "lists", x.width)
    log.append(0, x.vertices().select("v", F.lit(0).cast("bigint").alias("val")))
    for step, level in enumerate(alg.bfs(x, 0).lists, start=1):
        log.append(step, level.select("v", F.col("parent").alias("val")))
    return log


_UL = oracles._levels("trade", 0, 8) + f", a as materialized (select 0 as superstep, unnest(range({oracles.SIZES['trade']})) as v, 0::bigint as val union all select (level + 1)::int, v, parent from t)"
_NEWEST = f"{_UL} select v, max_by(val, superstep) as val, max(superstep)::int as superstep from a group by v"
add("log_resolve", g("trade", lambda x: _lists(x).resolve(), width=_WIDTH), _NEWEST)
add("log_active", g("trade", lambda x: _lists(x).active()), f"{_UL} select v, val from a where superstep = (select max(superstep) from a)")


def _compacted(x: Graph) -> DataFrame:
    log = _lists(x)
    log.compact(2)
    return log.resolve().select("v", "val")


add("log_resolve_some", g("trade", lambda x: (log := _lists(x)).resolve(log.active(2).select("v")).select("v", "val"), width=_WIDTH), f"{_UL} select v, max_by(val, superstep) as val from a where v in (select v from a where superstep = 2) group by v")
add("log_compact", g("trade", _compacted), f"{_UL} select v, max_by(val, superstep) as val from a group by v")


def _frontier(x: Graph, strategy: str) -> DataFrame:
    active = x.edges.where("src = 0").select(F.col("dst").alias("v")).distinct()
    return layout.edges_of(active, x.edges, strategy).select("src", "dst")


_FR = f"with {oracles.graph('trade')} select g.src, g.dst from g join (select distinct dst as v from g where src = 0) f on f.v = g.src"
for _s in ("seek", "scan", "auto"):
    add(f"expand_{_s}", g("trade", partial(_frontier, strategy=_s)), _FR)
for _hint in ("broadcast", "merge", "shuffle_hash"):
    add(f"expand_{_hint}", g("trade", lambda x, h=_hint: x.edges.join(x.edges.where("src = 0").select(F.col("dst").alias("src")).distinct().hint(h), "src").select("src", "dst")), _FR)
_V = "select v, val from (select c_custkey as v, c_nationkey::bigint as val from customer)"
_A, _B = "(select c_custkey as v, c_nationkey::bigint as val from customer where c_custkey % 3 <> 0)", "(select s_suppkey * 7 as v, s_nationkey::bigint + 100 as val from supplier)"
add("split_runs", lambda s, d: vsource.split(_x(s, d), 100, 4).groupBy("way").agg(F.count("*").alias("n"), F.sum("v").alias("total")), f"with o as (select v, row_number() over (order by v) - 1 as ord from {_A}) select ((ord // 100) % 4)::int as way, count(*) as n, sum(v)::bigint as total from o group by 1")
add("partition_log", g("copurchase", lambda x: partition_log(x.edges.select("dst", "src"), 128, 8).groupBy("part").agg(F.count("*").alias("records"), F.countDistinct("dst").alias("keys"))), f"with {oracles.graph('copurchase')} select (dst // 128)::int as part, count(*) as records, count(distinct dst) as keys from g group by 1")


# ---------------------------------------------------------------- vertex sources

def _x(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "customer").where("c_custkey % 3 <> 0").select(F.col("c_custkey").alias("v"), F.col("c_nationkey").cast("bigint").alias("val"))


def _y(spark: SparkSession, sf_dir: str) -> DataFrame:
    return load(spark, sf_dir, "supplier").select((F.col("s_suppkey") * 7).alias("v"), (F.col("s_nationkey").cast("bigint") + 100).alias("val"))


def _sparse(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = f"{Scratch(spark, 'sparse').root}/list"
    vsource.write_sparse(_x(spark, sf_dir), path)
    return vsource.sparse(spark, path)


def _dense(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = f"{Scratch(spark, 'dense').root}/list"
    most = load(spark, sf_dir, "customer").agg(F.max("c_custkey")).first()[0]
    vsource.write_dense(_x(spark, sf_dir), most + 1, path, width=500)
    return vsource.dense(spark, path)


_FULL = f"from {_A} a full join {_B} b on a.v = b.v"
add("vs_sparse", _sparse, f"select * from {_A}")
add("vs_dense", _dense, f"select n.v, a.val from (select unnest(range((select max(c_custkey) + 1 from customer))) as v) n left join {_A} a on a.v = n.v")
add("encoding_choice", lambda s, d: s.createDataFrame([(n, layout.choose_encoding(f(s, d), load(s, d, t).count())) for n, f, t in (("customer", _x, "customer"), ("supplier", _y, "part"))], "list string, encoding string"),
    "select 'customer' as list, case when (select count(*) from customer where c_custkey % 3 <> 0) >= 0.5 * (select count(*) from customer) then 'dense' else 'sparse' end as encoding union all select 'supplier', case when (select count(*) from supplier) >= 0.5 * (select count(*) from part) then 'dense' else 'sparse' end")
add("vs_seek", lambda s, d: vsource.seek(_sparse(s, d), 1000), f"select * from {_A} where v >= 1000")
add("vs_arith", lambda s, d: vsource.arith(_x(s, d), lambda v: v * 3 + 1), f"select v, val * 3 + 1 as val from {_A}")
add("vs_union", lambda s, d: vsource.union(_x(s, d), _y(s, d)), f"select coalesce(a.v, b.v) as v, case when a.v is not null then a.val else b.val end as val {_FULL}")
add("vs_difference", lambda s, d: vsource.difference(_x(s, d), _y(s, d)), f"select * from {_A} where v not in (select v from {_B})")
add("vs_intersect", lambda s, d: vsource.intersect(_x(s, d), _y(s, d)), f"select * from {_A} where v in (select v from {_B})")
add("vs_minimum", lambda s, d: vsource.minimum(_x(s, d), _y(s, d)), f"select a.v, least(a.val, b.val) as val from {_A} a join {_B} b on a.v = b.v")
add("vs_custom_inner", lambda s, d: vsource.custom(_x(s, d), _y(s, d), lambda a, b: a * 1000 + b), f"select a.v, a.val * 1000 + b.val as val from {_A} a join {_B} b on a.v = b.v")
add("vs_custom_outer", lambda s, d: vsource.custom(_x(s, d), _y(s, d), lambda a, b: a + b, "outer"), f"select coalesce(a.v, b.v) as v, coalesce(a.val, 0) + coalesce(b.val, 0) as val {_FULL}")
add("vs_converge", lambda s, d: vsource.converge(_x(s, d), _y(s, d), lambda a, b: F.abs(a - b) <= 100), f"select a.v, a.val from {_A} a join {_B} b on a.v = b.v where abs(a.val - b.val) > 100")
add("vs_cascade", lambda s, d: vsource.cascade([_x(s, d), _y(s, d), _x(s, d)], F.sum), f"select v, sum(val)::bigint as val from (select * from {_A} union all select * from {_B} union all select * from {_A}) group by v")


# ---------------------------------------------------------------- algorithms

_CAPS = {"copurchase": 4, "trade": 8, "kron": 8, "weblink": 14, "eventchain": 120}
for _name, _cap in _CAPS.items():
    add(f"bfs_{_name}", g(_name, lambda x: alg.bfs(x, 0).rows()), oracles.bfs(_name, 0, _cap))
add("bfs_levels", g("trade", lambda x: alg.bfs(x, 0).rows().groupBy("level").agg(F.count("*").alias("reached"))), oracles.bfs_levels("trade", 0, 8))
add("bfs_multi", g("partseq", lambda x: alg.bfs_multi(x, [0, 5, 9])), oracles.bfs_multi("partseq", [0, 5, 9], 8))
add("trace_path", g("trade", lambda x: alg.trace_path(alg.bfs(x, 0), 100)), oracles.path("trade", 0, 100, 8))

add("pagerank_step", g("partseq", lambda x: alg.rank_fixed(x, 1)), oracles.rank_fixed("partseq", 1))
for _name in ("copurchase", "kron", "weblink"):
    add(f"pagerank_step_{_name}", g(_name, lambda x: alg.rank_fixed(x, 1)), oracles.rank_fixed(_name, 1))
add("pagerank_step_double", g("partseq", lambda x: alg.rank_step(x, x.vertices().select("v", F.lit(1.0 / x.n).alias("rank"))).select("v", F.round("rank", 9).alias("rank"))), oracles.rank_double("partseq", 1))
add("pagerank_fixed_10", g("partseq", lambda x: alg.rank_fixed(x, 10)), oracles.rank_fixed("partseq", 10))
add("pagerank_keep", g("kron", lambda x: alg.rank_fixed(x, 3, untouched="keep")), oracles.rank_fixed("kron", 3, untouched="keep"))
add("pagerank_redistribute", g("kron", lambda x: alg.rank_fixed(x, 3, dangling="redistribute")), oracles.rank_fixed("kron", 3, dangling="redistribute"))
add("pagerank_lazy", g("partseq", lambda x: alg.rank_fixed(x, 3, lazy=True)), oracles.rank_fixed("partseq", 3))


def _converged(x: Graph, active: str, tol: float = 1e-9, most: int = 20) -> DataFrame:
    return alg.rank_converged(x, tol=tol, max_iter=most, active=active)[0].select("v", F.round("rank", 6).alias("rank"))


_CONV = oracles.rank_double("partseq", 20, 6)
add("pagerank_converged", g("partseq", partial(_converged, active="all")), _CONV)
add("pagerank_converged_copurchase", g("copurchase", partial(_converged, active="all")), oracles.rank_double("copurchase", 20, 6))
add("pagerank_residual", g("partseq", partial(_converged, active="residual")), _CONV)
add("pagerank_unconverged_active", g("partseq", partial(_converged, active="unconverged", most=12)), oracles.rank_unconverged("partseq", 12))


def _bc(x: Graph, kind: str) -> DataFrame:
    tree = alg.bfs(x, 0)
    return {"children": alg.bc_children, "descendants": alg.bc_descendants}[kind](tree)


for _name, _cap in (("trade", 8), ("kron", 8), ("weblink", 14)):
    add(f"bc_descendants_{_name}", g(_name, partial(_bc, kind="descendants")), oracles.bc_descendants(_name, 0, _cap))
add("bc_children", g("trade", partial(_bc, kind="children")), oracles.bc_children("trade", 0, 8))


def _six_digits(value: Column) -> Column:
    """As SQL rounds in doubles: ``F.round`` to digits goes by the decimal text and differs at halves such as 1.0015625."""
    return F.round(value * 1e6) / 1e6


for _name, _cap, _depth in (("trade", 8, 4), ("kron", 8, 4), ("weblink", 14, 7)):
    add(f"bc_exact_{_name}", g(_name, lambda x: alg.bc_exact(x, 0).select("v", _six_digits(F.col("score")).alias("score"))), oracles.bc_exact(_name, 0, _cap, _depth))
add("bc_multi", g("partseq", lambda x: alg.bc_multi(x, [0, 5, 9])), oracles.bc_multi("partseq", [0, 5, 9], 8))
add("sssp_trade", g("trade", lambda x: alg.sssp(x, 0)), oracles.sssp("trade", 0, 16))
add("sssp_trade_by_ranges", g("trade", lambda x: alg.sssp(x, 0), width=_WIDTH), oracles.sssp("trade", 0, 16))
add("bfs_trade_by_ranges", g("trade", lambda x: alg.bfs(x, 0).rows(), width=_WIDTH), oracles.bfs("trade", 0, 8))
add("sssp_partseq", g("partseq", lambda x: alg.sssp(x, 0)), oracles.sssp("partseq", 0, 20))
add("components_weblink", g("weblink", alg.components), oracles.components("weblink"))
add("components_dialog", g("dialog", alg.components), oracles.components("dialog"))
_VOTE = f"with {oracles.graph('partseq')}, p0 as (select unnest(range({oracles.SIZES['partseq']})) as v, v as label)" + "".join(
    f", c{k} as (select g.dst, p.label, count(*) as n from g join p{k - 1} p on p.v = g.src group by 1, 2), b{k} as (select dst, label from c{k} qualify row_number() over (partition by dst order by n desc, label) = 1),"
    f" p{k} as materialized (select p.v, coalesce(b.label, p.label) as label from p{k - 1} p left join b{k} b on b.dst = p.v)" for k in (1, 2, 3))  # fmt: skip
add("label_vote_rounds", g("partseq", lambda x: alg.label_vote(x, 3)), f"{_VOTE} select v, label from p3")
add("degree_out", g("partseq", lambda x: alg.degree(x), False), f"{_PS} select src as v, count(*) as val from g group by src")
add("degree_in", g("partseq", lambda x: alg.degree(x, "in"), False), f"{_PS} select dst as v, count(*) as val from g group by dst")
add("weighted_in", g("partseq", alg.weighted_in, False), f"{_PS} select dst as v, sum(w)::bigint as val from g group by dst")


# ---------------------------------------------------------------- baselines

def _run(x: Graph, engine: Engine, task: str) -> DataFrame:
    if task == "pagerank":
        return alg.rank_fixed(x, 2, engine=engine)
    tree = alg.bfs(x, 0, engine=engine)
    return tree.rows() if task == "bfs" else alg.bc_descendants(tree)


def _with(engine: str, task: str) -> Callable[[Graph], DataFrame]:
    return lambda x: _run(x, ENGINES[engine](), task)


_SAME = {"pagerank": ("partseq", oracles.rank_fixed("partseq", 2)), "bfs": ("trade", oracles.bfs("trade", 0, 8)), "bc": ("trade", oracles.bc_descendants("trade", 0, 8))}
for _task, (_name, _sql) in _SAME.items():
    for _engine in ENGINES:
        if _engine != "sort_reduce":
            add(f"baseline_{_engine}_{_task}", g(_name, _with(_engine, _task)), _sql)


def _all_engines(x: Graph, task: str) -> DataFrame:
    """Every engine on one graph: how many vertices it gives and a sum over its values."""
    spark, out = x.edges.sparkSession, []
    value = {"pagerank": F.col("rank_u"), "bfs": F.col("parent") + F.col("level") * 1000, "bc": F.col("score")}[task]
    alone = {"pagerank": lambda: local.rank_single(x, 2), "bfs": lambda: local.bfs_local(x, 0), "bc": lambda: local.bc_local(x, 0)}[task]
    runs = {**{name: (lambda name=name: _with(name, task)(x)) for name in ENGINES}, "single_thread": alone}
    for name, run in runs.items():
        row = run().agg(F.count("*").alias("n"), F.sum(value).alias("t")).first()
        out.append((name, row["n"], int(row["t"])))
    return spark.createDataFrame(out, "engine string, vertices bigint, total bigint")


_ENGINE_ROWS = "unnest(['sort_reduce', 'semi_external', 'edge_scan', 'multi_pass', 'cached', 'dataflow', 'single_thread']) as engine"
for _task, _value, _names in (("pagerank", "rank_u", ("copurchase", "kron", "weblink")), ("bfs", "parent + level * 1000", ("copurchase", "kron", "weblink")), ("bc", "score", ("copurchase", "kron", "weblink"))):
    for _name in _names:
        _sql = {"pagerank": lambda n: oracles.rank_fixed(n, 2), "bfs": lambda n: oracles.bfs(n, 0, 14), "bc": lambda n: oracles.bc_descendants(n, 0, 14)}[_task](_name)
        add(f"engines_{_task}_{_name}", g(_name, partial(_all_engines, task=_task)), f"with r as materialized ({_sql}) select {_ENGINE_ROWS}, (select count(*) from r) as vertices, (select sum({_value})::bigint from r) as total")


def _converged_engines(x: Graph) -> DataFrame:
    out = []
    for name, make in ENGINES.items():
        done, rounds = alg.rank_converged(x, tol=1e-6, max_iter=20, engine=make())
        row = done.agg(F.round(F.sum("rank"), 6).alias("t"), F.count("*").alias("n")).first()
        out.append((name, rounds, row["n"], row["t"]))
    return x.edges.sparkSession.createDataFrame(out, "engine string, rounds int, vertices bigint, total double")


add("engines_rank_converged", g("partseq", _converged_engines), f"select engine, rounds, vertices, total from ({oracles.rank_rounds('partseq', 20, '1e-6')}) r, (select {_ENGINE_ROWS}) e where engine <> 'single_thread'")


def _budgets(x: Graph) -> DataFrame:
    """Engines at budgets below and above what a vertex value each needs: what runs, in how many partitions, or refuses."""
    out, first = [], {}
    for task, algorithm in (("pagerank", "rank"), ("bfs", "bfs"), ("bc", "betweenness")):
        state = cost.STATE[algorithm]
        for share in (1, 2, 4, 8):
            memory = x.n * state * share // 4
            for name in ("sort_reduce", "semi_external", "edge_scan"):
                e = {"sort_reduce": Engine, "semi_external": lambda: ENGINES["semi_external"](memory, state), "edge_scan": lambda: ENGINES["edge_scan"](memory, state)}[name]()
                try:
                    e.prepare(x)
                except CapacityExceeded:
                    out.append((task, name, share, "refused", 0, None))
                    continue
                parts = getattr(e, "partitions", 1)
                if (task, name, parts) not in first:
                    first[task, name, parts] = int(_run(x, e, task).agg(F.sum({"pagerank": "rank_u", "bfs": "parent", "bc": "score"}[task])).first()[0])
                out.append((task, name, share, "done", parts, first[task, name, parts]))
    return x.edges.sparkSession.createDataFrame(out, "task string, engine string, quarters int, status string, partitions int, total bigint")


_BUDGET_SQL = " union all ".join(
    f"select '{t}' as task, engine, q::int as quarters, case when engine = 'semi_external' and q < 4 then 'refused' else 'done' end as status,"
    f" (case when engine = 'semi_external' and q < 4 then 0 when engine = 'edge_scan' then case when q < 2 then 4 when q < 4 then 2 else 1 end else 1 end)::int as partitions,"
    f" case when engine = 'semi_external' and q < 4 then null else (select sum({c})::bigint from {t}) end as total from (select unnest(['sort_reduce', 'semi_external', 'edge_scan']) as engine), (values (1), (2), (4), (8)) as b(q)"
    for t, c in (("pagerank", "rank_u"), ("bfs", "parent"), ("bc", "score"))
)
add("budget_matrix", g("weblink", _budgets), f"with pagerank as materialized ({oracles.rank_fixed('weblink', 2)}), bfs as materialized ({oracles.bfs('weblink', 0, 14)}), bc as materialized ({oracles.bc_descendants('weblink', 0, 14)}) {_BUDGET_SQL}")
_COPIES, _SIZED = 100_000, ("partseq", "nextuser", "eventchain")


def _grown(spark: SparkSession, sf_dir: str) -> dict[str, tuple[int, int]]:
    """Vertices and edges of graphs of the given tables, if these were repeated ``_COPIES`` times with other keys."""
    made = [GRAPHS[name](spark, sf_dir) for name in _SIZED]
    return {x.name: (x.n * _COPIES, x.edges.count() * _COPIES) for x in made}


_GROWN = "e(graph, n, m) as materialized (" + " union all ".join(f"select 'g_{n}', ({oracles.SIZES[n]} * {_COPIES})::bigint, ((select count(*) from ({oracles.GRAPHS[n]})) * {_COPIES})::bigint" for n in _SIZED) + ")"
add("edge_scan_partitions", lambda s, d: s.createDataFrame([(name, gib, cost.edge_scan_partitions(n, gib << 30)) for name, (n, _) in _grown(s, d).items() for gib in (8, 16, 32, 64)], "graph string, gib int, partitions int"),
    f"with {_GROWN} select graph, gib::int as gib, (2 ** greatest(0, ceil(log2(n::double * 16 / (gib * 1073741824::bigint)))))::int as partitions from e, (values (8), (16), (32), (64)) as t(gib)")
add("baseline_single_thread_pagerank", g("partseq", lambda x: local.rank_single(x, 2)), _SAME["pagerank"][1])
add("baseline_worklist_pagerank", g("partseq", lambda x: local.rank_worklist(x).select("v", F.round("rank", 6).alias("rank"))), oracles.rank_double("partseq", 20, 6))
for _order, _engine in (("levels", "single_thread"), ("worklist", "worklist")):
    add(f"baseline_{_engine}_bfs", g("trade", partial(local.bfs_local, root=0, order=_order)), _SAME["bfs"][1])
    add(f"baseline_{_engine}_bc", g("trade", partial(local.bc_local, root=0, order=_order)), _SAME["bc"][1])


# ---------------------------------------------------------------- measures

def _trace(x: Graph) -> tuple[alg.Tree, list[int], list[int], int]:
    """A search, the edges that leave each level, those in the ranges that its rounds opened, and all edges."""
    tree, out = alg.bfs(x, 0), x.degrees()
    used = {r["level"]: r["n"] for r in tree.rows().join(out, "v").groupBy("level").agg(F.sum("degree").alias("n")).collect()}
    return tree, [used.get(i, 0) for i in range(len(tree.sizes))], tree.edges_read(x), x.edges.count()


def _efficiency(x: Graph) -> DataFrame:
    tree, used, read, m = _trace(x)
    rows = metrics.scan_efficiency(tree.sizes, used, read, m)
    return x.edges.sparkSession.createDataFrame(rows, "engine string, step int, active bigint, edges_read bigint, useful bigint")


def _tail(x: Graph) -> DataFrame:
    tree, _, read, m = _trace(x)
    rounds = len(tree.sizes)
    rows = [("edge_scan", rounds, m * rounds, cost.project(rounds, 500.0)), ("sort_reduce", rounds, sum(read), cost.project(rounds, 500.0 * sum(read) / (m * rounds)))]
    return x.edges.sparkSession.createDataFrame(rows, "engine string, rounds int, edges_read bigint, seconds double")


def _rows_read(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows that the scans of a whole search report, beside the edges in the ranges that it opened."""
    out = []
    for name, engines in (("trade", ("sort_reduce", "semi_external", "edge_scan", "multi_pass", "dataflow")), ("eventchain", ("sort_reduce",))):
        x = GRAPHS[name](spark, sf_dir).stored(_WIDTH)
        for engine in engines:
            trees: list[alg.Tree] = []
            use = metrics.stage_totals(spark, lambda x=x, engine=engine, trees=trees: trees.append(alg.bfs(x, 0, engine=ENGINES[engine]())))
            out.append((x.name, engine, len(trees[0].sizes), int(use["rows_read"]), sum(trees[0].edges_read(x)), use["cpu_seconds"]))
    return spark.createDataFrame(out, "graph string, engine string, rounds int, rows_read bigint, edges_opened bigint, cpu_seconds double")


for _name, _cap in (("trade", 8), ("eventchain", 120)):
    _suffix = "" if _name == "eventchain" else f"_{_name}"
    add(f"scan_efficiency{_suffix}", g(_name, _efficiency, width=_WIDTH), oracles.scans(_name, 0, _cap, _WIDTH) + " select 'sort_reduce' as engine, step, active, opened as edges_read, useful from s union all select 'edge_scan', step, active, m, useful from s, m union all select 'multi_pass', step, active, m * 4, useful from s, m")
    add(f"long_tail_projection{_suffix}", g(_name, _tail, width=_WIDTH), oracles.long_tail(_name, 0, _cap, "500.0", _WIDTH))
add("trace_bfs_eventchain", g("eventchain", lambda x: x.edges.sparkSession.createDataFrame([(i, n) for i, n in enumerate(alg.bfs(x, 0).sizes)], "step int, active bigint")), oracles._levels("eventchain", 0, 120) + " select level::int as step, count(*) as active from lv group by level")
add("scan_rows_measured", _rows_read)
_PG = f"with {oracles.graph('kron')}, l as (select dst * 8 // 8192 as page, row_number() over (order by src, dst) - 1 as ord from g)"
add("page_reads_random", g("kron", lambda x: metrics.page_reads(metrics.log_of(x.edges)).select("random_pages", "log")), f"{_PG} select count(*) filter (b is null or b <> page) as random_pages, count(*) as log from (select page, lag(page) over (order by ord) as b from l)")
add("page_reads_sorted", g("kron", lambda x: metrics.page_reads(metrics.log_of(x.edges)).select("sorted_pages", "log")), f"{_PG} select count(distinct page) as sorted_pages, count(*) as log from l")
_NEED = f"with {_GROWN}, " "st(algorithm, w) as (values ('rank', 20), ('bfs', 16), ('betweenness', 28)), q as (select graph, algorithm, unnest([{'e': 'sort_reduce', 'b': 16 * 536870912::bigint + 4194304::bigint * 64}, {'e': 'semi_external', 'b': w * n::bigint}, {'e': 'edge_scan', 'b': 16 * n::bigint}, {'e': 'multi_pass', 'b': w * n::bigint // 4}, {'e': 'cached', 'b': 24 * m::bigint + w * n::bigint}]) as x from e, st), w as (select graph, algorithm, x.e as engine, x.b as bytes from q)"
add("memory_need", lambda s, d: s.createDataFrame(cost.needs(_grown(s, d)), "graph string, algorithm string, engine string, bytes bigint"), f"{_NEED} select graph, algorithm, engine, bytes from w")
add("crossover_grid", lambda s, d: s.createDataFrame(cost.crossover(graphs=_grown(s, d)), "graph string, algorithm string, engine string, gib int, fits boolean"), f"{_NEED} select graph, algorithm, engine, gib::int as gib, bytes <= gib * 1073741824::bigint as fits from w, (values (16), (32), (48), (64), (96), (128)) as t(gib)")
add("fleet_cost", lambda s, d: s.createDataFrame([(name, *cost.fleet(16 * m, 128 << 30)) for name, (_, m) in _grown(s, d).items()], "graph string, nodes bigint, dollars bigint, watts bigint"), f"with {_GROWN} select graph, k as nodes, k * 2500 as dollars, k * 170 as watts from (select graph, (16 * m + 137438953471) // 137438953472 as k from e)")


def _accuracy_rank(x: Graph) -> DataFrame:
    exact = Scratch(x.edges.sparkSession, "exact").keep(alg.rank_converged(x, max_iter=40)[0])
    out = None
    for kind in ("unconverged", "residual"):
        row = metrics.compare(alg.rank_converged(x, active=kind, max_iter=40)[0], exact, val="rank").select(F.lit(kind).alias("variant"), "metric", "value")
        out = row if out is None else out.unionByName(row)
    return out


def _accuracy_bc(x: Graph) -> DataFrame:
    tree = alg.bfs(x, 0)
    exact = alg.bc_exact(x, 0, tree)
    pairs = {"children": alg.bc_children(tree), "descendants": alg.bc_descendants(tree)}
    rows = [metrics.compare(s.where("v <> 0"), exact, val="score").select(F.lit(k).alias("variant"), "metric", "value") for k, s in pairs.items()]
    return rows[0].unionByName(rows[1])


def _agree(x: Graph) -> DataFrame:
    first = Scratch(x.edges.sparkSession, "mode").keep(_one_round(x, "fused"))
    rows = [(m, metrics.same(first, _one_round(x, m))) for m in ("in_place", "sort_first", "interleaved")]
    for name, make in ENGINES.items():
        e, active = make(), x.degrees().select("v", F.expr(f"{10**12 // x.n} div degree").alias("val"))
        rows.append((name, metrics.same(first, e.round(active, e.prepare(x), F.col("val"), "sum").select(F.col("dst").alias("v"), "val"))))
        e.finish()
    return x.edges.sparkSession.createDataFrame(rows, "mode string, same boolean")


def _overlap(x: Graph) -> DataFrame:
    """How many of the best by exact rank are among the best of the variants."""
    exact = Scratch(x.edges.sparkSession, "exact").keep(alg.rank_converged(x)[0])
    rows = [(kind, k, metrics.top_overlap(exact, alg.rank_converged(x, active=kind)[0], k, val="rank")) for kind in ("unconverged", "residual") for k in (10,)]
    return x.edges.sparkSession.createDataFrame(rows, "variant string, k int, overlap double")


add("accuracy_top_overlap", g("nextuser", _overlap))
add("accuracy_rank_variants", g("nextuser", _accuracy_rank))
add("accuracy_bc_variants", g("trade", _accuracy_bc))
add("modes_agree", g("partseq", _agree), "select unnest(['in_place', 'sort_first', 'interleaved', 'sort_reduce', 'semi_external', 'edge_scan', 'multi_pass', 'cached', 'dataflow']) as mode, true as same")


# ---------------------------------------------------------------- the surface around the methods

for _name in relational.TEXTS:
    add(_name, lambda s, d, n=_name: relational.run(s, d, n), relational.oracle(_name))


def _roundtrip(x: Graph, kind: str) -> DataFrame:
    spark, path = x.edges.sparkSession, f"{Scratch(x.edges.sparkSession, 'trip').root}/{kind}"
    getattr(x.edges.write, kind)(path)
    back = getattr(spark.read.schema("src bigint, dst bigint, w bigint"), kind)(path)
    return back.groupBy("src").agg(F.count("*").alias("n"), F.sum("dst").alias("total"), F.max("w").alias("most"))


for _kind in ("csv", "json", "orc", "parquet"):
    add(f"roundtrip_{_kind}", g("partseq", partial(_roundtrip, kind=_kind), False), f"{_PS} select src, count(*) as n, sum(dst)::bigint as total, max(w) as most from g group by src")


def _imported(x: Graph) -> DataFrame:
    path = f"{Scratch(x.edges.sparkSession, 'text').root}/edges"
    x.edges.select("src", "dst").write.csv(path, sep="\t")
    return layout.import_text(x.edges.sparkSession, path).groupBy("src").agg(F.count("*").alias("n"), F.sum("dst").alias("total"))


add("import_text", g("partseq", _imported, False), f"{_PS} select src, count(*) as n, sum(dst)::bigint as total from g group by src")


def _bucketed(x: Graph) -> DataFrame:
    """Edges stored in buckets by destination, folded without an exchange."""
    table = layout.write_bucketed(x.edges, f"{Scratch(x.edges.sparkSession, 'buckets').root}/edges", "dst", 16)
    return table.groupBy("dst").agg(F.count("*").alias("n"), F.sum("w").alias("total"))


add("sink_bucketed", g("partseq", _bucketed, False), f"{_PS} select dst, count(*) as n, sum(w)::bigint as total from g group by dst")


def _source(spark: SparkSession, sf_dir: str) -> DataFrame:
    from vertexlog.sources.kron_source import KronSource

    spark.dataSource.register(KronSource)
    m = load(spark, sf_dir, "lineitem").count()
    return spark.read.format("kron").option("edges", m).option("scale", graphs.KRON_SCALE).load()


add("kron_source", _source, oracles.GRAPHS["kron"])
_HOST = r"regexp_extract(url, '^[a-z]+://([^/?#]*)', 1)"
add("url_host_graph", lambda s, d: load(s, d, "pages").select(F.regexp_extract("url", "^[a-z]+://([^/?#]*)", 1).alias("host"), "page_id").groupBy("host").agg(F.count("*").alias("pages"), F.min("page_id").alias("first_page")), f"select {_HOST} as host, count(*) as pages, min(page_id) as first_page from pages group by 1")
add("filter_json_prop", lambda s, d: load(s, d, "events").select(F.col("event_id").alias("v"), F.get_json_object("props", "$.k").cast("bigint").alias("k")).where("k > 50"), "select event_id as v, k from (select event_id, json_extract_string(props, '$.k')::bigint as k from events) where k > 50")
add("props_parse", lambda s, d: load(s, d, "events").select("event_type", F.from_json("props", "k bigint").alias("p")).groupBy("event_type").agg(F.sum("p.k").alias("total"), F.count("p.k").alias("n")), "select event_type, sum(json_extract_string(props, '$.k')::bigint)::bigint as total, count(json_extract_string(props, '$.k')) as n from events group by event_type")
add("asof_edges", lambda s, d: streams.as_of(load(s, d, "events")), "select b.event_id as src, a.event_id as dst from events a asof join (select * from events where event_type = 'purchase') b on a.ts > b.ts where a.event_type = 'view'")
add("adjacency_lists", g("partseq", lambda x: x.edges.groupBy("src").agg(F.array_sort(F.collect_list(F.struct("dst", "w"))).alias("n")).select("src", F.size("n").alias("degree"), F.element_at("n", 1)["dst"].alias("first"), F.aggregate("n", F.lit(0).cast("bigint"), lambda a, e: a + e["w"]).alias("total"), F.array_join(F.transform(F.filter("n", lambda e: e["w"] > 9000000), lambda e: e["dst"].cast("string")), ",").alias("heavy"))),
    f"{_PS} select src, count(*)::int as degree, min(dst) as first, sum(w)::bigint as total, coalesce(string_agg(dst::varchar, ',' order by dst, w) filter (w > 9000000), '') as heavy from g group by src")
add("adjacency_explode", g("partseq", lambda x: x.edges.groupBy("src").agg(F.array_sort(F.collect_set("dst")).alias("n")).select("src", F.posexplode("n").alias("pos", "dst"))), f"{_PS} select src, (row_number() over (partition by src order by dst) - 1)::int as pos, dst from (select distinct src, dst from g)")
add("neighbor_map", g("partseq", lambda x: x.edges.groupBy("src", "dst").agg(F.min("w").alias("w")).groupBy("src").agg(F.map_from_entries(F.collect_list(F.struct("dst", "w"))).alias("m")).select("src", F.size("m").alias("n"), F.array_max(F.map_values("m")).alias("most"), F.array_min(F.map_keys("m")).alias("nearest"))), f"{_PS}, d as (select src, dst, min(w) as w from g group by 1, 2) select src, count(*)::int as n, max(w) as most, min(dst) as nearest from d group by src")
add("levels_pivot", g("trade", lambda x: alg.bfs(x, 0).rows().withColumn("k", F.when(F.col("v") % 2 == 0, "even").otherwise("odd")).groupBy("level").pivot("k", ["even", "odd"]).count()), oracles._levels("trade", 0, 8) + " select level::int as level, nullif(count(*) filter (v % 2 = 0), 0) as even, nullif(count(*) filter (v % 2 = 1), 0) as odd from lv group by level")
add("degree_quantile", g("trade", lambda x: x.degrees().agg(F.percentile("degree", 0.5).alias("p50"), F.percentile("degree", 0.9).alias("p90"), F.percentile("degree", 0.99).alias("p99")).select(*(F.round(c, 6).alias(c) for c in ("p50", "p90", "p99")))), f"with {oracles.graph('trade')}, d as (select count(*) as c from g group by src) select round(quantile_cont(c, 0.5), 6) as p50, round(quantile_cont(c, 0.9), 6) as p90, round(quantile_cont(c, 0.99), 6) as p99 from d")
add("approx_reach", g("trade", lambda x: x.edges.agg(F.approx_count_distinct("dst").alias("dsts"), F.approx_count_distinct("src").alias("srcs"))))
add("approx_reach_within", g("trade", lambda x: x.edges.agg(F.count_distinct("dst").alias("dsts"), F.count_distinct("src").alias("srcs"), F.approx_count_distinct("dst").alias("d"), F.approx_count_distinct("src").alias("s")).select("dsts", "srcs", F.expr("abs(d - dsts) <= 0.15 * dsts and abs(s - srcs) <= 0.15 * srcs").alias("within"))),
    f"with {oracles.graph('trade')} select count(distinct dst) as dsts, count(distinct src) as srcs, true as within from g")
add("top_rank", g("partseq", lambda x: alg.rank_fixed(x, 1).orderBy(F.desc("rank_u"), "v").limit(20)), oracles.rank_fixed("partseq", 1) + " order by rank_u desc, v limit 20")
add("sorted_log", g("partseq", lambda x: x.edges.groupBy("dst").agg(F.count("*").alias("n")).orderBy("dst")), f"{_PS} select dst, count(*) as n from g group by dst order by dst")
add("rank_within_orders", g("partseq", lambda x: x.edges.withColumn("place", F.dense_rank().over(Window.partitionBy("src").orderBy("w"))).groupBy("src").agg(F.max("place").alias("prices"))), f"{_PS} select src, count(distinct w)::int as prices from g group by src")

add("sql_bfs_by_level", lambda s, d: sqlsurface.sql(s, d, "select level, count(*) as reached, min(parent) as first_parent from bfs('g_trade', 0) group by level"), oracles._levels("trade", 0, 8) + " select level::int as level, count(*) as reached, min(parent) as first_parent from t group by level")
add("sql_rank_of_reached", lambda s, d: sqlsurface.sql(s, d, "select r.v, r.rank_u, b.level from rank('g_partseq', 1) r join bfs('g_partseq', 0) b on r.v = b.v where b.level = 1"), f"with recursive lv as ({oracles.bfs('partseq', 0, 8)}), rk as ({oracles.rank_fixed('partseq', 1)}) select rk.v, rk.rank_u, lv.level from rk join lv on rk.v = lv.v where lv.level = 1")


def _kron_udtf(spark: SparkSession, sf_dir: str) -> DataFrame:
    m = load(spark, sf_dir, "lineitem").count()
    spark.udtf.register("kron_range", KronRange)
    return spark.sql(f"select t.src, t.dst from (select id * 1000 as low, least((id + 1) * 1000, {m}) as high from range({-(-m // 1000)})) r, lateral kron_range(r.low, r.high, {graphs.KRON_SCALE}) t")


add("kron_udtf", _kron_udtf, oracles.GRAPHS["kron"])
add("edge_function_pandas", g("partseq", lambda x: x.edges.join(x.degrees().withColumnRenamed("v", "src"), "src").groupBy("dst").agg(F.sum(damped(F.col("w").cast("double"), F.col("degree").cast("double"))).alias("s")).select(F.col("dst").alias("v"), F.round(F.col("s") / 7, 3).alias("val"))), f"{_PS}, d as (select src, count(*) as c from g group by src) select dst as v, round(sum(0.85 * w::double / c) / 7, 3) as val from g join d using (src) group by dst")
add("reduce_pandas_udaf", g("partseq", lambda x: x.edges.groupBy(F.col("dst").alias("v")).agg(spread(F.col("w")).alias("val"))), f"{_PS} select dst as v, max(w) - min(w) as val from g group by dst")


def _sweep(x: Graph) -> DataFrame:
    """The same fold for a grid of block sizes and fan-ins."""
    first, rows = Scratch(x.edges.sparkSession, "sweep").keep(_one_round(x, "fused")), []
    for n, k in ((512, 2), (512, 16), (4096, 2), (4096, 16)):
        active, engine = x.degrees().select("v", F.expr(f"{10**12 // x.n} div degree").alias("val")), Engine("interleaved", n, k)
        done = engine.round(active, engine.prepare(x), F.col("val"), "sum").select(F.col("dst").alias("v"), "val")
        rows.append((n, k, metrics.same(first, done)))
    return x.edges.sparkSession.createDataFrame(rows, "n int, k int, same boolean")


add("param_sweep", g("partseq", _sweep), "select n::int as n, k::int as k, true as same from (values (512), (4096)) as a(n), (values (2), (16)) as b(k)")


def _storage(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes of each graph as laid-out files and as text."""
    rows = []
    for name in GRAPHS:
        x, where = GRAPHS[name](spark, sf_dir), Scratch(spark, "sizes").root
        x.edges.select("src", "dst").repartitionByRange("src", "dst").sortWithinPartitions("src", "dst").write.parquet(f"{where}/binary")
        x.edges.select("src", "dst").write.csv(f"{where}/text", sep="\t")
        rows.append((x.name, spark.read.parquet(f"{where}/binary").count(), layout.stored_bytes(spark, f"{where}/binary"), layout.stored_bytes(spark, f"{where}/text")))
    return spark.createDataFrame(rows, "graph string, edges bigint, binary bigint, text bigint")


def _resources(x: Graph) -> DataFrame:
    """Processor time and bytes moved of one rank round by each form and of a search by each engine, from task metrics."""
    spark, rows = x.edges.sparkSession, []
    actions = {("rank round", mode): (lambda mode=mode: _one_round(x, mode).write.format("noop").mode("overwrite").save()) for mode in ("fused", "in_place", "sort_first", "interleaved")}
    actions |= {("bfs", name): (lambda make=make: alg.bfs(x, 0, engine=make())) for name, make in ENGINES.items()}
    for (task, name), action in actions.items():
        u = metrics.stage_totals(spark, action)
        rows.append((task, name, u["seconds"], u["cpu_seconds"], 100 * u["cpu_seconds"] / max(u["seconds"], 1e-9), *(int(u[k]) for k in ("rows_read", "bytes_read", "bytes_logged", "bytes_merged", "bytes_written"))))
    return spark.createDataFrame(rows, "task string, form string, seconds double, cpu_seconds double, cpu_percent double, rows_read bigint, bytes_read bigint, bytes_logged bigint, bytes_merged bigint, bytes_written bigint")


add("storage_sizes", _storage)
add("resource_use", g("copurchase", _resources))
def _tuned(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Settings for some machines, and the blocks and merge phases that they give the log of each grown graph."""
    rows = []
    for name, (_, m) in _grown(spark, sf_dir).items():
        for gib in (8, 16, 32):
            for cores in (8, 32):
                t = cost.tune(gib << 30, cores, 6e9)
                rows.append((name, gib, cores, t.n, t.k, t.threads, t.mergers, -(-m // t.n), metrics.merge_phases(m, t.n, t.k)))
    return spark.createDataFrame(rows, "graph string, gib int, cores int, n bigint, k int, threads int, mergers int, blocks bigint, phases int")


add("tuning_grid", _tuned,
    f"with {_GROWN}, c as (select gib, cores, greatest(1, least(16, cores // 2)) as threads, greatest(1, least(cores // 4, 6)) as mergers from (values (8), (16), (32)) as a(gib), (values (8), (32)) as b(cores)), t as (select gib::int as gib, cores::int as cores, greatest(1048576, least(536870912, gib * 1073741824::bigint // (2 * threads))) // 16 as n, greatest(2, least(64, gib * 1073741824::bigint // (4 * mergers * 4194304::bigint)))::int as k, threads::int as threads, mergers::int as mergers from c) select e.graph, t.*, (e.m + t.n - 1) // t.n as blocks, ceil(ln((e.m + t.n - 1) // t.n) / ln(t.k) - 1e-9)::int as phases from e, t")

for _name, (_query, _sql) in streams.QUERIES.items():
    add(_name, _query, _sql)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Highest ranks after one round on the part sequence graph."""
    return QUERIES["top_rank"](spark, sf_dir)


def queries() -> dict[str, Query]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
