"""SQL of the graphs and of the algorithms on them, for comparison in another engine (tables as given views)."""

from __future__ import annotations

HREF = "select distinct page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) as target from pages"


def _kron(scale: int = 12) -> str:
    steps = ["k0 as (select i, (48271 * i + 69621 * 42 + 1) % 2147483647 as x, 0::bigint as s, 0::bigint as d from (select unnest(range((select count(*) from lineitem))) as i))"]
    for b in range(1, scale + 1):
        x = "(16807 * ((48271 * x + 11) % 2147483647) + 7) % 2147483647"
        steps.append(f"y{b} as (select i, {x} as x, s, d from k{b - 1})")
        steps.append(
            f"k{b} as (select i, x, 2 * s + case when x % 100 >= 76 then 1 else 0 end as s,"
            f" 2 * d + case when (x % 100 >= 57 and x % 100 < 76) or x % 100 >= 95 then 1 else 0 end as d from y{b})"
        )
    return f"with {', '.join(steps)} select s as src, d as dst from k{scale}"


GRAPHS = {
    "partseq": "select src, dst, w from (select l_partkey as src, lead(l_partkey) over (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey, l_extendedprice) as dst,"
    " round(l_extendedprice * 100)::bigint as w from lineitem) where dst is not null",
    "copurchase": "select distinct a.l_partkey as src, b.l_partkey as dst from lineitem a join lineitem b on a.l_orderkey = b.l_orderkey and a.l_partkey <> b.l_partkey",
    "trade": "with sz as (select (select count(*) from customer) as c, (select count(*) from part) as p),"
    " h as (select o_custkey as a, l_partkey + c as b, round(l_extendedprice * 100)::bigint as w from lineitem join orders on l_orderkey = o_orderkey, sz"
    " union all select l_partkey + c, l_suppkey + c + p, round(l_extendedprice * 100)::bigint from lineitem, sz),"
    " o as (select a, b, min(w) as w from h group by a, b) select a as src, b as dst, w from o union all select b, a, w from o",
    "nextuser": "select a.user_id as src, b.user_id as dst from events a join events b on b.event_id = a.event_id + 1",
    "eventchain": "select src, dst from (select event_id as src, lead(event_id) over (partition by user_id order by ts) as dst from events) where dst is not null",
    "weblink": f"with l as ({HREF}), t as (select target, dense_rank() over (order by target) - 1 + (select count(*) from pages) as b from (select distinct target from l)),"
    " p as (select page_id as a, b from l join t using (target)) select a as src, b as dst from p union all select b, a from p",
    "dialog": "select src, dst from (select conv_id * 1024 + turn as src, conv_id * 1024 + lead(turn) over (partition by conv_id order by turn) as dst from conversations) where dst is not null",
    "kron": _kron(),
}

SIZES = {
    "partseq": "(select count(*) from part)",
    "copurchase": "(select count(*) from part)",
    "trade": "((select count(*) from customer) + (select count(*) from part) + (select count(*) from supplier))",
    "nextuser": "(select max(user_id) + 1 from events)",
    "eventchain": "(select count(*) from events)",
    "weblink": f"((select count(*) from pages) + (select count(distinct target) from ({HREF})))",
    "dialog": "(select 1024 * (max(conv_id) + 1) from conversations)",
    "kron": "4096",
}


def graph(name: str) -> str:
    return f"g as materialized ({GRAPHS[name]})"


def _levels(name: str, root: int, cap: int) -> str:
    return (
        f"with recursive {graph(name)}, r(v, level) as (select {root}::bigint, 0 union select g.dst, r.level + 1 from r join g on g.src = r.v where r.level < {cap}),"
        " lv as materialized (select v, min(level) as level from r group by v),"
        f" t as materialized (select lv.v, case when lv.v = {root} then {root}::bigint else min(g.src) end as parent, lv.level from lv left join (select g.src, g.dst, u.level from g join lv u on u.v = g.src) g"
        " on g.dst = lv.v and g.level = lv.level - 1 group by lv.v, lv.level)"
    )


def bfs(name: str, root: int = 0, cap: int = 10) -> str:
    return _levels(name, root, cap) + " select v, parent, level::int as level from t"


def bfs_levels(name: str, root: int = 0, cap: int = 10) -> str:
    return _levels(name, root, cap) + " select level::int as level, count(*) as reached from t group by level"


def bfs_multi(name: str, roots: list[int], cap: int = 10) -> str:
    values = " union all ".join(f"select {r}::bigint" for r in roots)
    return (
        f"with recursive {graph(name)}, q(root) as ({values}), r(root, v, level) as (select root, root, 0 from q union select r.root, g.dst, r.level + 1 from r join g on g.src = r.v where r.level < {cap}),"
        " lv as materialized (select root, v, min(level) as level from r group by root, v)"
        " select lv.root, lv.v, case when lv.v = lv.root then lv.root else min(x.src) end as parent, lv.level::int as level from lv"
        " left join (select u.root, g.src, g.dst, u.level from g join lv u on u.v = g.src) x on x.root = lv.root and x.dst = lv.v and x.level = lv.level - 1 group by lv.root, lv.v, lv.level"
    )


def path(name: str, root: int, v: int, cap: int = 10) -> str:
    return _levels(name, root, cap) + f", p(pos, v) as (select 0, {v}::bigint union all select pos + 1, t.parent from p join t on t.v = p.v where p.v <> {root}) select pos::int as pos, v from p"


def bc_children(name: str, root: int, cap: int) -> str:
    return _levels(name, root, cap) + f" select parent as v, count(*) as score from t where v <> {root} group by parent"


def bc_descendants(name: str, root: int, cap: int) -> str:
    return _levels(name, root, cap) + (
        f", up(v, a) as (select v, parent from t where v <> {root} union all select up.v, t.parent from up join t on t.v = up.a where up.a <> {root}) select a as v, count(*) as score from up group by a"
    )


def bc_multi(name: str, roots: list[int], cap: int) -> str:
    return f"with recursive t as materialized ({bfs_multi(name, roots, cap)}), " + (
        "up(root, v, a) as (select root, v, parent from t where v <> root union all select up.root, up.v, t.parent from up join t on t.root = up.root and t.v = up.a where up.a <> up.root)"
        " select a as v, count(*) as score from up group by a"
    )


def bc_exact(name: str, root: int, cap: int, depth: int) -> str:
    sql = _levels(name, root, cap) + f", gm as materialized (select src, dst, count(*)::double as m from g group by src, dst), s0 as materialized (select {root}::bigint as v, 1.0::double as sigma)"
    for k in range(1, depth + 1):
        sql += f", s{k} as materialized (select gm.dst as v, sum(s.sigma * gm.m) as sigma from s{k - 1} s join gm on gm.src = s.v join lv on lv.v = gm.dst and lv.level = {k} group by gm.dst)"
    sql += f", d{depth} as materialized (select v, sigma, 0.0::double as score from s{depth})"
    for k in range(depth - 1, 0, -1):
        sql += (
            f", d{k} as materialized (select s.v, s.sigma, coalesce(sum(s.sigma * gm.m / c.sigma * (1 + c.score)), 0.0) as score from s{k} s left join"
            f" (gm join d{k + 1} c on c.v = gm.dst) on gm.src = s.v group by s.v, s.sigma)"
        )
    return sql + " " + " union all ".join(f"select v, round(score, 6) as score from d{k}" for k in range(1, depth + 1))


def rank_fixed(name: str, rounds: int, untouched: str = "base", dangling: str = "drop", final: str = "select v, val as rank_u from p{}") -> str:
    sql = (
        f"with {graph(name)}, d as materialized (select src, count(*) as c from g group by src), z as materialized (select {SIZES[name]}::bigint as n),"
        " s as materialized (select n, 1000000000000 // n as share from z), p0 as materialized (select unnest(range(n)) as v, share as val from s)"
    )
    for k in range(1, rounds + 1):
        lost = f"(select coalesce(sum(p.val), 0)::bigint // (select n from s) from p{k - 1} p where p.v not in (select src from d))" if dangling == "redistribute" else "0"
        new = f"(15 * share + (coalesce(t.total, 0) + {lost}) * 85) // 100"
        if untouched == "keep":
            new = f"case when t.total is null then p.val else {new} end"
        sql += (
            f", p{k} as materialized (select p.v, ({new})::bigint as val from p{k - 1} p cross join s left join"
            f" (select g.dst, sum(q.val // d.c)::bigint as total from g join p{k - 1} q on q.v = g.src join d on d.src = g.src group by g.dst) t on t.dst = p.v)"
        )
    return sql + " " + final.format(rounds)


def _rank_steps(name: str, rounds: int) -> str:
    sql = (
        f"with {graph(name)}, d as materialized (select src, count(*) as c from g group by src), z as materialized (select {SIZES[name]}::bigint as n),"
        " p0 as materialized (select unnest(range(n)) as v, (1.0::double / n) as val from z)"
    )
    for k in range(1, rounds + 1):
        sql += (
            f", p{k} as materialized (select p.v, (0.15::double / (select n from z) + 0.85::double * coalesce(t.total, 0)) as val from p{k - 1} p left join"
            f" (select g.dst, sum(q.val / d.c) as total from g join p{k - 1} q on q.v = g.src join d on d.src = g.src group by g.dst) t on t.dst = p.v)"
        )
    return sql


def rank_double(name: str, rounds: int, digits: int = 9) -> str:
    return _rank_steps(name, rounds) + f" select v, round(val, {digits}) as rank from p{rounds}"


def rank_rounds(name: str, rounds: int, tol: str, digits: int = 6) -> str:
    """(rounds, vertices, total): the first round in which no vertex moved by ``tol``, and its values summed."""
    steps = " union all ".join(
        f"select {k} as k, max(abs(b.val - a.val)) < {tol} or {k} = {rounds} as done, count(*) as n, sum(b.val) as t from p{k - 1} a join p{k} b using (v)" for k in range(1, rounds + 1)
    )
    return _rank_steps(name, rounds) + f", c as ({steps}) select k::int as rounds, n as vertices, round(t, {digits}) as total from c where done order by k limit 1"


def rank_unconverged(name: str, rounds: int, digits: int = 6, tol: str = "1e-9") -> str:
    """Rank pushed by those vertices only that moved in the round before; the others keep their value."""
    sql = (
        f"with {graph(name)}, d as materialized (select src, count(*) as c from g group by src), z as materialized (select {SIZES[name]}::bigint as n),"
        " p0 as materialized (select unnest(range(n)) as v, (1.0::double / n) as val, true as moves from z)"
    )
    for k in range(1, rounds + 1):
        sql += (
            f", u{k} as materialized (select p.v, p.val as old, case when t.total is null then p.val else 0.15::double / (select n from z) + 0.85::double * t.total end as val from p{k - 1} p left join"
            f" (select g.dst, sum(q.val / d.c) as total from g join p{k - 1} q on q.v = g.src join d on d.src = g.src where q.moves group by g.dst) t on t.dst = p.v),"
            f" p{k} as materialized (select v, val, abs(val - old) >= {tol}::double as moves from u{k})"
        )
    return sql + f" select v, round(val, {digits}) as rank from p{rounds}"


def scans(name: str, root: int, cap: int, width: int) -> str:
    """s (step, active, useful, opened) and m: edges that leave each level, and edges in the source ranges it lies in."""
    return _levels(name, root, cap) + (
        f", z as materialized (select n, {width} as width from (select {SIZES[name]}::bigint as n)), m as materialized (select count(*) as m from g)"
        ", o as (select src, count(*) as n from g group by src), a as (select level, count(*) as active, coalesce(sum(o.n), 0)::bigint as useful from lv left join o on o.src = lv.v group by level)"
        ", rg as (select distinct level, v // width as p from lv, z), h as (select src // width as p, count(*) as n from g, z group by 1)"
        ", e as (select level, coalesce(sum(h.n), 0)::bigint as found from rg left join h on h.p = rg.p group by level)"
        ", s as materialized (select (a.level + 1)::int as step, active, useful, case when 4 * active <= z.n then found else m end as opened from a join e on e.level = a.level, z, m)"
    )


def long_tail(name: str, root: int, cap: int, seconds: str, width: int) -> str:
    """Rounds, edges read and projected seconds of an edge scan and of selective reading."""
    return scans(name, root, cap, width) + (
        ", x as (select count(*)::int as rounds, sum(opened)::bigint as opened from s)"
        f" select 'edge_scan' as engine, rounds, (m * rounds)::bigint as edges_read, rounds * {seconds}::double as seconds from x, m"
        f" union all select 'sort_reduce', rounds, opened, rounds * ({seconds}::double * opened / (m * rounds)) from x, m"
    )


def sssp(name: str, root: int, rounds: int) -> str:
    sql = f"with {graph(name)}, p0 as (select {root}::bigint as v, 0::bigint as dist)"
    for k in range(1, rounds + 1):
        sql += f", p{k} as materialized (select v, min(dist)::bigint as dist from (select * from p{k - 1} union all select g.dst, p.dist + g.w from p{k - 1} p join g on g.src = p.v) group by v)"
    return sql + f" select v, dist from p{rounds}"


def components(name: str) -> str:
    return (
        f"with recursive {graph(name)}, e as materialized (select distinct a, b from (select src as a, dst as b from g union all select dst, src from g)),"
        " r(v, label) as (select a, a from e union select e.b, r.label from r join e on e.a = r.v where r.label < e.b) select v, min(label) as label from r group by v"
    )


def curve(name: str, n: int, k: int, phases: int) -> str:
    sizes = ", ".join(f"({p + 1}, {n * k**p})" for p in range(phases + 1))
    return (
        f"with {graph(name)}, l as materialized (select dst, row_number() over (order by src, dst) - 1 as ord from g), m as (select count(*) as m from l),"
        f" q as (select p, size, dst, ord // size as block from l, (values {sizes}) as s(p, size))"
        f" select 0::int as phase, ((m + {n} - 1) // {n})::bigint as blocks, m::bigint as records, (m / m::double) as fraction from m"
        " union all select p::int, count(distinct block)::bigint, count(distinct (block, dst))::bigint, count(distinct (block, dst)) / (select m from m)::double from q group by p"
    )
