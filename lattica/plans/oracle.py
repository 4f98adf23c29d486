"""SQL for the queries, written apart from the engine: graph views and clustering steps as DuckDB text."""

from __future__ import annotations

from ..functions import hash_sql

WIDTH = "(select max(d) from (select unnest(range(1, cast(floor(sqrt(t.n)) as bigint) + 1)) as d, t.n from (select count(*) as n from part) t) where n % d = 0)"


def _grid(steps):
    return f"select p.p_partkey as a, p.p_partkey + s.dx + s.dy * k.w as b from part p, (select {WIDTH} as w, (select count(*) from part) as n) k, (values {steps}) s(dx, dy) where p.p_partkey % k.w + s.dx between 0 and k.w - 1 and p.p_partkey // k.w + s.dy < k.n // k.w"


PAIRS = {
    "lattice2d": _grid("(1, 0), (0, 1)"),
    "lattice8": _grid("(1, 0), (0, 1), (1, 1), (-1, 1)"),
    "ring_cliques": "select p.p_partkey as a, q.p_partkey as b from part p join part q on p.p_partkey // 10 = q.p_partkey // 10 and p.p_partkey < q.p_partkey union all select p_partkey, (p_partkey + 10) % (select count(*) from part) from part where p_partkey % 10 = 0",
    "part_cooc": "select x.l_partkey as a, y.l_partkey as b from lineitem x join lineitem y using (l_orderkey) where x.l_partkey < y.l_partkey",
    "order_part": "select l_orderkey * 4 as a, l_partkey * 4 + 1 as b from lineitem",
    "part_supp": "select l_partkey * 4 as a, l_suppkey * 4 + 1 as b from lineitem",
    "cust_part": "select o_custkey * 4 as a, l_partkey * 4 + 1 as b from orders join lineitem on o_orderkey = l_orderkey",
    "geo_tree": "select n_regionkey::bigint * 4 as a, n_nationkey::bigint * 4 + 1 as b from nation union all select c_nationkey::bigint * 4 + 1, c_custkey * 4 + 2 from customer union all select o_custkey * 4 + 2, o_orderkey * 4 + 3 from orders",
    "order_chain": "select * from (select o_orderkey as a, lead(o_orderkey) over (partition by o_custkey order by o_orderdate, o_orderkey) as b from orders) where b is not null union all select * from (select o_orderkey as a, lead(o_orderkey) over (partition by o_orderdate order by o_orderkey) as b from orders) where b is not null",
    "status_hub": "select o_orderkey * 4 as a, (dense_rank() over (order by encode(o_orderpriority)) - 1) * 4 + 1 as b from orders union all select a * 4, b * 4 from (select o_orderkey as a, lead(o_orderkey) over (partition by o_custkey order by o_orderdate, o_orderkey) as b from orders) where b is not null",
    "user_trans": "select * from (select user_id as a, lead(user_id) over (order by ts, event_id) as b from events) where b is not null and a <> b",
    "page_nav": "select page_id * 4 as a, (dense_rank() over (order by encode(name)) - 1) * 4 + 1 as b from (select distinct page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) as name from pages)",
    "page_host": "select page_id * 4 as a, (dense_rank() over (order by encode(regexp_extract(url, '^[a-z]+://([^/]+)', 1))) - 1) * 4 + 1 as b from pages",
    "doc_line": "with l as (select distinct doc_id, unnest(string_split(text, chr(10))) as line from documents), f as (select line, min(doc_id) as first from l where line <> '' group by line) select l.doc_id as a, f.first as b from l join f using (line)",
    "embed_knn": "with v as (select vec_id, list_transform(embedding, lambda x: x::double) as e from embeddings where embedding is not null), s as (select x.vec_id as a, y.vec_id as b, round(list_cosine_similarity(x.e, y.e), 12) as c from v x join v y on x.vec_id <> y.vec_id) select a, b from s qualify row_number() over (partition by a order by c desc, b) <= 10",
}


def edges(view: str) -> str:
    """CTEs p and edges(src, dst, w)."""
    return f"p as (select distinct least(a, b)::bigint as a, greatest(a, b)::bigint as b from ({PAIRS[view]}) where a <> b), edges as (select a as src, b as dst, 1::bigint as w from p union all select b, a, 1 from p)"


def graph(view: str) -> str:
    return f"with {edges(view)} select src, dst, w from edges"


def profile(view: str) -> str:
    return f"with {edges(view)}, d as (select src, count(*) as d from edges group by src) select count(*) as n, (sum(d) / 2)::bigint as m, max(d) as max_degree, max(d) / avg(d) as skew from d"


def base(view: str, vw: str = "sum(w)::bigint", num: str = "1", den: str | None = None) -> str:
    """edges, verts(id, vw) and lam(num, den); modularity unless told otherwise."""
    return f"{edges(view)}, verts as materialized (select src as id, {vw} as vw from edges group by src), lam as materialized (select {num}::bigint as num, {den or '(select sum(w) from edges)'}::bigint as den)"


def clusters(expr: str, name: str = "c") -> str:
    """A clustering by an expression of id, labelled by smallest members."""
    return f"{name} as materialized (select id, min(id) over (partition by {expr}) as cid from verts)"


def choose(p: str, c: str, e: str = "edges") -> str:
    """Frames of the best destination for clustering c: {p}t totals, {p}a affinity, {p}o own, {p}b best, {p}d destination."""
    h = hash_sql("a.id", "a.cid")
    return f"""{p}t as materialized (select cid, sum(vw)::bigint as t from {c} join verts using (id) group by cid),
{p}a as materialized (select e.dst as id, c.cid, sum(e.w)::bigint as k from {e} e join {c} c on c.id = e.src group by e.dst, c.cid),
{p}o as materialized (select v.id, v.vw, c.cid, t.t as tw, coalesce(a.k, 0) as k_own, lam.den * coalesce(a.k, 0) - lam.num * v.vw * (t.t - v.vw) as s_own from verts v join {c} c using (id) join {p}t t using (cid) left join {p}a a on a.id = v.id and a.cid = c.cid, lam),
{p}b as materialized (select a.id, a.cid as x, lam.den * a.k - lam.num * o.vw * t.t as s from {p}a a join {p}o o on o.id = a.id and o.cid <> a.cid join {p}t t on t.cid = a.cid, lam
  qualify row_number() over (partition by a.id order by lam.den * a.k - lam.num * o.vw * t.t desc, {h}, a.cid) = 1),
{p}d as materialized (select o.*, case when s_own < 0 and (s is null or s < 0) then null else x end as c_new, case when s_own < 0 and (s is null or s < 0) then 0 else s end as s_new from {p}o o left join {p}b b using (id))"""


def candidates(p: str, a: int, b: int) -> str:
    return f"{p}m as materialized (select id, cid as c_old, c_new, (s_new - s_own)::bigint as gain, vw from {p}d where s_new is not null and {b} * s_new >= {b - a} * s_own)"


def replay(p: str, e: str = "edges") -> str:
    hu, hv = hash_sql("u.id", "0"), hash_sql("v.id", "0")
    return f"""{p}h as materialized (select u.*, {hu} as h from {p}m u),
{p}x as (select v.id, sum((lam.den * e.w - lam.num * u.vw * v.vw) * (
    case when u.c_old = v.c_old then 1 when u.c_old = v.c_new then -1 else 0 end + case when u.c_new = v.c_old then -1 when u.c_new = v.c_new then 1 else 0 end)) as change
  from {e} e join {p}h u on u.id = e.src join {p}h v on v.id = e.dst, lam
  where 10 * (u.gain - v.gain) >= lam.den or (10 * (u.gain - v.gain) > -lam.den and (u.h < v.h or (u.h = v.h and u.id < v.id))) group by v.id),
{p}f as materialized (select m.* from {p}m m left join {p}x x using (id) where m.gain + coalesce(x.change, 0) >= 0)"""


def applied(p: str, c: str, out: str, moves: str) -> str:
    return f"{p}r as (select c.id, case when f.id is null then c.cid else coalesce(f.c_new, -1 - c.id) end as raw from {c} c left join {moves} f using (id)), {out} as materialized (select id, min(id) over (partition by raw) as cid from {p}r)"


def one_pass(p: str, c: str, out: str, a: int, b: int) -> str:
    return f"{choose(p, c)}, {candidates(p, a, b)}, {replay(p)}, {applied(p, c, out, p + 'f')}"


def objective(p: str) -> str:
    return f"(select sum(lam.den * k_own - lam.num * vw * (tw - vw))::bigint from {p}d, lam)"


def passes(view: str, schedule) -> str:
    """The best of the states before and after each pass."""
    parts = [base(view), clusters("id", "c0")]
    for i, (a, b) in enumerate(schedule):
        parts.append(one_pass(f"p{i}", f"c{i}", f"c{i + 1}", a, b))
    n = len(schedule)
    parts.append(choose(f"p{n}", f"c{n}"))
    score = " union all ".join(f"select {i} as i, {objective(f'p{i}')} as v" for i in range(n + 1))
    every = " union all ".join(f"select {i} as i, id, cid from c{i}" for i in range(n + 1))
    return f"with {', '.join(parts)}, score as ({score}), best as (select i from score order by v desc, i limit 1) select id, cid from ({every}) join best using (i)"


def batch_passes(view: str, phi, n: int, batch: str, batches: int, replayed: bool = False, prune: bool = False) -> str:
    """n passes at one temperature, each in batches (an expression over verts); with prune only beside the movers of the pass before."""
    a, b = phi
    parts = [base(view), clusters("id", "c0_0"), f"bt as materialized (select id, {batch} as batch from verts)"]
    for i in range(n):
        movers = []
        for k in range(batches):
            p, c = f"p{i}_{k}", f"c{i}_{k}"
            nxt = f"c{i}_{k + 1}" if k + 1 < batches else f"c{i + 1}_0"
            open_ = f" and id in (select id from act{i})" if prune and i else ""
            parts.append(choose(p, c))
            parts.append(f"{p}m as materialized (select id, cid as c_old, c_new, (s_new - s_own)::bigint as gain, vw from {p}d where s_new is not null and {b} * s_new >= {b - a} * s_own and id in (select id from bt where batch = {k}){open_})")
            parts.append(replay(p) if replayed else f"{p}f as materialized (select * from {p}m where gain > 0)")
            parts.append(applied(p, c, nxt, f"{p}f"))
            movers.append(f"select id from {p}f")
        if prune:
            gone = " union ".join(movers)
            parts.append(f"mv{i} as materialized ({gone}), act{i + 1} as materialized (select id from mv{i} union select e.dst from edges e join mv{i} m on m.id = e.src)")
    parts.append(choose(f"p{n}_0", f"c{n}_0"))
    score = " union all ".join(f"select {i} as i, {objective(f'p{i}_0')} as v" for i in range(n + 1))
    every = " union all ".join(f"select {i} as i, id, cid from c{i}_0" for i in range(n + 1))
    return f"with {', '.join(parts)}, score as ({score}), best as (select i from score order by v desc, i limit 1) select id, cid from ({every}) join best using (i)"


#: Every proper subset of the clusters of 2 to 6 members: mem has a row for each member and subset, wts the weights.
SUBSETS = """m as (select c.cid, c.id, v.vw, row_number() over (partition by c.cid order by c.id) - 1 as i, count(*) over (partition by c.cid) as n from c join verts v using (id)),
masks as (select cid, unnest(range(1, (1 << n) - 1)) as mask from (select distinct cid, n from m where n between 2 and 6)),
mem as materialized (select cid, mask, id, vw, (mask >> i) & 1 as x from masks join m using (cid)),
wts as (select cid, mask, sum(case when x = 1 then vw else 0 end) as wx, sum(vw) as w from mem group by cid, mask)"""


def step(view: str, select: str, *ctes: str) -> str:
    return f"with {', '.join([base(view), *ctes])} {select}"
