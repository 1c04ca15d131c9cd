"""SQL (DuckDB) of graph databases, supports and the lattice, of which the oracles of the queries are made."""

from __future__ import annotations

from latticewalk.sources import builders


def case(column: str, names: tuple[str, ...]) -> str:
    return f"list_position([{', '.join(repr(n) for n in names)}], {column}) - 1"


def values(keys) -> str:
    return ", ".join(f"('{k}')" for k in keys)


CLICK = f"""
e0 as (select user_id, ts, event_id, event_type, case when lag(ts) over w is null or ts - lag(ts) over w > interval 12 hours then 1 else 0 end as brk
       from events window w as (partition by user_id order by ts, event_id)),
e1 as (select *, sum(brk) over (partition by user_id order by ts, event_id rows unbounded preceding) as sess from e0),
e2 as (select (user_id * {builders.SESSIONS} + sess)::bigint as gid, row_number() over (partition by user_id, sess order by ts, event_id) - 1 as vid,
       count(*) over (partition by user_id, sess) as size, event_type from e1),
v as (select gid, vid::int as vid, ({case('event_type', builders.CLICK)})::int as label, event_type from e2 where size >= 2),
ed as (select gid, coalesce(last_value(case when event_type = 'view' then vid end ignore nulls)
       over (partition by gid order by vid rows between unbounded preceding and 1 preceding), 0)::int as src, vid as dst from v qualify vid > 0)"""

DENSE = f"""
l0 as (select l_orderkey, l_returnflag || l_linestatus as name, l_quantity, count(*) over (partition by l_orderkey) as size,
       row_number() over (partition by l_orderkey order by l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice, l_shipdate,
                          l_returnflag || l_linestatus) - 1 as vid from lineitem),
v as (select l_orderkey as gid, vid::int as vid, ({case('name', builders.DENSE)})::int as label, l_quantity as q from l0 where size >= 8),
ed as (select a.gid, a.vid as src, b.vid as dst from v a join v b on a.gid = b.gid and a.vid < b.vid and abs(a.q - b.q) <= 27)"""

PROFILE = f"""
o as (select o_custkey as gid, o_orderkey, o_orderdate, o_orderpriority, row_number() over w as vid, lag(o_orderdate) over w as before,
      count(*) over (partition by o_custkey) as n from orders window w as (partition by o_custkey order by o_orderdate, o_orderkey)),
l as (select o.gid, o.vid as src, l_returnflag, o.n + row_number() over (partition by o.gid order by o.vid, l_linenumber, l_partkey, l_suppkey,
      l_quantity, l_extendedprice, l_shipdate, l_returnflag) as vid from lineitem join o on l_orderkey = o_orderkey),
v as (select c_custkey as gid, 0::int as vid, ({case('c_mktsegment', builders.PROFILE)})::int as label from customer
      union all select gid, vid::int, ({case('o_orderpriority', builders.PROFILE)})::int from o
      union all select gid, vid::int, ({case('l_returnflag', builders.PROFILE)})::int from l),
ed as (select gid, 0::int as src, vid::int as dst from o union all select gid, src::int, vid::int from l
       union all select gid, (vid - 1)::int, vid::int from o where datediff('day', before, o_orderdate) <= 30)"""

EGO = f"""
x0 as (select vec_id, label, embedding::double[] as y from embeddings),
x1 as (select vec_id, label, list_transform(y, lambda a: a / sqrt(list_sum(list_transform(y, lambda b: b * b)))) as x from x0),
x2 as (select *, {' || '.join(f"(x[{i + 1}] > 0)::int::varchar" for i in range(builders.EGO_SIGNS))} as cell from x1),
x3 as (select *, row_number() over (partition by cell order by x[{builders.EGO_SIGNS + 1}], vec_id) as r from x2),
nb as (select a.vec_id as gid, a.label as own, b.vec_id, b.label, b.x, round(list_inner_product(a.x, b.x), 9) as c
       from x3 a join x3 b on a.cell = b.cell and a.vec_id <> b.vec_id and abs(a.r - b.r) <= {builders.EGO_REACH}),
nr as (select *, row_number() over (partition by gid order by c desc, vec_id) as vid from nb qualify vid <= 9),
v as (select vec_id as gid, 0::int as vid, label::int as label from x3 union all select gid, vid::int, label::int from nr),
ed as (select gid, 0::int as src, vid::int as dst from nr union all
       select a.gid, a.vid::int, b.vid::int from nr a join nr b on a.gid = b.gid and a.vid < b.vid
       where round(list_inner_product(a.x, b.x), 9) >= {builders.EGO_NEAR})"""

BASE = {"click": CLICK, "dense": DENSE, "profile": PROFILE, "ego": EGO}

HALF = """h as (select ed.gid, src as v, dst as w, a.label as lv, b.label as lw from ed join v a on a.gid = ed.gid and a.vid = src join v b on b.gid = ed.gid and b.vid = dst
union all select ed.gid, dst, src, b.label, a.label from ed join v a on a.gid = ed.gid and a.vid = src join v b on b.gid = ed.gid and b.vid = dst)"""

EDGE_KEYS = "ek as (select distinct gid, lv || ',' || lw || '|0-1' as pattern_key from h where lv <= lw)"


def path_key(c: str, p: str, q: str) -> str:
    """The key of a path with the middle c and ends p <= q: the middle stands after the ends with smaller labels."""
    return f"""case when {c} <= {p} then {c} || ',' || {p} || ',' || {q} || '|0-1,0-2' when {c} <= {q} then {p} || ',' || {c} || ',' || {q} || '|0-1,1-2'
else {p} || ',' || {q} || ',' || {c} || '|0-2,1-2' end"""


PATH_KEYS = f"""pk as (select distinct x.gid, {path_key('x.lv', 'x.lw', 'y.lw')} as pattern_key
from h x join h y on x.gid = y.gid and x.v = y.v and x.w <> y.w and x.lw <= y.lw)"""
TRIANGLE_KEYS = """tk as (select distinct a.gid, a.lv || ',' || a.lw || ',' || b.lw || '|0-1,0-2,1-2' as pattern_key
from h a join h b on a.gid = b.gid and a.w = b.v join h c on c.gid = b.gid and c.v = b.w and c.w = a.v where a.lv <= a.lw and a.lw <= b.lw)"""
MINED = "sup as (select pattern_key, count(*) as support from (select * from ek union all select * from pk) group by 1)"
MINED_3 = "sup as (select pattern_key, count(*) as support from (select * from ek union all select * from pk union all select * from tk) group by 1)"


def table(name: str) -> str:
    """v, ed, h and sup: the supports of all patterns of one or two edges."""
    return f"{BASE[name]},\n{HALF},\n{EDGE_KEYS},\n{PATH_KEYS},\n{MINED}"


def table_3(name: str) -> str:
    """The same with triangles."""
    return f"{BASE[name]},\n{HALF},\n{EDGE_KEYS},\n{PATH_KEYS},\n{TRIANGLE_KEYS},\n{MINED_3}"


#: The labels that occur in a database.
SEEN = "select distinct label from v where label is not null"


def space(labels: int | str) -> str:
    """se, sp, st: all edges, paths of two edges and triangles over so many labels, or those of a query, whether or not they occur."""
    return f"""l(l) as ({labels if isinstance(labels, str) else 'values ' + ', '.join(f'({i})' for i in range(labels))}),
se as (select a.l || ',' || b.l || '|0-1' as k, a.l as a, b.l as b from l a join l b on a.l <= b.l),
sp as (select {path_key('c.l', 'p.l', 'q.l')} as k, c.l as c, p.l as p, q.l as q from l c, l p join l q on p.l <= q.l),
st as (select a.l || ',' || b.l || ',' || c.l || '|0-1,0-2,1-2' as k, a.l as a, b.l as b, c.l as c from l a join l b on a.l <= b.l join l c on b.l <= c.l),
ep as (select distinct se.k as e, sp.k as p from sp join se on (se.a = least(c, p) and se.b = greatest(c, p)) or (se.a = least(c, q) and se.b = greatest(c, q))),
pt as (select sp.k as p, st.k as t from sp join st on list_sort([sp.c, sp.p, sp.q]) = [st.a, st.b, st.c])"""


#: pattern_key, near_key, kind: the lattice of patterns of up to three vertices and edges.
LATTICE = """lat as (select e as pattern_key, p as near_key, 'super_forward' as kind from ep union all select p, e, 'sub' from ep
union all select p, t, 'super_back' from pt union all select t, p, 'sub' from pt)"""
#: The same of up to two edges, where there are no triangles.
LATTICE_2 = "lat as (select e as pattern_key, p as near_key, 'super_forward' as kind from ep union all select p, e, 'sub' from ep)"
