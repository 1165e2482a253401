"""Plain SQL, by recursion, for the answers of a graph view: what the methods are held against."""

from __future__ import annotations

from .views import edge_sql, vertex_sql


def _with(name: str, edges: str | None = None, vertices: str | None = None) -> str:
    e, v = edges or edge_sql(name), vertices if vertices is not None else (vertex_sql(name) if not edges else None)
    every = "select a as vid from e union select b from e" + (f" union select vid from ({v})" if v else "")
    return f"""with recursive p as materialized ({e}),
e as materialized (select least(x, y) as a, greatest(x, y) as b, cast(count(*) as integer) as mult from p where x is not null and y is not null and x <> y group by 1, 2),
nodes as materialized ({every}),
s as materialized (select a as u, b as v from e union all select b, a from e),
comp(vid, c) using key (vid) as (
  select vid, vid from nodes
  union
  select s.v, min(comp.c) from comp join s on s.u = comp.vid join recurring.comp r on r.vid = s.v where comp.c < r.c group by s.v)"""


def components(name: str, **parts) -> str:
    return _with(name, **parts) + "\nselect cast(vid as bigint) as vid, cast(c as bigint) as comp from comp"


def _blocks(name: str, **parts) -> str:
    return _with(name, **parts) + """,
dep(vid, d) using key (vid) as (
  select vid, case when vid = c then 0 else 1000000000 end from comp
  union
  select s.v, min(dep.d) + 1 from dep join s on s.u = dep.vid join recurring.dep r on r.vid = s.v where dep.d + 1 < r.d group by s.v),
par as materialized (select s.v as vid, min(s.u) as up from s join dep x on x.vid = s.u join dep y on y.vid = s.v where x.d = y.d - 1 group by s.v),
anc(vid, above) as (select vid, vid from par union all select anc.vid, par.up from anc join par on par.vid = anc.above join par q on q.vid = par.up),
side as materialized (select e.a as x, e.b as y from e left join par pa on pa.vid = e.b and pa.up = e.a left join par pb on pb.vid = e.a and pb.up = e.b where pa.vid is null and pb.vid is null),
both_ways as materialized (select x, y from side union all select y, x from side),
rel as materialized (
  select x, y from side
  union
  select b.x, n.above from both_ways b join anc n on n.vid = b.x left join anc o on o.vid = b.y and o.above = n.above where o.vid is null and n.above <> b.x),
rs as materialized (select x as u, y as v from rel union select y, x from rel),
blk(vid, c) using key (vid) as (
  select vid, vid from par
  union
  select rs.v, min(blk.c) from blk join rs on rs.u = blk.vid join recurring.blk r on r.vid = rs.v where blk.c < r.c group by rs.v),
eb as materialized (
  select e.a, e.b, e.mult, blk.c as block
  from e join dep x on x.vid = e.a join dep y on y.vid = e.b join blk on blk.vid = case when y.d > x.d then e.b else e.a end),
named as materialized (select eb.*, first_value(a) over w as block_a, first_value(b) over w as block_b, count(*) over (partition by block) as n from eb window w as (partition by block order by a, b))"""


def blocks(name: str, **parts) -> str:
    return _blocks(name, **parts) + "\nselect a, b, block_a, block_b from named"


def bridges(name: str, **parts) -> str:
    return _blocks(name, **parts) + "\nselect a, b from named where n = 1 and mult = 1"


def articulation(name: str, **parts) -> str:
    return _blocks(name, **parts) + "\nselect vid from (select a as vid, block from eb union select b, block from eb) group by vid having count(*) > 1"


def two_edge(name: str, **parts) -> str:
    """Bridges in a query of their own: a recursion that follows others in one list is much slower."""
    e, v = parts.get("edges") or edge_sql(name), parts.get("vertices") or (vertex_sql(name) if not parts.get("edges") else None)
    every = "select a as vid from e union select b from e" + (f" union select vid from ({v})" if v else "")
    return f"""with recursive cut as materialized (select * from ({bridges(name, **parts)})),
e as materialized (select distinct least(x, y) as a, greatest(x, y) as b from ({e}) where x is not null and y is not null and x <> y),
kept as materialized (select e.a, e.b from e left join cut on cut.a = e.a and cut.b = e.b where cut.a is null),
nodes as materialized ({every}),
t as materialized (select a as u, b as v from kept union all select b, a from kept),
te(vid, c) using key (vid) as (
  select vid, vid from nodes
  union
  select t.v, min(te.c) from te join t on t.u = te.vid join recurring.te r on r.vid = t.v where te.c < r.c group by t.v)
select cast(vid as bigint) as vid, cast(c as bigint) as comp from te"""
