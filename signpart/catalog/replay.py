"""SQL that replays the greedy edge by edge, for checking against another engine."""

from __future__ import annotations


def replay(edges: str, exclusions: str = "[]::bigint[]") -> str:
    """Common table expressions up to ``last`` (g, lab), ``named`` (g, x, i), ``eo`` and ``run``.

    ``edges`` is a query of (g, u, v, w).  The state of a graph is a list of labels
    and a list of excluded pairs; one step takes the next edge of every graph.
    """
    moved = "case when {0} = hi then lo else {0} end"
    a, b = moved.format("(p // 100000)"), moved.format("(p % 100000)")
    return f"""
with recursive e0 as ({edges}),
ends as (select g, u as x from e0 union select g, v from e0),
named as (select g, x, row_number() over (partition by g order by x) as i from ends),
eo as (
  select e0.g, a.i as iu, b.i as iv, e0.u, e0.v, e0.w, row_number() over (partition by e0.g order by abs(e0.w) desc, e0.u, e0.v) as k
  from e0 join named a on a.g = e0.g and a.x = e0.u join named b on b.g = e0.g and b.x = e0.v
), sized as (select g, count(*) as n from named group by g),
run(g, k, lab, ex, d) as (
  select g, 0::bigint, range(1, n + 1), {exclusions}, '' from sized
  union all
  select g, k,
    case when d = 'merge' then list_transform(lab, lambda x: case when x = hi then lo else x end) else lab end,
    case when d = 'merge' then list_distinct(list_transform(ex, lambda p: least({a}, {b}) * 100000 + greatest({a}, {b})))
         when d = 'exclude' then list_append(ex, lo * 100000 + hi) else ex end,
    d
  from (
    select *, case when w > 0 then case when lo = hi then 'joined' when list_contains(ex, lo * 100000 + hi) then 'blocked' else 'merge' end
                   else case when lo = hi then 'ignored' when list_contains(ex, lo * 100000 + hi) then 'repeat' else 'exclude' end end as d
    from (select r.g, e.k, e.w, r.lab, r.ex, least(r.lab[e.iu], r.lab[e.iv]) as lo, greatest(r.lab[e.iu], r.lab[e.iv]) as hi
          from run r join eo e on e.g = r.g and e.k = r.k + 1)
  )
),
last as (select g, lab, ex, k from run qualify row_number() over (partition by g order by k desc) = 1),
labels as (
  select n.g, n.x as v, m.x as cluster from last l join named n on n.g = l.g join named m on m.g = l.g and m.i = l.lab[n.i]
)
"""


def reach(links: str, vertices: str) -> str:
    """CTEs up to ``labels`` (v, cluster): components of small graphs, by walking; links is a query of (u, v)."""
    return f"""
with recursive l0 as ({links}),
ways as (select u as a, v as b from l0 union select v, u from l0),
walk(v, o) as (select v, v from ({vertices}) union select walk.v, ways.b from walk join ways on walk.o = ways.a),
labels as (select v, min(o) as cluster from walk group by v)
"""


def contraction(edges: str, by_size: bool = False) -> str:
    """CTEs up to ``labels`` (v, cluster): additive contraction of one small graph, one merge (or cannot-link) a step.

    ``edges`` is a query of (u, v, w).  Each step adds up the costs between the
    clusters anew and takes the largest positive sum; with ``by_size`` the largest
    absolute sum among pairs that aren't kept apart, and a negative one keeps its
    pair apart.
    """
    moved = "case when {0} = hi then lo else {0} end"
    a, b = moved.format("(p // 100000)"), moved.format("(p % 100000)")
    rank, wanted = ("abs(c)", "c <> 0 and not list_contains(ex, lo * 100000 + hi)") if by_size else ("c", "c > 0")
    return f"""
with recursive e0 as materialized ({edges}),
named as materialized (select x, row_number() over (order by x) as i from (select u as x from e0 union select v from e0)),
eo as materialized (select a.i as iu, b.i as iv, e0.w from e0 join named a on a.x = e0.u join named b on b.x = e0.v),
run(k, lab, ex) as (
  select 0::bigint, range(1, (select count(*) from named) + 1), []::bigint[]
  union all
  select k + 1,
    case when c > 0 then list_transform(lab, lambda x: case when x = hi then lo else x end) else lab end,
    case when c > 0 then list_distinct(list_transform(ex, lambda p: least({a}, {b}) * 100000 + greatest({a}, {b}))) else list_append(ex, lo * 100000 + hi) end
  from (
    select * from (
      select k, lab, ex, lo, hi, sum(w) as c
      from (select r.k, r.lab, r.ex, e.w, least(r.lab[e.iu], r.lab[e.iv]) as lo, greatest(r.lab[e.iu], r.lab[e.iv]) as hi from run r, eo e)
      where lo <> hi group by k, lab, ex, lo, hi
    ) where {wanted} qualify row_number() over (order by {rank} desc, lo, hi) = 1
  )
),
labels as (
  select n.x as v, m.x as cluster from (select lab from run order by k desc limit 1) l, named n join named m on m.i = l.lab[n.i]
)
"""


#: Labelings of up to nine vertices named 0 … n-1 by rank: CTEs ``place`` (v, i) and ``cand`` (cand, lab).
def labelings(vertices: str) -> str:
    return f"""
with recursive place as (select v, row_number() over (order by v) as i from ({vertices})),
grown(n, lab, top) as (
  select 0::bigint, []::bigint[], -1::bigint
  union all
  select n + 1, list_append(lab, c), greatest(top, c)
  from (select n, lab, top, unnest(range(0, top + 2)) as c from grown where n < (select count(*) from place))
),
cand as (select array_to_string(lab, ',') as cand, lab from grown where n = (select count(*) from place))
"""
