"""DuckDB SQL for the tree queries: Prim by recursion, chains for one axis, and pieces."""

from __future__ import annotations


def prim_cte(points: str, d: int, k_pts: int = 1, measure=None) -> str:
    """CTEs that end in tree(lo, hi, w, d2): every step joins the point of least key (w, d2, lo, hi). measure(a, b): a metric's
    square, if not Euclid's."""
    xs = [f"x{i}" for i in range(d)]
    gap = lambda a, b: " + ".join(f"({a}.{x} - {b}.{x}) * ({a}.{x} - {b}.{x})" for x in xs)
    core = (
        "core as (select pid, 0 as c from pts)" if k_pts == 1 else
        f"core as (select pid, d2 as c from (select a.pid, {gap('a', 'b')} as d2, row_number() over (partition by a.pid order by {gap('a', 'b')}, b.pid) as r from pts a, pts b) where r = {k_pts})"
    )
    cols = ", ".join(xs)
    far = measure or gap
    new = f"(greatest(g.c, n.c, {far('g', 'n')}), {gap('g', 'n')}, least(g.pid, n.pid), greatest(g.pid, n.pid))"
    return f"""pts as ({points}), {core},
 base as (select pts.pid, {cols}, core.c from pts join core using (pid)),
 root as (select * from base order by pid limit 1),
 grow as (
  select b.pid, {', '.join('b.' + x for x in xs)}, b.c, false as done, greatest(b.c, r.c, {far('b', 'r')}) as w, {gap('b', 'r')} as d2, least(b.pid, r.pid) as lo, greatest(b.pid, r.pid) as hi from base b, root r where b.pid <> r.pid
  union all
  select pid, {cols}, c, pid = np, case when keep then w else nw end, case when keep then d2 else nd end, case when keep then lo else nlo end, case when keep then hi else nhi end
  from (select g.*, n.pid as np, greatest(g.c, n.c, {far('g', 'n')}) as nw, {gap('g', 'n')} as nd, least(g.pid, n.pid) as nlo, greatest(g.pid, n.pid) as nhi, g.pid = n.pid or (g.w, g.d2, g.lo, g.hi) <= {new} as keep
    from grow g, (select * from grow where not done order by w, d2, lo, hi limit 1) n where not g.done)
 ),
 tree as (select lo, hi, w, d2 from grow where done)"""


def tree_sql(points: str, d: int, k_pts: int = 1, measure=None) -> str:
    return f"with recursive {prim_cte(points, d, k_pts, measure)} select cast(lo as bigint) as lo, cast(hi as bigint) as hi, cast(d2 as bigint) as d2, sqrt(cast(w as double)) as length from tree"


def over_tree(points: str, d: int, body: str) -> str:
    return f"with recursive {prim_cte(points, d)} {body}"


def chain_sql(points: str) -> str:
    """Tree of points on one axis: copies hang on their smallest pid, and distinct places form a chain."""
    return f"""with pts as ({points}), s as (select x0, min(pid) as pid from pts group by x0),
 e as (select pid as a, lead(pid) over (order by x0) as b, lead(x0) over (order by x0) - x0 as g from s)
 select cast(least(a, b) as bigint) as lo, cast(greatest(a, b) as bigint) as hi, cast(g * g as bigint) as d2, cast(g as double) as length from e where b is not null
 union all select cast(s.pid as bigint), cast(p.pid as bigint), cast(0 as bigint), cast(0 as double) from pts p join s using (x0) where p.pid > s.pid"""


def morton_sql(xs: list[str], bits: int) -> str:
    """The code bit by bit."""
    d = len(xs)
    return "(" + " | ".join(f"((({x} >> {b}) & 1) << {d * b + i})" for b in range(bits) for i, x in enumerate(xs)) + ")"


def grouped_tree_cte(points: str, group: str, d: int) -> str:
    """CTEs that end in gtree(g, lo, hi, d2): the tree of each group's points, all grown at once, a point
    of each group at a step. points has the columns ``group``, pid and x0..; places are distinct in a group or
    ties of the key settle them."""
    xs = [f"x{i}" for i in range(d)]
    cols = ", ".join(xs)
    gap = lambda a, b: " + ".join(f"({a}.{x} - {b}.{x}) * ({a}.{x} - {b}.{x})" for x in xs)
    new = f"({gap('g', 'n')}, least(g.pid, n.pid), greatest(g.pid, n.pid))"
    return f"""gp as ({points}), gfirst as (select {group} as g, min(pid) as pid from gp group by 1),
 ggrow as (
  select 0 as step, p.{group} as g, p.pid, {', '.join('p.' + x for x in xs)}, p.pid = r.pid as joined, {gap('p', 'r')} as d2, least(p.pid, r.pid) as lo, greatest(p.pid, r.pid) as hi
  from gp p join gfirst f on f.g = p.{group} join gp r on r.{group} = f.g and r.pid = f.pid
  union all
  select g.step + 1, g.g, g.pid, {', '.join('g.' + x for x in xs)}, g.joined or g.pid = n.pid,
   case when g.joined or g.pid = n.pid or (g.d2, g.lo, g.hi) <= {new} then g.d2 else {gap('g', 'n')} end,
   case when g.joined or g.pid = n.pid or (g.d2, g.lo, g.hi) <= {new} then g.lo else least(g.pid, n.pid) end,
   case when g.joined or g.pid = n.pid or (g.d2, g.lo, g.hi) <= {new} then g.hi else greatest(g.pid, n.pid) end
  from ggrow g join (select * from (select *, row_number() over (partition by g order by d2, lo, hi) as place from ggrow where not joined) where place = 1) n on g.g = n.g
 ),
 gtree as (select distinct g.g, lo, hi, d2 from ggrow g join (select g, max(step) as step from ggrow group by g) m using (g, step) where pid not in (select pid from gfirst f where f.g = g.g))"""


def lattice_sql(points: str, d: int) -> str:
    """Tree of points of which many share a place: the tree of the places' smallest pids, and the copies
    tied to these."""
    xs = [f"x{i}" for i in range(d)]
    cols, same = ", ".join(xs), " and ".join(f"p.{x} = s.{x}" for x in xs)
    sites = f"select min(pid) as pid, {cols} from ({points}) group by {cols}"
    return f"""with recursive {prim_cte(sites, d)}, every as ({points})
 select cast(lo as bigint) as lo, cast(hi as bigint) as hi, cast(d2 as bigint) as d2, sqrt(cast(w as double)) as length from tree
 union all select cast(s.pid as bigint), cast(p.pid as bigint), cast(0 as bigint), cast(0 as double) from every p join pts s on {same} where p.pid > s.pid"""


def real_tree_sql(table: str, pid: str, vector: str, digits: int) -> str:
    """Tree of vectors of doubles, its lengths rounded."""
    gap = lambda a, b: f"list_sum(list_transform(list_zip({a}.v, {b}.v), lambda z: (z[1] - z[2]) * (z[1] - z[2])))"
    return f"""with recursive base as (select {pid} as pid, list_transform({vector}, lambda x: cast(x as double)) as v from {table}),
 dist as materialized (select a.pid as p, b.pid as q, {gap('a', 'b')} as d2 from base a, base b where a.pid <> b.pid),
 first as (select min(pid) as pid from base),
 grow as (
  select 0 as step, q as pid, false as joined, d2, least(p, q) as lo, greatest(p, q) as hi from dist, first where p = first.pid
  union all
  select g.step + 1, g.pid, g.joined or g.pid = n.pid, case when g.joined or d.d2 is null or g.d2 <= d.d2 then g.d2 else d.d2 end,
   case when g.joined or d.d2 is null or g.d2 <= d.d2 then g.lo else least(g.pid, n.pid) end, case when g.joined or d.d2 is null or g.d2 <= d.d2 then g.hi else greatest(g.pid, n.pid) end
  from grow g, (select pid from grow where not joined order by d2, lo, hi limit 1) n left join dist d on d.p = n.pid and d.q = g.pid
 )
 select lo, hi, round(sqrt(d2), {digits}) as length from grow where step = (select max(step) from grow)"""
