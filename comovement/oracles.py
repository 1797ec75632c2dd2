"""SQL of the registered queries for DuckDB, written from the definitions."""

from __future__ import annotations

from .params import HOUR, SET_A, SET_B, SET_C, JoinParams

_EVENTS = "select user_id as traj, epoch_us(ts) as t, value as x, cast(json_extract_string(props, '$.k') as double) as y, event_id as pid, event_type from events"
_COMPANIONS = (
    "select traj, t, x, y, pid from ev union all select traj + 1000000, t + 60000000 * (pid % 5), x + pid % 3 + case when pid % 6 = 0 then 1000000.0 else 0.0 end, y, pid + 10000000 from ev where traj % 5 = 0"
)
_NUMBERED = "select *, row_number() over (partition by traj order by t, pid) as seq, lead(t) over (partition by traj order by t, pid) as next_t, lead(x) over (partition by traj order by t, pid) as next_x, lead(y) over (partition by traj order by t, pid) as next_y"


def base(companions: bool = False, where: str = "true") -> str:
    """with-list: ev (points), pts (numbered points)."""
    return f"ev as ({_EVENTS}), src as ({_COMPANIONS if companions else 'select traj, t, x, y, pid from ev'}), pts as ({_NUMBERED} from src where {where})"


def pairs(p: JoinParams, where: str = "a.traj <> b.traj", left: str = "pts", right: str = "pts", space: str | None = None) -> str:
    near = space or f"(a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) <= {p.eps_sp**2!r}"
    return f"select a.traj as r_traj, a.seq as r_seq, a.t as r_t, b.traj as s_traj, b.seq as s_seq, b.t as s_t from {left} a join {right} b on b.t between a.t - {p.eps_t_us} and a.t + {p.eps_t_us} and {near} and {where}"


def matches(p: JoinParams, jp: str = "jp", pts: str = "pts") -> str:
    """with-list up to ``m``: maximal matches by enumerating pieces of runs and testing the definitions."""

    def pieces(side: str) -> str:
        return f"""{side}_pos as (select distinct r_traj, s_traj, {side}_seq as q from {jp}),
{side}_run as (select *, q - row_number() over (partition by r_traj, s_traj order by q) as g from {side}_pos),
{side}_piece as (select a.r_traj, a.s_traj, a.q as f, b.q as l, pa.t as tf, pb.t as tl from {side}_run a join {side}_run b
  on a.r_traj = b.r_traj and a.s_traj = b.s_traj and a.g = b.g and a.q + {p.min_points - 1} <= b.q
  join {pts} pa on pa.traj = a.{side}_traj and pa.seq = a.q join {pts} pb on pb.traj = a.{side}_traj and pb.seq = b.q)"""

    return f"""{pieces('r')}, {pieces('s')},
duo as (select x.r_traj, x.s_traj, x.f as rf, x.l as rl, x.tf as rtf, x.tl as rtl, y.f as sf, y.l as sl, y.tf as stf, y.tl as stl
  from r_piece x join s_piece y on x.r_traj = y.r_traj and x.s_traj = y.s_traj where least(x.tl, y.tl) - greatest(x.tf, y.tf) >= {p.lifespan_floor_us}),
ok as (select d.r_traj, d.s_traj, rf, rl, sf, sl, any_value(rtf) rtf, any_value(rtl) rtl, any_value(stf) stf, any_value(stl) stl from duo d join {jp} e
  on e.r_traj = d.r_traj and e.s_traj = d.s_traj and e.r_seq between rf and rl and e.s_seq between sf and sl group by 1, 2, 3, 4, 5, 6
  having count(distinct e.r_seq) = rl - rf + 1 and count(distinct e.s_seq) = sl - sf + 1),
m as (select r_traj, rf as r_from, rl as r_to, rtf as r_t_from, rtl as r_t_to, s_traj, sf as s_from, sl as s_to, stf as s_t_from, stl as s_t_to,
  least(rtl, stl) - greatest(rtf, stf) as lifespan_us, rl - rf + 1 as n_r, sl - sf + 1 as n_s from ok a where not exists (select 1 from ok b where b.r_traj = a.r_traj and b.s_traj = a.s_traj
  and b.rf <= a.rf and b.rl >= a.rl and b.sf <= a.sf and b.sl >= a.sl and (b.rf < a.rf or b.rl > a.rl or b.sf < a.sf or b.sl > a.sl)))"""


def match_query(p: JoinParams, companions: bool = True, tail: str = "select * from m", where: str = "true") -> str:
    return f"with {base(companions, where)}, jp as ({pairs(p, 'a.traj < b.traj')}), {matches(p)} {tail}"


def windowed(p: JoinParams, gate: str) -> str:
    """The windowed refine over directed pairs, by correlated ranges over the points of each run."""
    reach = p.inner_window_us
    test = f"max(r_t) - min(r_t) >= {p.delta_t_us}" if gate == "span" else f"least(max(r_t), max(s_t)) - greatest(min(r_t), min(s_t)) >= {p.lifespan_floor_us}"
    return f"""with {base(True)}, jp as ({pairs(p)}),
xs as (select *, s_seq - row_number() over (partition by r_traj, s_traj order by s_seq) as xr from (select distinct r_traj, s_traj, s_seq from jp)),
e as (select jp.*, xr from jp join xs using (r_traj, s_traj, s_seq)),
ps as (select *, r_seq - row_number() over (partition by r_traj, s_traj, xr order by r_seq) as pr from (select distinct r_traj, s_traj, xr, r_seq, r_t from e)),
g as (select e.*, pr from e join ps using (r_traj, s_traj, xr, r_seq)),
open as (select r_traj, s_traj, xr, pr, max(r_seq) as top from g group by 1, 2, 3, 4 having {test}),
p as (select distinct g.r_traj, g.s_traj, g.xr, g.pr, g.r_seq, g.r_t, n.t as after from g join open using (r_traj, s_traj, xr, pr) left join pts n on n.traj = g.r_traj and n.seq = open.top + 1),
win as (select a.r_traj, a.s_traj, a.xr, a.pr, a.r_seq as f, max(b.r_seq) as l from p a join p b using (r_traj, s_traj, xr, pr)
  where b.r_t between a.r_t and a.r_t + {reach} and (a.after is null or a.after > a.r_t + {reach}) group by 1, 2, 3, 4, 5),
hit as (select distinct p.r_traj, p.s_traj, p.xr, p.pr, p.r_seq from p join win using (r_traj, s_traj, xr, pr) where p.r_seq between win.f and win.l),
seg as (select *, r_seq - row_number() over (partition by r_traj, s_traj, xr, pr order by r_seq) as sg from hit),
m as (select r_traj, min(r_seq) as r_from, max(r_seq) as r_to, min(r_t) as r_t_from, max(r_t) as r_t_to, s_traj, min(s_seq) as s_from, max(s_seq) as s_to, min(s_t) as s_t_from, max(s_t) as s_t_to
  from g join seg using (r_traj, s_traj, xr, pr, r_seq) group by r_traj, s_traj, xr, pr, sg)
select *, least(r_t_to, s_t_to) - greatest(r_t_from, s_t_from) as lifespan_us, r_to - r_from + 1 as n_r, s_to - s_from + 1 as n_s from m where r_to > r_from and s_to > s_from"""


P10 = JoinParams(10.0, 2 * HOUR)
_BOUNDS = "span as (select min(t) as lo, max(t) as hi from src)"
_WIDTH = "((hi - lo + 16) // 16)"
_CELLS = """box as (select min(x) x0, max(x) x1, min(y) y0, max(y) y1, count(*) n from src),
fine as (select least(greatest(floor((x - x0) / ((x1 - x0) / 1024)), 0), 1023)::bigint as ix, least(greatest(floor((y - y0) / ((y1 - y0) / 1024)), 0), 1023)::bigint as iy from src, box),
lev as (select d, ix >> (10 - d) as ix, iy >> (10 - d) as iy, count(*) as k from fine, (select unnest(range(11)) as d) group by 1, 2, 3),
split as (select lev.* from lev, box where d < 10 and k > 0.03 * n),
kids as (select 0 as d, 0 as ix, 0 as iy union all select d + 1, 2 * ix + a, 2 * iy + b from split, (select unnest([0, 1]) as a), (select unnest([0, 1]) as b)),
leaf as (select k.d, k.ix, k.iy from kids k where not exists (select 1 from split s where s.d = k.d and s.ix = k.ix and s.iy = k.iy)
  and (k.d = 0 or exists (select 1 from split s where s.d = k.d - 1 and s.ix = k.ix // 2 and s.iy = k.iy // 2)))"""


def _touch(eps: float) -> str:
    """Leaves that the box of half-width eps meets, on the finest grid of the tree."""
    cell = lambda v, e, o: f"least(greatest(floor(({v} {e} - {o}0) / (({o}1 - {o}0) / (1 << dm))), 0), (1 << dm) - 1)::bigint"
    return f"""deep as (select max(d) as dm from leaf),
met as (select pid, l.d, l.ix, l.iy from src, box, deep, leaf l where (l.ix + 1) * (1 << (dm - l.d)) > {cell('x', f'- {eps!r}', 'x')} and l.ix * (1 << (dm - l.d)) <= {cell('x', f'+ {eps!r}', 'x')}
  and (l.iy + 1) * (1 << (dm - l.d)) > {cell('y', f'- {eps!r}', 'y')} and l.iy * (1 << (dm - l.d)) <= {cell('y', f'+ {eps!r}', 'y')})"""


def _jp(p: JoinParams = P10, companions: bool = False, where: str = "true") -> str:
    return f"with {base(companions, where)}, jp as ({pairs(p)})"


_LIVE = "live as (select distinct r_traj as traj, r_seq as seq from jp)"
_HIT = "hit as (select distinct r_traj, s_traj, s_seq from jp)"
_SWEEP_T = [60, 90, 120, 150, 180]
_SWEEP_SP = [1.5625, 3.125, 4.6875, 6.25, 7.8125, 10.0, 20.0]

ORACLES: dict[str, str] = {
    "points_events": f"with {base()} select traj, t, x, y, pid from src",
    "points_lineitem_dedup": "select l_suppkey::bigint as traj, epoch_us(l_shipdate) as t, min(l_quantity)::double as x, min(l_discount * 1000)::double as y, epoch_us(l_shipdate) as pid from lineitem group by l_suppkey, l_shipdate",
    "points_orders": "select o_custkey::bigint as traj, epoch_us(o_orderdate) as t, o_totalprice / 1000 as x, c_acctbal / 100 as y, o_orderkey::bigint as pid from orders join customer on o_custkey = c_custkey",
    "traj_sequence": f"with {base()} select traj, seq, t, pid, lag(t) over w as prev_t, next_t, lag(x) over w as prev_x, next_x from pts window w as (partition by traj order by t, pid)",
    "traj_summary": f"with {base()}, g as (select *, t - lag(t) over (partition by traj order by t, pid) as gap from src) select traj, count(*) as n, min(t) as t_min, max(t) as t_max, min(x) as x_min, max(x) as x_max, min(y) as y_min, max(y) as y_max, max(gap) as max_gap from g group by traj",
    "traj_gaps": f"{_jp()}, bp as (select traj, seq from pts except select r_traj, r_seq from jp), i as (select *, seq - row_number() over (partition by traj order by seq) as g from bp) select traj, min(seq) as seq_from, max(seq) as seq_to, count(*) as n from i group by traj, g",
    "traj_sessions": f"with {base()}, m as (select *, case when t - lag(t) over w > {24 * HOUR} then 1 else 0 end as b from src window w as (partition by traj order by t, pid)), s as (select *, sum(b) over (partition by traj order by t, pid) + 1 as trip from m) select traj, trip::bigint as trip, count(*) as n, min(t) as t_from, max(t) as t_to from s group by traj, trip",
    "lifespan_pairs": f"with {base()}, s as (select traj, min(t) lo, max(t) hi from pts group by 1) select a.traj as r_traj, b.traj as s_traj, least(a.hi, b.hi) - greatest(a.lo, b.lo) as lifespan_us from s a, s b where a.traj < b.traj and least(a.hi, b.hi) - greatest(a.lo, b.lo) >= {480 * HOUR}",
    "traj_nested": f"with {base()} select traj, count(*) as n, min(t) as first_t, max(t) as last_t from src group by traj",
    "traj_slice": f"with {base()} select traj, seq, t, pid from pts where seq between 3 and 7",
    "traj_clean": f"with {base()}, d as (select * from (select *, row_number() over (partition by traj, t order by pid) as k from src where x <= 300 and y >= 5) where k = 1) select traj, t, x, y, pid from (select *, count(*) over (partition by traj) as n from d) where n >= 40",
    "jp_naive": f"{_jp()} select * from jp",
    **{f"jp_{k}": f"{_jp()} select * from jp" for k in ("slab_nested", "basic", "prepart", "indexed", "grid", "grid_distinct", "sweep_kernel", "indexed_no_traj_index", "indexed_no_spatial_index", "prepart_shuffled", "indexed_shuffled", "grid_coarse")},
    "jp_two_relation": f"with {base()}, l as (select * from pts where traj % 2 = 0), r as (select * from pts where traj % 2 = 1) {pairs(P10, 'true', 'l', 'r')}",
    "jp_metric_manhattan": f"with {base()} {pairs(P10, space='abs(a.x - b.x) + abs(a.y - b.y) <= 10.0')}",
    "jp_metric_chebyshev": f"with {base()} {pairs(P10, space='greatest(abs(a.x - b.x), abs(a.y - b.y)) <= 10.0')}",
    "jp_embeddings": "select a.vec_id as r_id, b.vec_id as s_id from embeddings a join embeddings b on b.vec_id between a.vec_id - 25 and a.vec_id + 25 and a.label <> b.label and list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda z: (z[1]::double - z[2]::double) * (z[1]::double - z[2]::double))) <= 120.5",
    "jp_cross_slab": f"{_jp()}, {_BOUNDS} select jp.* from jp, span where (r_t - lo) // {_WIDTH} <> (s_t - lo) // {_WIDTH}",
    "jp_lineitem_narrow": f"with src as (select l_suppkey::bigint as traj, epoch_us(l_shipdate) as t, min(l_quantity)::double as x, min(l_discount * 1000)::double as y, epoch_us(l_shipdate) as pid from lineitem group by l_suppkey, l_shipdate), pts as ({_NUMBERED} from src) select r_traj, s_traj, count(*) as n_jp from ({pairs(JoinParams(3.0, 48 * HOUR))}) group by 1, 2",
    "bp_points": f"{_jp()} select traj, seq, t from pts where (traj, seq) not in (select r_traj, r_seq from jp)",
    "jp_bp_outer": f"{_jp()} select p.traj as r_traj, p.seq as r_seq, p.t as r_t, s_traj, s_seq, s_t, case when s_traj is null then 'BP' else 'JP' end as kind from pts p left join jp on r_traj = p.traj and r_seq = p.seq",
    "njp_counts": f"{_jp()}, {_LIVE}, every as (select count(*) as k from pts a, pts b where a.traj <> b.traj), l as (select count(*) as k from live a, live b where a.traj <> b.traj), j as (select count(*) as k from jp) select every.k as n_pairs, j.k as n_jp, l.k - j.k as n_njp, every.k - l.k as n_with_bp from every, l, j",
    "miss_effective": f"{_jp()}, {_LIVE}, {_HIT} select distinct h.r_traj, h.s_traj, l.seq as s_seq from hit h join live l on l.traj = h.s_traj and abs(l.seq - h.s_seq) = 1 where not exists (select 1 from hit k where k.r_traj = h.r_traj and k.s_traj = h.s_traj and k.s_seq = l.seq)",
    "miss_literal": f"""{_jp()}, {_LIVE}, sj as (select l.traj, l.seq, p.t from live l join pts p using (traj, seq)),
c as (select distinct r.traj as r_traj, r.seq as r_seq, s.traj as s_traj, s.seq as s_seq, r.t as rt, s.t as st from jp j join sj s on s.traj = j.s_traj and abs(s.seq - j.s_seq) = 1 join sj r on r.traj = j.r_traj and r.seq <> j.r_seq)
select r_traj, r_seq, s_traj, s_seq from c where not exists (select 1 from jp where jp.r_traj = c.r_traj and jp.r_seq = c.r_seq and jp.s_traj = c.s_traj and jp.s_seq = c.s_seq)
and not exists (select 1 from pts o where o.traj = c.r_traj and o.seq <> c.r_seq and abs(o.t - c.st) <= abs(c.rt - c.st))""",
    "miss_candidates": f"{_jp()}, {_HIT} select distinct j.r_traj, j.r_seq, j.s_traj, p.seq as s_seq from jp j join pts p on p.traj = j.s_traj and abs(p.seq - j.s_seq) = 1 where not exists (select 1 from hit h where h.r_traj = j.r_traj and h.s_traj = j.s_traj and h.s_seq = p.seq)",
    **{f"match_exact_{k}": match_query(SET_A) for k in ("basic", "prepart", "indexed", "materialized", "auto", "stored")},
    "match_exact_plain": match_query(SET_A, False),
    "match_rounds": match_query(SET_A),
    "match_udtf": f"with {base(True)}, jp as ({pairs(SET_A, 'a.traj < b.traj')}), {matches(JoinParams(SET_A.eps_sp, SET_A.eps_t_us, 0, min_points=2))} select r_traj, s_traj, r_from, r_to, s_from, s_to from m",
    "match_brute_force": match_query(SET_A),
    "match_binding": match_query(SET_B),
    "match_directed": match_query(SET_A, tail="select * from m union all select s_traj, s_from, s_to, s_t_from, s_t_to, r_traj, r_from, r_to, r_t_from, r_t_to, lifespan_us, n_s, n_r from m"),
    "match_two_relation": f"with {base(True)}, l as (select * from pts where traj < 1000000), r as (select * from pts where traj >= 1000000), jp as ({pairs(SET_A, 'true', 'l', 'r')}), {matches(SET_A)} select * from m",
    "match_windowed_span": windowed(SET_B, "span"),
    "match_windowed_lifespan": windowed(SET_B, "lifespan"),
    "match_grid_complete": windowed(SET_B, "lifespan"),
    "match_delta_zero_grid": match_query(SET_C),
    "match_whole": f"""with {base(True)}, jp as ({pairs(SET_A, 'a.traj < b.traj')}), n as (select traj, count(*) as k, min(t) as lo, max(t) as hi from pts group by 1),
c as (select r_traj, s_traj, count(distinct r_seq) as cr, count(distinct s_seq) as cs from jp group by 1, 2)
select r_traj, 1::bigint as r_from, a.k as r_to, a.lo as r_t_from, a.hi as r_t_to, s_traj, 1::bigint as s_from, b.k as s_to, b.lo as s_t_from, b.hi as s_t_to, least(a.hi, b.hi) - greatest(a.lo, b.lo) as lifespan_us, a.k as n_r, b.k as n_s
from c join n a on a.traj = r_traj join n b on b.traj = s_traj where cr = a.k and cs = b.k and a.k > 1 and b.k > 1 and least(a.hi, b.hi) - greatest(a.lo, b.lo) >= {SET_A.lifespan_floor_us}""".replace("case when pid % 6 = 0 then 1000000.0 else 0.0 end", "0.0"),
    "match_fixed_duration": f"""with {base(True)}, jp as ({pairs(SET_A)}),
xs as (select *, s_seq - row_number() over (partition by r_traj, s_traj order by s_seq) as xr from (select distinct r_traj, s_traj, s_seq from jp)),
ps as (select *, r_seq - row_number() over (partition by r_traj, s_traj, xr order by r_seq) as pr from (select distinct r_traj, s_traj, xr, r_seq, r_t from jp join xs using (r_traj, s_traj, s_seq))),
w as (select a.r_traj, a.s_traj, a.r_seq as r_from, max(b.r_seq) filter (b.r_t <= a.r_t + {SET_A.delta_t_us}) as r_to, max(b.r_t) as last, any_value(a.r_t) as t0 from ps a join ps b using (r_traj, s_traj, xr, pr) where b.r_t >= a.r_t group by a.r_traj, a.s_traj, a.xr, a.pr, a.r_seq)
select distinct r_traj, s_traj, r_from, r_to from w where last >= t0 + {SET_A.delta_t_us} and r_to > r_from
and not exists (select 1 from pts o where o.traj = r_traj and o.seq > r_to and o.t <= t0 + {SET_A.delta_t_us})""",
    "match_jp_only_errors": f"""with {base(True)}, jp as ({pairs(SET_B, 'a.traj < b.traj')}), {matches(SET_B)},
j as (select *, r_seq - dense_rank() over (partition by r_traj, s_traj order by r_seq) as g from jp),
q as (select r_traj, s_traj, min(r_seq) a, max(r_seq) b, min(s_seq) c, max(s_seq) d, least(max(r_t), max(s_t)) - greatest(min(r_t), min(s_t)) as life from j group by r_traj, s_traj, g),
z as (select r_traj, s_traj, a, b, c, d from q where b > a and d > c and life >= {SET_B.lifespan_floor_us}), x as (select r_traj, s_traj, r_from, r_to, s_from, s_to from m)
select (select count(*) from (from z except from x)) as only_left, (select count(*) from (from x except from z)) as only_right, (select count(*) from (from z intersect from x)) as both, 0::bigint as repeated_left""",
    "compare_methods": f"{_jp()} select 0::bigint as only_left, 0::bigint as only_right, count(*) as both, 0::bigint as repeated_left from jp",
    "check_matching": match_query(SET_A, tail="select count(*) as n, count(*) as n_matching, count(*) as n_maximal from m"),
    "quad_cells": f"with {base()}, {_CELLS} select d::bigint as depth, ix::bigint as ix, iy::bigint as iy from leaf",
    "quad_home_counts": f"with {base()}, {_CELLS} select l.d::bigint as depth, l.ix::bigint as ix, l.iy::bigint as iy, count(f.ix) as n from leaf l left join fine f on f.ix >> (10 - l.d) = l.ix and f.iy >> (10 - l.d) = l.iy group by 1, 2, 3",
    "quad_replication": f"with {base()}, {_CELLS}, {_touch(4.6875)}, c as (select pid, count(*) as k from met group by 1) select count(*) as n_points, sum(k)::bigint as n_rows, max(k) as most_cells from c",
    "slab_uniform_sizes": f"with {base()}, {_BOUNDS}, k as (select unnest(range(16)) as slab) select slab::int as slab, count(t) filter ((t - lo) // {_WIDTH} = slab) as n, count(t) filter ((t - {2 * HOUR} < lo + (slab + 1) * {_WIDTH} or slab = 15) and (t + {2 * HOUR} >= lo + slab * {_WIDTH} or slab = 0)) as n_expanded from src, span, k group by slab",
    "slab_equidepth_sizes": f"with {base()}, r as (select t, rank() over (order by t) - 1 as k, count(*) over () as n from src) select (k * 16 // n)::int as slab, count(*) as n, min(t) as t_from, max(t) as t_to from r group by 1",
    "slab_balance": f"with {base()}, {_BOUNDS}, s as (select (t - lo) // {_WIDTH} as k, count(*) as n from src, span group by 1), a as (select coalesce(n, 0) as n from (select unnest(range(16)) as k) left join s using (k)) select round(stddev_pop(n), 6) as sigma, round(avg(n), 6) as mean, min(n) as least, max(n) as most from a",
    "slab_replication": f"with {base()}, {_BOUNDS}, e as (select least(15, (t + {2 * HOUR} - lo) // {_WIDTH}) - greatest(0, case when t - {2 * HOUR} < lo then 0 else (t - {2 * HOUR} - lo) // {_WIDTH} end) + 1 as k from src, span) select count(*) as n, sum(k)::bigint as n_expanded, round(sum(k) / count(*), 6) as factor from e",
    "slab_plan": f"""with {base()}, n as (select 48 * count(*) as total from pts), c(block, nodes) as (values (134217728, 48), (1048576, 4), (65536, 48)),
m as (select *, greatest(1, (total + block - 1) // block) as slabs from n, c)
select total::bigint as total_bytes, block::bigint as block_bytes, nodes::bigint as nodes, slabs::bigint as slabs, ((slabs + nodes - 1) // nodes)::bigint as per_node from m""",
    "cost_candidates": f"with {base()}, c as (select count(*) as candidates, count(*) filter ((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) <= 100.0) as n_jp from pts a join pts b on b.t between a.t - {2 * HOUR} and a.t + {2 * HOUR} and a.traj <> b.traj), n as (select count(*) as n from pts) select n, candidates, n_jp, round(candidates / (n * n), 9) as a, round(n_jp / candidates, 9) as b from c, n",
    "cost_intermediate": f"{_jp()}, {_HIT}, b as (select count(*) as k from pts where (traj, seq) not in (select r_traj, r_seq from jp)), q as (select count(*) as k from (select distinct j.r_traj, j.r_seq, j.s_traj, p.seq from jp j join pts p on p.traj = j.s_traj and abs(p.seq - j.s_seq) = 1 anti join hit h on h.r_traj = j.r_traj and h.s_traj = j.s_traj and h.s_seq = p.seq)), i as (select count(*) as k from pts), j as (select count(*) as k from jp) select i.k as n_in, j.k as n_jp, b.k as n_bp, q.k as n_miss, round((j.k + b.k + q.k) / i.k, 6) as ratio from i, j, b, q",
    "cost_index_size": f"""with {base()}, {_CELLS}, {_touch(4.6875)}, c as (select (select count(*) from met) as s, (select count(*) from src) as t, (select count(*) from leaf) as l)
select s as spatial_rows, t as trajectory_rows, 12 * s + 48 * l as spatial_bytes, 16 * t as trajectory_bytes, round((12 * s + 48 * l + 16 * t) / (48 * t), 6) as ratio from c""",
    "cost_model": f"""with {base()}, {_CELLS}, {_touch(SET_A.eps_sp)}, q as (select count(*) as candidates, count(*) filter ((a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) <= {SET_A.eps_sp**2}) as n_jp
  from pts a join pts b on b.t between a.t - {SET_A.eps_t_us} and a.t + {SET_A.eps_t_us} and a.traj <> b.traj),
rk as (select traj, rank() over (order by t) as r from src), ends as (select traj, max(r) - min(r) as steps, count(*) - 1 as k from rk group by 1),
bk as (select sum(steps) / sum(k) as back, count(*) as m from ends),
wn as (select avg(sw) as sw, avg(dt) as dt from (select count(*) over (partition by traj order by t range between current row and {SET_A.delta_t_us} following) as sw, count(*) over (partition by traj order by t range between current row and {SET_A.inner_window_us} following) as dt from src)),
hm as (select l.d, l.ix, l.iy, count(*)::double as own from leaf l join fine f on f.ix >> (10 - l.d) = l.ix and f.iy >> (10 - l.d) = l.iy group by 1, 2, 3), nr as (select d, ix, iy, count(*)::double as p from met group by 1, 2, 3),
o as (select n::double as n, n_jp, candidates / (n * n) as a, n_jp / candidates as b, back, m, n / m as t, sw, dt from box, q, bk, wn),
ix as (select sum(own * dm * log2(p) * a * p * ((1 - b) * p + 2 * b * p * (2 * log2(t) + a * t))) as ops from hm join nr using (d, ix, iy), o, deep)
select n::bigint as n, (select count(*) from leaf) as leaves, round(back, 6) as scan_back, round(sw, 6) as in_window, round(dt, 6) as in_inner_window, round(log10(n * a * ((1 - b) * n + 2 * b * n * (back + 2 * a * n))), 6) as sweep_log10,
  round(log10(ops), 6) as indexed_log10, round(log10(m * t * sw * dt * (n_jp / n)), 6) as refine_log10 from o, ix""",
    "slab_balance_warped": f"""with {base()}, ends as (select min(t) as t0, max(t) - min(t) as w from src), wt as (select t0 + floor(w * ((t - t0) / w::double) * ((t - t0) / w::double) * ((t - t0) / w::double))::bigint as t from src, ends),
span as (select min(t) as lo, max(t) as hi from wt), u as (select (t - lo) // {_WIDTH} as k, count(*) as n from wt, span group by 1), un as (select coalesce(n, 0) as n from (select unnest(range(16)) as k) left join u using (k)),
r as (select rank() over (order by t) - 1 as k, count(*) over () as c from wt), en as (select count(*) as n from r group by k * 16 // c),
every as (select 'uniform' as kind, n from un union all select 'equi-depth', n from en)
select kind, round(stddev_pop(n), 6) as sigma, round(avg(n), 6) as mean, min(n) as least, max(n) as most from every group by kind""",
    "points_unnested": f"with {base()} select traj, t, x, y, pid, seq from pts",
    "point_distances": f"""with {base()} select pid, abs(t - next_t) as temporal, round(sqrt((x - next_x) * (x - next_x) + (y - next_y) * (y - next_y)), 6) as euclid, round(abs(x - next_x) + abs(y - next_y), 6) as manhattan,
  round(greatest(abs(x - next_x), abs(y - next_y)), 6) as chebyshev, round(2 * 6371.0088 * asin(sqrt(least(pow(sin(radians(next_y - y) / 2), 2) + cos(radians(y)) * cos(radians(next_y)) * pow(sin(radians(next_x - x) / 2), 2), 1.0))), 6) as haversine from pts where next_t is not null""",
    "jp_suppliers_customers": f"""with l as (select l_suppkey::bigint as traj, epoch_us(l_shipdate) as t, min(l_quantity)::double as x, min(l_discount * 1000)::double as y from lineitem group by 1, 2),
o as (select o_custkey::bigint as traj, epoch_us(o_orderdate) as t, o_totalprice / 1000 as x, c_acctbal / 100 as y from orders join customer on o_custkey = c_custkey)
select l.traj as r_traj, o.traj as s_traj, count(*) as n_jp from l join o on o.t between l.t - {24 * HOUR} and l.t + {24 * HOUR} and (l.x - o.x) * (l.x - o.x) + (l.y - o.y) * (l.y - o.y) <= 9.0 group by 1, 2""",
    "jp_two_relation_sweep": f"with {base()}, l as (select * from pts where traj % 2 = 0), r as (select * from pts where traj % 2 = 1) {pairs(P10, 'true', 'l', 'r')}",
    "jp_owned": f"{_jp()}, {_BOUNDS} select ((r_t - lo) // {_WIDTH})::int as slab, count(*) as n_jp from jp, span group by 1",
    "slab_sufficiency": f"{_jp()} select 'JP' as kind, 0::bigint as only_left, 0::bigint as only_right, count(*) as both from jp union all select 'BP', 0, 0, count(*) from pts where (traj, seq) not in (select r_traj, r_seq from jp)",
    "op_merge_intervals": match_query(SET_A, tail=""", i as (select r_traj, greatest(r_t_from, s_t_from) as t_from, least(r_t_to, s_t_to) as t_to from m), k as (select *, case when t_from <= max(t_to) over (partition by r_traj order by t_from, t_to rows between unbounded preceding and 1 preceding) then 0 else 1 end as b from i),
g as (select *, sum(b) over (partition by r_traj order by t_from, t_to rows unbounded preceding) as g from k) select r_traj, min(t_from) as t_from, max(t_to) as t_to, count(*) as n from g group by r_traj, g"""),
    "op_match_json": match_query(SET_A, tail="select r_traj, s_traj, r_from, '{\"r_traj\":' || r_traj || ',\"r_from\":' || r_from || ',\"r_to\":' || r_to || ',\"s_traj\":' || s_traj || ',\"s_from\":' || s_from || ',\"s_to\":' || s_to || ',\"lifespan_us\":' || lifespan_us || '}' as json from m"),
    "op_match_files": match_query(SET_A),
    "op_decorate": match_query(SET_A, tail="select r_name, n_name, count(*) as n, sum(lifespan_us)::bigint as together_us from m join customer on c_custkey = r_traj join nation on n_nationkey = c_nationkey join region on r_regionkey = n_regionkey group by rollup (r_name, n_name)"),
    "cost_index_vs_eps": " union all ".join(f"(with {base()}, {_CELLS}, {_touch(e)} select {e!r}::double as eps_sp, count(*) as spatial_rows from met)" for e in _SWEEP_SP),
    "gap_definition_window": match_query(SET_B, tail=f"select count(*) as n_matches, count(*) filter (r_t_to - r_t_from < {SET_B.delta_t_us}) as n_short_span from m"),
    "sweep_eps_t": " union all ".join(f"({_jp(JoinParams(10.0, m * 60_000_000))} select {m}::bigint as eps_t_min, count(*) as n_jp from jp)" for m in _SWEEP_T),
    "sweep_eps_sp": " union all ".join(f"({_jp(JoinParams(e, 2 * HOUR))} select {e!r}::double as eps_sp, count(*) as n_jp from jp)" for e in _SWEEP_SP),
    "sweep_delta_t": " union all ".join(f"({match_query(JoinParams(10.0, 2 * HOUR, h * HOUR), tail=f'select {h}::bigint as delta_t_h, (select count(*) from jp) as n_jp, count(*) as n_matches from m')})" for h in (0, 4, 5, 6, 7, 8, 9)),
    "sweep_capacity": " union all ".join(f"(with {base()}, {_CELLS.replace('0.03', f'0.0{c}')} select {c}::bigint as capacity_pct, count(*) as leaves, max(d)::bigint as depth from leaf)" for c in (1, 2, 3, 4, 5)),
    "size_portions": " union all ".join(f"({_jp(where=f'pid % 5 < {i}')} select {i}::bigint as fifths, (select count(*) from pts) as n_points, count(*) as n_jp from jp)" for i in (1, 2, 3, 4, 5)),
    "balance_portions": " union all ".join(f"""(with {base()}, q as (select * from src where pid % 5 < {i}), span as (select min(t) as lo, max(t) as hi from q), s as (select (t - lo) // {_WIDTH} as k, count(*) as n from q, span group by 1),
u as (select coalesce(n, 0) as n from (select unnest(range(16)) as k) left join s using (k)), r as (select rank() over (order by t) - 1 as k, count(*) over () as c from q), d as (select count(*) as n from r group by k * 16 // c), every as (select 'uniform' as kind, n from u union all select 'equi-depth', n from d)
select {i}::bigint as fifths, kind, round(stddev_pop(n), 6) as sigma, round(avg(n), 6) as mean from every group by kind)""" for i in (1, 2, 3, 4, 5)),
    "app_neighbour_count": f"{_jp()} select p.traj, p.seq, count(distinct s_traj) as n_objects, count(s_traj) as n_points from pts p left join jp on r_traj = p.traj and r_seq = p.seq group by 1, 2",
    "app_rideshare": match_query(SET_A, tail=f"select r_traj, s_traj, count(*) as trips, sum(lifespan_us)::bigint as together_us from m group by 1, 2 having sum(lifespan_us) >= {3 * HOUR}"),
    "app_suspicious": match_query(SET_B, tail=f"select r_traj, s_traj, count(*) as times, max(lifespan_us) as longest_us from m where lifespan_us >= {3 * HOUR} group by 1, 2 having count(*) >= 2"),
    "app_groups": match_query(SET_B, tail=", d as (select r_traj as traj, s_traj as o from m union select s_traj, r_traj from m) select traj, count(*) as partners from d group by 1 having count(*) >= 3"),
    "app_topk_partners": match_query(SET_B, tail=", d as (select r_traj, s_traj, lifespan_us from m union all select s_traj, r_traj, lifespan_us from m), b as (select r_traj, s_traj, max(lifespan_us) as longest_us from d group by 1, 2) select * from (select *, row_number() over (partition by r_traj order by longest_us desc, s_traj) as rank from b) where rank <= 3"),
    "app_longest": match_query(SET_B, tail="select * from m order by lifespan_us desc, r_traj, s_traj, r_from limit 20"),
    "app_network": match_query(SET_A, tail=", st as (select floor(p.x / 20.0)::bigint as from_x, floor(p.y / 20.0)::bigint as from_y, floor(p.next_x / 20.0)::bigint as to_x, floor(p.next_y / 20.0)::bigint as to_y, p.traj, m.s_traj from pts p join m on p.traj = m.r_traj and p.seq >= m.r_from and p.seq < m.r_to) select from_x, from_y, to_x, to_y, count(distinct (traj, s_traj)) as pairs from st group by 1, 2, 3, 4"),
    "op_band": f"with {base()} select a.traj as r_traj, a.pid as r_pid, b.traj as s_traj, b.pid as s_pid from pts a join pts b on b.t between a.t - {HOUR} and a.t + {HOUR} and a.traj < b.traj",
    "op_overlap": f"with {base()}, s as (select traj, min(t) lo, max(t) hi from src group by 1) select a.traj as r_traj, b.traj as s_traj from s a join s b on a.lo <= b.hi and b.lo <= a.hi and a.traj < b.traj",
    "op_asof": f"with {base()}, p as (select traj, t, pid from src where pid % 3 <> 0), q as (select traj, t, min(pid) as v from src where pid % 3 = 0 group by 1, 2) select p.traj, p.t, p.pid, q.t as match_t, q.v as match_value from p asof left join q on p.traj = q.traj and p.t >= q.t",
    "op_knn": f"with {base()}, c as (select a.traj as r_traj, a.seq as r_seq, b.traj as s_traj, b.seq as s_seq, (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) as d2 from pts a join pts b on b.t between a.t - {6 * HOUR} and a.t + {6 * HOUR} and a.traj <> b.traj) select * from (select *, row_number() over (partition by r_traj, r_seq order by d2, s_traj, s_seq) as rank from c) where rank <= 3",
    "op_semi": f"{_jp()} select traj, count(*) as n from pts where (traj, seq) in (select r_traj, r_seq from jp) group by 1",
    "op_anti": f"{_jp()} select traj, count(*) as n from pts where (traj, seq) not in (select r_traj, r_seq from jp) group by 1",
    "op_full_outer": f"with {base()}, a as (select traj, count(*) as n_click from ev where event_type = (select min(event_type) from events) group by 1), b as (select traj, count(*) as n_other from ev where event_type = (select max(event_type) from events) group by 1) select coalesce(a.traj, b.traj) as traj, n_click, n_other from a full join b on a.traj = b.traj",
    "op_rollup": "select r_name, n_name, count(*) as n, sum(l_quantity)::double as quantity from lineitem join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by rollup (r_name, n_name)",
    "op_cube": f"with {base()} select (t // {24 * HOUR})::bigint as day, event_type, count(*) as n from ev group by cube (day, event_type)",
    "op_grouping_sets": f"with {base()} select day, cell, event_type, count(*) as n, grouping_id(day, cell, event_type)::bigint as gid from (select *, (t // {24 * HOUR})::bigint as day, floor(x / 50)::bigint as cell from ev) group by grouping sets ((day, cell), (event_type), ())",
    "op_ranks": f"with {base()} select traj, pid, rank() over w as rnk, dense_rank() over w as dense, ntile(4) over w2 as quarter, round(percent_rank() over w, 9) as pct, round(cume_dist() over w, 9) as cume, nth_value(pid, 2) over (partition by traj order by x, pid rows between unbounded preceding and unbounded following) as second from pts window w as (partition by traj order by floor(x)), w2 as (partition by traj order by x, pid)",
    "op_range_frame": f"with {base()} select traj, pid, count(*) over (partition by traj order by t range between {12 * HOUR} preceding and {12 * HOUR} following) as n_near from src",
    "op_rows_frame": f"with {base()}, s as (select traj, pid, t, x, coalesce(sqrt((x - lag(x) over w) * (x - lag(x) over w) + (y - lag(y) over w) * (y - lag(y) over w)), 0) as step from src window w as (partition by traj order by t, pid)) select traj, pid, round(step, 6) as step, max(x) over (partition by traj order by t, pid rows between 2 preceding and current row) as max3 from s",
    "op_setops": f"with {base()}, a as (select traj from src where pid % 2 = 0), b as (select traj from src where pid % 3 = 0) select 'except' as op, count(*) as n from (from a except from b) union all select 'intersect', count(*) from (from a intersect from b) union all select 'except_all', count(*) from (from a except all from b) union all select 'intersect_all', count(*) from (from a intersect all from b) union all select 'union', count(*) from (from a union from b)",
    "op_arrays": f"{_jp()}, l as (select r_traj, list_distinct(list(s_traj)) as p from jp group by 1) select a.r_traj as a, b.r_traj as b, len(list_intersect(a.p, b.p))::bigint as common from l a join l b on a.r_traj < b.r_traj where len(list_intersect(a.p, b.p)) > 0",
    "op_maps": match_query(SET_B, tail=f", b as (select r_traj, s_traj, max(lifespan_us) as v from m group by 1, 2) select r_traj, count(*) as partners, count(*) filter (v >= {5 * HOUR}) as long_partners, sum(v // 1000000)::bigint as seconds from b group by 1"),
    "op_json": "select event_id, cast(json_extract_string(props, '$.k') as bigint) as k, '{\"traj\":' || user_id || ',\"k\":' || json_extract_string(props, '$.k') || '}' as js from events",
    "op_dates": "select event_id, date_trunc('hour', ts) as hour, dayofweek(ts)::int + 1 as dow, year(ts)::int as y, upper(event_type) as kind, lpad(user_id::varchar, 8, '0') as code from events",
    "op_morton": f"with {base()}, {_CELLS}, f as (select pid, ix, iy from (select pid, least(greatest(floor((x - x0) / ((x1 - x0) / 16)), 0), 15)::bigint as ix, least(greatest(floor((y - y0) / ((y1 - y0) / 16)), 0), 15)::bigint as iy from src, box)) select pid, ix, iy, ((ix >> 3) & 1) * 128 + ((iy >> 3) & 1) * 64 + ((ix >> 2) & 1) * 32 + ((iy >> 2) & 1) * 16 + ((ix >> 1) & 1) * 8 + ((iy >> 1) & 1) * 4 + (ix & 1) * 2 + (iy & 1) as code, concat(((ix >> 3) & 1) * 2 + ((iy >> 3) & 1), ((ix >> 2) & 1) * 2 + ((iy >> 2) & 1), ((ix >> 1) & 1) * 2 + ((iy >> 1) & 1), (ix & 1) * 2 + (iy & 1)) as path from f",
    "op_histogram": f"with {base()} select least(floor(x / 50), 9)::bigint as bx, floor(y / 10)::bigint as by, count(*) as n from src group by 1, 2",
    "op_pivot": f"with {base()}, {_BOUNDS} select event_type, " + ", ".join(f"count(*) filter ((t - lo) // {_WIDTH} = {k}) as slab_{k}" for k in (0, 5, 10, 15)) + " from ev, span group by 1",
    "stream_jp_batch_equiv": f"with {base()} select a.traj as r_traj, a.pid as r_pid, b.traj as s_traj, b.pid as s_pid from src a join src b on b.t between a.t - {2 * HOUR} and a.t + {2 * HOUR} and (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) <= 100.0 and a.traj <> b.traj",
    "stream_bp": f"with {base()}, top as (select max(t) as m from src) select traj, pid from src a, top where t < m - {6 * HOUR} and not exists (select 1 from src b where b.t between a.t - {2 * HOUR} and a.t + {2 * HOUR} and (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y) <= 100.0 and a.traj <> b.traj)",
    "stream_windows": f"with {base()}, top as (select max(t) as m from src) select (t // {24 * HOUR}) * {24 * HOUR} as start_us, count(*) as n_points from src, top where (t // {24 * HOUR} + 1) * {24 * HOUR} <= m group by 1",
    "stream_sessions": f"with {base()}, top as (select max(t) as m from src), g as (select traj, t, case when t - lag(t) over (partition by traj order by t) >= {12 * HOUR} then 1 else 0 end as b from src), s as (select traj, t, sum(b) over (partition by traj order by t rows unbounded preceding) as k from g) select traj, min(t) as start_us, max(t) + {12 * HOUR} as end_us, count(*) as n_points from s, top group by traj, k, m having max(t) + {12 * HOUR} <= m",
}
