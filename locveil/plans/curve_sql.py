"""The curve zoning and what is built on it as recursive SQL, for checks against the operators.

All start from a table ``r(rot, rank, cell_id, x, y, prior, eps)`` of cells on the
curve.  eps_param -1 stands for the cells' own budgets.
"""

from __future__ import annotations

KEY = "rot, eps_param, e_min"


def runs(params: list[tuple[float, float]]) -> str:
    """``og``: every run of ranks with its mass, reach and whether it meets the floor, for each parameter pair."""
    pairs = ", ".join(f"({e}::double, {m}::double)" for e, m in params)
    return f"""sd as (select a.rot, a.rank r, b.rank g, a.prior, a.eps, sqrt((a.x-b.x)*(a.x-b.x)+(a.y-b.y)*(a.y-b.y)) d from r a join r b on a.rot=b.rot),
 se as (select s.rot, s.rank a, t.rank b from r s join r t on s.rot=t.rot and s.rank<t.rank),
 sc as (select se.rot, a, b, g, sum(prior*d)/sum(prior) err, sum(prior) mass, max(case when g between a and b then d end) far, min(eps) least from se join sd on sd.rot=se.rot and sd.r between a and b group by all),
 sg as (select rot, a, b, max(mass) mass, max(far) reach, min(err) a_out, min(least) least from sc group by all),
 pr(eps_param, e_min) as (values {pairs}),
 og as (select {KEY}, a, b, mass, reach, a_out>=exp(case when eps_param<0 then least else eps_param end)*e_min-1e-12 ok from sg, pr)"""


def walk() -> str:
    """``res(rot, eps_param, e_min, res)``: the runs that the walk from both ends leaves, null where the whole curve fails."""
    return f"""ga as (select {KEY}, a, list(b order by b) filter (where ok) bs from og group by all), gb as (select {KEY}, b, list(a order by a) filter (where ok) starts from og group by all),
 wk as (select {KEY}, 0::bigint la, 1::bigint lb, b-1 ra, b rb, []::struct(a bigint, b bigint)[] lefts, []::struct(a bigint, b bigint)[] rights, []::varchar[] lasts, false fin from og where ok and a=0 and b=(select max(rank) from r)
 union all select {KEY}, case when gap>=2 and out_left then lb+1 else la end, case when gap>=2 and out_left then lb+2 else lb end, case when gap>=2 and not out_left then ra-2 else ra end, case when gap>=2 and not out_left then ra-1 else rb end,
  case when gap>=2 and out_left then list_append(lefts, {{'a': la, 'b': lb}}) else lefts end, case when gap>=2 and not out_left then list_append(rights, {{'a': ra, 'b': rb}}) else rights end,
  case when gap<2 then lasts when out_left then list_append(lasts, 'l') else list_append(lasts, 'r') end, gap<2
  from (select s2.rot, s2.eps_param, s2.e_min, la, lb, s2.ra, rb, lefts, rights, lasts, s2.ra-lb-1 gap, u.reach>=v.reach out_left
   from (select s1.rot, s1.eps_param, s1.e_min, la, lb, coalesce(list_max(list_filter(starts, lambda x: x>lb and x<=ra)), lb+1) ra, rb, lefts, rights, lasts
    from (select wk.rot, wk.eps_param, wk.e_min, la, coalesce(list_min(list_filter(bs, lambda x: x>=lb and x<ra)), ra-1) lb, ra, rb, lefts, rights, lasts from wk join ga on ga.rot=wk.rot and ga.eps_param=wk.eps_param and ga.e_min=wk.e_min and ga.a=la where not fin) s1
    join gb on gb.rot=s1.rot and gb.eps_param=s1.eps_param and gb.e_min=s1.e_min and gb.b=rb) s2
   join sg u on u.rot=s2.rot and u.a=la and u.b=lb join sg v on v.rot=s2.rot and v.a=s2.ra and v.b=rb)),
 en as (select {KEY}, la, rb, lefts, rights, lasts, case when gap=1 and near_l<=near_r then lb+1 else lb end lb, case when gap=1 and near_l>near_r then ra-1 else ra end ra
  from (select *, ra-lb-1 gap, (select min(d) from sd where sd.rot=wk.rot and r=lb+1 and g between la and lb) near_l, (select min(d) from sd where sd.rot=wk.rot and r=lb+1 and g between ra and rb) near_r from wk where fin)),
 ks as (select *, len(lasts)-k keep, len(list_filter(lasts[len(lasts)-k+1:], lambda x: x='l')) pl from (select *, unnest(range(len(lasts)+1)) k from en)),
 kt as (select {KEY}, k, case when pl>0 then lefts[len(lefts)-pl+1].a else la end ua, case when k-pl>0 then rights[len(rights)-(k-pl)+1].b else rb end ub, lefts[1:len(lefts)-pl] lf, rights[1:len(rights)-(k-pl)] rg from ks),
 both_ok as (select en.rot, en.eps_param, en.e_min, -1 k, 0 way, 0.0::double score, 0::bigint cut, lefts || [{{'a': la, 'b': lb}}, {{'a': ra, 'b': rb}}] || rights res from en
  join og u on u.rot=en.rot and u.eps_param=en.eps_param and u.e_min=en.e_min and u.a=la and u.b=lb and u.ok join og v on v.rot=en.rot and v.eps_param=en.eps_param and v.e_min=en.e_min and v.a=ra and v.b=rb and v.ok),
 whole_ok as (select kt.rot, kt.eps_param, kt.e_min, k, 0 way, 0.0::double score, 0::bigint cut, lf || [{{'a': ua, 'b': ub}}] || rg res from kt join og u on u.rot=kt.rot and u.eps_param=kt.eps_param and u.e_min=kt.e_min and u.a=ua and u.b=ub and u.ok),
 kc as (select *, unnest(range(ua-1, ub+1)) cut, lf[len(lf)].a ba, rg[len(rg)].b ab from kt),
 cut_ok as (select kc.rot, kc.eps_param, kc.e_min, k, 1 way, round((coalesce(u.mass*u.reach,0)+coalesce(v.mass*v.reach,0))/(coalesce(u.mass,0)+coalesce(v.mass,0)),12) score, cut,
   case when ba is null then lf else list_append(lf[1:len(lf)-1], {{'a': ba, 'b': cut}}) end || case when ab is null then rg else list_append(rg[1:len(rg)-1], {{'a': cut+1, 'b': ab}}) end res
  from kc left join og u on u.rot=kc.rot and u.eps_param=kc.eps_param and u.e_min=kc.e_min and u.a=ba and u.b=cut left join og v on v.rot=kc.rot and v.eps_param=kc.eps_param and v.e_min=kc.e_min and v.a=cut+1 and v.b=ab
  where (ba is not null or cut=ua-1) and (ab is not null or cut=ub) and (ba is null or u.ok) and (ab is null or v.ok) and (ba is not null or ab is not null)),
 won as (select *, row_number() over (partition by {KEY} order by k, way, score, cut) rn from (select * from both_ok union all select * from whole_ok union all select * from cut_ok)),
 res as (select kr.*, res from (select distinct {KEY} from og) kr left join (select {KEY}, res from won where rn=1) w using ({KEY}))"""


def optimum() -> str:
    """``res`` by a dynamic programme over all ways to cut the curve."""
    return f"""wb as (select {KEY}, b, list(case when ok then mass*reach else 'inf'::double end order by a) w from og group by all),
 dp as (select distinct {KEY}, 1::bigint nxt, [0.0::double, 'inf'::double] cost, [-1::bigint] back from og
 union all select dp.rot, dp.eps_param, dp.e_min, nxt+1, list_append(cost, list_min(list_transform(range(1, nxt+1), lambda i: cost[i]+w[i]))), list_append(back, case when list_min(list_transform(range(1, nxt+1), lambda i: cost[i]+w[i]))='inf'::double then -1 else list_position(list_transform(range(1, nxt+1), lambda i: cost[i]+w[i]), list_min(list_transform(range(1, nxt+1), lambda i: cost[i]+w[i])))-1 end)
  from dp join wb on wb.rot=dp.rot and wb.eps_param=dp.eps_param and wb.e_min=dp.e_min and wb.b=nxt),
 tr as (select {KEY}, nxt-1 b, back, []::struct(a bigint, b bigint)[] res from dp where nxt=(select max(rank)+1 from r) and back[nxt]>=0
 union all select {KEY}, back[b+1]-1, back, list_prepend({{'a': back[b+1], 'b': b}}, res) from tr where b>=0),
 res as (select kr.*, res from (select distinct {KEY} from og) kr left join (select {KEY}, res from tr where b<0) w using ({KEY}))"""


def zones() -> str:
    """``zn(rot, eps_param, e_min, cell_id, zone_id, avg_reach)``; an infeasible setting has one row of nulls."""
    return f"""rn as (select {KEY}, unnest(res) s from res where res is not null), ar as (select {KEY}, sum(mass*reach)/sum(mass) avg_reach from rn join sg using (rot) where sg.a=s.a and sg.b=s.b group by all),
 mb as (select rn.rot, eps_param, e_min, cell_id, min(cell_id) over (partition by rn.rot, eps_param, e_min, s.a) zone_id from rn join r on r.rot=rn.rot and rank between s.a and s.b),
 zn as (select {KEY}, cell_id, zone_id, avg_reach from mb join ar using ({KEY}) union all select {KEY}, null, null, null from res where res is null)"""


def best() -> str:
    """``bz``: the rotation of least average reach; ties and infeasible settings to the lowest."""
    return "bz as (select * exclude (rn) from (select *, dense_rank() over (partition by eps_param, e_min order by coalesce(round(avg_reach,12), 'inf'::double), rot) rn from zn) where rn=1)"


def report(domain: str, source: str = "zn") -> str:
    return f" select '{domain}' domain_id, eps_param, e_min, rot::bigint rot, cell_id, zone_id, round(avg_reach,6) avg_reach from {source}"
