"""Every operator, variant, measure and workload as a query, with SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import hilbert, portable_uniform
from ..operators import attack, condition, crowd, domains, exponential, geometry, metrics, sample, table_functions, zoning
from ..sources import read
from ..streaming import pings as live
from . import cost, curve_sql, experiments

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
SQL: dict[str, str] = {}

ORDERS = {"dense": 5, "sparse": 7}
EPS, E_MIN = 1.0, 0.1


def query(sql: str | None = None) -> Callable[[Query], Query]:
    def add(f: Query) -> Query:
        QUERIES[f.__name__] = f
        if sql is not None:
            SQL[f.__name__] = sql
        return f

    return add


# ---- SQL building blocks (common table expressions) ---------------------------------------------------------------

_PRIOR = "p50 as (select unnest(range(50)) pid, unnest([" + ",".join(f"{v}::double" for v in domains.PRIOR) + "]) pv)"
_DENSE = "pts as (select 'dense' domain_id, cast(floor(22.0::double*embedding[1]::double) as int) cx, cast(floor(22.0::double*embedding[2]::double) as int) cy, vec_id first_at from embeddings)"
_SPARSE = "pts as (select 'sparse' domain_id, cast((3*cast(props->>'$.k' as int))//10 as int) cx, cast(floor(value/5) as int) cy, event_id first_at from events)"
_TILES = "pts as (select 'tile:'||l_suppkey domain_id, cast(l_quantity as int) cx, cast(floor(l_extendedprice/2000) as int) cy, l_orderkey first_at from lineitem)"
_FIRST = "f as (select domain_id, cx, cy, min(first_at) first_at from pts group by all), n as (select *, row_number() over (partition by domain_id order by first_at, cx, cy)-1 cell_id from f), raw as (select domain_id, cell_id, cx, cy, cx+0.5::double x, cy+0.5::double y from n where cell_id<50)"
_WITH_PRIOR = "c as (select raw.*, pv/(sum(pv) over (partition by domain_id)) prior, 1.0::double eps from raw join p50 on pid=cell_id)"


def cells_sql(domain: str) -> str:
    return ", ".join([_PRIOR, {"dense": _DENSE, "sparse": _SPARSE, "tiles": _TILES}[domain], _FIRST, _WITH_PRIOR])


_PAIRS = "d as (select a.domain_id, a.cell_id i, b.cell_id j, sqrt((a.x-b.x)*(a.x-b.x)+(a.y-b.y)*(a.y-b.y)) d from c a join c b using (domain_id))"
_ZONES = "z as (select domain_id, cell_id, cast(floor(cell_id/5.0)*5 as bigint) zone_id from c)"
_STATS = """zc as (select z.domain_id, zone_id, d.j g, sum(c.prior*d.d)/sum(c.prior) err from z join c using (domain_id, cell_id) join d on d.domain_id=z.domain_id and d.i=z.cell_id group by all),
 ao as (select domain_id, zone_id, min(err) a_out from zc group by all), ai as (select zc.domain_id, zc.zone_id, min(err) a_in from zc join z on z.domain_id=zc.domain_id and z.zone_id=zc.zone_id and z.cell_id=zc.g group by all),
 rc as (select a.domain_id, a.zone_id, max(d.d) reach from z a join z b on a.domain_id=b.domain_id and a.zone_id=b.zone_id join d on d.domain_id=a.domain_id and d.i=a.cell_id and d.j=b.cell_id group by all),
 mz as (select z.domain_id, zone_id, count(*) size, sum(prior) mass, min(eps) eps_zone from z join c using (domain_id, cell_id) group by all),
 st as (select * from mz join rc using (domain_id, zone_id) join ao using (domain_id, zone_id) join ai using (domain_id, zone_id))"""
_KERNEL = "kw as (select d.domain_id, d.i, d.j, exp(-(eps_zone/(2*reach))*d.d) w from d join z on z.domain_id=d.domain_id and z.cell_id=d.i join st on st.domain_id=z.domain_id and st.zone_id=z.zone_id), k as (select domain_id, i, j, w/(sum(w) over (partition by domain_id, i)) k from kw)"
_JOINT = "jw as (select k.domain_id, k.i, k.j, prior*k w from k join c on c.domain_id=k.domain_id and c.cell_id=k.i), ev as (select domain_id, j, sum(w) pr from jw group by all)"
_OPT = """gc as (select jw.domain_id, jw.j, d.j g, sum(w*d.d) cost from jw join d on d.domain_id=jw.domain_id and d.i=jw.i group by all),
 rk as (select *, row_number() over (partition by domain_id, j order by round(cost,12), g) rn from gc), o as (select domain_id, j, g guess_opt, cost from rk where rn=1)"""
_MAP = "bm as (select domain_id, j, i guess_map, w from (select *, row_number() over (partition by domain_id, j order by round(w,14) desc, i) rn from jw) where rn=1)"


def chain(domain: str, *parts: str) -> str:
    return "with " + ", ".join([cells_sql(domain), *parts]) + " "


def hilbert_sql(source: str, order: int, rots: str = "select 0 rot") -> str:
    """The curve by a recursive walk down the bits; ``source`` has domain_id, cell_id, gx, gy."""
    side = (1 << order) - 1
    return f"""hr as (select domain_id, cell_id, rot, case rot when 1 then gy when 2 then {side}-gx when 3 then {side}-gy else gx end x, case rot when 1 then {side}-gx when 2 then {side}-gy when 3 then gx else gy end y, 0::bigint h, {order}-1 lv from {source}, ({rots})
 union all select domain_id, cell_id, rot, case when ry=0 then case when rx=1 then s-1-ly else ly end else lx end, case when ry=0 then case when rx=1 then s-1-lx else lx end else ly end, h*4+xor(3*rx,ry), lv-1
 from (select *, (1<<lv) s, (x//(1<<lv))%2 rx, (y//(1<<lv))%2 ry, x%(1<<lv) lx, y%(1<<lv) ly from hr where lv>=0))"""


def rank_sql(domain: str, rots: str = "select 0 rot") -> str:
    return (
        f"with recursive {cells_sql(domain)}, gs as (select *, cx-min(cx) over (partition by domain_id) gx, cy-min(cy) over (partition by domain_id) gy from c), "
        + hilbert_sql("gs", ORDERS[domain], rots)
        + ", hv as (select domain_id, cell_id, rot, h+1 h from hr where lv=-1), r as (select hv.domain_id, hv.rot, hv.cell_id, h, row_number() over (partition by hv.domain_id, hv.rot order by h, hv.cell_id)-1 rank, cx, cy, x, y, prior, eps from hv join c on c.domain_id=hv.domain_id and c.cell_id=hv.cell_id) "
    )


def _uniform_sql(ident: str, seed: int) -> str:
    return f"(cast(('0x'||substr(md5({ident}||':{seed}'),1,13)) as bigint)/4503599627370496.0::double)"


# ---- shared pieces -------------------------------------------------------------------------------------------------


def _cells(spark: SparkSession, sf_dir: str, domain: str = "dense") -> DataFrame:
    return domains.eps_constant(domains.prior_table2(getattr(domains, domain)(spark, sf_dir)), EPS)


def _r(df: DataFrame, *exact: str, **rounded: Column | str) -> DataFrame:
    return df.select(*exact, *(F.round(F.col(c) if isinstance(c, str) else c, 6).alias(n) for n, c in rounded.items()))


class _Plain:
    """Cells, distances, the plain zoning by blocks, its statistics and kernel."""

    def __init__(self, spark: SparkSession, sf_dir: str, domain: str = "dense"):
        self.cells = _cells(spark, sf_dir, domain)
        self.dist = geometry.pairs(self.cells)
        self.zones = zoning.blocks_by_id(self.cells, 5)
        self.stats = condition.zone_stats(self.zones, self.cells, self.dist)
        self.kernel = exponential.zonal_kernel(self.zones, self.stats, self.dist)


# ---- geometry and domains ------------------------------------------------------------------------------------------


def _domain_query(name: str) -> None:
    def f(spark: SparkSession, sf_dir: str) -> DataFrame:
        return getattr(domains, name)(spark, sf_dir).select("domain_id", "cell_id", F.col("cx").cast("long").alias("cx"), F.col("cy").cast("long").alias("cy"), "x", "y")

    f.__name__ = f"cells_{name}"
    query(chain(name) + "select domain_id, cell_id, cx::bigint cx, cy::bigint cy, x, y from raw")(f)


for _name in ("dense", "sparse", "tiles"):
    _domain_query(_name)


@query(chain("dense") + "select cell_id, round(prior,6) prior from c")
def prior_table2(spark, sf_dir):
    return _r(_cells(spark, sf_dir), "cell_id", prior="prior")


@query(chain("dense") + f", u as (select cell_id, 0.01::double+0.02::double*{_uniform_sql('cell_id', 7)} w from c) select cell_id, round(w/(sum(w) over ()),6) prior from u")
def prior_uniform(spark, sf_dir):
    return _r(domains.prior_uniform(domains.dense(spark, sf_dir)), "cell_id", prior="prior")


def _pings(spark, sf_dir):
    return domains.event_cells(read(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type", "value", "props"))


_PINGS = "pg as (select event_id, ts, user_id, event_type, value, props, cast((3*cast(props->>'$.k' as int))//10 as int) cx, cast(floor(value/5) as int) cy from events)"


@query("with " + cells_sql("sparse") + ", " + _PINGS + ", v as (select cx, cy, count(*) n from pg group by all), w as (select cell_id, coalesce(n,0)+1.0::double w from c left join v using (cx, cy)) select cell_id, round(w/(sum(w) over ()),6) prior from w")
def prior_visits(spark, sf_dir):
    return _r(domains.prior_visits(domains.sparse(spark, sf_dir), _pings(spark, sf_dir)), "cell_id", prior="prior")


@query("with " + cells_sql("sparse") + ", " + _PINGS + ", v as (select date_trunc('day', ts) window_start, cell_id, count(*) n from pg join c using (cx, cy) group by all) select epoch(window_start)::bigint window_start, cell_id, round(n/(sum(n) over (partition by window_start)),6) prior from v")
def prior_windowed(spark, sf_dir):
    df = domains.prior_windowed(domains.sparse(spark, sf_dir), _pings(spark, sf_dir))
    return _r(df.withColumn("window_start", F.unix_timestamp(F.col("window_start").cast("timestamp"))), "window_start", "cell_id", prior="prior")


@query("with " + cells_sql("dense") + f" select cell_id, round(0.5::double+1.0::double*{_uniform_sql('cell_id', 11)},6) eps from c")
def eps_uniform(spark, sf_dir):
    return _r(domains.eps_uniform(domains.dense(spark, sf_dir)), "cell_id", eps="eps")


@query("with " + cells_sql("sparse") + ", " + _PINGS + """, lv as (select c_custkey user_id, case c_mktsegment when 'AUTOMOBILE' then 0.5 when 'BUILDING' then 0.5 when 'FURNITURE' then 1.0 when 'HOUSEHOLD' then 1.5 when 'MACHINERY' then 1.5 end::double e from customer),
 m as (select cx, cy, min(e) e from pg join lv using (user_id) group by all) select cell_id, coalesce(e,1.0::double) eps from c left join m using (cx, cy)""")
def eps_levels_by_segment(spark, sf_dir):
    return domains.eps_levels(domains.sparse(spark, sf_dir), _pings(spark, sf_dir), read(spark, sf_dir, "customer", "c_custkey", "c_mktsegment")).select("cell_id", "eps")


@query(chain("dense", _PAIRS) + "select i, j, round(d,6) d from d")
def pair_distance(spark, sf_dir):
    return _r(geometry.pairs(_cells(spark, sf_dir)), "i", "j", d="d")


@query(chain("dense") + "select a.cell_id i, b.cell_id j, abs(a.x-b.x)+abs(a.y-b.y) d from c a, c b")
def pair_distance_manhattan(spark, sf_dir):
    return geometry.pairs(_cells(spark, sf_dir), "manhattan").select("i", "j", "d")


@query(chain("dense") + "select a.cell_id i, b.cell_id j, case when a.cell_id=b.cell_id then 0.0::double else 1.0::double end d from c a, c b")
def pair_hamming(spark, sf_dir):
    return geometry.pairs(_cells(spark, sf_dir), "hamming").select("i", "j", "d")


@query(chain("sparse", _PAIRS) + ", m as (select i cell_id, min(d) nearest from d where i<>j group by all) select cell_id, round(nearest,6) nearest, row_number() over (order by nearest, cell_id) isolation_rank from m")
def isolation_rank(spark, sf_dir):
    return _r(geometry.isolation(geometry.pairs(_cells(spark, sf_dir, "sparse"))), "cell_id", "isolation_rank", nearest="nearest")


def _grid_sql(order: int) -> str:
    n = 1 << order
    gs = f"gs as (select 'g' domain_id, (gy*{n}+gx)::bigint cell_id, gx, gy, lines from (select cast(l_quantity as int)%{n} gx, cast(floor(l_extendedprice/2000) as int)%{n} gy, count(*) lines from lineitem group by all))"
    return f"with recursive {gs}, " + hilbert_sql("gs", order) + " select gs.gx::bigint cx, gs.gy::bigint cy, lines, h+1 h from hr join gs using (cell_id) where lv=-1"


def _grid(spark: SparkSession, sf_dir: str, order: int) -> DataFrame:
    """Places of the curve on a grid that the tiles' cells are folded onto, with the lines there."""
    n = 1 << order
    cells = read(spark, sf_dir, "lineitem", "l_quantity", "l_extendedprice")
    cells = cells.select((F.col("l_quantity").cast("int") % n).alias("cx"), (F.floor(F.col("l_extendedprice") / 2000).cast("int") % n).alias("cy"))
    at = cells.groupBy("cx", "cy").agg(F.count("*").alias("lines"))
    return at.select(F.col("cx").cast("long").alias("cx"), F.col("cy").cast("long").alias("cy"), "lines", hilbert("cx", "cy", order).alias("h"))


@query(_grid_sql(2))
def hilbert_4x4(spark, sf_dir):
    return _grid(spark, sf_dir, 2)


@query(_grid_sql(3))
def hilbert_8x8(spark, sf_dir):
    return _grid(spark, sf_dir, 3)


def _ranked(spark, sf_dir, domain="dense", rots=(0,)):
    return geometry.rank_on_curve(_cells(spark, sf_dir, domain), ORDERS[domain], rots)


@query(rank_sql("dense") + "select cell_id, h, rank from r")
def curve_order_dense(spark, sf_dir):
    return _ranked(spark, sf_dir).select("cell_id", "h", F.col("rank").cast("long").alias("rank"))


@query(rank_sql("sparse", "select unnest([0,1,2,3]) rot") + "select rot::bigint rot, cell_id, h, rank from r")
def curve_rotations(spark, sf_dir):
    return _ranked(spark, sf_dir, "sparse", (0, 1, 2, 3)).select(F.col("rot").cast("long").alias("rot"), "cell_id", "h", F.col("rank").cast("long").alias("rank"))


@query(rank_sql("dense") + "select a.cell_id i, b.cell_id j, abs(a.rank-b.rank) gap from r a join r b on (b.cx=a.cx+1 and b.cy=a.cy) or (b.cx=a.cx and b.cy=a.cy+1)")
def curve_gap(spark, sf_dir):
    return geometry.curve_gap(_ranked(spark, sf_dir)).select("i", "j", "gap")


@query("with " + cells_sql("sparse") + ", " + _PINGS + ", o as (select * from pg where not exists (select 1 from c where c.cx=pg.cx and c.cy=pg.cy)), s as (select event_id, cell_id, sqrt((o.cx+0.5-x)*(o.cx+0.5-x)+(o.cy+0.5-y)*(o.cy+0.5-y))::double d from o, c), k as (select *, row_number() over (partition by event_id order by d, cell_id) rn from s) select event_id, cell_id, round(d,6) d from k where rn=1")
def snap_nearest_cell(spark, sf_dir):
    cells = _cells(spark, sf_dir, "sparse")
    return _r(geometry.snap(domains.outside(_pings(spark, sf_dir), cells).select("event_id", "cx", "cy"), cells), "event_id", "cell_id", d="d")


@query(chain("sparse", _PAIRS) + ", m as (select j, sum(prior*d)/sum(prior) e from d join c on c.cell_id=d.i group by all) select count(*) cells, round(min(e),6) a_out, (select round(max(d),6) from d) diameter from m")
def domain_stats(spark, sf_dir):
    cells = _cells(spark, sf_dir, "sparse")
    dist = geometry.pairs(cells)
    stats = condition.zone_stats(condition.whole(cells), cells, dist)
    return _r(stats, F.col("size").alias("cells"), a_out="a_out", diameter="reach")


# ---- zone condition ------------------------------------------------------------------------------------------------

_SEG = """, sd as (select a.rot, a.rank r, b.rank g, a.prior, sqrt((a.x-b.x)*(a.x-b.x)+(a.y-b.y)*(a.y-b.y)) d from r a join r b on a.rot=b.rot), se as (select s.rank a, t.rank b from r s join r t on s.rank<t.rank),
 sc as (select a, b, g, sum(prior*d)/sum(prior) err, sum(prior) mass, max(case when g between a and b then d end) far from se join sd on sd.r between a and b group by all) """


@query(rank_sql("dense") + _SEG + "select a, b, round(max(mass),6) mass, round(max(far),6) reach, round(min(err),6) a_out, round(min(case when g between a and b then err end),6) a_in from sc group by all")
def segments_curve(spark, sf_dir):
    seg = condition.segments(_ranked(spark, sf_dir)).where("a < b")
    return _r(seg, F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b"), mass="mass", reach="reach", a_out="a_out", a_in="a_in")


@query(chain("dense", _PAIRS, _ZONES, _STATS) + "select zone_id, round(a_out,6) a_out from st")
def anchor_outer_zones(spark, sf_dir):
    return _r(_Plain(spark, sf_dir).stats, "zone_id", a_out="a_out")


@query(chain("dense", _PAIRS, _ZONES, _STATS) + "select zone_id, round(a_in,6) a_in from st")
def anchor_inner_zones(spark, sf_dir):
    return _r(_Plain(spark, sf_dir).stats, "zone_id", a_in="a_in")


@query(chain("sparse", _PAIRS, _ZONES, _STATS) + "select zone_id, size, round(mass,6) mass, round(reach,6) reach, round(a_out,6) a_out, round(a_in,6) a_in, a_out>=exp(eps_zone)*2.0-1e-12 ok from st")
def zone_condition(spark, sf_dir):
    stats = condition.satisfied(_Plain(spark, sf_dir, "sparse").stats, 2.0)
    return _r(stats, "zone_id", "size", "ok", mass="mass", reach="reach", a_out="a_out", a_in="a_in")


@query(chain("sparse", _PAIRS, _ZONES, _STATS) + "select zone_id, m::double e_min from st, (select unnest(range(1,400)) / 20.0 m) where a_in>=exp(eps_zone)*m-1e-12 and a_out<exp(eps_zone)*m-1e-12")
def inner_outer_gap(spark, sf_dir):
    stats = _Plain(spark, sf_dir, "sparse").stats.withColumn("e_min", F.explode(F.transform(F.sequence(F.lit(1), F.lit(399)), lambda m: m / 20.0)))
    floor = F.exp("eps_zone") * F.col("e_min")
    return stats.where((F.col("a_in") >= floor - 1e-12) & (F.col("a_out") < floor - 1e-12)).select("zone_id", "e_min")


_TRIPLES = _ZONES.replace("5", "3")
_CROSS = "((p{b}x-p{a}x)*(q.y-p{a}y)-(p{b}y-p{a}y)*(q.x-p{a}x))"
_SIDES = [_CROSS.format(a=a, b=b) for a, b in ((1, 2), (2, 3), (3, 1))]
_HULLS = f""", tri as (select zone_id, arg_min(x,z.cell_id) p1x, arg_min(y,z.cell_id) p1y, max(case when z.cell_id=zone_id+1 then x end) p2x, max(case when z.cell_id=zone_id+1 then y end) p2y, arg_max(x,z.cell_id) p3x, arg_max(y,z.cell_id) p3y from z join c using (domain_id, cell_id) group by all),
 held as (select distinct tri.zone_id from tri, c q where q.cell_id not between zone_id and zone_id+2 and (p2x-p1x)*(p3y-p1y)<>(p2y-p1y)*(p3x-p1x) and ({" and ".join(f"{x}>=0" for x in _SIDES)} or {" and ".join(f"{x}<=0" for x in _SIDES)}))"""


@query(chain("sparse", _PAIRS, _TRIPLES, _STATS) + _HULLS + " select zone_id, round(a_in,6) a_in, round(a_out,6) a_out, a_in>a_out gap, zone_id not in (select zone_id from held) convex from st")
def toy_counterexample(spark, sf_dir):
    """Zones of three cells: where a guess from outside beats every guess inside, though no other cell lies in the hull."""
    cells = _cells(spark, sf_dir, "sparse")
    return _counterexamples(cells, zoning.blocks_by_id(cells, 3)).drop("domain_id")


def _counterexamples(cells: DataFrame, zones: DataFrame) -> DataFrame:
    stats = condition.zone_stats(zones, cells, geometry.pairs(cells))
    both = stats.join(geometry.is_convex_in(cells, zones), ["domain_id", "zone_id"])
    return _r(both, "domain_id", "zone_id", (F.col("a_in") > F.col("a_out")).alias("gap"), "convex", a_in="a_in", a_out="a_out")


@query("with " + ", ".join([cells_sql("dense"), _PAIRS]) + ", m as (select j, sum(prior*d)/sum(prior) e from d join c on c.cell_id=d.i group by all), a as (select min(e) a_out from m) select eps, e_min, round(exp(eps)*e_min,6) floor, a_out>=exp(eps)*e_min-1e-12 ok from a, (select unnest([" + ",".join(f"{e}::double" for e in (*experiments.EPS_DENSE, 2.1)) + "]) eps), (select unnest([" + ",".join(f"{m}::double" for m in experiments.E_MINS) + "]) e_min)")
def domain_feasible_grid(spark, sf_dir):
    params = spark.createDataFrame([(e, m) for e in (*experiments.EPS_DENSE, 2.1) for m in experiments.E_MINS], "eps double, e_min double")
    cells = _cells(spark, sf_dir)
    return _r(condition.feasible(cells, geometry.pairs(cells), params), "eps", "e_min", "ok", floor="floor")


# ---- zonings -------------------------------------------------------------------------------------------------------

_GRID = [(e, m) for e in experiments.REACH_EPS for m in experiments.REACH_E_MIN]


def _zone_report(zones: DataFrame) -> DataFrame:
    return zones.select("domain_id", "eps_param", "e_min", F.col("rot").cast("long").alias("rot"), "cell_id", "zone_id", F.round("avg_reach", 6).alias("avg_reach"))


_FOUR = "select unnest([0,1,2,3]) rot"


def _curve_query_sql(domain: str, params: list, rots: str = "select 0 rot", made: str = "", last: str = "zn") -> str:
    return rank_sql(domain, rots) + ", " + ", ".join(x for x in (curve_sql.runs(params), made or curve_sql.walk(), curve_sql.zones(), last) if x != "zn") + curve_sql.report(domain, "zn" if last == "zn" else "bz")


@query(_curve_query_sql("dense", _GRID))
def zones_curve_dense(spark, sf_dir):
    return _zone_report(zoning.zone_curve(_cells(spark, sf_dir), _GRID, order=ORDERS["dense"]))


@query(_curve_query_sql("sparse", _GRID))
def zones_curve_sparse(spark, sf_dir):
    return _zone_report(zoning.zone_curve(_cells(spark, sf_dir, "sparse"), _GRID, order=ORDERS["sparse"]))


@query(_curve_query_sql("sparse", _GRID, _FOUR, last=curve_sql.best()))
def zones_curve_best(spark, sf_dir):
    return _zone_report(zoning.zone_best_curve(_cells(spark, sf_dir, "sparse"), _GRID, ORDERS["sparse"]))


@query(_curve_query_sql("dense", [(-1.0, 0.2)]).replace("1.0::double eps from raw", f"0.5::double+1.0::double*{_uniform_sql('cell_id', 11)} eps from raw"))
def zones_curve_personal(spark, sf_dir):
    return _zone_report(zoning.zone_curve(domains.eps_uniform(_cells(spark, sf_dir)), [(None, 0.2)], order=ORDERS["dense"]))


@query()
def zones_qkm_dense(spark, sf_dir):
    return _zone_report(zoning.zone_qkm(_cells(spark, sf_dir), [(1.0, 0.2)]))


@query()
def zones_qkm_sparse(spark, sf_dir):
    return _zone_report(zoning.zone_qkm(_cells(spark, sf_dir, "sparse"), [(1.0, 0.2)]))


def _by_k(spark, sf_dir):
    """All k that zones of two cells allow (k = 1 is the whole domain), with all restarts."""
    cells = _cells(spark, sf_dir)
    return zoning.qkm_by_k(cells, [(1.0, 0.2)], list(range(1, cells.count() // 2 + 1)))


@query()
def zones_qkm_by_k(spark, sf_dir):
    return _by_k(spark, sf_dir).select("domain_id", "e_min", F.col("k").cast("long").alias("k"), F.round("avg_reach", 6).alias("avg_reach"))


@query()
def zones_qkm_choose_k(spark, sf_dir):
    return zoning.choose_k(_by_k(spark, sf_dir))


@query()
def zones_qkm_personal_general(spark, sf_dir):
    return _zone_report(zoning.zone_qkm(domains.eps_uniform(_cells(spark, sf_dir)), [(None, 0.1)]))


@query()
def zones_qkm_personal_weight(spark, sf_dir):
    return _zone_report(zoning.zone_qkm(domains.eps_uniform(_cells(spark, sf_dir)), [(None, 0.1)], lam=0.5))


def _valid_query(name: str, make: Callable, expected: str) -> None:
    def f(spark: SparkSession, sf_dir: str) -> DataFrame:
        cells, zones, e_min = make(spark, sf_dir)
        zones = zones.where("status = 'ok'").select("domain_id", "cell_id", "zone_id")
        return zoning.validate(zones, cells, condition.zone_stats(zones, cells, geometry.pairs(cells)), e_min)

    f.__name__ = name
    query(f"select {expected} domain_id, 0::bigint uncovered, 0::bigint doubled, 0::bigint small, 0::bigint below_floor")(f)


_valid_query("valid_curve_dense", lambda s, d: (c := _cells(s, d), zoning.zone_best_curve(c, [(1.0, 0.3)]), 0.3), "'dense'")
_valid_query("valid_curve_sparse", lambda s, d: (c := _cells(s, d, "sparse"), zoning.zone_best_curve(c, [(1.0, 0.5)]), 0.5), "'sparse'")
_valid_query("valid_curve_personal", lambda s, d: (c := domains.eps_uniform(_cells(s, d)), zoning.zone_curve(c, [(None, 0.3)]), 0.3), "'dense'")
_valid_query("valid_qkm_dense", lambda s, d: (c := _cells(s, d), zoning.zone_qkm(c, [(1.0, 0.3)], 8), 0.3), "'dense'")
_valid_query("valid_qkm_personal", lambda s, d: (c := domains.eps_uniform(_cells(s, d, "sparse")), zoning.zone_qkm(c, [(None, 0.3)], 8, lam=0.5), 0.3), "'sparse'")


@query("with t as (select distinct 'tile:'||l_suppkey domain_id from lineitem) select domain_id, 0::bigint uncovered, 0::bigint doubled, 0::bigint small, 0::bigint below_floor from t")
def zones_validate_tiles(spark, sf_dir):
    cells = domains.eps_constant(domains.prior_table2(domains.tiles(spark, sf_dir)), EPS)
    zones = zoning.zone_curve(cells, [(1.0, 0.2)]).where("status = 'ok'").select("domain_id", "cell_id", "zone_id")
    return zoning.validate(zones, cells, condition.zone_stats(zones, cells, geometry.pairs(cells)), 0.2)


def _adaptive_sql(err: str, last: str = " select cell_id, a, b, round(reach,6) reach from cv where rn=1") -> str:
    return rank_sql("sparse") + _SEG + f""", sg as (select a, b, max(far) reach, min(err) a_out, min(case when g between a and b then err end) a_in from sc where b-a<10 group by all),
 cv as (select cell_id, a, b, reach, row_number() over (partition by cell_id order by round(reach,12), a, b) rn from r join sg on r.rank between a and b where {err}>=exp(1.0::double)*0.1-1e-12)""" + last


def _adaptive(spark, sf_dir, kind):
    ranked = _ranked(spark, sf_dir, "sparse")
    return zoning.zone_per_cell(condition.segments(ranked), ranked, E_MIN, kind=kind)


@query(_adaptive_sql("a_in"))
def zones_adaptive_inner(spark, sf_dir):
    return _r(_adaptive(spark, sf_dir, "a_in"), "cell_id", "a", "b", reach="reach")


@query(_adaptive_sql("a_out"))
def zones_adaptive_outer(spark, sf_dir):
    return _r(_adaptive(spark, sf_dir, "a_out"), "cell_id", "a", "b", reach="reach")


@query(_adaptive_sql("a_in", ", o as (select distinct a, b, reach from cv where rn=1) select x.a, x.b, y.a a2, y.b b2, least(x.b,y.b)-greatest(x.a,y.a)+1 shared, abs(x.reach-y.reach)>1e-12 reach_differs from o x join o y on (x.a<y.a or (x.a=y.a and x.b<y.b)) and y.a<=x.b and x.a<=y.b"))
def zones_overlap_adaptive(spark, sf_dir):
    return zoning.overlaps(_adaptive(spark, sf_dir, "a_in")).select("a", "b", "a2", "b2", "shared", "reach_differs")


@query(_adaptive_sql("a_out", " select cell_id, a, b, round(max(reach) over (),6) reach from cv where rn=1"))
def zones_common_reach(spark, sf_dir):
    return _r(zoning.common_reach(_adaptive(spark, sf_dir, "a_out")), "cell_id", "a", "b", reach="reach")


@query()
def zones_bruteforce_toy6(spark, sf_dir):
    cells = domains.eps_constant(domains.prior_table2(domains.by_type(spark, sf_dir, 6)), EPS)
    return zoning.best_partition(cells, [(0.5, 0.1), (1.0, 0.5)]).select("domain_id", "e_min", "cell_id", "zone_id", F.round("avg_reach", 6).alias("avg_reach"))


@query(_curve_query_sql("sparse", _GRID, made=curve_sql.optimum()))
def zones_contiguous_optimum(spark, sf_dir):
    return _zone_report(zoning.zone_curve(_cells(spark, sf_dir, "sparse"), _GRID, exact=True, order=ORDERS["sparse"]))


@query(f"select eps, lam, count(*) users, sum(pings)::bigint pings, round(1+lam-least(eps,1.0)/greatest(eps,1.0),6) weight from (select round(0.5::double+1.5::double*{_uniform_sql('user_id', 11)},1) eps, pings from (select user_id, count(*) pings from events group by all)), (select unnest([0.0::double,0.5::double,1.0::double]) lam) group by eps, lam")
def eps_weight_curve(spark, sf_dir):
    return experiments.weight_curve(spark, sf_dir)


# ---- kernels -------------------------------------------------------------------------------------------------------


@query(chain("dense", _PAIRS, _ZONES, _STATS, _KERNEL) + "select i, j, round(k,6) k from k")
def kernel_zonal(spark, sf_dir):
    return _r(_Plain(spark, sf_dir).kernel, "i", "j", k="k")


@query("with " + cells_sql("dense").replace("1.0::double eps", f"0.5::double+1.0::double*{_uniform_sql('cell_id', 11)} eps") + ", " + ", ".join([_PAIRS, _ZONES, _STATS, _KERNEL]) + " select i, j, round(k,6) k from k")
def kernel_personal(spark, sf_dir):
    cells = domains.eps_uniform(_cells(spark, sf_dir))
    dist, zones = geometry.pairs(cells), zoning.blocks_by_id(cells, 5)
    return _r(exponential.zonal_kernel(zones, condition.zone_stats(zones, cells, dist), dist), "i", "j", k="k")


_CONST = "kc as (select i, j, exp(-1.0*d/(2*{r})) w from d) select i, j, round(w/(sum(w) over (partition by i)),6) k from kc"


@query("with " + ", ".join([cells_sql("dense"), _PAIRS]) + ", " + _CONST.format(r="1.66"))
def kernel_constant(spark, sf_dir):
    return _r(exponential.constant_kernel(geometry.pairs(_cells(spark, sf_dir)), 1.66, EPS), "i", "j", k="k")


@query("with " + ", ".join([cells_sql("dense"), _PAIRS, _ZONES, _STATS]) + ", " + _CONST.format(r="(select max(reach) from st)"))
def kernel_constant_maxreach(spark, sf_dir):
    p = _Plain(spark, sf_dir)
    return _r(exponential.constant_kernel(p.dist, exponential.largest_reach(p.stats), EPS), "i", "j", k="k")


@query(_adaptive_sql("a_in", f", {_PAIRS}, kw as (select d.i, d.j, exp(-d.d/(2*reach)) w from d join cv on cv.cell_id=d.i where rn=1) select i, j, round(w/(sum(w) over (partition by i)),6) k from kw"))
def kernel_adaptive(spark, sf_dir):
    cells = _cells(spark, sf_dir, "sparse")
    return _r(exponential.adaptive_kernel(_adaptive(spark, sf_dir, "a_in"), geometry.pairs(cells)), "i", "j", k="k")


@query(chain("dense") + "select a.cell_id i, b.cell_id j, case when a.cell_id=b.cell_id then 1.0::double else 0.0::double end k from c a, c b")
def kernel_identity(spark, sf_dir):
    return exponential.identity_kernel(geometry.pairs(_cells(spark, sf_dir))).select("i", "j", "k")


@query(chain("dense", _PAIRS, _ZONES, _STATS) + "select zone_id, round(reach,6) sensitivity from st")
def sensitivity_equals_reach(spark, sf_dir):
    p = _Plain(spark, sf_dir)
    return _r(exponential.sensitivity(p.zones, p.dist), "zone_id", sensitivity="sensitivity")


@query(chain("dense") + "select cell_id i, 1.0::double total from c")
def kernel_rowsums(spark, sf_dir):
    return _r(_Plain(spark, sf_dir).kernel.groupBy("i").agg(F.sum("k").alias("s")), "i", total="s")


_BY_TYPE = _SPARSE.replace("'sparse' domain_id", "'type:'||event_type domain_id")


@query(f"with {_BY_TYPE}, {_FIRST}, c as (select * from raw where cell_id<2), {_PAIRS}, g as (select domain_id, exp(0.05*max(d)) r from d group by all) select domain_id, i, j, round(case when i=j then r else 1 end/(1+r),4) k from d join g using (domain_id)")
def lp_geo_toy2(spark, sf_dir):
    """Domains of two cells with equal priors, where the programme has a closed form."""
    cells = domains.by_type(spark, sf_dir, 2).withColumns({"prior": F.lit(0.5), "eps": F.lit(EPS)})
    return exponential.lp_kernel(cells, 0.05, 0.0).select("domain_id", "i", "j", F.round("k", 4).alias("k"))


@query("select 'dense' domain_id, true ok, true optimal")
def lp_geo_feasible(spark, sf_dir):
    cells = _cells(spark, sf_dir)
    k = exponential.lp_kernel(cells, 0.3)
    cert = k.groupBy("domain_id").agg((F.max("gap") <= 1e-3 * F.max("loss")).alias("optimal"))
    return metrics.geoind_all_pairs(k, geometry.pairs(cells), 0.3).join(cert, "domain_id").select("domain_id", "ok", "optimal")


@query("select 'dense' domain_id, true ok, true bound_met")
def lp_joint_feasible(spark, sf_dir):
    cells = _cells(spark, sf_dir)
    dist = geometry.pairs(cells)
    k = exponential.lp_kernel(cells, 0.6, 0.05, 3.0)
    return metrics.geoind_all_pairs(k, dist, 0.6).join(metrics.exp_err(k, cells, dist), "domain_id").select("domain_id", "ok", (F.col("exp_err") >= 3.0 - 1e-3).alias("bound_met"))


_LP_GRID = "(select unnest(['dense','sparse']) domain_id), (select unnest([" + ",".join(f"{e}::double" for e in experiments.EPS_DENSE) + "]) eps_g), (select unnest(['geo','joint']) programme)"


@query(f"select domain_id, eps_g, programme, 'solved' status, true gap_ok, true residual_ok, true error_ok from {_LP_GRID}")
def lp_gap(spark, sf_dir):
    got = experiments.lp_grid(spark, sf_dir).where("eps_g > 0")
    error_ok = (F.col("programme") == "geo") | (F.col("exp_err") >= F.col("target") - 1e-4)
    return got.select("domain_id", "eps_g", "programme", "status", (F.col("gap") <= 1e-3 * F.greatest("loss", F.lit(0.1))).alias("gap_ok"), (F.col("residual") < 1e-6).alias("residual_ok"), error_ok.alias("error_ok"))


@query("select unnest(['dense','dense','sparse','sparse']) domain_id, unnest(['geo','joint','geo','joint']) programme, true meets, true least")
def lp_tuned_least(spark, sf_dir):
    got = experiments.lp_grid(spark, sf_dir, ())
    return got.select("domain_id", "programme", (F.abs(F.col("exp_err") - F.col("target")) <= 0.0051).alias("meets"), (F.col("below") > F.col("target") + 0.005).alias("least"))


@query("select unnest(['dense','sparse']) domain_id, true ok")
def spanner_stretch(spark, sf_dir):
    return experiments.lp_grid(spark, sf_dir, ()).where("programme = 'geo'").select("domain_id", (F.col("stretch") <= 1.05 + 1e-9).alias("ok"))


# ---- adversary and measures ----------------------------------------------------------------------------------------

_ALL = (_PAIRS, _ZONES, _STATS, _KERNEL, _JOINT)


@query(chain("dense", *_ALL) + "select jw.j, jw.i, round(w/pr,6) post from jw join ev using (domain_id, j)")
def posterior(spark, sf_dir):
    p = _Plain(spark, sf_dir)
    return _r(attack.posterior(p.kernel, p.cells), "j", "i", post="post")


@query(chain("dense", *_ALL, _OPT) + "select j, guess_opt, round(cost,6) cost from o")
def attack_optimal(spark, sf_dir):
    p = _Plain(spark, sf_dir)
    return _r(attack.optimal(p.kernel, p.cells, p.dist), "j", "guess_opt", cost="cost")


@query(chain("dense", *_ALL, _MAP) + "select j, guess_map, round(w,6) w from bm")
def attack_bayesian(spark, sf_dir):
    p = _Plain(spark, sf_dir)
    return _r(attack.bayesian(p.kernel, p.cells), "j", "guess_map", w="w")


def _zone_attack_sql(narrow: str) -> str:
    return chain("dense", *_ALL) + f""", zg as (select z.zone_id, jw.j, d.j g, sum(w*d.d) cost from jw join z on z.cell_id=jw.i join d on d.i=jw.i {narrow} group by all), rz as (select *, row_number() over (partition by zone_id, j order by round(cost,12), g) rn from zg) select zone_id, j, g guess_opt, round(cost,6) cost from rz where rn=1"""


@query(_zone_attack_sql(""))
def attack_known_zone(spark, sf_dir):
    p = _Plain(spark, sf_dir)
    return _r(attack.known_zone(p.kernel, p.cells, p.dist, p.zones), "zone_id", "j", "guess_opt", cost="cost")


@query(_zone_attack_sql("join z zn on zn.zone_id=z.zone_id and zn.cell_id=d.j"))
def attack_narrow(spark, sf_dir):
    p = _Plain(spark, sf_dir)
    return _r(attack.known_zone(p.kernel, p.cells, p.dist, p.zones, narrow=True), "zone_id", "j", "guess_opt", cost="cost")


@query(chain("dense", *_ALL, _OPT) + "select j, round(cost/pr,6) exper from o join ev using (domain_id, j)")
def exper_by_report(spark, sf_dir):
    p = _Plain(spark, sf_dir)
    return _r(metrics.exper_by_report(p.kernel, p.cells, p.dist), "j", exper="exper")


@query(chain("dense") + "select cell_id j, true ok from c")
def exper_bound_holds(spark, sf_dir):
    p = _Plain(spark, sf_dir)
    return metrics.exper_bound(p.kernel, p.cells, p.dist, p.zones, p.stats).select("j", "ok")


@query(chain("dense", *_ALL, _OPT) + "select round(sum(cost),6) exp_err from o")
def exp_err(spark, sf_dir):
    p = _Plain(spark, sf_dir)
    return _r(metrics.exp_err(p.kernel, p.cells, p.dist), exp_err="exp_err")


@query(chain("dense", *_ALL) + "select round(sum(w*d.d),6) q_loss from jw join d using (domain_id, i, j)")
def q_loss(spark, sf_dir):
    p = _Plain(spark, sf_dir)
    return _r(metrics.q_loss(p.kernel, p.cells, p.dist), q_loss="q_loss")


@query(chain("dense", *_ALL) + "select i, round(sum(k*d.d),6) loss from k join d using (domain_id, i, j) group by all")
def q_loss_by_cell(spark, sf_dir):
    p = _Plain(spark, sf_dir)
    return _r(metrics.q_loss_by_cell(p.kernel, p.dist), "i", loss="loss")


@query(chain("dense", *_ALL, _OPT) + "select k.i, round(sum(k*d.d),6) avg_err from k join o using (domain_id, j) join d on d.i=k.i and d.j=o.guess_opt group by all")
def avg_err(spark, sf_dir):
    p = _Plain(spark, sf_dir)
    return _r(metrics.avg_err(p.kernel, p.cells, p.dist), "i", avg_err="avg_err")


_PS = "ps as (select k.i, sum(case when guess_map=k.i then k else 0 end) p_s from k join bm using (domain_id, j) group by all)"


@query(chain("dense", *_ALL, _MAP, _PS) + "select i, round(p_s,6) p_s from ps")
def success_prob(spark, sf_dir):
    p = _Plain(spark, sf_dir)
    return _r(metrics.success(p.kernel, p.cells), "i", p_s="p_s")


@query(chain("dense", *_ALL, _MAP, _PS) + "select threshold, round(avg(case when p_s>threshold then 1.0::double else 0.0::double end),6) share from ps, (select unnest([0.1::double,0.2::double,0.5::double]) threshold) group by all")
def success_thresholds(spark, sf_dir):
    p = _Plain(spark, sf_dir)
    return _r(metrics.success_over(metrics.success(p.kernel, p.cells), (0.1, 0.2, 0.5)), "threshold", share="share")


@query(chain("dense", _PAIRS, _ZONES, _STATS) + "select round(sum(mass*reach)/sum(mass),6) avg_reach from st")
def avg_reach_blocks(spark, sf_dir):
    return _r(metrics.avg_reach(_Plain(spark, sf_dir).stats), avg_reach="avg_reach")


@query(chain("dense", *_ALL) + ", x as (select zone_id, k.j, max(ln(k))-min(ln(k)) r from k join z on z.cell_id=k.i group by all) select zone_id, round(max(r),6) worst, true ok from x group by all")
def dp_audit_zone(spark, sf_dir):
    p = _Plain(spark, sf_dir)
    return _r(metrics.dp_audit(p.kernel, p.zones, p.stats), "zone_id", "ok", worst="worst")


@query(chain("dense", _ZONES) + "select distinct zone_id, true ok from z")
def geoind_audit(spark, sf_dir):
    p = _Plain(spark, sf_dir)
    return metrics.geoind_audit(p.kernel, p.zones, p.stats, p.dist).select("zone_id", "ok")


@query(chain("dense", *_ALL) + """, x as (select zone_id, k.j, max(ln(k)) hi, min(ln(k)) lo from k join z on z.cell_id=k.i group by all), y as (select a.zone_id za, b.zone_id zb, max(a.hi-b.lo) worst from x a join x b using (j) group by all)
 select za, zb, round(worst,6) worst, round((select max(d) from d)*(1/sa.reach+1/sb.reach)/2,6) bound, true ok from y join st sa on sa.zone_id=za join st sb on sb.zone_id=zb""")
def weak_dp_audit(spark, sf_dir):
    p = _Plain(spark, sf_dir)
    return _r(metrics.weak_dp_audit(p.kernel, p.zones, p.stats, p.dist), "za", "zb", "ok", worst="worst", bound="bound")


@query("select 'dense' domain_id, true ok")
def weak_dp_domain(spark, sf_dir):
    p = _Plain(spark, sf_dir)
    return metrics.weak_dp_domain(p.kernel, p.stats, p.dist).select("domain_id", "ok")


@query("select d domain_id, s scheme, true breaks_budget from (select unnest(['dense','sparse']) d), (select unnest(['adaptive','adaptive_outer']) s)")
def dp_audit_adaptive(spark, sf_dir):
    return experiments.audit_adaptive(spark, sf_dir).select("domain_id", "scheme", "breaks_budget")


@query()
def bound_audit_adaptive(spark, sf_dir):
    """The predecessor's reports against the error bound, with the worst log ratio."""
    return experiments.audit_adaptive(spark, sf_dir).select("domain_id", "scheme", "worst", "min_exper", "breaks_bound")


# ---- sampling and crowdsourcing ------------------------------------------------------------------------------------


def _inside(spark, sf_dir):
    cells = _cells(spark, sf_dir, "sparse")
    return cells, _pings(spark, sf_dir).join(cells.select("domain_id", "cell_id", "cx", "cy"), ["cx", "cy"]).select("domain_id", "event_id", "ts", "user_id", "event_type", "cell_id")


_IN = _PINGS + ", ip as (select event_id, ts, user_id, event_type, cell_id from pg join c using (cx, cy))"
_CDF = "cd as (select i, j, sum(k) over (partition by i order by j rows unbounded preceding) cdf from k)"


@query(chain("sparse", *_ALL, _IN, _CDF) + f", q as (select ip.*, {_uniform_sql('event_id', 42)} u from ip), w as (select q.event_id, q.cell_id, least(count(*) filter (where cdf<=u), 49) reported_cell from q join cd on cd.i=q.cell_id group by q.event_id, q.cell_id) select * from w")
def sample_reports(spark, sf_dir):
    p = _Plain(spark, sf_dir, "sparse")
    _, at = _inside(spark, sf_dir)
    return sample.draw(at, exponential.packed(p.kernel), 42, 2500).select("event_id", "cell_id", "reported_cell")


_GUMBEL = f"""sk as (select z.cell_id, eps_zone/(2*reach) scale from z join st using (zone_id)), pv as (select event_id, c.cell_id, c.x, c.y, scale from pg join c on c.cx=pg.cx and c.cy=pg.cy join sk on sk.cell_id=c.cell_id),
 gv as (select event_id, pv.cell_id, o.cell_id out_id, -scale*sqrt(pow(o.x-pv.x,2)+pow(o.y-pv.y,2))-ln(-ln(greatest({_uniform_sql("(event_id||'/'||o.cell_id)", 42)},1e-300))) v from pv, c o) select event_id, cell_id, arg_max(out_id, v) reported_cell from gv group by all"""


@query(chain("sparse", _PAIRS, _ZONES, _STATS, _PINGS, _GUMBEL.rsplit(" select ", 1)[0]) + " select " + _GUMBEL.rsplit(" select ", 1)[1])
def sample_gumbel(spark, sf_dir):
    p = _Plain(spark, sf_dir, "sparse")
    return sample.draw_gumbel(_inside(spark, sf_dir)[1], p.cells, p.zones, p.stats, 42).select("event_id", "cell_id", "reported_cell")


@query()
def sample_alias(spark, sf_dir):
    p = _Plain(spark, sf_dir, "sparse")
    return sample.draw_alias(_inside(spark, sf_dir)[1], sample.alias_rows(p.kernel), 42).select("event_id", "cell_id", "reported_cell")


@query(SQL["sample_reports"].replace(" select * from w", """, gn as (select cell_id, count(*) n from w group by all), go as (select cell_id, reported_cell j, count(*) o from w group by all)
 select gn.cell_id, gn.n, round(sum(pow(coalesce(o,0)-gn.n*k,2)/(gn.n*k)),6) chi2, count(*) cells from gn join k on i=gn.cell_id left join go on go.cell_id=i and go.j=k.j group by gn.cell_id, gn.n"""))
def sample_goodness(spark, sf_dir):
    p = _Plain(spark, sf_dir, "sparse")
    reports = sample.draw(_inside(spark, sf_dir)[1], exponential.packed(p.kernel), 42)
    return _r(sample.goodness(reports, p.kernel), "cell_id", "n", "cells", chi2="chi2")


@query("with " + ", ".join([cells_sql("sparse"), _PINGS]) + " select event_id from pg where exists (select 1 from c where c.cx=pg.cx and c.cy=pg.cy)")
def pings_in_domain(spark, sf_dir):
    return domains.inside(_pings(spark, sf_dir), _cells(spark, sf_dir, "sparse")).select("event_id")


@query("with " + ", ".join([cells_sql("sparse"), _PINGS]) + " select event_id from pg where not exists (select 1 from c where c.cx=pg.cx and c.cy=pg.cy)")
def pings_outside(spark, sf_dir):
    return domains.outside(_pings(spark, sf_dir), _cells(spark, sf_dir, "sparse")).select("event_id")


_TASKS = "tk as (select event_id task_id, ts, cell_id task_cell from ip where event_type='purchase' order by event_id desc limit 100)"
_WORK = f"""wk as (select task_id, task_cell, ip.user_id||'/'||ip.event_type worker_id, arg_max(ip.event_id, ip.event_id) event_id, arg_max(ip.cell_id, ip.event_id) cell_id from tk join ip on ip.ts<=tk.ts and ip.event_type<>'purchase' group by all),
 ws as (select *, row_number() over (partition by task_id order by {_uniform_sql("task_id||'-'||worker_id", 5)}, worker_id) rn from wk)"""


@query(chain("sparse", _IN, _TASKS, _WORK) + "select task_id, worker_id, event_id, cell_id from ws where rn<=30")
def workers_asof(spark, sf_dir):
    _, at = _inside(spark, sf_dir)
    return crowd.workers_asof(crowd.tasks(at), at).select("task_id", "worker_id", "event_id", "cell_id")


@query(chain("sparse", _IN, _TASKS) + "select task_id, ip.event_id, ip.user_id from tk join ip on cast(floor(epoch(ip.ts)) as bigint)<=cast(floor(epoch(tk.ts)) as bigint) and cast(floor(epoch(ip.ts)) as bigint)>cast(floor(epoch(tk.ts)) as bigint)-600")
def tasks_interval_join(spark, sf_dir):
    _, at = _inside(spark, sf_dir)
    return crowd.pings_near(crowd.tasks(at), at).select("task_id", "event_id", "user_id")


@query(chain("sparse", _PAIRS, _IN, _TASKS, _WORK) + ", nn as (select ws.task_id, worker_id, row_number() over (partition by ws.task_id order by round(d.d,9), worker_id) rn from ws join d on d.i=ws.task_cell and d.j=ws.cell_id where ws.rn<=30) select task_id, worker_id, rn from nn where rn<=3")
def three_nearest_workers(spark, sf_dir):
    cells, at = _inside(spark, sf_dir)
    work = crowd.workers_asof(crowd.tasks(at), at)
    return crowd.assign(work, geometry.pairs(cells), by="cell_id").select("task_id", "worker_id", F.col("rn").cast("long").alias("rn"))


# ---- surrounding operators -----------------------------------------------------------------------------------------


@query("with t as (select l_suppkey, count(distinct (cast(l_quantity as int), cast(floor(l_extendedprice/2000) as int))) cells from lineitem group by all) select n_regionkey, n_nationkey, count(*) tiles, sum(cells)::bigint cells from t join supplier on s_suppkey=l_suppkey join nation on n_nationkey=s_nationkey group by rollup (n_regionkey, n_nationkey)")
def report_rollup_region(spark, sf_dir):
    df = read(spark, sf_dir, "lineitem", "l_suppkey", "l_quantity", "l_extendedprice")
    t = df.groupBy("l_suppkey").agg(F.countDistinct(F.col("l_quantity").cast("int"), F.floor(F.col("l_extendedprice") / 2000)).alias("cells"))
    s = read(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey")
    n = read(spark, sf_dir, "nation", "n_nationkey", "n_regionkey")
    joined = t.join(s, F.col("l_suppkey") == F.col("s_suppkey")).join(F.broadcast(n), F.col("s_nationkey") == F.col("n_nationkey"))
    return joined.rollup("n_regionkey", "n_nationkey").agg(F.count("*").alias("tiles"), F.sum("cells").alias("cells"))


@query(chain("sparse", _IN) + "select event_type, cell_id, count(*) pings from ip group by cube (event_type, cell_id)")
def report_cube(spark, sf_dir):
    return _inside(spark, sf_dir)[1].cube("event_type", "cell_id").agg(F.count("*").alias("pings"))


@query("with o as (select *, case when epoch(ts)-epoch(lag(ts) over (partition by user_id order by ts))<1800 then 0 else 1 end s from events), q as (select *, sum(s) over (partition by user_id order by ts, event_id rows unbounded preceding) g from o) select user_id, cast(floor(epoch(min(ts))) as bigint) start_s, count(*) pings from q group by user_id, g")
def reports_sessions(spark, sf_dir):
    df = live.trips(read(spark, sf_dir, "events", "event_id", "ts", "user_id"))
    return df.select("user_id", F.unix_timestamp(F.col("start").cast("timestamp")).alias("start_s"), "pings")


@query(chain("sparse", _IN) + "select epoch(date_trunc('hour', ts))::bigint start_s, cell_id, count(*) pings from ip group by all")
def reports_tumbling(spark, sf_dir):
    df = _inside(spark, sf_dir)[1].groupBy(F.window("ts", "1 hour").alias("w"), "cell_id").agg(F.count("*").alias("pings"))
    return df.select(F.unix_timestamp(F.col("w.start").cast("timestamp")).alias("start_s"), "cell_id", "pings")


@query(chain("sparse", _IN) + ", e as (select *, (cast(floor(epoch(ts)) as bigint)//21600)*21600 b from ip) select b-21600*k start_s, cell_id, count(*) pings from e, (select unnest(range(4)) k) group by all")
def reports_sliding(spark, sf_dir):
    df = _inside(spark, sf_dir)[1].groupBy(F.window("ts", "1 day", "6 hours").alias("w"), "cell_id").agg(F.count("*").alias("pings"))
    return df.select(F.unix_timestamp(F.col("w.start").cast("timestamp")).alias("start_s"), "cell_id", "pings")


@query(chain("dense", *_ALL, _MAP, _PS) + "select round(quantile_cont(p_s,0.25),6) q1, round(quantile_cont(p_s,0.5),6) q2, round(quantile_cont(p_s,0.75),6) q3, round(stddev_samp(p_s),6) sd from ps")
def success_percentiles(spark, sf_dir):
    p = _Plain(spark, sf_dir)
    s = metrics.success(p.kernel, p.cells)
    return s.agg(*(F.round(F.percentile("p_s", q), 6).alias(f"q{i}") for i, q in enumerate((0.25, 0.5, 0.75), 1)), F.round(F.stddev_samp("p_s"), 6).alias("sd"))


@query(chain("dense", _ZONES) + "select zone_id, count(*) size, min(cell_id) first_cell, max(cell_id) last_cell from z group by all")
def zone_arrays(spark, sf_dir):
    df = zoning.zone_arrays(zoning.blocks_by_id(_cells(spark, sf_dir), 5))
    return df.select("zone_id", F.size("cells").cast("long").alias("size"), F.array_min("cells").alias("first_cell"), F.array_max("cells").alias("last_cell"))


@query("select c_custkey, case c_mktsegment when 'AUTOMOBILE' then 'conservative' when 'BUILDING' then 'conservative' when 'FURNITURE' then 'moderate' else 'liberal' end level_name from customer")
def level_map_lookup(spark, sf_dir):
    table = F.create_map(*(F.lit(x) for kv in domains.SEGMENT_LEVEL.items() for x in kv))
    return read(spark, sf_dir, "customer", "c_custkey", "c_mktsegment").select("c_custkey", F.element_at(table, F.col("c_mktsegment")).alias("level_name"))


@query("select event_id, cast(props->>'$.k' as bigint) k from events")
def props_json(spark, sf_dir):
    return read(spark, sf_dir, "events", "event_id", "props").select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


@query("with " + cells_sql("dense") + ", dd as (select cx, cy from raw), " + _PINGS + ", ss as (select distinct cx, cy from pg) select 'both' which, count(*) n from (select * from dd intersect select * from ss) union all select 'only_dense', count(*) from (select * from dd except select * from ss)")
def set_ops_cells(spark, sf_dir):
    a = domains.dense(spark, sf_dir).select("cx", "cy")
    b = _pings(spark, sf_dir).select("cx", "cy").distinct()
    both, only = a.intersect(b), a.subtract(b)
    return both.agg(F.count("*").alias("n")).select(F.lit("both").alias("which"), "n").unionByName(only.agg(F.count("*").alias("n")).select(F.lit("only_dense").alias("which"), "n"))


@query(f"select event_id, round({_uniform_sql('event_id', 3)},9) u from events")
def uniform_portable(spark, sf_dir):
    return read(spark, sf_dir, "events", "event_id").select("event_id", F.round(portable_uniform("event_id", 3), 9).alias("u"))


# ---- experiments ---------------------------------------------------------------------------------------------------


@query()
def exp_reach_grid(spark, sf_dir):
    return experiments.reach_grid(spark, sf_dir)


@query()
def exp_reach_change(spark, sf_dir):
    return experiments.changes(experiments.reach_grid(spark, sf_dir), "zonal_curve", "zonal_qkm", "avg_reach")


@query()
def exp_joint_change(spark, sf_dir):
    return experiments.changes(experiments.joint_loss(spark, sf_dir), "joint_lp_qkm", "zonal_qkm", "q_loss")


@query()
def exp_weight_ablation(spark, sf_dir):
    return experiments.weight_ablation(spark, sf_dir)


@query()
def exp_skew_avgerr(spark, sf_dir):
    return experiments.skew(spark, sf_dir, "avg_err")


@query()
def exp_skew_success(spark, sf_dir):
    return experiments.skew(spark, sf_dir, "success")


@query()
def exp_table3(spark, sf_dir):
    return experiments.table3(spark, sf_dir)


@query()
def exp_em_maxreach(spark, sf_dir):
    return experiments.em_maxreach(spark, sf_dir)


@query("select unnest(['dense','sparse']) domain_id, true ok")
def exp_em_calibrated(spark, sf_dir):
    return experiments.em_calibrated(spark, sf_dir).select("domain_id", "ok")


@query()
def exp_vary_eps(spark, sf_dir):
    return experiments.vary_eps(spark, sf_dir)


@query()
def exp_vary_emin(spark, sf_dir):
    return experiments.vary_emin(spark, sf_dir)


@query()
def exp_joint_loss(spark, sf_dir):
    return experiments.joint_loss(spark, sf_dir)


@query()
def exp_personal(spark, sf_dir):
    return experiments.personal_gain(spark, sf_dir)


@query()
def exp_wtd(spark, sf_dir):
    return experiments.wtd_grid(spark, sf_dir)


@query()
def tiles_zonal(spark, sf_dir):
    return experiments.tiles_zonal(spark, sf_dir)


_PER_CELL = """ae as (select k.i, sum(k*d.d) avg_err from k join o using (j) join d on d.i=k.i and d.j=guess_opt group by all), su as (select k.i, sum(case when guess_map=k.i then k else 0 end) p_s from k join bm using (j) group by all), lo as (select k.i, sum(k*d.d) loss from k join d on d.i=k.i and d.j=k.j group by all)"""


@query(_curve_query_sql("sparse", [(1.0, 0.1)], _FOUR, last=curve_sql.best()).rsplit(" select '", 1)[0] + ", z as (select 'sparse' domain_id, cell_id, zone_id from bz where cell_id is not null), " + ", ".join([_PAIRS, _STATS, _KERNEL, _JOINT, _OPT, _MAP, _PER_CELL]) + " select 'sparse' domain_id, z.cell_id, z.zone_id, round(reach,6) reach, round(avg_err,6) avg_err, round(p_s,6) p_s, round(loss,6) loss from z join st on st.zone_id=z.zone_id join ae on ae.i=z.cell_id join su on su.i=z.cell_id join lo on lo.i=z.cell_id")
def flagship(spark, sf_dir):
    return experiments.flagship(spark, sf_dir)


# ---- streaming: the result of the stream over the whole table ------------------------------------------------------


def _stream(spark, sf_dir):
    df = live.pings(spark, f"{sf_dir}/event[s].parquet")  # a pattern, as one file is no folder
    return domains.event_cells(df)


@query(SQL["sample_reports"].replace("select * from w", "select event_id, reported_cell from w"))
def stream_reports(spark, sf_dir):
    p = _Plain(spark, sf_dir, "sparse")
    rows = exponential.packed(p.kernel).persist()
    got = live.run_available(live.obfuscate(_stream(spark, sf_dir), p.cells, rows, 42).select("event_id", "reported_cell"), name="reports")
    rows.unpersist()
    return got


@query("select event_id, user_id from events")
def stream_dedup(spark, sf_dir):
    df = live.dedup(live.with_lateness(_stream(spark, sf_dir).unionByName(_stream(spark, sf_dir)), "400 days"))
    return live.run_available(df.select("event_id", "user_id"), name="dedup")


@query(chain("sparse", _IN) + ", e as (select *, (cast(floor(epoch(ts)) as bigint)//21600)*21600 b from ip) select b-21600*k start_s, cell_id, count(*) visits from e, (select unnest(range(4)) k) group by all")
def stream_windowed_prior(spark, sf_dir):
    df = live.windowed_visits(live.with_lateness(_stream(spark, sf_dir)), domains.sparse(spark, sf_dir))
    got = live.run_available(df, "complete", "windows")
    return got.select(F.unix_timestamp(F.col("window_start").cast("timestamp")).alias("start_s"), "cell_id", "visits")


@query(SQL["reports_sessions"])
def stream_session_trips(spark, sf_dir):
    got = live.run_available(live.trips(live.with_lateness(_stream(spark, sf_dir))), "complete", "trips")
    return got.select("user_id", F.unix_timestamp(F.col("start").cast("timestamp")).alias("start_s"), "pings")


@query(SQL["sample_reports"].replace("select * from w", "select user_id, epoch(date_trunc('day', ts))::bigint start_s, count(*) reports, round(count(*)*1.0::double,6) spent from w join ip using (event_id) group by all"))
def stream_budget_spent(spark, sf_dir):
    p = _Plain(spark, sf_dir, "sparse")
    reports = live.obfuscate(live.with_lateness(_stream(spark, sf_dir)), p.cells, exponential.packed(p.kernel), 42)
    got = live.run_available(live.budget_spent(reports, p.cells), "complete", "budget")
    return got.select("user_id", F.unix_timestamp(F.col("window_start").cast("timestamp")).alias("start_s"), "reports", F.round("spent", 6).alias("spent"))


@query(SQL["stream_reports"])
def stream_late(spark, sf_dir):
    """The same reports when the pings come shuffled and in many files: draws are keyed, not ordered."""
    from ..sources.scratch import folder

    at = folder(spark, "replay")
    read(spark, sf_dir, "events").repartition(6, F.xxhash64("event_id")).write.parquet(at)
    p = _Plain(spark, sf_dir, "sparse")
    df = domains.event_cells(live.pings(spark, at, max_files=2))
    return live.run_available(live.obfuscate(df, p.cells, exponential.packed(p.kernel), 42).select("event_id", "reported_cell"), name="late")


# ---- entries for SQL users, cost of a run -----------------------------------------------------------------------------


@query("with " + ", ".join([cells_sql("dense"), _PAIRS, _ZONES, _STATS]) + " select zone_id, round(a_out,6) a_out from st")
def anchor_outer_aggregate(spark, sf_dir):
    p = _Plain(spark, sf_dir)
    table_functions.register(spark)
    points = p.cells.groupBy("domain_id").agg(F.array_sort(F.collect_list(F.struct("x", "y"))).alias("at"))
    members = p.zones.select("domain_id", "cell_id", "zone_id").join(p.cells, ["domain_id", "cell_id"]).join(points, "domain_id")
    got = members.groupBy("domain_id", "zone_id").agg(table_functions.anchor_outer_agg("x", "y", "prior", F.col("at.x"), F.col("at.y")).alias("a_out"))
    return _r(got, "zone_id", a_out="a_out")


_ONE_SETTING = [(1.0, 0.1)]


@query(_curve_query_sql("dense", _ONE_SETTING))
def zones_table_function(spark, sf_dir):
    table_functions.register(spark)
    geometry.rank_on_curve(_cells(spark, sf_dir), ORDERS["dense"], (0,)).createOrReplaceTempView("ranked_cells")
    eps, e_min = _ONE_SETTING[0]
    got = spark.sql(f"SELECT * FROM make_zones(TABLE(ranked_cells) PARTITION BY (domain_id), {eps}D, {e_min}D, 'curve')")
    return _zone_report(got.withColumns({"eps_param": F.lit(eps), "e_min": F.lit(e_min), "rot": F.lit(0)}))


@query("with " + ", ".join([cells_sql("dense"), _PAIRS]) + " select 'pairs' query, count(*) n_rows, true timed, true has_jobs, true has_shuffle from d")
def run_cost(spark, sf_dir):
    got = cost.cost(geometry.pairs(_cells(spark, sf_dir)), "pairs")
    return got.select("query", F.col("rows").alias("n_rows"), (F.col("seconds") > 0).alias("timed"), (F.col("jobs") > 0).alias("has_jobs"), (F.col("shuffle_bytes") > 0).alias("has_shuffle"))
