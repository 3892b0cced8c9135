"""The experiment workloads: parameter grids as one plan each."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import eps_weight, portable_uniform
from ..operators import condition, core, crowd, domains, exponential, geometry, lp, metrics, sample, zoning
from ..sources import read
from ..sources.scratch import materialise
from . import schemes

# The parameter grids.
E_MINS = tuple(round(0.05 * i, 2) for i in range(1, 11))
EPS_DENSE = (*(round(0.1 + 0.2 * i, 1) for i in range(10)), 2.0)
EPS_SPARSE = tuple(round(0.1 + 0.2 * i, 1) for i in range(13))

WTD_E_MINS = (0.1, 0.2)
WTD_SCHEMES = ("zonal_qkm", "joint_lp", "none")

#: Values of the 3 x 3 comparison of zonings; the text names none.
REACH_EPS, REACH_E_MIN = (0.5, 1.0, 1.5), (0.05, 0.1, 0.2)


def both(spark: SparkSession, sf_dir: str, eps: float = 1.0) -> DataFrame:
    """Dense and sparse stand-ins with the printed prior."""
    cells = domains.dense(spark, sf_dir).unionByName(domains.sparse(spark, sf_dir))
    return domains.eps_constant(domains.prior_table2(cells), eps)


def personal(spark: SparkSession, sf_dir: str, seed: int = 11) -> DataFrame:
    return domains.eps_uniform(domains.prior_table2(domains.dense(spark, sf_dir).unionByName(domains.sparse(spark, sf_dir))), seed=seed)


def scalars(measures: DataFrame, *names: str) -> DataFrame:
    return measures.where("cell_id is null").where(F.col("measure").isin(*names) if names else F.lit(True)).select("domain_id", "scheme", "eps_param", "e_min", "measure", F.round("value", 4).alias("value"))


def reach_grid(spark: SparkSession, sf_dir: str, max_samp: int = 20) -> DataFrame:
    """Average reach of both zonings over 3 budgets and 3 error bounds."""
    params = [(e, m) for e in REACH_EPS for m in REACH_E_MIN]
    return scalars(schemes.run(both(spark, sf_dir), ["zonal_curve", "zonal_qkm"], params, max_samp), "avg_reach", "zones", "infeasible")


def weight_curve(spark: SparkSession, sf_dir: str, seed: int = 11) -> DataFrame:
    """The budget weight against eps for a zone at 1.0 and three lambdas, over the budgets of the users in events: U[0.5, 2] to one decimal."""
    users = read(spark, sf_dir, "events", "user_id").groupBy("user_id").agg(F.count("*").alias("pings"))
    users = users.withColumn("eps", F.round(F.lit(0.5) + 1.5 * portable_uniform("user_id", seed), 1))
    df = users.groupBy("eps").agg(F.count("*").alias("users"), F.sum("pings").alias("pings"))
    df = df.withColumn("lam", F.explode(F.array(*(F.lit(x) for x in (0.0, 0.5, 1.0)))))
    return df.select("eps", "lam", "users", "pings", F.round(eps_weight(F.col("eps"), F.lit(1.0), 0.0) + F.col("lam"), 6).alias("weight"))


def weight_ablation(spark: SparkSession, sf_dir: str, e_min: float = 0.1, max_samp: int = 20, seed: int = 11) -> DataFrame:
    """Personal quasi-k-means with and without the weight: loss, reach and the share of cells improved."""
    got = schemes.run(personal(spark, sf_dir, seed), ["personal_qkm_general", "personal_qkm"], [(-1.0, e_min)], max_samp)
    loss = got.where("measure = 'loss'").select("domain_id", "scheme", F.col("cell_id").alias("i"), F.col("value").alias("loss"))
    share = metrics.share_improved(loss.where("scheme = 'personal_qkm_general'").drop("scheme"), loss.where("scheme = 'personal_qkm'").drop("scheme"))
    share = share.select("domain_id", F.lit("personal_qkm").alias("scheme"), F.lit(-1.0).alias("eps_param"), F.lit(e_min).alias("e_min"), F.lit("share_improved").alias("measure"), F.round("share", 4).alias("value"))
    return scalars(got, "q_loss", "exp_err", "avg_reach").unionByName(share)


SKEW = ["zonal_curve", "em_tuned", "geo_lp", "joint_lp"]


def skew(spark: SparkSession, sf_dir: str, measure: str, eps: float = 1.0, e_min: float = 0.05) -> DataFrame:
    """One measure per cell for four mechanisms at equal expected inference error; isolated cells rank last."""
    cells = both(spark, sf_dir, eps)
    got = schemes.run(cells, SKEW, [(eps, e_min)]).where(F.col("measure") == measure)
    far = geometry.isolation(geometry.pairs(cells))
    return got.join(far, ["domain_id", "cell_id"]).select("domain_id", "scheme", "cell_id", "isolation_rank", F.round("value", 4).alias(measure))


def table3(spark: SparkSession, sf_dir: str, eps: float = 1.0, e_min: float = 0.05) -> DataFrame:
    """Shares of cells above each success threshold, the loss and the achieved error of four mechanisms, one column each."""
    got = materialise(schemes.run(both(spark, sf_dir, eps), SKEW, [(eps, e_min)]), "table3")  # read twice
    p_s = got.where("measure = 'success'").select(F.concat_ws("|", "domain_id", "scheme").alias("domain_id"), F.col("value").alias("p_s"))
    over = metrics.success_over(p_s).select(F.split("domain_id", r"\|")[0].alias("domain_id"), F.split("domain_id", r"\|")[1].alias("scheme"), F.concat(F.lit("over_"), F.format_number(F.col("threshold") * 100, 0)).alias("measure"), F.col("share").alias("value"))
    rest = got.where("measure in ('q_loss', 'exp_err', 'target', 'reach', 'eps_g', 'gap', 'residual', 'unsolved', 'infeasible')").select("domain_id", "scheme", "measure", "value")
    return over.unionByName(rest).groupBy("domain_id", "measure").pivot("scheme", SKEW).agg(F.round(F.first("value"), 4))


def em_calibrated(spark: SparkSession, sf_dir: str, eps: float = 1.0, e_min: float = 0.05) -> DataFrame:
    """The constant reach that gives the zonal scheme's error, and how near it comes."""
    got = schemes.run(both(spark, sf_dir, eps), ["em_tuned"], [(eps, e_min)])
    df = got.where("cell_id is null").groupBy("domain_id").pivot("measure", ["reach", "exp_err", "target", "q_loss"]).agg(F.first("value"))
    return df.select("domain_id", F.round("reach", 3).alias("reach"), F.round("exp_err", 3).alias("exp_err"), F.round("q_loss", 3).alias("q_loss"), (F.abs(F.col("exp_err") - F.col("target")) <= 0.005).alias("ok"))


def em_maxreach(spark: SparkSession, sf_dir: str, eps: float = 1.0, e_min: float = 0.05) -> DataFrame:
    """The constant mechanism with the largest zone reach against the zonal one."""
    got = schemes.run(both(spark, sf_dir, eps), ["zonal_curve", "em_maxreach"], [(eps, e_min)])
    return scalars(got, "q_loss", "exp_err", "reach", "max_reach", "min_exper")


def vary_eps(spark: SparkSession, sf_dir: str, e_min: float = 0.2, max_samp: int = 20, dense_eps: tuple = EPS_DENSE, sparse_eps: tuple = EPS_SPARSE) -> DataFrame:
    """Error and loss of both zonings over the budgets of each set."""
    cells = both(spark, sf_dir)
    out = [schemes.run(cells.where(F.col("domain_id") == name), ["zonal_curve", "zonal_qkm"], [(e, e_min) for e in grid], max_samp) for name, grid in (("dense", dense_eps), ("sparse", sparse_eps))]
    return scalars(out[0].unionByName(out[1]), "exp_err", "q_loss", "avg_reach", "infeasible")


def vary_emin(spark: SparkSession, sf_dir: str, eps: float = 1.0, max_samp: int = 20, e_mins: tuple = E_MINS) -> DataFrame:
    return scalars(schemes.run(both(spark, sf_dir), ["zonal_curve", "zonal_qkm"], [(eps, m) for m in e_mins], max_samp), "exp_err", "q_loss", "avg_reach", "infeasible")


def joint_grid(name: str) -> list[tuple[float, float]]:
    """Budgets of a set at e_min 0.2, then error bounds at eps 1.0."""
    return [(e, 0.2) for e in (EPS_DENSE if name == "dense" else EPS_SPARSE)] + [(1.0, m) for m in E_MINS]


def joint_loss(spark: SparkSession, sf_dir: str, params: list[tuple[float, float]] | None = None, max_samp: int = 20) -> DataFrame:
    """Quasi-k-means zoning against the joint programme at equal expected inference error."""
    cells = both(spark, sf_dir)
    out = [schemes.run(cells.where(F.col("domain_id") == name), ["zonal_qkm", "joint_lp_qkm"], params or joint_grid(name), max_samp) for name in ("dense", "sparse")]
    return scalars(out[0].unionByName(out[1]), "exp_err", "q_loss", "target", "eps_g", "gap", "residual", "unsolved", "infeasible")


def lp_grid(spark: SparkSession, sf_dir: str, eps_gs: tuple = EPS_DENSE, delta: float = 0.05) -> DataFrame:
    """Both programmes over a grid of eps_g, one task each: status, gap and residual, loss and error, and the spanner's worst stretch.

    The joint programme asks for half of the largest error there is; ``eps_g`` 0 stands for the least that meets it.
    """
    table = spark.createDataFrame([(e, p) for e in (0.0, *eps_gs) for p in ("geo", "joint")], "eps_g double, programme string")
    live = both(spark, sf_dir).select("domain_id", "cell_id", "x", "y", "prior").crossJoin(F.broadcast(table))

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("cell_id").reset_index(drop=True)
        p, d = pdf["prior"].to_numpy(), core.distances(pdf["x"].to_numpy(), pdf["y"].to_numpy())
        e, name = float(pdf["eps_g"].iloc[0]), pdf["programme"].iloc[0]
        target = 0.5 * float((d @ p).min())
        used = e or lp.least_eps_g(p, d, target, delta)
        got = lp.solve(p, d, used, delta, target if name == "joint" else None)
        below = np.nan if e else lp.exp_err(lp.solve(p, d, 0.97 * used, delta).kernel, p, d)
        path = np.full(d.shape, np.inf)
        np.fill_diagonal(path, 0.0)
        for a, b in lp.greedy_spanner(d, 1 + delta):
            path[a, b] = path[b, a] = d[a, b]
        for k in range(len(p)):
            path = np.minimum(path, path[:, [k]] + path[[k], :])
        off = d > 0
        row = {"domain_id": pdf["domain_id"].iloc[0], "eps_g": e, "programme": name, "status": got.status, "gap": got.gap, "residual": got.residual, "loss": got.loss, "exp_err": lp.exp_err(got.kernel, p, d), "target": target, "below": below, "stretch": float((path[off] / d[off]).max())}
        return pd.DataFrame([row])

    schema = "domain_id string, eps_g double, programme string, status string, gap double, residual double, loss double, exp_err double, target double, below double, stretch double"
    return live.repartition(64, "domain_id", "eps_g", "programme").groupBy("domain_id", "eps_g", "programme").applyInPandas(one, schema)


def changes(measures: DataFrame, base: str, other: str, *names: str) -> DataFrame:
    """Mean and largest relative change over the settings of a grid."""
    got = metrics.relative(measures.where(F.col("measure").isin(*names)), base, other)
    return got.select("domain_id", "measure", F.round("mean_change", 4).alias("mean_change"), F.round("max_change", 4).alias("max_change"), "settings")


def personal_gain(spark: SparkSession, sf_dir: str, e_mins: tuple = E_MINS, max_samp: int = 20, seed: int = 11) -> DataFrame:
    """Two personal schemes against two with the least budget for all."""
    names = ["personal_curve", "unified_curve", "personal_qkm", "unified_qkm"]
    return scalars(schemes.run(personal(spark, sf_dir, seed), names, [(-1.0, m) for m in e_mins], max_samp), "exp_err", "q_loss", "avg_reach", "infeasible")


_KERNELS = "domain_id string, eps_param double, e_min double, scheme string, i long, j long, k double"


def _wtd_kernels(cells: DataFrame, params: DataFrame, max_samp: int, delta: float = 0.05) -> DataFrame:
    """Zonal kernel and the joint programme tuned to its error, one task for each domain and parameter pair."""
    live = cells.select("domain_id", "cell_id", "x", "y", "prior").join(F.broadcast(params), "domain_id")

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("cell_id").reset_index(drop=True)
        xy, p, ids, n = pdf[["x", "y"]].to_numpy(), pdf["prior"].to_numpy(), pdf["cell_id"].to_numpy(), len(pdf)
        d = core.distances(xy[:, 0], xy[:, 1])
        e, m = float(pdf["eps_param"].iloc[0]), float(pdf["e_min"].iloc[0])
        dom = schemes.Domain(p, xy, d, np.full(n, e), [])
        zone = schemes.zoned(dom, "qkm", dom.eps, m, None, max_samp)
        made = {}
        if zone is not None:
            made["zonal_qkm"] = core.kernel(core.zonal_scale(zone, dom.eps, d), d)
            target = lp.exp_err(made["zonal_qkm"], p, d)
            got, _ = lp.tuned(p, d, target, delta, target)
            if got.status == "solved":  # else its distance stays null
                made["joint_lp"] = got.kernel
            made["none"] = np.eye(n)
        rows = [(pdf["domain_id"].iloc[0], e, m, name, int(i), int(j), float(k[a, b])) for name, k in made.items() for a, i in enumerate(ids) for b, j in enumerate(ids)]
        return pd.DataFrame(rows, columns=["domain_id", "eps_param", "e_min", "scheme", "i", "j", "k"])

    # The rows are few but the work is long: an explicit count keeps them from being coalesced into one task.
    return live.repartition(64, "domain_id", "eps_param", "e_min").groupBy("domain_id", "eps_param", "e_min").applyInPandas(one, _KERNELS)


def wtd_grid(spark: SparkSession, sf_dir: str, params: list[tuple[str, float, float]] | None = None, n_tasks: int = 100, max_samp: int = 20, seed: int = 5) -> DataFrame:
    """Travel distance of the three workers assigned by reported cells: zonal, joint programme at the same error, and no privacy.

    ``params`` are (domain, eps, e_min); by default both domains, e_min 0.1 and 0.2, all budgets.
    An infeasible setting has a null distance.
    """
    params = params or [(name, e, m) for name, grid in (("dense", EPS_DENSE), ("sparse", EPS_SPARSE)) for e in grid for m in WTD_E_MINS]
    table = spark.createDataFrame([(n, float(e), float(m)) for n, e, m in params], "domain_id string, eps_param double, e_min double")
    cells = both(spark, sf_dir).join(F.broadcast(table.select("domain_id").distinct()), "domain_id", "left_semi")
    kernels = materialise(_wtd_kernels(cells, table, max_samp), "wtd-kernels")
    events = domains.event_cells(read(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type", "value", "props"))
    at = events.join(cells.select("domain_id", "cell_id", "cx", "cy"), ["cx", "cy"]).drop("props", "value")
    task = None
    for name in sorted({n for n, _, _ in params}):  # two domains; each has its own last tasks
        own = crowd.tasks(at.where(F.col("domain_id") == name), n_tasks)
        task = own if task is None else task.unionByName(own)
    work = crowd.workers_asof(task, at, seed=seed)
    # One domain for each setting and scheme: the operators below are keyed by domain_id.
    names = table.crossJoin(spark.createDataFrame([(x,) for x in WTD_SCHEMES], "scheme string"))
    key = F.concat_ws("|", "domain_id", "eps_param", "e_min", "scheme")
    keyed = F.broadcast(names.select("domain_id", key.alias("key")))
    dist = geometry.pairs(cells).join(keyed, "domain_id").drop("domain_id").withColumnRenamed("key", "domain_id")
    work = work.join(keyed, "domain_id").drop("domain_id").withColumnRenamed("key", "domain_id")
    seen = sample.draw(work, exponential.packed(kernels.select(key.alias("domain_id"), "i", "j", "k")), seed)
    got = crowd.wtd(crowd.assign(seen, dist), dist).withColumnRenamed("domain_id", "key")
    return names.withColumn("key", key).join(got, "key", "left").select("domain_id", "scheme", "eps_param", "e_min", F.round("wtd", 4).alias("wtd"), "tasks")


def crowd_wtd(spark: SparkSession, sf_dir: str, e_min: float = 0.1, eps: float = 1.0, n_tasks: int = 100, seed: int = 5) -> DataFrame:
    """One setting of the sparse domain."""
    return wtd_grid(spark, sf_dir, [("sparse", eps, e_min)], n_tasks, seed=seed).select("domain_id", "scheme", "wtd", "tasks")


def audit_adaptive(spark: SparkSession, sf_dir: str, eps: float = 1.0, e_min: float = 0.1) -> DataFrame:
    """The predecessor's two flaws on each domain: log ratios above the budget, and reports below the error bound."""
    cells = both(spark, sf_dir, eps)
    ranked = geometry.rank_on_curve(cells)
    dist = geometry.pairs(cells)
    seg = condition.segments(ranked)
    out = []
    for name, kind in (("adaptive", "a_in"), ("adaptive_outer", "a_out")):
        per = zoning.zone_per_cell(seg, ranked, e_min, kind=kind)
        k = exponential.adaptive_kernel(per, dist)
        # Neighbours: cells of the row's own zone.
        member = per.select("domain_id", F.col("cell_id").alias("i"), F.explode(F.sequence("a", "b")).alias("rank")).join(ranked.select("domain_id", F.col("cell_id").alias("i2"), F.col("rank").cast("long").alias("rank")), ["domain_id", "rank"])
        rows = k.select("domain_id", "i", "j", F.ln("k").alias("l"))
        other = rows.select("domain_id", F.col("i").alias("i2"), "j", F.col("l").alias("l2"))
        worst = rows.join(member.drop("rank"), ["domain_id", "i"]).join(other, ["domain_id", "i2", "j"]).groupBy("domain_id").agg(F.max(F.abs(F.col("l") - F.col("l2"))).alias("worst"))
        low = metrics.exper_by_report(k, cells, dist).groupBy("domain_id").agg(F.min("exper").alias("min_exper"))
        out.append(worst.join(low, "domain_id").select("domain_id", F.lit(name).alias("scheme"), F.round("worst", 4).alias("worst"), (F.col("worst") > eps + 1e-9).alias("breaks_budget"), F.round("min_exper", 4).alias("min_exper"), (F.col("min_exper") < e_min).alias("breaks_bound")))
    return out[0].unionByName(out[1])


def tiles_zonal(spark: SparkSession, sf_dir: str, eps: float = 1.0, e_min: float = 0.1, n: int = 50) -> DataFrame:
    """Many domains at once: one tile per supplier, zoned and measured, rolled up nation to region."""
    cells = domains.eps_constant(domains.prior_uniform(domains.tiles(spark, sf_dir, n)), eps)
    got = scalars(schemes.run(cells, ["zonal_curve"], [(eps, e_min)]), "q_loss", "exp_err", "min_exper", "zones")
    wide = got.groupBy("domain_id").pivot("measure", ["q_loss", "exp_err", "min_exper", "zones"]).agg(F.first("value"))
    supplier = read(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey").join(F.broadcast(read(spark, sf_dir, "nation", "n_nationkey", "n_regionkey")), F.col("s_nationkey") == F.col("n_nationkey"))
    wide = wide.withColumn("s_suppkey", F.split("domain_id", ":")[1].cast("long")).join(supplier, "s_suppkey")
    return wide.rollup("n_regionkey", "n_nationkey").agg(F.count("*").alias("tiles"), F.round(F.avg("q_loss"), 4).alias("q_loss"), F.round(F.avg("exp_err"), 4).alias("exp_err"), F.min(F.col("min_exper") >= e_min - 1e-3).alias("bound_ok"), F.sum("zones").cast("long").alias("zones"))


def flagship(spark: SparkSession, sf_dir: str, eps: float = 1.0, e_min: float = 0.1) -> DataFrame:
    """Best-of-four curve zoning, zonal kernel and both attacks on the sparse set: one row per cell."""
    cells = domains.eps_constant(domains.prior_table2(domains.sparse(spark, sf_dir)), eps)
    dist = geometry.pairs(cells)
    zones = zoning.zone_best_curve(cells, [(eps, e_min)]).where("status = 'ok'").select("domain_id", "cell_id", "zone_id")
    stats = condition.zone_stats(zones, cells, dist)
    k = exponential.zonal_kernel(zones, stats, dist)
    out = zones.join(stats.select("domain_id", "zone_id", "reach"), ["domain_id", "zone_id"]).withColumnRenamed("cell_id", "i")
    for part in (metrics.avg_err(k, cells, dist), metrics.success(k, cells), metrics.q_loss_by_cell(k, dist)):
        out = out.join(part, ["domain_id", "i"])
    return out.select("domain_id", F.col("i").alias("cell_id"), "zone_id", *(F.round(c, 6).alias(c) for c in ("reach", "avg_err", "p_s", "loss")))


