"""Privacy and utility measures of kernels and zonings, and audits of their guarantees."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import attack


def exper_by_report(kernel: DataFrame, cells: DataFrame, dist: DataFrame) -> DataFrame:
    """Conditional expected inference error of each report: ``domain_id, j, exper``."""
    best = attack.optimal(kernel, cells, dist)
    return best.join(attack.evidence(kernel, cells), ["domain_id", "j"]).where("pr > 0").select("domain_id", "j", (F.col("cost") / F.col("pr")).alias("exper"))


def min_exper(kernel: DataFrame, cells: DataFrame, dist: DataFrame, e_min: float) -> DataFrame:
    worst = exper_by_report(kernel, cells, dist).groupBy("domain_id").agg(F.min("exper").alias("min_exper"))
    return worst.withColumn("ok", F.col("min_exper") >= e_min - 1e-9)


def exper_bound(kernel: DataFrame, cells: DataFrame, dist: DataFrame, zones: DataFrame, stats: DataFrame) -> DataFrame:
    """Lower bound of each report's error from its zones: ``domain_id, j, bound, exper, ok``."""
    zone = zones.select("domain_id", F.col("cell_id").alias("i"), "zone_id")
    share = attack.posterior(kernel, cells).join(zone, ["domain_id", "i"]).groupBy("domain_id", "j", "zone_id").agg(F.sum("post").alias("share"))
    part = share.join(stats.select("domain_id", "zone_id", (F.exp(-F.col("eps_zone")) * F.col("a_out")).alias("least")), ["domain_id", "zone_id"])
    bound = part.groupBy("domain_id", "j").agg(F.sum(F.col("share") * F.col("least")).alias("bound"))
    return bound.join(exper_by_report(kernel, cells, dist), ["domain_id", "j"]).withColumn("ok", F.col("exper") >= F.col("bound") - 1e-9)


def exp_err(kernel: DataFrame, cells: DataFrame, dist: DataFrame) -> DataFrame:
    """Unconditional expected inference error: ``domain_id, exp_err``."""
    return attack.optimal(kernel, cells, dist).groupBy("domain_id").agg(F.sum("cost").alias("exp_err"))


def q_loss_by_cell(kernel: DataFrame, dist: DataFrame) -> DataFrame:
    return kernel.join(dist, ["domain_id", "i", "j"]).groupBy("domain_id", "i").agg(F.sum(F.col("k") * F.col("d")).alias("loss"))


def q_loss(kernel: DataFrame, cells: DataFrame, dist: DataFrame) -> DataFrame:
    """Expected distance between truth and report: ``domain_id, q_loss``."""
    prior = cells.select("domain_id", F.col("cell_id").alias("i"), "prior")
    return q_loss_by_cell(kernel, dist).join(prior, ["domain_id", "i"]).groupBy("domain_id").agg(F.sum(F.col("prior") * F.col("loss")).alias("q_loss"))


def avg_err(kernel: DataFrame, cells: DataFrame, dist: DataFrame) -> DataFrame:
    """Average error of the optimal attack for each true cell: ``domain_id, i, avg_err``."""
    guess = attack.optimal(kernel, cells, dist).select("domain_id", "j", F.col("guess_opt").alias("g"))
    far = dist.select("domain_id", "i", F.col("j").alias("g"), "d")
    return kernel.join(guess, ["domain_id", "j"]).join(far, ["domain_id", "i", "g"]).groupBy("domain_id", "i").agg(F.sum(F.col("k") * F.col("d")).alias("avg_err"))


def success(kernel: DataFrame, cells: DataFrame) -> DataFrame:
    """Chance that the Bayesian attack names the true cell: ``domain_id, i, p_s`` (one minus the failure probability)."""
    guess = attack.bayesian(kernel, cells).select("domain_id", "j", "guess_map")
    hit = F.when(F.col("guess_map") == F.col("i"), F.col("k")).otherwise(0.0)
    return kernel.join(guess, ["domain_id", "j"]).groupBy("domain_id", "i").agg(F.sum(hit).alias("p_s"))


def success_over(p_s: DataFrame, thresholds: tuple[float, ...] = (0.5, 0.7, 0.9)) -> DataFrame:
    """Share of cells whose success probability exceeds each threshold: ``domain_id, threshold, share``."""
    t = F.explode(F.array(*(F.lit(x) for x in thresholds)))
    return p_s.withColumn("threshold", t).groupBy("domain_id", "threshold").agg(F.avg(F.when(F.col("p_s") > F.col("threshold"), 1.0).otherwise(0.0)).alias("share"))


def avg_reach(stats: DataFrame) -> DataFrame:
    return stats.groupBy("domain_id").agg((F.sum(F.col("mass") * F.col("reach")) / F.sum("mass")).alias("avg_reach"))


def _extremes(kernel: DataFrame, zones: DataFrame) -> DataFrame:
    zone = zones.select("domain_id", F.col("cell_id").alias("i"), "zone_id")
    return kernel.join(zone, ["domain_id", "i"]).groupBy("domain_id", "zone_id", "j").agg(F.max(F.ln("k")).alias("hi"), F.min(F.ln("k")).alias("lo"))


def dp_audit(kernel: DataFrame, zones: DataFrame, stats: DataFrame) -> DataFrame:
    """Worst log ratio inside each zone against its budget; one aggregate, no self-join: ``domain_id, zone_id, worst, eps_zone, ok``."""
    worst = _extremes(kernel, zones).groupBy("domain_id", "zone_id").agg(F.max(F.col("hi") - F.col("lo")).alias("worst"))
    return worst.join(stats.select("domain_id", "zone_id", "eps_zone"), ["domain_id", "zone_id"]).withColumn("ok", F.col("worst") <= F.col("eps_zone") + 1e-9)


def geoind_audit(kernel: DataFrame, zones: DataFrame, stats: DataFrame, dist: DataFrame, deviation: bool = True) -> DataFrame:
    """Log ratios inside a zone against eps_g (d + theta), eps_g = eps / (2 reach), theta the reach: ``domain_id, zone_id, worst_slack, ok``."""
    zone = zones.select("domain_id", F.col("cell_id").alias("i"), "zone_id").join(stats.select("domain_id", "zone_id", "reach", "eps_zone"), ["domain_id", "zone_id"])
    rows = kernel.join(zone, ["domain_id", "i"]).select("domain_id", "zone_id", "j", "i", F.ln("k").alias("l"), "reach", "eps_zone")
    other = rows.select("domain_id", "zone_id", "j", F.col("i").alias("i2"), F.col("l").alias("l2"))
    far = dist.select("domain_id", "i", F.col("j").alias("i2"), "d")
    both = rows.join(other, ["domain_id", "zone_id", "j"]).where("i <> i2").join(far, ["domain_id", "i", "i2"])
    theta = F.col("reach") if deviation else F.lit(0.0)
    slack = F.col("l") - F.col("l2") - F.col("eps_zone") / (2 * F.col("reach")) * (F.col("d") + theta)
    return both.groupBy("domain_id", "zone_id").agg(F.max(slack).alias("worst_slack")).withColumn("ok", F.col("worst_slack") <= 1e-9)


def geoind_all_pairs(kernel: DataFrame, dist: DataFrame, eps_g: float) -> DataFrame:
    """Log ratios of all pairs of a domain against eps_g d, for the linear programmes: ``domain_id, worst_slack, unbounded, ok``.

    Every entry counts; unbounded is the number of reports that one cell of a pair can
    give and the other cannot.
    """
    rows = kernel.select("domain_id", "j", "i", "k")
    other = rows.select("domain_id", "j", F.col("i").alias("i2"), F.col("k").alias("k2"))
    far = dist.select("domain_id", "i", F.col("j").alias("i2"), "d")
    both = rows.where("k > 0").join(other, ["domain_id", "j"]).where("i <> i2").join(far, ["domain_id", "i", "i2"])
    slack = F.when(F.col("k2") > 0, F.ln("k") - F.ln("k2") - F.lit(eps_g) * F.col("d"))
    out = both.groupBy("domain_id").agg(F.max(slack).alias("worst_slack"), F.count_if(F.col("k2") <= 0).alias("unbounded"))
    return out.withColumn("ok", (F.col("worst_slack") <= 1e-4) & (F.col("unbounded") == 0))


def weak_dp_audit(kernel: DataFrame, zones: DataFrame, stats: DataFrame, dist: DataFrame) -> DataFrame:
    """Log ratios across two zones against (D/D_a + D/D_b) eps / 2: ``domain_id, za, zb, worst, bound, ok``."""
    whole = dist.groupBy("domain_id").agg(F.max("d").alias("diameter"))
    ends = _extremes(kernel, zones)
    a = ends.select("domain_id", "j", F.col("zone_id").alias("za"), "hi")
    b = ends.select("domain_id", "j", F.col("zone_id").alias("zb"), "lo")
    worst = a.join(b, ["domain_id", "j"]).groupBy("domain_id", "za", "zb").agg(F.max(F.col("hi") - F.col("lo")).alias("worst"))
    sa = stats.select("domain_id", F.col("zone_id").alias("za"), (F.col("eps_zone") / F.col("reach")).alias("ra"))
    sb = stats.select("domain_id", F.col("zone_id").alias("zb"), (F.col("eps_zone") / F.col("reach")).alias("rb"))
    out = worst.join(sa, ["domain_id", "za"]).join(sb, ["domain_id", "zb"]).join(whole, "domain_id")
    bound = F.col("diameter") * (F.col("ra") + F.col("rb")) / 2
    return out.select("domain_id", "za", "zb", "worst", bound.alias("bound"), (F.col("worst") <= bound + 1e-9).alias("ok"))


def weak_dp_domain(kernel: DataFrame, stats: DataFrame, dist: DataFrame) -> DataFrame:
    """The whole domain's worst log ratio against eps D / D_min."""
    worst = kernel.groupBy("domain_id", "j").agg((F.max(F.ln("k")) - F.min(F.ln("k"))).alias("w")).groupBy("domain_id").agg(F.max("w").alias("worst"))
    bound = stats.groupBy("domain_id").agg(F.max(F.col("eps_zone") / F.col("reach")).alias("r")).join(dist.groupBy("domain_id").agg(F.max("d").alias("diameter")), "domain_id")
    return worst.join(bound, "domain_id").select("domain_id", "worst", (F.col("r") * F.col("diameter")).alias("bound")).withColumn("ok", F.col("worst") <= F.col("bound") + 1e-9)


def relative(measures: DataFrame, base: str, other: str) -> DataFrame:
    """``measures(domain_id, scheme, eps_param, e_min, measure, value)``: mean and largest change of ``other`` against ``base``."""
    both = measures.where(F.col("scheme").isin(base, other)).groupBy("domain_id", "eps_param", "e_min", "measure").pivot("scheme", [base, other]).agg(F.first("value"))
    change = F.col(f"`{other}`") / F.col(f"`{base}`") - 1
    return both.where(F.col(f"`{base}`").isNotNull() & F.col(f"`{other}`").isNotNull()).groupBy("domain_id", "measure").agg(F.avg(change).alias("mean_change"), F.max(change).alias("max_change"), F.count("*").alias("settings"))


def share_improved(loss_before: DataFrame, loss_after: DataFrame) -> DataFrame:
    """Share of cells whose loss is lower after: ``domain_id, share``."""
    after = loss_after.select("domain_id", "i", F.col("loss").alias("after"))
    return loss_before.join(after, ["domain_id", "i"]).groupBy("domain_id").agg(F.avg(F.when(F.col("after") < F.col("loss") - 1e-12, 1.0).otherwise(0.0)).alias("share"))
