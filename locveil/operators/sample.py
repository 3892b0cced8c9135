"""Drawing pseudo-locations for pings: all of it in generated code."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import draw_from_cdf, portable_uniform, secret_uniform

#: Kernel rows are broadcast only below this many stored numbers (16 bytes each); beyond, pings and rows meet by a shuffle.
BROADCAST_NUMBERS = 2_000_000


def _uniform(ident: str, seed: int | str) -> Column:
    return portable_uniform(ident, seed) if isinstance(seed, int) else secret_uniform(ident, seed)


def draw(pings: DataFrame, rows: DataFrame, seed: int | str, numbers: int | None = None) -> DataFrame:
    """``pings(domain_id, event_id, cell_id, ...)`` to the same with ``reported_cell`` by inverse CDF on packed kernel rows.

    ``numbers`` is the size of the kernel where the caller knows it; unknown or
    large kernels are joined by shuffle (AQE splits hot cells).
    """
    small = numbers is not None and numbers <= BROADCAST_NUMBERS
    side = rows.select("domain_id", F.col("i").alias("cell_id"), "outs", "cdf")
    got = pings.join(F.broadcast(side) if small else side, ["domain_id", "cell_id"])
    return got.withColumn("reported_cell", draw_from_cdf("outs", "cdf", _uniform("event_id", seed))).drop("outs", "cdf")


def draw_gumbel(pings: DataFrame, cells: DataFrame, zones: DataFrame, stats: DataFrame, seed: int) -> DataFrame:
    """The same without a stored kernel: the largest of -scale d + Gumbel noise over the domain's cells."""
    scale = zones.select("domain_id", "cell_id", "zone_id").join(stats.select("domain_id", "zone_id", (F.col("eps_zone") / (2 * F.col("reach"))).alias("scale")), ["domain_id", "zone_id"])
    true = cells.select("domain_id", "cell_id", "x", "y").join(scale.select("domain_id", "cell_id", "scale"), ["domain_id", "cell_id"])
    outs = cells.groupBy("domain_id").agg(F.array_sort(F.collect_list(F.struct("cell_id", "x", "y"))).alias("outs"))
    df = pings.join(true, ["domain_id", "cell_id"]).join(outs, "domain_id")
    noise = lambda o: portable_uniform(F.concat_ws("/", F.col("event_id").cast("string"), o["cell_id"].cast("string")), seed)
    value = lambda o: -F.col("scale") * F.sqrt(F.pow(o["x"] - F.col("x"), 2) + F.pow(o["y"] - F.col("y"), 2)) - F.ln(-F.ln(F.greatest(noise(o), F.lit(1e-300))))
    best = F.array_max(F.transform("outs", lambda o: F.struct(value(o).alias("v"), o["cell_id"].alias("c"))))
    return df.withColumn("reported_cell", best["c"]).drop("outs", "x", "y", "scale")


def alias_rows(kernel: DataFrame) -> DataFrame:
    """``domain_id, i, outs, keep, other``: alias tables for draws by two look-ups, built from batches of packed kernel rows."""
    import numpy as np
    import pyarrow as pa

    def table(p: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        p = p * len(p)
        keep, other = np.ones(len(p)), np.arange(len(p))
        small, large = [i for i in range(len(p)) if p[i] < 1], [i for i in range(len(p)) if p[i] >= 1]
        while small and large:
            s, big = small.pop(), large[-1]
            keep[s], other[s] = p[s], big
            p[big] -= 1 - p[s]
            if p[big] < 1:
                small.append(large.pop())
        return keep, other

    def build(batches):
        for batch in batches:
            keep, other = [], []
            for ids, p in zip(batch.column("outs"), batch.column("p"), strict=True):
                ids = ids.values.to_numpy()
                k, o = table(p.values.to_numpy())
                keep.append(k)
                other.append(ids[o])
            cols = [*(batch.column(c) for c in ("domain_id", "i", "outs")), pa.array(keep, pa.list_(pa.float64())), pa.array(other, pa.list_(pa.int64()))]
            yield pa.RecordBatch.from_arrays(cols, ["domain_id", "i", "outs", "keep", "other"])

    rows = kernel.groupBy("domain_id", "i").agg(F.array_sort(F.collect_list(F.struct("j", "k"))).alias("r"))
    rows = rows.select("domain_id", "i", F.col("r.j").alias("outs"), F.col("r.k").alias("p"))
    return rows.mapInArrow(build, "domain_id string, i long, outs array<long>, keep array<double>, other array<long>")


def draw_alias(pings: DataFrame, rows: DataFrame, seed: int) -> DataFrame:
    side = rows.select("domain_id", F.col("i").alias("cell_id"), "outs", "keep", "other")
    u = portable_uniform("event_id", seed) * F.size("outs")
    at = F.floor(u).cast("int")
    df = pings.join(side, ["domain_id", "cell_id"])
    return df.withColumn("reported_cell", F.when(u - at < F.get("keep", at), F.get("outs", at)).otherwise(F.get("other", at))).drop("outs", "keep", "other")


def goodness(reports: DataFrame, kernel: DataFrame) -> DataFrame:
    """``domain_id, cell_id, n, chi2, cells``: observed against expected reports of each true cell."""
    n = reports.groupBy("domain_id", "cell_id").agg(F.count("*").alias("n"))
    seen = reports.groupBy("domain_id", "cell_id", F.col("reported_cell").alias("j")).agg(F.count("*").alias("o"))
    want = kernel.select("domain_id", F.col("i").alias("cell_id"), "j", "k").join(n, ["domain_id", "cell_id"]).join(seen, ["domain_id", "cell_id", "j"], "left")
    e = F.col("n") * F.col("k")
    return want.groupBy("domain_id", "cell_id", "n").agg(F.sum(F.pow(F.coalesce("o", F.lit(0)) - e, 2) / e).alias("chi2"), F.count("*").alias("cells"))
