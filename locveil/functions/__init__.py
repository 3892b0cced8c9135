"""Column expressions that stay inside generated code, and their SQL forms."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F


def portable_uniform(ident: Column | str, seed: int) -> Column:
    """A double in [0, 1) from 52 bits of ``md5("id:seed")``; any SQL engine can repeat it.

    For tests and repeatable benchmarks only: a public seed would give the true cell away.
    """
    ident = F.col(ident) if isinstance(ident, str) else ident
    digest = F.md5(F.concat_ws(":", ident.cast("string"), F.lit(str(seed))))
    return F.conv(F.substring(digest, 1, 13), 16, 10).cast("bigint") / F.lit(4503599627370496.0)


def secret_uniform(ident: Column | str, key: str) -> Column:
    """A double in [0, 1) that only the holder of ``key`` can repeat."""
    ident = F.col(ident) if isinstance(ident, str) else ident
    digest = F.sha2(F.concat_ws(":", F.lit(key), ident.cast("string"), F.lit(key)), 256)
    return F.conv(F.substring(digest, 1, 13), 16, 10).cast("bigint") / F.lit(4503599627370496.0)


def hilbert(cx: Column | str, cy: Column | str, order: int, rot: int | Column = 0) -> Column:
    """Position on the Hilbert curve over a 2^order square, from 1; ``rot`` quarter turns clockwise.

    One fold over the bits from the highest: the quadrant gives two bits of the
    position and tells how the rest of the square is turned.
    """
    x, y = (F.col(c) if isinstance(c, str) else c for c in (cx, cy))
    side = (1 << order) - 1
    rot = F.lit(rot) if isinstance(rot, int) else rot
    tx = F.when(rot == 1, y).when(rot == 2, F.lit(side) - x).when(rot == 3, F.lit(side) - y).otherwise(x).cast("int")
    ty = F.when(rot == 1, F.lit(side) - x).when(rot == 2, F.lit(side) - y).when(rot == 3, x).otherwise(y).cast("int")
    start = F.struct(tx.alias("x"), ty.alias("y"), F.lit(0).cast("long").alias("h"))

    def fold(acc: Column, bit: Column) -> Column:
        one = F.call_function("shiftleft", F.lit(1), bit)
        qx = F.when(acc["x"].bitwiseAND(one) > 0, 1).otherwise(0)
        qy = F.when(acc["y"].bitwiseAND(one) > 0, 1).otherwise(0)
        digit = (3 * qx).bitwiseXOR(qy)
        mask = one - 1
        lx, ly = acc["x"].bitwiseAND(mask), acc["y"].bitwiseAND(mask)
        flip = (qy == 0) & (qx == 1)
        ux, uy = F.when(flip, mask - lx).otherwise(lx), F.when(flip, mask - ly).otherwise(ly)
        return F.struct(F.when(qy == 0, uy).otherwise(ux).cast("int").alias("x"), F.when(qy == 0, ux).otherwise(uy).cast("int").alias("y"), (acc["h"] * 4 + digit).cast("long").alias("h"))

    return F.aggregate(F.sequence(F.lit(order - 1), F.lit(0), F.lit(-1)), start, fold, lambda acc: acc["h"] + 1)


def eps_weight(eps: Column | str, eps_zone: Column | str, lam: float = 0.5) -> Column:
    """Assignment weight of a cell with budget ``eps`` for a zone that has ``eps_zone``: from lam (equal) to 1 + lam."""
    a, b = (F.col(c) if isinstance(c, str) else c for c in (eps, eps_zone))
    return F.lit(1.0 + lam) - F.least(a, b) / F.greatest(a, b)


def draw_from_cdf(outs: Column | str, cdf: Column | str, u: Column) -> Column:
    """The first entry of ``outs`` whose cumulative probability exceeds ``u``; the last one guards against rounding."""
    outs, cdf = (F.col(c) if isinstance(c, str) else c for c in (outs, cdf))
    at = F.size(F.filter(cdf, lambda c: c <= u))
    return F.get(outs, F.least(at, F.size(outs) - 1))


def distance(xa: Column, ya: Column, xb: Column, yb: Column, metric: str = "euclidean") -> Column:
    """Distance of two points: euclidean, hamming, manhattan or haversine (degrees in, km out)."""
    dx, dy = xa - xb, ya - yb
    if metric == "euclidean":
        return F.sqrt(dx * dx + dy * dy)
    if metric == "hamming":
        return F.when((dx == 0) & (dy == 0), 0.0).otherwise(1.0)
    if metric == "manhattan":
        return F.abs(dx) + F.abs(dy)
    if metric == "haversine":
        a = F.pow(F.sin(F.radians(dy) / 2), 2) + F.cos(F.radians(ya)) * F.cos(F.radians(yb)) * F.pow(F.sin(F.radians(dx) / 2), 2)
        return F.lit(2 * 6371.0088) * F.asin(F.least(F.lit(1.0), F.sqrt(a)))
    raise ValueError(f"unknown metric: {metric}")


def register_sql(spark: SparkSession) -> None:
    """The same functions for SQL users."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION cell_distance(xa DOUBLE, ya DOUBLE, xb DOUBLE, yb DOUBLE) RETURNS DOUBLE RETURN sqrt((xa - xb) * (xa - xb) + (ya - yb) * (ya - yb))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION portable_uniform(ident STRING, seed STRING) RETURNS DOUBLE RETURN cast(conv(substring(md5(concat(ident, ':', seed)), 1, 13), 16, 10) AS BIGINT) / 4503599627370496.0D")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION privacy_floor(eps DOUBLE, e_min DOUBLE) RETURNS DOUBLE RETURN exp(eps) * e_min")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION eps_weight(eps DOUBLE, eps_zone DOUBLE, lam DOUBLE) RETURNS DOUBLE RETURN 1 + lam - least(eps, eps_zone) / greatest(eps, eps_zone)")
