"""Python entries for SQL users: an aggregate for anchor errors and a table function for zonings."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf
from pyspark.sql.types import DoubleType

from . import zoning


@pandas_udf(DoubleType())
def anchor_outer_agg(x: pd.Series, y: pd.Series, p: pd.Series, dom_x: pd.Series, dom_y: pd.Series) -> float:
    """Outer anchor error of a group of cells: the best single guess among the domain's points, which come as arrays.

    Null where the group holds no prior mass or the domain no point.  A group is held by one task.
    """
    mass = p.sum()
    if not mass > 0 or not len(dom_x.iloc[0]):
        return float("nan")
    gx, gy = np.asarray(dom_x.iloc[0], float), np.asarray(dom_y.iloc[0], float)
    error = np.zeros(len(gx))
    for a, b, w in zip(x, y, p, strict=True):  # one row of distances at a time: groups may be large
        error += w * np.hypot(gx - a, gy - b)
    return float(error.min() / mass)


class MakeZones:
    """``make_zones(TABLE(cells) PARTITION BY (domain_id), eps, e_min, method)``: the zoning of each domain.

    Takes ``domain_id, cell_id, x, y, prior``, for method 'curve' and 'contiguous'
    also ``rank``, and with eps null each cell's own ``eps``.  Methods: 'curve',
    'contiguous' (best contiguous zoning) and 'qkm'.  A domain without a zoning
    gives one row with status 'infeasible'; no rows give none.
    """

    def __init__(self):
        self.cells, self.how = [], None

    def eval(self, row, eps, e_min, method):
        own = row["eps"] if eps is None else eps
        self.how = e_min, method
        self.cells.append((row["domain_id"], row["cell_id"], row["x"], row["y"], row["prior"], own, row["rank"] if method != "qkm" else 0))

    def terminate(self):
        if not self.cells:
            return
        e_min, method = self.how
        pdf = pd.DataFrame(self.cells, columns=["domain_id", "cell_id", "x", "y", "prior", "eps", "rank"]).assign(e_min=float(e_min), eps_param=-1.0, rot=0)
        if method == "qkm":
            got = zoning.searched(pdf)
        elif method in ("curve", "contiguous"):
            got = zoning.walked(pdf, exact=method == "contiguous")
        else:
            raise ValueError(f"unknown method: {method}")
        for r in got.astype(object).where(got.notna(), None).itertuples():
            yield r.domain_id, r.status, r.avg_reach, r.cell_id, r.zone_id


make_zones = udtf(MakeZones, returnType="domain_id string, status string, avg_reach double, cell_id bigint, zone_id bigint")


def register(spark: SparkSession) -> None:
    """Both under their names in SQL."""
    spark.udf.register("anchor_outer_agg", anchor_outer_agg)
    spark.udtf.register("make_zones", make_zones)
