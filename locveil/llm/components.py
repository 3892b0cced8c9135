"""Connected components of an edge list, by repeated contraction."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ._scratch import drop, written


def components(edges: DataFrame) -> DataFrame:
    """``edges(a long, b long)`` to ``(node, comp)``: each node's smallest reachable node.

    Every round hooks each node to its smallest neighbour (a partial aggregate, so a
    node with very many links costs one row per task) and contracts the edges; the
    number of nodes at least halves, so the driver loop has logarithmically many
    rounds and only ever reads a row count.  Nodes are those that occur in an edge;
    no edges give an empty table.  Null ends and self links are ignored.
    """
    live = written(edges.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "edges")
    made: DataFrame | None = None
    old: list[DataFrame] = []
    while True:
        both = live.select(F.col("a").alias("node"), F.col("b").alias("other")).union(live.select(F.col("b").alias("node"), F.col("a").alias("other")))
        hook = written(both.groupBy("node").agg(F.min("other").alias("m")).select("node", F.least("node", "m").alias("up")), "hooks")
        if made is None:
            made = hook.select("node", F.col("up").alias("comp"))
        else:
            up = hook.select(F.col("node").alias("comp"), "up")
            made = written(made.join(up, "comp", "left").select("node", F.coalesce("up", "comp").alias("comp")), "labels")
        left = hook.select(F.col("node").alias("a"), F.col("up").alias("ua"))
        right = hook.select(F.col("node").alias("b"), F.col("up").alias("ub"))
        contracted = live.join(left, "a").join(right, "b").where("ua <> ub")
        contracted = written(contracted.select(F.least("ua", "ub").alias("a"), F.greatest("ua", "ub").alias("b")).distinct(), "edges")
        old.append(live)
        live = contracted
        if live.isEmpty():
            break
    drop(*old, live)
    return made
