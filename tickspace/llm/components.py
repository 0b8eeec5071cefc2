"""Connected components of an edge table by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import materialise, shared_dir


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """Hang neighbours on the smallest one: ``large`` keeps, for every node,
    the neighbours above it; otherwise those below it and the node itself."""
    if large:
        both = edges.select("u", "v").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    else:
        both = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    low = both.groupBy("u").agg(F.min("v").alias("low")).withColumn("low", F.least("low", "u"))
    hung = both.join(low, "u")
    if large:
        out = hung.where("v > u").select(F.col("v").alias("u"), F.col("low").alias("v"))
    else:
        out = hung.select(F.col("v").alias("u"), F.col("low").alias("v")).unionByName(low.select("u", F.col("low").alias("v")))
    return out.where("u <> v").distinct()


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(node, root) of every node that has an edge; edges: columns u, v of one
    orderable type.  The root is the component's smallest node.

    Each round is two grouped minima with a join back; a hub's rows are split
    by the skew join.  Rounds are written to the shared folder, so a lost
    executor costs at most one of them.  Nulls and loops are ignored; an empty
    table gives an empty result.
    """
    base = shared_dir(edges.sparkSession)
    now = materialise(edges.where("u is not null and v is not null and u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "e0", base)
    seen = None
    for i in range(max_rounds):
        now = materialise(_star(_star(now, True), False), f"e{i + 1}", base)
        mark = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v") % F.lit(1 << 40))).first()
        if tuple(mark) == seen:
            break
        seen = tuple(mark)
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return now.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(now.select(F.col("v").alias("node"), F.col("v").alias("root"))).distinct()
