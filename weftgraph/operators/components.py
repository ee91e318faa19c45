"""Connected components of an edge list by alternating stars.

Each round is two aggregations and two joins over the edges, and the number
of rounds grows with the logarithm of the longest chain. No node's
neighbours are ever collected into one row, and hot nodes are split by
adaptive execution, so one star may hold a third of all edges.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from weftgraph.plans.common import cut, other_key


def _with_min(pairs: DataFrame) -> DataFrame:
    """Rows (u, v) with the smallest v of each u as ``m``."""
    least = pairs.groupBy("u").agg(F.min("v").alias("m")).select(other_key(F.col("u")).alias("ju"), "m")
    return pairs.withColumn("ju", other_key(F.col("u"))).join(least, "ju").select("u", "v", "m")


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(nid, component) for every node of ``edges(u, v)``.

    ``component`` is the smallest node id reachable. Rows with a null end are
    ignored, loops give their node a component of its own, repeated rows
    change nothing, and an empty input gives an empty result.
    """
    edges = edges.select(F.col("u").cast("long"), F.col("v").cast("long")).dropna()
    loops = edges.where("u = v").select("u").distinct()
    now = cut(edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct())
    before = None
    for _ in range(max_rounds):
        # each node's larger neighbours move to its smallest neighbour
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = _with_min(both).where("v > u").select(F.col("v").alias("u"), F.least("m", "u").alias("v")).distinct()
        # a node and its smaller neighbours move to the smallest of them
        small = _with_min(large).select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct("u", F.col("m").alias("v")))).alias("e")).select("e.u", "e.v").where("u <> v").distinct()
        now = cut(small)
        state = now.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).head()
        if state == before:
            break
        before = state
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    roots = now.select(F.col("v").alias("nid")).distinct().withColumn("component", F.col("nid"))
    found = now.select(F.col("u").alias("nid"), F.col("v").alias("component")).unionByName(roots)
    return found.unionByName(loops.join(found, loops["u"] == found["nid"], "left_anti").select(F.col("u").alias("nid"), F.col("u").alias("component")))
