"""Weights changed at solve time: by value, by factors at places, by time, by restriction."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from weftgraph.functions.geo import near_cells
from weftgraph.model import Graph


def override(graph: Graph, values: DataFrame) -> Graph:
    """Weights of ``values(eid, value)`` replace those of the edges; several values of an edge: the least."""
    one = values.groupBy("eid").agg(F.min("value").alias("_v"))
    edges = graph.edges.join(one, "eid", "left").withColumn("weight", F.coalesce(F.col("_v"), F.col("weight"))).drop("_v")
    return graph.with_edges(edges.select(*graph.edges.columns))


def restrict_edges(graph: Graph, off: DataFrame | None = None, extra: DataFrame | None = None) -> Graph:
    """Switch edges off (``off(eid)``), or add to their cost (``extra(eid, extra)``)."""
    edges = graph.edges
    if off is not None:
        edges = edges.join(off.select("eid").distinct(), "eid", "left_anti")
    if extra is not None:
        total = extra.groupBy("eid").agg(F.sum("extra").alias("_x"))
        edges = edges.join(total, "eid", "left").withColumn("weight", F.col("weight") + F.coalesce(F.col("_x"), F.lit(0))).drop("_x")
    return graph.with_edges(edges.select(*graph.edges.columns))


def restrict_nodes(graph: Graph, off: DataFrame) -> Graph:
    """Switch nodes off, with all their edges."""
    gone = off.select("nid").distinct()
    edges = graph.edges.join(gone.toDF("src"), "src", "left_anti").join(gone.toDF("dst"), "dst", "left_anti")
    return graph.with_edges(edges.select(*graph.edges.columns))


def travel_time(length: Column, speed: Column) -> Column:
    """Length over speed, null where the speed is not positive."""
    return F.when(speed > 0, length / speed)


def midpoints(graph: Graph) -> DataFrame:
    """(eid, mx, my) of edges whose ends have coordinates."""
    at = graph.nodes.select("nid", "x", "y")
    both = graph.edges.select("eid", "src", "dst").join(at.toDF("src", "x1", "y1"), "src").join(at.toDF("dst", "x2", "y2"), "dst")
    return both.select("eid", ((F.col("x1") + F.col("x2")) / 2).alias("mx"), ((F.col("y1") + F.col("y2")) / 2).alias("my"))


def idw(graph: Graph, points: DataFrame, power: int = 2, radius: float | None = None, limit: int = 20_000) -> DataFrame:
    """(eid, factor): factors of ``points(x, y, factor)`` spread by inverse distance.

    A point on the midpoint decides alone (several: their mean). With
    ``radius`` only points that near count, and edges without any get factor
    1; points and edges then meet in grid cells. Without it every point counts
    for every edge, so their number is checked and they travel as one array.
    """
    mid = midpoints(graph)
    square = (F.col("mx") - F.col("px")) * (F.col("mx") - F.col("px")) + (F.col("my") - F.col("py")) * (F.col("my") - F.col("py"))
    named = points.select(F.col("x").alias("px"), F.col("y").alias("py"), "factor")
    if radius is None:
        if named.limit(limit + 1).count() > limit:
            raise ValueError(f"more than {limit} points; give a radius")
        # the points travel as one array, whose size is checked above, and each edge folds over it
        table = named.agg(F.collect_list(F.struct("px", "py", "factor")).alias("p"))
        gap = lambda p: (F.col("mx") - p["px"]) * (F.col("mx") - p["px"]) + (F.col("my") - p["py"]) * (F.col("my") - p["py"])
        zero = F.struct(F.lit(0.0).alias("w"), F.lit(0.0).alias("f"), F.lit(0).cast("long").alias("n"), F.lit(0.0).alias("hit"))

        def add(acc, p):
            near = gap(p) == 0
            weight = F.when(near, 0.0).otherwise(1 / F.pow(gap(p), F.lit(power / 2)))
            return F.struct((acc["w"] + weight).alias("w"), (acc["f"] + weight * p["factor"]).alias("f"), (acc["n"] + near.cast("long")).alias("n"), (acc["hit"] + F.when(near, p["factor"]).otherwise(0.0)).alias("hit"))

        tasks = int(graph.spark.conf.get("spark.sql.shuffle.partitions"))
        folded = mid.repartition(tasks).join(F.broadcast(table)).select("eid", F.aggregate("p", zero, add).alias("s"))
        return folded.select("eid", F.when(F.col("s.n") > 0, F.col("s.hit") / F.col("s.n")).when(F.col("s.w") > 0, F.col("s.f") / F.col("s.w")).otherwise(1.0).alias("factor"))
    else:
        spread = near_cells(named, "px", "py", radius)
        cells = mid.withColumns({"cx": F.floor(F.col("mx") / radius + 0.5).cast("long"), "cy": F.floor(F.col("my") / radius + 0.5).cast("long")})
        met = cells.join(spread, ["cx", "cy"]).where(square <= radius * radius)
    part = met.select("eid", "factor", square.alias("d2"))
    w = F.when(F.col("d2") > 0, 1 / F.pow("d2", F.lit(power / 2)))
    got = part.groupBy("eid").agg(F.avg(F.when(F.col("d2") == 0, F.col("factor"))).alias("hit"), (F.sum(w * F.col("factor")) / F.sum(w)).alias("mean")).select("eid", F.coalesce("hit", "mean").alias("factor"))
    return mid.select("eid").join(got, "eid", "left").select("eid", F.coalesce("factor", F.lit(1.0)).alias("factor"))


def scaled(graph: Graph, factors: DataFrame, scale: int = 1) -> Graph:
    """Whole-number weights times factor and ``scale``, rounded; edges without a factor keep factor 1."""
    edges = graph.edges.join(factors.select("eid", F.col("factor").alias("_f")), "eid", "left")
    edges = edges.withColumn("weight", F.round(F.col("weight") * F.coalesce("_f", F.lit(1.0)) * scale).cast("long")).drop("_f")
    return graph.with_edges(edges.select(*graph.edges.columns))


def by_time(graph: Graph, profile: DataFrame, hour: int) -> Graph:
    """Weights times the multiplier of ``profile(eid, hour, factor)`` in force at an hour: the latest not after it."""
    now = profile.where(F.col("hour") <= hour).groupBy("eid").agg(F.max_by("factor", "hour").alias("factor"))
    return scaled(graph, now)
