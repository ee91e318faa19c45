"""Geometry as column expressions: points, lines and boxes in WKT, distances, cells, zones.

Coordinates may be degrees or planar units of any scale; ``metric`` names
which. Everything stays in built-in functions.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

EARTH_RADIUS_M = 6371008.8  # mean radius
#: Most nodes around a cell in one row; denser places come in several.
BLOCK_NODES = 1_024


def _number(text: Column) -> Column:
    return text.try_cast("double")



def parse_point(wkt: Column) -> Column:
    """struct<x, y> of a POINT; null if the text is none."""
    pair = F.regexp_extract(wkt, r"(?i)^\s*POINT\s*\(\s*([^)]*?)\s*\)\s*$", 1)
    parts = F.split(pair, r"\s+")
    x, y = _number(F.get(parts, 0)), _number(F.get(parts, 1))
    return F.when(x.isNotNull() & y.isNotNull(), F.struct(x.alias("x"), y.alias("y")))


def parse_line(wkt: Column) -> Column:
    """array<struct<x, y>> of a LINESTRING; null if the text is none."""
    inner = F.regexp_extract(wkt, r"(?i)^\s*LINESTRING\s*\(\s*([^)]*?)\s*\)\s*$", 1)
    points = F.transform(F.split(inner, r"\s*,\s*"), lambda p: F.struct(_number(F.get(F.split(p, r"\s+"), 0)).alias("x"), _number(F.get(F.split(p, r"\s+"), 1)).alias("y")))
    return F.when(F.length(inner) > 0, points)


def point_wkt(x: Column, y: Column) -> Column:
    return F.concat(F.lit("POINT("), x.cast("string"), F.lit(" "), y.cast("string"), F.lit(")"))


def line_wkt(points: Column) -> Column:
    """LINESTRING of an array of struct<x, y>."""
    return F.concat(F.lit("LINESTRING("), F.array_join(F.transform(points, lambda p: F.concat_ws(" ", p["x"].cast("string"), p["y"].cast("string"))), ", "), F.lit(")"))


def distance_xy(x1: Column, y1: Column, x2: Column, y2: Column) -> Column:
    return F.sqrt((x1 - x2) * (x1 - x2) + (y1 - y2) * (y1 - y2))


def distance_m(lon1: Column, lat1: Column, lon2: Column, lat2: Column) -> Column:
    """Great-circle distance in metres (haversine)."""
    a, b = F.sin(F.radians(lat2 - lat1) / 2), F.sin(F.radians(lon2 - lon1) / 2)
    return 2 * EARTH_RADIUS_M * F.asin(F.least(F.lit(1.0), F.sqrt(a * a + F.cos(F.radians(lat1)) * F.cos(F.radians(lat2)) * b * b)))


def distance(metric: str, x1: Column, y1: Column, x2: Column, y2: Column) -> Column:
    if metric not in ("planar", "geodesic"):
        raise ValueError("metric must be planar or geodesic")
    return distance_xy(x1, y1, x2, y2) if metric == "planar" else distance_m(x1, y1, x2, y2)


def line_length(points: Column, metric: str = "planar") -> Column:
    """Sum over the segments of an array of struct<x, y>."""
    steps = F.zip_with(F.slice(points, 1, F.size(points) - 1), F.slice(points, 2, F.size(points) - 1), lambda a, b: distance(metric, a["x"], a["y"], b["x"], b["y"]))
    return F.when(F.size(points) > 1, F.aggregate(steps, F.lit(0.0), lambda s, d: s + d)).otherwise(F.lit(0.0))


def cell(v: Column, size: float) -> Column:
    """The index of the bin of width ``size`` centred on its multiples."""
    return F.floor(v / F.lit(size) + F.lit(0.5)).cast("long")


def extent(df: DataFrame, x: str = "x", y: str = "y") -> DataFrame:
    return df.agg(F.min(x).alias("xmin"), F.min(y).alias("ymin"), F.max(x).alias("xmax"), F.max(y).alias("ymax"))


def point_segment(px: Column, py: Column, ax: Column, ay: Column, bx: Column, by: Column) -> Column:
    """struct<d, t, x, y>: distance, place along the segment (0 to 1), and foot point."""
    dx, dy = bx - ax, by - ay
    square = dx * dx + dy * dy
    t = F.when(square > 0, F.greatest(F.lit(0.0), F.least(F.lit(1.0), ((px - ax) * dx + (py - ay) * dy) / square))).otherwise(F.lit(0.0))
    fx, fy = ax + t * dx, ay + t * dy
    return F.struct(distance_xy(px, py, fx, fy).alias("d"), t.alias("t"), fx.alias("x"), fy.alias("y"))


def bearing(x1: Column, y1: Column, x2: Column, y2: Column) -> Column:
    """Planar direction in degrees, counter-clockwise from east."""
    return F.degrees(F.atan2(y2 - y1, x2 - x1))


def turn_angle(before: Column, after: Column) -> Column:
    """Change of bearing in (-180, 180]; positive to the left."""
    return F.lit(180.0) - F.pmod(F.lit(180.0) - (after - before), F.lit(360.0))


def segment_meets_box(ax, ay, bx, by, xmin, ymin, xmax, ymax) -> Column:
    """Whether a segment touches a closed box, by clipping its parameter range."""
    low, high = F.lit(0.0), F.lit(1.0)
    ok = F.lit(True)
    for p, q in ((ax - bx, ax - xmin), (bx - ax, xmax - ax), (ay - by, ay - ymin), (by - ay, ymax - ay)):
        r = q / F.when(p != 0, p)
        ok = ok & F.when(p == 0, q >= 0).otherwise(F.lit(True))
        low = F.greatest(low, F.when(p < 0, r).otherwise(F.lit(0.0)))
        high = F.least(high, F.when(p > 0, r).otherwise(F.lit(1.0)))
    return ok & (low <= high)


def line_meets_box(points: Column, xmin, ymin, xmax, ymax) -> Column:
    """Whether any segment (or the single point) of a line touches a closed box."""
    n = F.size(points)
    pairs = F.zip_with(F.slice(points, 1, F.greatest(n - 1, F.lit(1))), F.slice(points, F.when(n > 1, 2).otherwise(1), F.greatest(n - 1, F.lit(1))), lambda a, b: F.struct(a.alias("a"), b.alias("b")))
    return F.exists(pairs, lambda s: segment_meets_box(s["a"]["x"], s["a"]["y"], s["b"]["x"], s["b"]["y"], xmin, ymin, xmax, ymax))


def near_cells(df: DataFrame, x: str, y: str, size: float, rings: int = 1) -> DataFrame:
    """``df`` once for each cell within ``rings`` of its own, as (cx, cy)."""
    steps = F.sequence(F.lit(-rings), F.lit(rings))
    return df.withColumn("_sx", F.explode(steps)).withColumn("_sy", F.explode(steps)).withColumns({"cx": cell(F.col(x), size) + F.col("_sx"), "cy": cell(F.col(y), size) + F.col("_sy")}).drop("_sx", "_sy")


def touched_cells(df: DataFrame, x: str, y: str, size: float, reach: float) -> DataFrame:
    """``df`` once for each cell that a square of half width ``reach`` around its point touches, as (cx, cy)."""
    span = lambda v: F.sequence(cell(F.col(v) - reach, size), cell(F.col(v) + reach, size))
    return df.withColumn("cx", F.explode(span(x))).withColumn("cy", F.explode(span(y)))


def merge_points(points: DataFrame, tolerance: float, mode: str = "cell", key: str = "pid") -> DataFrame:
    """(key, rep): each point and the smallest key of those it is merged with.

    ``cell`` merges what falls into one bin; ``linked`` merges points of
    neighbouring bins that are within the tolerance, and chains of those.
    """
    binned = points.withColumns({"cx": cell(F.col("x"), tolerance), "cy": cell(F.col("y"), tolerance)})
    if mode == "cell":
        first = binned.groupBy("cx", "cy").agg(F.min(key).alias("rep"))
        return binned.join(first, ["cx", "cy"]).select(key, "rep")
    if mode != "linked":
        raise ValueError("mode must be cell or linked")
    from weftgraph.operators.components import connected_components

    # bins wide enough that most points look into their own only
    wide = 8 * tolerance
    binned = points.withColumns({"cx": cell(F.col("x"), wide), "cy": cell(F.col("y"), wide)})
    around = touched_cells(points.select(F.col(key).alias("k2"), F.col("x").alias("x2"), F.col("y").alias("y2")), "x2", "y2", wide, tolerance)
    pairs = binned.join(around, ["cx", "cy"]).where((F.col(key) > F.col("k2")) & (distance_xy(F.col("x"), F.col("y"), F.col("x2"), F.col("y2")) <= tolerance))
    merged = connected_components(pairs.select(F.col(key).alias("u"), F.col("k2").alias("v")))
    return points.join(merged, points[key] == merged["nid"], "left").select(key, F.coalesce("component", key).alias("rep"))


def snap(points: DataFrame, nodes: DataFrame, size: float) -> DataFrame:
    """(pid, nid, dist): the nearest node of each point, ties to the smaller id.

    A point looks into its cell of width ``size`` and those around it, and is
    settled when a node lies nearer than what is outside them. The others look
    down a pyramid of occupied cells: from the level where one cell holds all
    nodes, each point keeps the cells that may hold its nearest node, so points
    at any distance are settled by a few cells a level. Points without
    coordinates, or without any node, come back with a null node.
    """
    from weftgraph.plans.common import checked_broadcast, cut

    placed = nodes.where("x IS NOT NULL AND y IS NOT NULL").select("nid", F.col("x").alias("nx"), F.col("y").alias("ny"))
    binned = placed.withColumns({"cx": cell(F.col("nx"), size), "cy": cell(F.col("ny"), size)})
    here = points.select("pid", "x", "y")
    d = distance_xy(F.col("x"), F.col("y"), F.col("nx"), F.col("ny"))
    least = F.min(F.struct(d.alias("dist"), F.col("nid").alias("nid"))).alias("b")
    # the nodes around each cell as one array, so that a point meets one row and needs no aggregate
    around = near_cells(placed.groupBy("nx", "ny").agg(F.min("nid").alias("nid")), "nx", "ny", size)
    most = around.groupBy("cx", "cy").count().agg(F.max("count")).head()[0] or 0
    pieces = -(-most // BLOCK_NODES) or 1
    blocks = cut(around.groupBy("cx", "cy", F.pmod(F.xxhash64("nid"), F.lit(pieces)).alias("piece")).agg(F.collect_list(F.struct("nx", "ny", "nid")).alias("nodes")).drop("piece"))
    best = F.array_min(F.transform("nodes", lambda n: F.struct(distance_xy(F.col("x"), F.col("y"), n["nx"], n["ny"]).alias("dist"), n["nid"].alias("nid"))))
    near = here.withColumns({"cx": cell(F.col("x"), size), "cy": cell(F.col("y"), size)}).join(checked_broadcast(blocks), ["cx", "cy"]).select("pid", best.alias("b"))
    if pieces > 1:
        near = near.groupBy("pid").agg(F.min("b").alias("b"))
    near = cut(near.select("pid", "b.nid", "b.dist").where(F.col("dist") <= size))  # what lies outside the square is farther
    rest = cut(here.where("x IS NOT NULL AND y IS NOT NULL").join(near.select("pid"), "pid", "left_anti"))
    blank = here.where("x IS NULL OR y IS NULL").select("pid", F.lit(None).cast("long").alias("nid"), F.lit(None).cast("double").alias("dist"))
    if not rest.limit(1).count():
        return near.unionByName(blank)
    far = _snap_far(rest, binned, size, least)
    return near.unionByName(rest.join(far, "pid", "left").select("pid", "nid", "dist")).unionByName(blank)


def _snap_far(rest: DataFrame, binned: DataFrame, size: float, least: Column) -> DataFrame:
    """Nearest nodes by halving cells: a cell stays while its nearest point is no farther than the farthest one of the best cell."""
    from weftgraph.plans.common import cut

    e = binned.agg(F.min("cx"), F.max("cx"), F.min("cy"), F.max("cy")).head()
    if e[0] is None:
        return rest.select("pid", F.lit(None).cast("long").alias("nid"), F.lit(None).cast("double").alias("dist"))
    depth = max(1, int(max(e[1] - e[0], e[3] - e[2]) + 1).bit_length())
    used = cut(binned.select((F.col("cx") - e[0]).alias("ix"), (F.col("cy") - e[2]).alias("iy")).distinct())
    kept = rest.select("pid", "x", "y", F.lit(0).cast("long").alias("ix"), F.lit(0).cast("long").alias("iy"))
    for level in range(depth - 1, -1, -1):  # cells of 2^level times the width
        finer = used.select(F.shiftright("ix", level).alias("ix"), F.shiftright("iy", level).alias("iy")).distinct()
        split = finer.select(F.shiftright("ix", 1).alias("px"), F.shiftright("iy", 1).alias("py"), "ix", "iy")
        below = kept.withColumnsRenamed({"ix": "px", "iy": "py"}).join(split, ["px", "py"])
        width = size * (1 << level)
        low = lambda i, first: (F.col(i) * (1 << level) + F.lit(first) - 0.5) * size  # noqa: E731, B023
        x0, y0 = low("ix", e[0]), low("iy", e[2])
        gap = lambda v, a: F.greatest(a - v, v - a - width, F.lit(0.0))  # noqa: E731, B023
        reach = lambda v, a: F.greatest(F.abs(v - a), F.abs(v - a - width))  # noqa: E731, B023
        x, y = F.col("x"), F.col("y")
        sized = below.withColumns({"_lo": F.sqrt(gap(x, x0) * gap(x, x0) + gap(y, y0) * gap(y, y0)), "_hi": F.sqrt(reach(x, x0) * reach(x, x0) + reach(y, y0) * reach(y, y0))})
        bound = sized.groupBy("pid").agg(F.min("_hi").alias("_bound"))
        kept = cut(sized.join(bound, "pid").where(F.col("_lo") <= F.col("_bound") * (1 + 1e-12) + 1e-12).select("pid", "x", "y", "ix", "iy"))
    cells = kept.select("pid", "x", "y", (F.col("ix") + e[0]).alias("cx"), (F.col("iy") + e[2]).alias("cy"))
    return cells.join(binned, ["cx", "cy"]).groupBy("pid").agg(least).select("pid", "b.nid", "b.dist")


def voronoi_zone(points: DataFrame, generators: DataFrame, limit: int = 10_000) -> DataFrame:
    """(pid, gid): the nearest generator of each point, ties to the smaller id.

    Generators are prescribed by the user, few by nature; their number is
    checked, since they are compared with every point.
    """
    g = generators.select("gid", F.col("x").alias("gx"), F.col("y").alias("gy"))
    if g.limit(limit + 1).count() > limit:
        raise ValueError(f"more than {limit} generators; snap the points to them instead")
    table = g.agg(F.collect_list(F.struct("gid", "gx", "gy")).alias("g"))
    nearest = F.array_min(F.transform("g", lambda z: F.struct(((F.col("x") - z["gx"]) * (F.col("x") - z["gx"]) + (F.col("y") - z["gy"]) * (F.col("y") - z["gy"])).alias("d"), z["gid"].alias("gid"))))
    return points.join(F.broadcast(table)).select("pid", nearest["gid"].alias("gid"))


def join_within(points: DataFrame, boxes: DataFrame, size: float) -> DataFrame:
    """(pid, bid): points inside closed boxes, joined on the cells that a box covers."""
    spans = boxes.withColumn("cx", F.explode(F.sequence(cell(F.col("xmin"), size), cell(F.col("xmax"), size)))).withColumn("cy", F.explode(F.sequence(cell(F.col("ymin"), size), cell(F.col("ymax"), size))))
    binned = points.withColumns({"cx": cell(F.col("x"), size), "cy": cell(F.col("y"), size)})
    return binned.join(spans, ["cx", "cy"]).where("x BETWEEN xmin AND xmax AND y BETWEEN ymin AND ymax").select("pid", "bid")
