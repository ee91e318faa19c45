"""Partitions: every edge in exactly one part, nodes repeated where parts meet.

A scheme gives each node a home part by a narrow expression after at most one
global aggregate; an edge belongs to the smaller home of its two ends. No part
scans the table for its own share.
"""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from weftgraph.functions.geo import extent
from weftgraph.model import Graph
from weftgraph.plans.common import checked_broadcast, cut, ordinal

#: Multiplier of the portable hash; its high bits are used, since the low ones repeat the id's.
HASH = 2_654_435_761


def id_range_home(nid: Column, low: int, high: int, parts: int) -> Column:
    """Equal ranges of ids from ``low`` to ``high``, in doubles: exact to the id below 2^53, without overflow above."""
    place = (nid.cast("double") - F.lit(float(low))) * parts / F.lit(float(high - low + 1))
    return F.least(F.floor(place), F.lit(parts - 1)).cast("int")



def box_home(x: Column, y: Column, box: tuple[float, float, float, float], nx: int, ny: int) -> Column:
    """Cell of an nx by ny lattice over the box; the far border belongs to the last cell."""
    x0, y0, x1, y1 = box
    cx = F.lit(0) if x1 == x0 else F.least(F.floor((x - x0) * nx / F.lit(x1 - x0)), F.lit(nx - 1))
    cy = F.lit(0) if y1 == y0 else F.least(F.floor((y - y0) * ny / F.lit(y1 - y0)), F.lit(ny - 1))
    return (cy * nx + cx).cast("int")


def random_home(key: Column, parts: int, numeric: bool = True) -> Column:
    """Hash then modulo, of an id or of a name.

    The product is taken modulo 2^32 in halves of 16 bits, so no id overflows.
    """
    if not numeric:
        return F.pmod(F.xxhash64(key), F.lit(parts)).cast("int")
    low, high = key.bitwiseAND(F.lit(0xFFFF)), F.shiftright(key, 16).bitwiseAND(F.lit(0xFFFF))
    product = (low * F.lit(HASH) + F.shiftleft((high * F.lit(HASH)).bitwiseAND(F.lit(0xFFFF)), 16)).bitwiseAND(F.lit((1 << 32) - 1))
    return (F.shiftright(product, 16) % parts).cast("int")


def _owned(edges: DataFrame, a: Column, b: Column) -> DataFrame:
    return edges.withColumn("part", F.least(a, b))


def assign_edges(graph: Graph, homes: DataFrame) -> Graph:
    """Edges by the smaller home; ``homes(nid, home)`` is joined to both ends."""
    h1, h2 = homes.select(F.col("nid").alias("src"), F.col("home").alias("_h1")), homes.select(F.col("nid").alias("dst"), F.col("home").alias("_h2"))
    edges = graph.edges.join(h1, "src").join(h2, "dst")
    return graph.with_edges(_owned(edges, F.col("_h1"), F.col("_h2")).drop("_h1", "_h2").select(*graph.edges.columns))


def by_id_range(graph: Graph, parts: int = 4) -> Graph:
    """Parts by ranges of node ids; an empty graph stays empty."""
    low, high = graph.nodes.agg(F.min("nid"), F.max("nid")).head()
    if low is None:
        return _marked(graph, "id_range", parts)
    home = lambda c: id_range_home(F.col(c), low, high, parts)
    return _marked(graph.with_edges(_owned(graph.edges, home("src"), home("dst"))), "id_range", parts)


def by_box(graph: Graph, nx: int = 2, ny: int = 2) -> Graph:
    """Parts by a lattice over the extent of the nodes' coordinates."""
    e = extent(graph.nodes).head()
    if e["xmin"] is None:
        raise ValueError("the box scheme needs coordinates")
    homes = graph.nodes.select("nid", box_home(F.col("x"), F.col("y"), (e["xmin"], e["ymin"], e["xmax"], e["ymax"]), nx, ny).alias("home"))
    out = assign_edges(graph, homes)
    return replace(_marked(out, "box", nx * ny), options=replace(out.options, scheme="box", parts=nx * ny, box=(nx, ny), mode="partitioned"))


def by_random(graph: Graph, parts: int = 4, on: str = "nid") -> Graph:
    """Parts by a hash of the node id, or of the name (``on='name'``)."""
    if on == "nid":
        home = lambda c: random_home(F.col(c), parts)
        return _marked(graph.with_edges(_owned(graph.edges, home("src"), home("dst"))), "random", parts)
    return _marked(assign_edges(graph, graph.nodes.select("nid", random_home(F.col("name"), parts, False).alias("home"))), "random", parts)


def explicit(graph: Graph, edge_part: Column, node_boundary: DataFrame | None = None) -> Graph:
    """Parts as given for each edge.

    ``node_boundary(nid, flag)`` states which nodes are repeated; a node whose
    flag does not agree with the parts it occurs in is an error.
    """
    out = _marked(graph.with_edges(graph.edges.withColumn("part", edge_part.cast("int"))), "explicit", 0)
    if node_boundary is not None:
        n = copies(out.edges).groupBy("nid").count()
        wrong = node_boundary.join(n, "nid").where((F.col("flag").cast("boolean")) != (F.col("count") > 1)).limit(5).collect()
        if wrong:
            raise ValueError(f"nodes whose boundary flag disagrees with their parts: {sorted(r['nid'] for r in wrong)}")
    return out


def auto(graph: Graph, parts: int = 4) -> Graph:
    """The scheme that the graph's columns allow: given parts, coordinates, names, then ids."""
    if graph.edges.where("part IS NOT NULL").limit(1).count():
        return explicit(graph, F.col("part"))
    if graph.nodes.where("x IS NOT NULL").limit(1).count():
        nx = max(d for d in range(1, int(parts**0.5) + 1) if parts % d == 0)
        return by_box(graph, nx, parts // nx)
    if graph.nodes.where("name IS NOT NULL").limit(1).count():
        return by_random(graph, parts, "name")
    return by_id_range(graph, parts)


def by_adaptive_tiles(graph: Graph, max_edges: int) -> Graph:
    """Parts no larger than ``max_edges``, by halving cells where edges are many."""
    from weftgraph.operators.tiles import build

    at = graph.nodes.select("nid", "x", "y")
    ends = graph.edges.join(at.toDF("src", "_x1", "_y1"), "src").join(at.toDF("dst", "_x2", "_y2"), "dst")
    tiled = build(ends.withColumns({"mx": (F.col("_x1") + F.col("_x2")) / 2, "my": (F.col("_y1") + F.col("_y2")) / 2}), max_edges)
    numbers = cut(ordinal(tiled.select("tile").distinct(), ["tile"], "_place"))
    parts = numbers.count()
    placed = tiled.drop("part").join(checked_broadcast(numbers), "tile").withColumn("part", F.col("_place").cast("int"))
    return _marked(graph.with_edges(placed.select(*graph.edges.columns)), "explicit", parts)


def _marked(graph: Graph, scheme: str, parts: int) -> Graph:
    return replace(graph, options=replace(graph.options, mode="partitioned", scheme=scheme, parts=parts))


def copies(edges: DataFrame) -> DataFrame:
    """(nid, part): each part a node occurs in."""
    return edges.select(F.explode(F.array("src", "dst")).alias("nid"), "part").distinct()


def boundary(edges: DataFrame) -> DataFrame:
    """(nid, part) of nodes that occur in two parts or more."""
    both = copies(edges)
    shared = both.groupBy("nid").agg(F.count("*").alias("n")).where("n > 1").select("nid")
    return both.join(shared, "nid")
