"""Many-to-many path queries with restrictions on columns the graph does not hold.

Hops are unrolled into one plan of equi-joins. Restrictions come as filters on
their base tables and reach the scans; label rules prune arcs before each
join; a backward pass from the targets keeps only nodes from which a target
is still in reach.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from weftgraph.model import Graph, arcs


@dataclass(frozen=True)
class Restriction:
    """Rows of a base table that forbid (or alone allow) edges or nodes."""

    kind: str
    keys: DataFrame
    allow: bool = True

    @staticmethod
    def edge(base: DataFrame, key: Column, on: Column) -> Restriction:
        """Only edges with a row in ``base`` for which ``on`` holds may be passed."""
        return Restriction("edge", base.where(on).select(key.alias("eid")).distinct())

    @staticmethod
    def not_edge(base: DataFrame, key: Column, off: Column) -> Restriction:
        return Restriction("edge", base.where(off).select(key.alias("eid")).distinct(), False)

    @staticmethod
    def not_node(base: DataFrame, key: Column, off: Column) -> Restriction:
        return Restriction("node", base.where(off).select(key.alias("nid")).distinct(), False)


@dataclass(frozen=True)
class Select:
    """Nodes by ids, names, labels, or a predicate on their columns; all that are given must hold."""

    ids: list[int] | None = None
    names: list[str] | None = None
    labels: list[str] | None = None
    where: Column | None = None

    def of(self, graph: Graph) -> DataFrame:
        nodes = graph.nodes
        if self.ids is not None:
            nodes = nodes.where(F.col("nid").isin(self.ids))
        if self.names is not None:
            nodes = nodes.where(F.col("name").isin(self.names))
        if self.labels is not None:
            nodes = nodes.where(F.arrays_overlap("labels", F.array(*[F.lit(x) for x in self.labels])))
        if self.where is not None:
            nodes = nodes.where(self.where)
        return nodes.select("nid").distinct()


@dataclass(frozen=True)
class Hops:
    """Bounds and rules of a traversal."""

    max_hops: int = 3
    min_hops: int = 1
    hop_labels: list[set[str]] | None = None
    exclude_labels: set[str] = field(default_factory=set)
    walks: bool = False
    direction: str = "out"


def restricted_arcs(graph: Graph, restrictions: list[Restriction], hops: Hops) -> DataFrame:
    """(eid, u, v, w, labels) that may be passed."""
    edges = graph.edges
    if hops.exclude_labels:
        edges = edges.where(~F.coalesce(F.arrays_overlap("labels", F.array(*[F.lit(x) for x in sorted(hops.exclude_labels)])), F.lit(False)))
    for r in restrictions:
        if r.kind == "edge":
            edges = edges.join(r.keys, "eid", "left_semi" if r.allow else "left_anti")
    if hops.direction == "both":
        edges = edges.withColumn("direction", F.lit(0))
    ways = arcs(edges)
    if hops.direction == "in":
        ways = ways.select("eid", F.col("v").alias("u"), F.col("u").alias("v"), "w", "part")
    for r in restrictions:
        if r.kind == "node":
            how = "left_semi" if r.allow else "left_anti"
            ways = ways.join(r.keys.toDF("u"), "u", how).join(r.keys.toDF("v"), "v", how)
    if hops.hop_labels:
        ways = ways.join(graph.edges.select("eid", "labels"), "eid")
    return ways


def paths(graph: Graph, sources: Select | DataFrame, targets: Select | DataFrame, hops: Hops = Hops(), restrictions: list[Restriction] = (), prune: bool = True, steps: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """(src, dst, hops, path, eids, cost): every path with the allowed number of hops.

    A path repeats no node unless ``walks`` is set, and may run through a
    target and go on. ``prune`` looks back from the targets first; it changes
    the work, not the result. ``steps`` stands for a graph whose edges are too
    many to be made: from rows with ``at`` it gives one for each arc (eid, v, w)
    that leaves there and may be passed, so that only arcs that a path meets
    are made and no join is needed.
    """
    if steps is not None:
        return _stepped(graph, sources, targets, hops, prune, steps)
    s = sources.of(graph) if isinstance(sources, Select) else sources.select("nid").distinct()
    t = targets.of(graph) if isinstance(targets, Select) else targets.select("nid").distinct()
    ways = restricted_arcs(graph, list(restrictions), hops)
    step = [ways if not hops.hop_labels else ways.where(F.arrays_overlap("labels", F.array(*[F.lit(x) for x in sorted(hops.hop_labels[min(i, len(hops.hop_labels) - 1)])]))) for i in range(hops.max_hops)]
    step = [w.select("eid", "u", "v", "w") for w in step]
    reach: list[DataFrame | None] = [None] * (hops.max_hops + 1)
    if prune:
        # near[i]: nodes from which a target can be met by the arcs of hops i, i+1, ...
        near = t
        for i in range(hops.max_hops - 1, 0, -1):
            back = step[i].join(near.toDF("v"), "v", "left_semi").select(F.col("u").alias("nid"))
            near = back.unionByName(t).distinct()
            reach[i] = near
        reach[hops.max_hops] = t
    rows = s.select(F.col("nid").alias("src"), F.col("nid").alias("at"), F.array("nid").alias("path"), F.array().cast("array<long>").alias("eids"), F.lit(0).cast("long").alias("cost"))
    found = []
    for i in range(hops.max_hops):
        ways_i = step[i] if reach[i + 1] is None else step[i].join(reach[i + 1].toDF("v"), "v", "left_semi")
        rows = rows.join(ways_i, rows["at"] == ways_i["u"])
        if not hops.walks:
            rows = rows.where(~F.array_contains("path", F.col("v")))
        rows = rows.select("src", F.col("v").alias("at"), F.array_append("path", F.col("v")).alias("path"), F.array_append("eids", F.col("eid")).alias("eids"), (F.col("cost") + F.col("w")).alias("cost"))
        if i + 1 >= hops.min_hops:
            found.append(rows.join(t.toDF("at"), "at", "left_semi").select("src", F.col("at").alias("dst"), F.lit(i + 1).alias("hops"), "path", "eids", "cost"))
    out = found[0]
    for f in found[1:]:
        out = out.unionByName(f)
    return out


def _stepped(graph: Graph, sources: Select | DataFrame, targets: Select | DataFrame, hops: Hops, prune: bool, steps: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """``paths`` by steps that are made in place; ``prune`` drops what ends the last hop elsewhere before its path is made."""
    from weftgraph.plans.common import checked_broadcast

    if hops.hop_labels or hops.exclude_labels or hops.direction != "out":
        raise ValueError("steps must come with labels and direction resolved")
    s = sources.of(graph) if isinstance(sources, Select) else sources.select("nid").distinct()
    t = checked_broadcast((targets.of(graph) if isinstance(targets, Select) else targets.select("nid").distinct()).withColumnRenamed("nid", "v"), 1_000_000)
    n = 4 * int(s.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    rows = s.select(F.col("nid").alias("src"), F.col("nid").alias("at"), F.array("nid").alias("path"), F.array().cast("array<long>").alias("eids"), F.lit(0).cast("long").alias("cost"))
    out = None
    for i in range(hops.max_hops):
        if i < 2:  # the first few rows stand for all the work
            rows = rows.repartition(n, "at")
        rows = steps(rows)
        if prune and i + 1 == hops.max_hops:
            rows = rows.join(t, "v", "left_semi")
        if not hops.walks:
            rows = rows.where(~F.array_contains("path", F.col("v")))
        rows = rows.select("src", F.col("v").alias("at"), F.array_append("path", F.col("v")).alias("path"), F.array_append("eids", F.col("eid")).alias("eids"), (F.col("cost") + F.col("w")).alias("cost"))
        if i + 1 >= hops.min_hops:
            ends = rows if prune and i + 1 == hops.max_hops else rows.join(t.withColumnRenamed("v", "at"), "at", "left_semi")
            ends = ends.select("src", F.col("at").alias("dst"), F.lit(i + 1).alias("hops"), "path", "eids", "cost")
            out = ends if out is None else out.unionByName(ends)
    return out


def long_form(found: DataFrame) -> DataFrame:
    """(path_id, src, dst, step, nid, eid): one row for each node of a path."""
    keyed = found.withColumn("path_id", F.xxhash64("path", "eids"))
    each = keyed.select("path_id", "src", "dst", "eids", F.posexplode("path").alias("step", "nid"))
    return each.select("path_id", "src", "dst", "step", "nid", F.get("eids", F.col("step") - 1).alias("eid"))


def with_parts(graph: Graph, found: DataFrame) -> DataFrame:
    """Paths with ``parts``: the distinct parts whose edges they pass, in ascending order.

    Hops are joins over all parts at once, so a path may leave a part and come
    back; the parts are looked up by edge afterwards.
    """
    keyed = found.withColumn("_path", F.xxhash64("path", "eids"))
    passed = keyed.select("_path", F.explode("eids").alias("eid")).distinct().join(graph.edges.select("eid", F.coalesce("part", F.lit(0)).alias("part")), "eid")
    parts = passed.groupBy("_path").agg(F.array_sort(F.collect_set("part")).alias("parts"))
    return keyed.join(parts, "_path", "left").drop("_path")


def neighbours(graph: Graph, sources: Select | DataFrame, max_hops: int, restrictions: list[Restriction] = (), hops: Hops | None = None) -> DataFrame:
    """(src, nid, hops): nodes within reach of each source, with the least number of hops."""
    s = sources.of(graph) if isinstance(sources, Select) else sources.select("nid").distinct()
    ways = restricted_arcs(graph, list(restrictions), hops or Hops()).select("u", "v").distinct()
    level = s.select(F.col("nid").alias("src"), "nid", F.lit(0).alias("hops"))
    out = level
    for i in range(max_hops):
        level = level.join(ways, level["nid"] == ways["u"]).select("src", F.col("v").alias("nid"), F.lit(i + 1).alias("hops")).distinct()
        out = out.unionByName(level)
    return out.groupBy("src", "nid").agg(F.min("hops").alias("hops")).where("hops > 0")


def all_paths(graph: Graph, start: int, end: int, max_hops: int, max_cost: float | None = None) -> DataFrame:
    """Paths between two nodes within bounds on hops and cost."""
    found = paths(graph, Select(ids=[start]), Select(ids=[end]), Hops(max_hops=max_hops))
    return found if max_cost is None else found.where(F.col("cost") <= max_cost)
