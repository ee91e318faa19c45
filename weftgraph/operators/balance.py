"""Rebalancing: renumber nodes by their cost from a source, then cut by id range.

Nodes at nearly equal cost get neighbouring ids, so ranges of the new ids are
bands between iso-cost lines that touch only their neighbours. Nodes that were
not reached come last. The order is found by a range sort with two passes.
"""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from weftgraph.model import Graph
from weftgraph.operators import partition
from weftgraph.operators.components import connected_components
from weftgraph.operators.sssp import SolveStats, costs
from weftgraph.plans.common import cut, ordinal


def default_source(graph: Graph) -> int:
    """The smallest id of the largest component (ties: the component with the smaller id)."""
    comp = connected_components(graph.edges.select(F.col("src").alias("u"), F.col("dst").alias("v")))
    top = comp.groupBy("component").count().orderBy(F.desc("count"), "component").head()
    if top is None:
        raise ValueError("the graph has no edges")
    return top["component"]


def export(graph: Graph, found: DataFrame) -> DataFrame:
    """The node table with all its columns and the solved cost, null where not reached."""
    return graph.nodes.join(found.select("nid", "cost"), "nid", "left")


def renumber(graph: Graph, found: DataFrame) -> DataFrame:
    """(old_id, new_id, cost): places in the order of cost and id, not reached nodes last."""
    rows = export(graph, found).select(F.col("nid").alias("old_id"), F.col("cost").isNull().alias("_late"), "cost")
    return ordinal(rows, ["_late", "cost", "old_id"], "new_id").select("old_id", "new_id", "cost")


def rekey(graph: Graph, ids: DataFrame) -> Graph:
    """The graph under new ids; every other column stays, old ids as ``old_id`` of nodes."""
    to = ids.select(F.col("old_id"), F.col("new_id"))
    nodes = graph.nodes.drop("old_id").join(to, graph.nodes["nid"] == to["old_id"]).withColumn("nid", F.col("new_id")).drop("new_id")
    edges = graph.edges.join(to.toDF("src", "_s"), "src").join(to.toDF("dst", "_d"), "dst").withColumns({"src": F.col("_s"), "dst": F.col("_d")}).select(*graph.edges.columns)
    return replace(graph, nodes=nodes, edges=edges, version=graph.version + 1)


def cut_by_edges(graph: Graph, parts: int) -> Graph:
    """Ranges of ids that own nearly equal numbers of edges, instead of equal ranges."""
    first = graph.edges.select(F.least("src", "dst").alias("nid")).groupBy("nid").agg(F.count("*").alias("n"))
    weighted = first.selectExpr("nid", "n")
    total = weighted.agg(F.sum("n")).head()[0] or 0
    bounds = _weighted_cuts(weighted, total, parts)
    home = lambda c: sum((F.when(F.col(c) > b, 1).otherwise(0) for b in bounds), F.lit(0))
    return partition._marked(graph.with_edges(graph.edges.withColumn("part", F.least(home("src"), home("dst")).cast("int"))), "id_range", parts)


def _weighted_cuts(weighted: DataFrame, total: int, parts: int, slots: int = 4096) -> list[int]:
    """Ids at which running edge counts pass each share.

    Counts in at most ``slots`` bins narrow each share down to one bin, and that
    bin is cut into bins again, until bins are single ids.
    """
    low, high = weighted.agg(F.min("nid"), F.max("nid")).head()
    if low is None:
        return []
    # for each share still open: (first id, last id, edges before the first id)
    spans = {g: (low, high, 0) for g in range(1, parts)}
    while any(a < b for a, b, _ in spans.values()):
        distinct = sorted({(a, b) for a, b, _ in spans.values() if a < b})
        width = {s: -(-(s[1] - s[0] + 1) // slots) for s in distinct}
        mark = F.lit(None).cast("struct<s:int,b:bigint>")
        for i, (a, b) in enumerate(distinct):
            inside = F.col("nid").between(a, b)
            mark = F.when(inside, F.struct(F.lit(i).alias("s"), F.floor((F.col("nid") - a) / width[a, b]).alias("b"))).otherwise(mark)
        rows = weighted.withColumn("m", mark).where("m IS NOT NULL").groupBy("m.s", "m.b").agg(F.sum("n").alias("n")).collect()  # at most slots for each share
        bins: dict[tuple[int, int], list[tuple[int, int]]] = {s: [] for s in distinct}
        for r in rows:
            bins[distinct[r["s"]]].append((r["b"], r["n"]))
        for g, (a, b, running) in spans.items():
            if a >= b:
                continue
            for place, n in sorted(bins[a, b]):
                first = a + place * width[a, b]
                if running + n >= total * g / parts:
                    spans[g] = (first, min(b, first + width[a, b] - 1), running)
                    break
                running += n
            else:
                spans[g] = (b, b, running)
    return [spans[g][0] for g in range(1, parts)]


def rebalance(graph: Graph, parts: int = 4, source: int | None = None, by: str = "nodes", rounds: int = 1, engine: str = "parts", stats: SolveStats | None = None) -> Graph:
    """Solve, renumber, cut again; ``by`` equal id ranges ('nodes') or equal edge counts ('edges')."""
    if by not in ("nodes", "edges"):
        raise ValueError("by must be nodes or edges")
    out = graph
    for _ in range(rounds):
        start = default_source(out) if source is None else source
        found = costs(out, start, engine, stats=stats)
        ids = cut(renumber(out, found))
        out = rekey(out, ids)
        out = partition.by_id_range(out, parts) if by == "nodes" else cut_by_edges(out, parts)
        source = None if source is None else ids.where(F.col("old_id") == source).head()["new_id"]
    return out


def assignments(graph: Graph) -> DataFrame:
    """(eid, part), to be given as explicit parts to a later graph with these edges."""
    return graph.edges.select("eid", "part")
