"""Rank, Markov chains and Eulerian paths."""

from __future__ import annotations

from collections import defaultdict

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from weftgraph.model import Graph, arcs
from weftgraph.operators.components import connected_components
from weftgraph.plans.common import cut


def pagerank(graph: Graph, damping: float = 0.85, iterations: int = 20, weighted: bool = False, tolerance: float | None = None) -> DataFrame:
    """(nid, score) after a number of iterations, or once no score moves more than ``tolerance``.

    Mass of nodes without arcs is spread evenly.
    """
    ways = arcs(graph.edges)
    nodes = graph.nodes.select("nid").distinct()
    n = nodes.count()
    if not n:
        return nodes.select("nid", F.lit(0.0).alias("score"))
    share = F.col("w").cast("double") if weighted else F.lit(1.0)
    out = ways.groupBy("u").agg(F.sum(share).alias("total"))
    moves = ways.join(out, "u").select("u", "v", (share / F.col("total")).alias("p")).repartition("u").persist()
    held = nodes.join(out.select(F.col("u").alias("nid"), F.lit(1).alias("has")), "nid", "left").select("nid", F.col("has").isNull().alias("dangling")).persist()
    scores = cut(held.withColumn("score", F.lit(1.0 / n)))
    for i in range(iterations):
        loose = scores.where("dangling").agg(F.sum("score")).head()[0] or 0.0
        came = scores.join(moves, scores["nid"] == moves["u"]).groupBy(F.col("v").alias("nid")).agg(F.sum(F.col("score") * F.col("p")).alias("in"))
        now = held.join(came, "nid", "left").select("nid", "dangling", (F.lit((1 - damping) / n) + damping * (F.coalesce("in", F.lit(0.0)) + F.lit(loose / n))).alias("score"))
        now = cut(now)
        if tolerance is not None:
            moved = now.join(scores.select("nid", F.col("score").alias("old")), "nid").agg(F.max(F.abs(F.col("score") - F.col("old")))).head()[0]
            scores = now
            if moved <= tolerance:
                break
        scores = now
    moves.unpersist()
    held.unpersist()
    return scores.select("nid", "score")


def transitions(graph: Graph) -> DataFrame:
    """(u, v, p): weights normalised by row; a state without arcs stays where it is."""
    ways = arcs(graph.edges).groupBy("u", "v").agg(F.sum("w").cast("double").alias("w"))
    total = ways.groupBy("u").agg(F.sum("w").alias("t")).where("t > 0")
    moves = ways.join(total, "u").select("u", "v", (F.col("w") / F.col("t")).alias("p"))
    stuck = graph.nodes.select(F.col("nid").alias("u")).distinct().join(total.select("u"), "u", "left_anti")
    return moves.unionByName(stuck.select("u", F.col("u").alias("v"), F.lit(1.0).alias("p")))


def markov(graph: Graph, start: DataFrame | int, steps: int) -> DataFrame:
    """(nid, p): distribution after a number of steps from a state, or from ``start(nid, p)``."""
    moves = transitions(graph).persist()
    now = start if isinstance(start, DataFrame) else graph.nodes.where(F.col("nid") == start).select("nid", F.lit(1.0).alias("p"))
    for _ in range(steps):
        now = cut(now.withColumnRenamed("p", "q").join(moves, F.col("nid") == F.col("u")).groupBy(F.col("v").alias("nid")).agg(F.sum(F.col("q") * F.col("p")).alias("p")))
    moves.unpersist()
    return now


def stationary(graph: Graph, tolerance: float = 1e-10, max_steps: int = 500) -> DataFrame:
    """(nid, p): the distribution that steps no longer change, from an even start."""
    n = graph.nodes.select("nid").distinct().count()
    now = cut(graph.nodes.select("nid").distinct().withColumn("p", F.lit(1.0 / max(n, 1))))
    moves = transitions(graph).persist()
    for _ in range(max_steps):
        new = cut(now.withColumnRenamed("p", "q").join(moves, F.col("nid") == F.col("u")).groupBy(F.col("v").alias("nid")).agg(F.sum(F.col("q") * F.col("p")).alias("p")))
        moved = now.withColumnRenamed("p", "q").join(new, "nid", "full_outer").agg(F.sum(F.abs(F.coalesce("p", F.lit(0.0)) - F.coalesce("q", F.lit(0.0))))).head()[0] or 0.0
        now = new
        if moved <= tolerance:
            break
    moves.unpersist()
    return now


def euler_degrees(graph: Graph, directed: bool = False) -> DataFrame:
    """(component, edges, odd, verdict): circuit, path or none, for each component with edges.

    ``odd`` counts nodes of odd degree, or of unequal in- and out-degree.
    """
    e = graph.edges
    comp = connected_components(e.select(F.col("src").alias("u"), F.col("dst").alias("v")))
    ends = e.select(F.explode(F.array(F.struct(F.col("src").alias("nid"), F.lit(1).alias("out"), F.lit(0).alias("in")), F.struct(F.col("dst").alias("nid"), F.lit(0).alias("out"), F.lit(1).alias("in")))).alias("s")).select("s.*")
    degree = ends.groupBy("nid").agg(F.sum("out").alias("out"), F.sum("in").alias("in")).join(comp, "nid")
    gap = F.col("out") - F.col("in")
    if directed:
        g = degree.groupBy("component").agg((F.sum("out")).alias("edges"), F.count(F.when(gap != 0, 1)).alias("odd"), F.max(F.abs(gap)).alias("worst"))
        verdict = F.when(F.col("odd") == 0, "circuit").when((F.col("odd") == 2) & (F.col("worst") == 1), "path").otherwise("none")
    else:
        g = degree.groupBy("component").agg((F.sum(F.col("out") + F.col("in")) / 2).cast("long").alias("edges"), F.count(F.when((F.col("out") + F.col("in")) % 2 == 1, 1)).alias("odd"))
        verdict = F.when(F.col("odd") == 0, "circuit").when(F.col("odd") == 2, "path").otherwise("none")
    return g.select("component", F.col("edges").cast("long").alias("edges"), F.col("odd").cast("long").alias("odd"), verdict.alias("verdict"))


def _trail(pdf: pd.DataFrame, directed: bool) -> pd.DataFrame:
    """Hierholzer's walk over the edges of one component."""
    rows = defaultdict(list)
    degree = defaultdict(int)
    for i, (a, b) in enumerate(zip(pdf["src"], pdf["dst"], strict=True)):
        rows[a].append((b, i))
        if directed:
            degree[a] += 1
            degree[b] -= 1
        else:
            degree[a] += 1
            degree[b] += 1
            if a != b:
                rows[b].append((a, i))
    for v in rows.values():
        v.sort(reverse=True)
    starts = sorted(n for n, d in degree.items() if (d > 0 if directed else d % 2))
    at = starts[0] if starts else min(rows)
    used, stack, out = set(), [(at, None)], []
    while stack:
        n, e = stack[-1]
        while rows[n] and rows[n][-1][1] in used:
            rows[n].pop()
        if rows[n]:
            m, i = rows[n].pop()
            used.add(i)
            stack.append((m, i))
        else:
            out.append(stack.pop())
    out.reverse()
    eid = pdf["eid"].to_numpy()
    return pd.DataFrame({"component": pdf["component"].iloc[0], "step": np.arange(len(out), dtype=np.int32), "nid": [n for n, _ in out], "eid": pd.array([None if e is None else int(eid[e]) for _, e in out], dtype="Int64")})


def euler(graph: Graph, directed: bool = False, max_edges: int = 5_000_000) -> DataFrame:
    """(component, step, nid, eid): a trail over every edge, for components that have one.

    A component with more than ``max_edges`` edges is refused with an error,
    since its trail is one sequence made in one task.
    """
    good = euler_degrees(graph, directed).where("verdict <> 'none'")
    largest = good.agg(F.max("edges")).head()[0] or 0
    if largest > max_edges:
        raise ValueError(f"a component has {largest} edges, more than {max_edges}")
    comp = connected_components(graph.edges.select(F.col("src").alias("u"), F.col("dst").alias("v")))
    rows = graph.edges.select("eid", "src", "dst").join(comp.toDF("src", "component"), "src").join(good.select("component"), "component", "left_semi")
    return rows.groupBy("component").applyInPandas(lambda pdf: _trail(pdf, directed), "component long, step int, nid long, eid long")
