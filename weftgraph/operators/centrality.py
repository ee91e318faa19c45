"""Closeness and betweenness, sources shared among tasks that hold the graph."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from weftgraph.model import Graph
from weftgraph.operators.kernels import brandes, settle
from weftgraph.operators.sssp import check_weights, replicate


def closeness(graph: Graph, sources: DataFrame | None = None) -> DataFrame:
    """(nid, score): (r - 1) / sum of costs, times (r - 1) / (N - 1), with r nodes reached.

    A node that reaches nothing has score 0. Costs are summed where they are
    found: one row for each source leaves a worker.
    """
    n = graph.nodes.select("nid").distinct().count()
    check_weights(graph.edges)
    shared = replicate(graph)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        block = shared.value
        lists = block.lists()
        for batch in batches:
            rows = []
            for s, at in zip(batch["nid"], block.place(batch["nid"].to_numpy(np.int64)), strict=True):
                dist = [float("inf")] * len(block.ids)
                got = settle(lists, dist, [(0, int(at))]) if at >= 0 else []
                rows.append((s, max(0, len(got) - 1), float(sum(dist[i] for i in got))))
            yield pd.DataFrame(rows, columns=["source", "r", "d"])

    tasks = int(graph.spark.conf.get("spark.sql.shuffle.partitions"))
    from_nodes = (graph.nodes.select("nid") if sources is None else sources.select("nid")).distinct().repartition(tasks, "nid")
    sums = from_nodes.mapInPandas(run, "source long, r long, d double")
    score = F.when((F.col("d") > 0) & F.lit(n > 1), F.col("r") / F.col("d") * F.col("r") / F.lit(max(n - 1, 1))).otherwise(0.0)
    return sums.select(F.col("source").alias("nid"), score.alias("score"))


def betweenness(graph: Graph, sources: DataFrame | None = None, weighted: bool = True, directed: bool = True) -> DataFrame:
    """(nid, score): sums of pair dependencies over all sources, or over those given (a sample).

    Undirected pairs count once. Ends of a path get nothing from it.
    """
    shared = replicate(graph)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        block = shared.value
        total = np.zeros(len(block.ids))
        for batch in batches:
            for s in batch["nid"]:
                at = int(block.place(np.array([s]))[0])
                if at >= 0:
                    total += brandes(block, at, weighted)
        yield pd.DataFrame({"nid": block.ids, "part": total})

    n = int(graph.spark.conf.get("spark.sql.shuffle.partitions"))
    from_nodes = (graph.nodes.select("nid") if sources is None else sources.select("nid")).distinct().repartition(n, "nid")
    parts = from_nodes.mapInPandas(run, "nid long, part double")
    score = F.sum("part") * F.lit(1.0 if directed else 0.5)
    sums = parts.groupBy("nid").agg(score.alias("score"))
    return graph.nodes.select("nid").distinct().join(sums, "nid", "left").select("nid", F.coalesce("score", F.lit(0.0)).alias("score"))
