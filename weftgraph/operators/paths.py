"""Paths from costs: tight arcs give predecessors, parts are walked backwards.

The walk starts at the targets. Inside a part it follows predecessors whose
edge the part owns; where the next edge belongs to another part, the walk is
handed over. A part may be visited again. All targets walk at once.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from weftgraph.functions.geo import line_wkt
from weftgraph.model import Graph, arcs
from weftgraph.plans.common import cut


def predecessors(graph: Graph, found: DataFrame, sources: DataFrame | None = None) -> DataFrame:
    """(nid, pred, eid, part): of the arcs that attain a node's cost, the smallest (pred, eid).

    Arcs of positive weight come first, as they cannot run in circles. A node
    that only arcs of weight zero attain is reached from the nodes settled
    before it, starting from those with a predecessor and from ``sources(nid)``,
    so that the hops over such arcs are as few as can be. Where weights of zero
    occur, the sources must be given.
    """
    tail = found.select(F.col("nid").alias("u"), F.col("cost").alias("du"))
    head = found.select(F.col("nid").alias("v"), F.col("cost").alias("dv"))
    ways = arcs(graph.edges)
    tight = ways.join(tail, "u").join(head, "v").where("dv = du + w")
    least = F.min(F.struct(F.col("u").alias("pred"), "eid", "part")).alias("m")
    shape = ["nid", "m.pred", "m.eid", F.coalesce("m.part", F.lit(0)).alias("part")]
    best = tight.where("w > 0").groupBy(F.col("v").alias("nid")).agg(least).select(*shape)
    if not ways.where("w = 0 AND u <> v").limit(1).count():
        return best
    if sources is None:
        raise ValueError("the graph has arcs of weight 0: give the sources of the solve")
    level = cut(tight.where("w = 0 AND u <> v"))
    best = cut(best)
    settled = cut(best.select("nid").unionByName(sources.select("nid")).distinct())
    while True:
        open_arcs = level.join(settled.select(F.col("nid").alias("v")), "v", "left_anti").join(settled.select(F.col("nid").alias("u")), "u", "left_semi")
        fresh = cut(open_arcs.groupBy(F.col("v").alias("nid")).agg(least).select(*shape))
        if not fresh.limit(1).count():
            return best
        best = cut(best.unionByName(fresh))
        settled = cut(settled.unionByName(fresh.select("nid")))


def _walk(block: pd.DataFrame, tokens: pd.DataFrame) -> pd.DataFrame:
    """Steps of each token inside the part; the last row of a token leaves the part or ends."""
    out: list[tuple] = []
    if len(tokens):
        step_of = dict(zip(block["nid"].tolist(), zip(block["pred"].tolist(), block["eid"].tolist(), strict=True), strict=True)) if len(block) else {}
        for target, nid, back, visit in zip(tokens["target"], tokens["nid"], tokens["back"], tokens["visit"], strict=True):
            part = int(tokens["part"].iloc[0])
            while nid in step_of:
                pred, eid = step_of[nid]
                out.append((target, back, nid, eid, part, visit, pred))
                nid, back = pred, back + 1
    return pd.DataFrame(out, columns=["target", "back", "nid", "eid", "part", "visit", "pred"]).astype({"target": "int64", "back": "int64", "nid": "int64", "eid": "int64", "part": "int32", "visit": "int32", "pred": "int64"})


def aggregate(graph: Graph, found: DataFrame, targets: DataFrame, max_rounds: int = 10_000, sources: DataFrame | None = None) -> DataFrame:
    """(target, step, nid, eid, part, visit, cost): the path to each target, from step 0 at the source.

    ``visit`` counts the stays in parts from the target backwards. Targets
    that were not reached have no rows; a target that is a source has one.
    ``sources(nid)`` are needed only where weights of zero occur.
    """
    pred = cut(predecessors(graph, found, sources))
    wanted = targets.select(F.col("nid").alias("target")).distinct().join(found.select(F.col("nid").alias("target")), "target", "left_semi")
    blocks = pred.repartition("part").persist()
    home = pred.select(F.col("nid"), F.col("part"))
    tokens = cut(wanted.select("target", F.col("target").alias("nid"), F.lit(0).cast("long").alias("back"), F.lit(0).alias("visit")).join(home, "nid").select("target", "nid", "back", "visit", "part"))
    steps = None
    for _ in range(max_rounds):
        if not tokens.limit(1).count():
            break
        walked = cut(blocks.groupBy("part").cogroup(tokens.groupBy("part")).applyInPandas(_walk, "target long, back long, nid long, eid long, part int, visit int, pred long"))
        steps = walked if steps is None else steps.unionByName(walked)
        last = walked.groupBy("target").agg(F.max(F.struct("back", "pred", "visit")).alias("m"))
        tokens = cut(last.select("target", F.col("m.pred").alias("nid"), (F.col("m.back") + 1).alias("back"), (F.col("m.visit") + 1).alias("visit")).join(home, "nid").select("target", "nid", "back", "visit", "part"))
    else:
        raise RuntimeError("paths did not end")
    blocks.unpersist()
    if steps is None:
        tail = wanted.select("target", F.lit(0).cast("long").alias("back"), F.col("target").alias("nid"), F.lit(None).cast("long").alias("eid"), F.lit(None).cast("int").alias("part"), F.lit(None).cast("int").alias("visit"))
    else:
        end = steps.groupBy("target").agg(F.max(F.struct("back", "pred")).alias("m")).select("target", (F.col("m.back") + 1).alias("back"), F.col("m.pred").alias("nid"), F.lit(None).cast("long").alias("eid"), F.lit(None).cast("int").alias("part"), F.lit(None).cast("int").alias("visit"))
        still = wanted.join(end.select("target"), "target", "left_anti").select("target", F.lit(0).cast("long").alias("back"), F.col("target").alias("nid"), F.lit(None).cast("long").alias("eid"), F.lit(None).cast("int").alias("part"), F.lit(None).cast("int").alias("visit"))
        tail = steps.drop("pred").unionByName(end).unionByName(still)
    whole = Window.partitionBy("target")
    placed = tail.withColumn("step", (F.max("back").over(whole) - F.col("back")).cast("int"))
    return placed.join(found.select("nid", "cost"), "nid").select("target", "step", "nid", "eid", "part", "visit", "cost")


def all_path_costs(graph: Graph, found: DataFrame, source: int) -> tuple[int, int]:
    """(sum of the costs of the paths to all targets, their number), added up along predecessors.

    Every node's path is aggregated at once: pointers to predecessors jump
    twice as far in each round and carry the weights they pass, so the rounds
    grow with the logarithm of the longest path, not with its length.
    """
    pred = predecessors(graph, found, found.where(F.col("nid") == source))
    weight = arcs(graph.edges).select("eid", F.col("u").alias("pred"), F.col("v").alias("nid"), "w")
    step = cut(found.select("nid").join(pred.join(weight, ["eid", "pred", "nid"]).select("nid", F.col("pred").alias("to"), "w"), "nid", "left").withColumn("w", F.coalesce("w", F.lit(0))))
    while step.where("to IS NOT NULL").limit(1).count():
        ahead = step.select(F.col("nid").alias("to"), F.col("to").alias("far"), F.col("w").alias("more"))
        step = cut(step.join(ahead, "to", "left").select("nid", F.col("far").alias("to"), (F.col("w") + F.coalesce("more", F.lit(0))).alias("w")))
    total, n = step.agg(F.sum("w"), F.count("*")).head()
    return total, n


def stays(steps: DataFrame) -> DataFrame:
    """(target, stays, parts): stays in parts on the way, and distinct parts among them."""
    moves = steps.where("part IS NOT NULL")
    return moves.groupBy("target").agg(F.countDistinct("visit").alias("stays"), F.countDistinct("part").alias("parts"))


def to_wkt(steps: DataFrame, nodes: DataFrame) -> DataFrame:
    """(target, wkt): one line string for each path."""
    at = steps.join(nodes.select("nid", "x", "y"), "nid")
    points = at.groupBy("target").agg(F.sort_array(F.collect_list(F.struct("step", "x", "y"))).alias("p"))
    return points.select("target", line_wkt(F.col("p")).alias("wkt"))


def path_places(ids: np.ndarray, before: dict[int, int], end: int) -> list[int]:
    """A path of local places by following predecessors, for kernels."""
    out = [end]
    while out[-1] in before:
        out.append(before[out[-1]])
    return [int(ids[i]) for i in reversed(out)]
