"""Turn penalties by expansion: arcs become nodes, movements become arcs.

The solver is not changed. A movement from one arc to the next costs the next
arc's weight and a penalty by its angle, or is forbidden; a cost of the
expanded graph belongs to the end of its arc, and dummies do not show in
results.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from weftgraph.functions.geo import bearing, turn_angle
from weftgraph.model import Graph, arcs
from weftgraph.operators import sssp


@dataclass(frozen=True)
class TurnRules:
    """Penalties by kind of turn; None forbids it. ``moves(eid_in, eid_out, extra)`` adds to or (null) bans single ones."""

    left: int | None = 0
    right: int | None = 0
    straight: int | None = 0
    u_turn: int | None = None
    moves: DataFrame | None = field(default=None)


def movements(graph: Graph, rules: TurnRules) -> tuple[DataFrame, DataFrame]:
    """(arc nodes, movements): arcs with an id, and allowed pairs with their weights."""
    at = graph.nodes.select("nid", "x", "y")
    ways = arcs(graph.edges).join(at.toDF("u", "ux", "uy"), "u").join(at.toDF("v", "vx", "vy"), "v")
    ways = ways.select((F.col("eid") * 2 + (F.col("u") > F.col("v")).cast("int")).alias("aid"), "eid", "u", "v", "w", bearing(F.col("ux"), F.col("uy"), F.col("vx"), F.col("vy")).alias("b"))
    a = ways.select(F.col("aid").alias("a"), F.col("eid").alias("eid_in"), F.col("u").alias("from"), F.col("v").alias("via"), F.col("b").alias("b1"))
    b = ways.select(F.col("aid").alias("b"), F.col("eid").alias("eid_out"), F.col("u").alias("via"), F.col("v").alias("to"), "w", F.col("b").alias("b2"))
    turn = turn_angle(F.col("b1"), F.col("b2"))
    kind = F.when(F.abs(turn) >= 160, "u").when(turn > 20, "left").when(turn < -20, "right").otherwise("straight")
    both = a.join(b, "via").withColumn("kind", kind)
    cost = F.lit(None).cast("long")
    for name, value in (("left", rules.left), ("right", rules.right), ("straight", rules.straight), ("u", rules.u_turn)):
        cost = F.when(F.col("kind") == name, F.lit(value).cast("long")).otherwise(cost)
    both = both.withColumn("penalty", cost)
    if rules.moves is not None:
        extra = rules.moves.select("eid_in", "eid_out", F.coalesce("extra", F.lit(0)).alias("_x"), F.col("extra").isNull().alias("_ban"))
        both = both.join(extra, ["eid_in", "eid_out"], "left").where("NOT coalesce(_ban, false)").withColumn("penalty", F.col("penalty") + F.coalesce("_x", F.lit(0)))
    moves = both.where("penalty IS NOT NULL").select("a", "b", (F.col("w") + F.col("penalty")).alias("weight"), "kind")
    return ways, moves


def expand(graph: Graph, rules: TurnRules) -> tuple[Graph, DataFrame]:
    """(expanded graph, arcs with their ids). Its nodes are arcs, at the coordinates of their ends."""
    ways, moves = movements(graph, rules)
    nodes = ways.join(graph.nodes.select(F.col("nid").alias("v"), "x", "y"), "v").select(F.col("aid").alias("nid"), "x", "y")
    edges = moves.select((F.col("a") * F.lit(1 << 31) + F.col("b")).alias("eid"), F.col("a").alias("src"), F.col("b").alias("dst"), "weight", F.lit(1).alias("direction"))
    return Graph.of(f"{graph.name}+turns", nodes, edges), ways


def costs(graph: Graph, source: int, rules: TurnRules, engine: str = "parts", parts: tuple[int, int] = (2, 2), **options) -> DataFrame:
    """(nid, cost) under turn rules; the source costs nothing."""
    from weftgraph.operators.partition import by_box

    big, ways = expand(graph, rules)
    big = big.materialised()
    starts = [(r["aid"], r["w"]) for r in ways.where(F.col("u") == source).select("aid", "w").collect()]  # arcs of one node
    if not starts:
        return graph.nodes.where(F.col("nid") == source).select("nid", F.lit(0).cast("long").alias("cost"))
    solved = sssp.costs(by_box(big, *parts) if engine == "parts" else big, starts, engine, **options)
    at_end = solved.join(ways.select("aid", "v"), solved["nid"] == ways["aid"]).groupBy(F.col("v").alias("nid")).agg(F.min("cost").alias("cost"))
    return at_end.where(F.col("nid") != source).unionByName(graph.nodes.where(F.col("nid") == source).select("nid", F.lit(0).cast("long").alias("cost")))
