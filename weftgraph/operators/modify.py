"""Changes to a graph: insertions, deletions, upserts, and reuse of freed ids.

A change gives a new version; readers of the old one are not disturbed. Only
rows at touched nodes are rewritten by ``relink``.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from weftgraph.operators.topology import build_double_link
from weftgraph.plans.common import ordinal


def allocate_ids(free: DataFrame, new: DataFrame, top: int, order: list[str], parts: int | None = None) -> DataFrame:
    """``new`` with column eid: freed ids first, oldest freed first, then fresh ones above ``top``.

    ``free`` has (id, freed_seq). Both sides are numbered by range sorts.
    """
    slots = ordinal(free.select("id", "freed_seq"), ["freed_seq", "id"], "_o", parts).select("_o", "id")
    rows = ordinal(new, order, "_o", parts)
    n = slots.agg(F.count("*")).head()[0]
    got = rows.join(slots, "_o", "left")
    return got.withColumn("eid", F.coalesce("id", F.lit(top) + F.col("_o") - n + 1)).drop("_o", "id")


@dataclass(frozen=True)
class Linked:
    """Edges with insertion order ``seq``, and the queue of freed edge ids."""

    edges: DataFrame
    free: DataFrame
    clock: int = 0

    def links(self) -> tuple[DataFrame, DataFrame]:
        return build_double_link(self.edges)


def start(edges: DataFrame) -> Linked:
    spark = edges.sparkSession
    return Linked(edges.withColumn("seq", F.col("eid")), spark.range(0).select(F.col("id"), F.lit(0).cast("long").alias("freed_seq")), edges.agg(F.max("eid")).head()[0] or 0)


def delete_edges(g: Linked, ids: DataFrame) -> Linked:
    """Edges go; their ids join the queue. Unknown ids change nothing."""
    gone = g.edges.join(ids.select("eid").distinct(), "eid", "left_semi").select(F.col("eid").alias("id"), F.lit(g.clock + 1).cast("long").alias("freed_seq"))
    return Linked(g.edges.join(ids.select("eid").distinct(), "eid", "left_anti"), g.free.unionByName(gone), g.clock + 1)


def delete_nodes(g: Linked, nodes: DataFrame) -> Linked:
    """Nodes go with all their edges."""
    n = nodes.select("nid").distinct()
    touched = g.edges.join(n.withColumnRenamed("nid", "src"), "src", "left_semi").select("eid").unionByName(g.edges.join(n.withColumnRenamed("nid", "dst"), "dst", "left_semi").select("eid"))
    return delete_edges(g, touched)


def insert_edges(g: Linked, new: DataFrame, order: list[str]) -> Linked:
    """New edges take freed ids first; ``order`` gives their order of insertion."""
    top = g.edges.agg(F.max("eid")).head()[0] or 0
    freed = g.free.agg(F.max("id")).head()[0] or 0
    got = allocate_ids(g.free, new, max(top, freed), order)
    placed = ordinal(got, order, "_s").withColumn("seq", F.lit(max(g.clock, top) + 1) + F.col("_s")).drop("_s")
    left = g.free.join(placed.select(F.col("eid").alias("id")), "id", "left_anti")
    return Linked(g.edges.unionByName(placed.select(*g.edges.columns)), left, max(g.clock, top) + 1 + new.count())


def relink_deleted(links: DataFrame, gone: DataFrame) -> DataFrame:
    """Link records after deletion: neighbours of deleted edges are bridged.

    Runs of deleted edges in a chain are jumped over by looking for the
    nearest survivor on either side, at touched nodes only.
    """
    dead = gone.select("eid").distinct().withColumn("dead", F.lit(True))
    sides = links.select("eid", F.explode(F.array(F.struct(F.lit(1).alias("side"), F.col("n1").alias("nid"), F.col("prev1").alias("prev")), F.struct(F.lit(2).alias("side"), F.col("n2").alias("nid"), F.col("prev2").alias("prev")))).alias("e")).select("eid", "e.side", "e.nid", "e.prev")
    flagged = sides.join(dead, "eid", "left")
    touched = flagged.where("dead").select("nid").distinct()
    at = flagged.join(touched, "nid", "left_semi")
    chain = Window.partitionBy("nid").orderBy("eid", "side")
    alive = F.when(F.col("dead").isNull(), F.col("eid"))
    zero = F.lit(0).cast("long")
    fixed = at.withColumns({"p": F.coalesce(F.last(alive, True).over(chain.rowsBetween(Window.unboundedPreceding, -1)), zero), "n": F.coalesce(F.first(alive, True).over(chain.rowsBetween(1, Window.unboundedFollowing)), zero)}).where("dead IS NULL")
    pick = lambda side, c: F.max(F.when(F.col("side") == side, F.col(c)))
    new = fixed.groupBy("eid").agg(pick(1, "p").alias("p1"), pick(2, "p").alias("p2"), pick(1, "n").alias("x1"), pick(2, "n").alias("x2"))
    kept = links.join(dead, "eid", "left_anti").join(new, "eid", "left")
    return kept.select("eid", "n1", "n2", F.coalesce("p1", "prev1").alias("prev1"), F.coalesce("p2", "prev2").alias("prev2"), F.coalesce("x1", "next1").alias("next1"), F.coalesce("x2", "next2").alias("next2"))


def upsert(edges: DataFrame, changes: DataFrame, keys: tuple[str, str] = ("src", "dst")) -> DataFrame:
    """(src, dst, weight, ts) after changes(op, src, dst, weight, ts, seq): the last change of a key wins.

    ``op`` is upsert or delete. Keys without changes keep their row. The
    result does not depend on how changes are batched.
    """
    latest = changes.groupBy(*keys).agg(F.max(F.struct("ts", "seq", "op", "weight")).alias("c"))
    old = edges.select(*keys, F.col("weight").alias("_w"), F.col("ts").alias("_t"))
    both = old.join(latest, list(keys), "full_outer")
    newer = F.col("c").isNotNull() & (F.col("_t").isNull() | (F.col("c.ts") >= F.col("_t")))
    out = both.select(*keys, F.when(newer, F.col("c.weight")).otherwise(F.col("_w")).alias("weight"), F.when(newer, F.col("c.ts")).otherwise(F.col("_t")).alias("ts"), F.when(newer, F.col("c.op") == "delete").otherwise(False).alias("_gone"))
    return out.where("NOT _gone").drop("_gone")
