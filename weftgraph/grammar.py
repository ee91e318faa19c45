"""Graphs from annotated columns: roles say what a column is, combinations say how edges come about.

A component is a table with a map from role to column, name or constant. The
roles present pick one of the permitted combinations; anything else is an
error that names what is missing.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from typing import Any

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from weftgraph.functions import geo
from weftgraph.model import BOTH, CreateOptions, Graph, implied_nodes, with_columns
from weftgraph.operators import partition, weights
from weftgraph.plans.common import cut, ordinal

NODE_ROLES = {"node.id", "node.name", "node.x", "node.y", "node.point", "node.label", "node.part_boundary", "node.key"}
#: What gives an edge its ends, and what an edge of that kind may have besides.
TOPOLOGIES = {
    "ids": {"edge.src_id", "edge.dst_id"},
    "names": {"edge.src_name", "edge.dst_name"},
    "points": {"edge.src_point", "edge.dst_point"},
    "line": {"edge.line"},
}
#: The permitted tuples, as (topology, with edge.id, with edge.direction, with edge.label).
COMBINATIONS = [
    ("ids", True, False, False), ("ids", True, True, False), ("names", True, False, False), ("points", True, False, False),
    ("line", True, False, False), ("line", True, True, False), ("ids", False, False, False), ("names", False, False, False),
    ("names", False, False, True), ("points", False, False, False), ("line", False, False, False), ("line", False, True, False),
]
#: Roles that any combination takes in addition.
OPTIONAL = {"edge.weight", "edge.label", "edge.part", "edge.key"}
DEFAULT_SCHEME = {"ids": "id_range", "names": "random", "points": "box", "line": "box"}


@dataclass(frozen=True)
class Component:
    """A table and the roles of its columns; values may be columns, column names, or constants as ``lit``."""

    table: DataFrame
    roles: dict[str, Any] = field(default_factory=dict)

    def column(self, role: str) -> Column:
        v = self.roles[role]
        if isinstance(v, Column):
            return v
        return F.col(v) if isinstance(v, str) else F.lit(v)


@dataclass(frozen=True)
class Combination:
    topology: str
    number: int
    scheme: str


def resolve(roles: set[str]) -> Combination:
    """The combination that edge roles amount to."""
    known = set().union(*TOPOLOGIES.values()) | OPTIONAL | {"edge.id", "edge.direction"}
    if unknown := sorted(roles - known):
        raise ValueError(f"unknown edge roles: {', '.join(unknown)}")
    whole = [t for t, need in TOPOLOGIES.items() if need <= roles]
    begun = [t for t, need in TOPOLOGIES.items() if need & roles]
    if len(begun) > 1:
        raise ValueError(f"roles of several kinds of ends: {', '.join(begun)}")
    if not whole:
        missing = sorted(TOPOLOGIES[begun[0]] - roles) if begun else ["edge.src_id and edge.dst_id, or names, points, or edge.line"]
        raise ValueError(f"edge roles are incomplete; missing: {', '.join(missing)}")
    topology = whole[0]
    key = (topology, "edge.id" in roles, "edge.direction" in roles)
    fits = [i for i, c in enumerate(COMBINATIONS) if c[:3] == key]
    if not fits:
        raise ValueError(f"edge.direction is not taken with these roles: {', '.join(sorted(roles))}")
    labelled = [i for i in fits if COMBINATIONS[i][3] and "edge.label" in roles]
    return Combination(topology, (labelled or fits)[0] + 1, DEFAULT_SCHEME[topology])


def name_dictionary(names: DataFrame) -> DataFrame:
    """(name, nid): ids from 0 in the order of the names; nulls have none."""
    return ordinal(names.select("name").where("name IS NOT NULL").distinct(), ["name"], "nid").select("name", "nid")


def attach_labels(nodes: DataFrame, labels: DataFrame, key: str = "nid") -> DataFrame:
    """Add the labels of ``labels(key, label)``; a node's labels stay sorted and distinct."""
    sets = labels.where("label IS NOT NULL").groupBy(key).agg(F.collect_set("label").alias("_l"))
    got = nodes.join(sets, key, "left")
    empty = F.array().cast("array<string>")
    return got.withColumn("labels", F.array_sort(F.array_distinct(F.concat(F.coalesce("labels", empty), F.coalesce("_l", empty))))).drop("_l")


def _labels(c: Component, role: str) -> Column:
    if role not in c.roles:
        return F.lit(None).cast("array<string>")
    v = c.column(role)
    kind = dict(c.table.select(v.alias("v")).dtypes)["v"]
    return v if kind.startswith("array") else F.when(v.isNotNull(), F.array(v.cast("string")))


def _node_table(c: Component) -> DataFrame:
    if bad := sorted(set(c.roles) - NODE_ROLES):
        raise ValueError(f"unknown node roles: {', '.join(bad)}")
    x, y = F.lit(None).cast("double"), F.lit(None).cast("double")
    if "node.point" in c.roles:
        p = geo.parse_point(c.column("node.point"))
        x, y = p["x"], p["y"]
    elif "node.x" in c.roles and "node.y" in c.roles:
        x, y = c.column("node.x").cast("double"), c.column("node.y").cast("double")
    get = lambda role, kind: c.column(role).cast(kind) if role in c.roles else F.lit(None).cast(kind)
    return c.table.select(get("node.id", "long").alias("nid"), get("node.name", "string").alias("name"), x.alias("x"), y.alias("y"), _labels(c, "node.label").alias("labels"), get("node.key", "string").alias("src_key"))


def create(spark: SparkSession, name: str, edges: list[Component], nodes: list[Component] = (), options: CreateOptions | None = None, overrides: DataFrame | None = None, restricted: DataFrame | None = None, metric: str = "planar") -> Graph:
    """A graph from components.

    ``overrides(eid, value)`` and ``restricted(eid)`` act at creation. Edges
    without ids are numbered in the order of their ends and weight. A missing
    weight is the length of the edge where it has coordinates, else 1. Nodes
    follow from the edges where none are given.
    """
    options = options or CreateOptions()
    plans = [(c, resolve(set(c.roles))) for c in edges]
    kinds = {p.topology for _, p in plans}
    if len(kinds) != 1:
        raise ValueError("all edge components must give their ends in the same way")
    kind = kinds.pop()
    given = None
    for c in nodes:
        t = _node_table(c)
        given = t if given is None else given.unionByName(t)
    rows = None
    for c, _ in plans:
        get = lambda role, cast, c=c: c.column(role).cast(cast) if role in c.roles else F.lit(None).cast(cast)
        base = {"eid": get("edge.id", "long"), "weight": c.column("edge.weight") if "edge.weight" in c.roles else F.lit(None).cast("double"), "direction": F.coalesce(get("edge.direction", "int"), F.lit(1 if options.directed else BOTH)), "labels": _labels(c, "edge.label"), "part": get("edge.part", "int"), "src_key": get("edge.key", "string")}
        if kind == "ids":
            base |= {"_a": get("edge.src_id", "long"), "_b": get("edge.dst_id", "long")}
        elif kind == "names":
            base |= {"_a": get("edge.src_name", "string"), "_b": get("edge.dst_name", "string")}
        elif kind == "points":
            a, b = geo.parse_point(c.column("edge.src_point")), geo.parse_point(c.column("edge.dst_point"))
            base |= {"_line": F.array(a, b)}
        else:
            base |= {"_line": geo.parse_line(c.column("edge.line"))}
        t = c.table.select(*[v.alias(k) for k, v in base.items()])
        rows = t if rows is None else rows.unionByName(t)
    if kind == "ids":
        table = rows.where("_a IS NOT NULL AND _b IS NOT NULL").withColumns({"src": F.col("_a"), "dst": F.col("_b"), "_length": F.lit(None).cast("double")})
        node_table = given
    elif kind == "names":
        names = rows.select(F.explode(F.array("_a", "_b")).alias("name"))
        if given is not None:
            names = names.unionByName(given.select("name"))
        ids = cut(name_dictionary(names))
        table = rows.join(ids.toDF("_a", "src"), "_a").join(ids.toDF("_b", "dst"), "_b").withColumn("_length", F.lit(None).cast("double"))
        extra = given.drop("nid") if given is not None else None
        node_table = ids if extra is None else ids.join(extra, "name", "left")
    else:
        table, node_table = _from_lines(rows.where("_line IS NOT NULL"), given, options.merge_tolerance, metric)
    if dict(table.dtypes)["weight"] in ("double", "float"):
        weight = F.coalesce(F.col("weight"), F.col("_length"), F.lit(1.0))
    else:
        weight = F.coalesce(F.col("weight").cast("long"), F.lit(1).cast("long"))
    table = table.withColumn("weight", weight).select("eid", "src", "dst", "weight", "direction", "labels", "part", "src_key")
    if any("edge.id" not in c.roles for c, _ in plans):
        numbered = table.withColumns({"_lo": F.least("src", "dst"), "_hi": F.greatest("src", "dst"), "_l": F.to_json("labels")})
        table = ordinal(numbered.drop("eid"), ["_lo", "_hi", "src", "weight", "_l"], "eid").drop("_lo", "_hi", "_l")
    g = Graph(name, with_columns(node_table if node_table is not None else implied_nodes(table), {"nid": "long", "name": "string", "x": "double", "y": "double", "labels": "array<string>", "src_key": "string"}), table.select("eid", "src", "dst", "weight", "direction", "labels", "part", "src_key"), options)
    if overrides is not None:
        g = weights.override(g, overrides)
    if restricted is not None:
        g = weights.restrict_edges(g, off=restricted)
    if options.mode == "partitioned":
        g = {"id_range": lambda: partition.by_id_range(g, options.parts), "random": lambda: partition.by_random(g, options.parts), "box": lambda: partition.by_box(g, *(options.box or (1, options.parts))), "explicit": lambda: partition.explicit(g, F.col("part")), None: lambda: partition.auto(g, options.parts)}[options.scheme]()
    return g


def _from_lines(rows: DataFrame, given: DataFrame | None, tolerance: float, metric: str) -> tuple[DataFrame, DataFrame]:
    """Ends of lines that lie within the tolerance, and chains of those, become one node; given nodes keep their ids.

    A node is represented by its given node with the smallest id, or by the
    first end in the order of its coordinates. New ids follow the order of the
    representatives by bins of the tolerance, lower rows first.
    """
    first, last = F.col("_line")[0], F.element_at("_line", -1)
    lines = rows.withColumns({"_ax": first["x"], "_ay": first["y"], "_bx": last["x"], "_by": last["y"], "_length": geo.line_length(F.col("_line"), metric)})
    spots = lines.select(F.explode(F.array(F.struct(F.col("_ax").alias("x"), F.col("_ay").alias("y")), F.struct(F.col("_bx").alias("x"), F.col("_by").alias("y")))).alias("e")).select("e.x", "e.y")
    if given is not None:
        spots = spots.unionByName(given.where("x IS NOT NULL AND y IS NOT NULL").select("x", "y"))
    spots = cut(ordinal(spots.distinct(), ["x", "y"], "pid"))
    group = geo.merge_points(spots, tolerance, "linked")
    # the smallest number of a group is its first end in the order of coordinates
    merged = spots.join(group, "pid").select("x", "y", "rep")
    reps = spots.join(group.select(F.col("rep").alias("pid")).distinct(), "pid", "left_semi").select(F.col("pid").alias("rep"), "x", "y", geo.cell(F.col("x"), tolerance).alias("cx"), geo.cell(F.col("y"), tolerance).alias("cy"))
    if given is None:
        nodes = cut(ordinal(reps, ["cy", "cx", "rep"], "nid"))
        named = nodes.select("nid", "x", "y")
        of_group = nodes.select("rep", "nid")
    else:
        own = given.join(merged.withColumnsRenamed({"x": "_gx", "y": "_gy"}), (F.col("x") == F.col("_gx")) & (F.col("y") == F.col("_gy"))).groupBy("rep").agg(F.min_by(F.struct(*given.columns), "nid").alias("n")).select("rep", "n.*")
        lone = given.where("x IS NULL OR y IS NULL")
        top = (given.agg(F.max("nid")).head()[0] or 0) + 1
        new = reps.join(own.select("rep"), "rep", "left_anti")
        fresh = ordinal(new, ["cy", "cx", "rep"], "_o").select("rep", (F.lit(top) + F.col("_o")).alias("nid"), "x", "y")
        nodes = cut(own.unionByName(fresh, allowMissingColumns=True))
        named = nodes.drop("rep").unionByName(lone, allowMissingColumns=True)
        of_group = nodes.select("rep", "nid")
    at = cut(merged.join(of_group, "rep").select("x", "y", "nid"))
    table = lines.join(at.toDF("_ax", "_ay", "src"), ["_ax", "_ay"]).join(at.toDF("_bx", "_by", "dst"), ["_bx", "_by"])
    return table, named


def label_nodes(graph: Graph, label: Column) -> Graph:
    """Add a label given by an expression over the node columns."""
    empty = F.array().cast("array<string>")
    added = F.when(label.isNotNull(), F.array_sort(F.array_distinct(F.array_append(F.coalesce("labels", empty), label)))).otherwise(F.col("labels"))
    return graph.with_nodes(graph.nodes.withColumn("labels", added))
