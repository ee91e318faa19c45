"""The graph: nodes and edges as DataFrames, with the options they were made with.

Only what topology needs is copied into a graph. ``src_key`` leads back to the
row of the table that an edge or node came from, so any column of that table
can restrict a traversal later.
"""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, field, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from weftgraph.plans.common import written

BOTH, FORWARD, BACKWARD = 0, 1, 2
NODE_COLUMNS = {"nid": "long", "name": "string", "x": "double", "y": "double", "labels": "array<string>", "src_key": "string"}
EDGE_COLUMNS = {"eid": "long", "src": "long", "dst": "long", "weight": "long", "direction": "int", "labels": "array<string>", "part": "int", "src_key": "string"}


def with_columns(df: DataFrame, wanted: dict[str, str]) -> DataFrame:
    """``df`` with every wanted column; those it lacks are null. Others follow."""
    given = [F.col(c) for c in df.columns if c not in wanted]
    return df.select(*[F.col(c) if c in df.columns else F.lit(None).cast(t).alias(c) for c, t in wanted.items()], *given)


@dataclass(frozen=True)
class CreateOptions:
    """mode: single, replicated or partitioned; scheme: id_range, box, random, explicit or None (from the roles)."""

    mode: str = "single"
    scheme: str | None = None
    parts: int = 4
    box: tuple[int, int] | None = None
    recreate: bool = False
    merge_tolerance: float = 1e-5
    directed: bool = False


@dataclass(frozen=True)
class Graph:
    """An immutable version of a graph."""

    name: str
    nodes: DataFrame
    edges: DataFrame
    options: CreateOptions = field(default_factory=CreateOptions)
    version: int = 1

    @staticmethod
    def of(name: str, nodes: DataFrame | None, edges: DataFrame, **options) -> Graph:
        """From canonical columns; nodes may be left out and follow from the edges."""
        edges = with_columns(edges, EDGE_COLUMNS)
        edges = edges.withColumn("direction", F.coalesce("direction", F.lit(BOTH)))
        if nodes is None:
            nodes = implied_nodes(edges)
        return Graph(name, with_columns(nodes, NODE_COLUMNS), edges, CreateOptions(**options))

    @property
    def spark(self) -> SparkSession:
        return self.edges.sparkSession

    def arcs(self) -> DataFrame:
        return arcs(self.edges)

    def with_edges(self, edges: DataFrame) -> Graph:
        return replace(self, edges=edges, version=self.version + 1)

    def with_nodes(self, nodes: DataFrame) -> Graph:
        return replace(self, nodes=nodes, version=self.version + 1)

    def materialised(self) -> Graph:
        """Both tables written to the shared folder, so that many solves reuse them."""
        return replace(self, nodes=written(self.nodes, "nodes"), edges=written(self.edges, "edges"))

    def save(self, path: str) -> None:
        """Parquet by part, and a manifest written last, as JSON lines."""
        edges = self.edges.withColumn("part", F.coalesce("part", F.lit(0)))
        edges.write.mode("overwrite").partitionBy("part").parquet(f"{path}/v{self.version}/edges")
        self.nodes.write.mode("overwrite").parquet(f"{path}/v{self.version}/nodes")
        manifest = json.dumps({"name": self.name, "version": self.version, "options": asdict(self.options)})
        self.spark.range(1).select(F.lit(manifest).alias("value")).coalesce(1).write.mode("overwrite").text(f"{path}/manifest")

    @staticmethod
    def load(spark: SparkSession, path: str) -> Graph:
        manifest = json.loads(spark.read.text(f"{path}/manifest").head()["value"])
        options = manifest["options"] | {"box": tuple(manifest["options"]["box"]) if manifest["options"]["box"] else None}
        top = f"{path}/v{manifest['version']}"
        return Graph(manifest["name"], spark.read.parquet(f"{top}/nodes"), with_columns(spark.read.parquet(f"{top}/edges"), EDGE_COLUMNS), CreateOptions(**options), manifest["version"])


def arcs(edges: DataFrame) -> DataFrame:
    """(eid, u, v, w, part): one row for each way an edge may be passed. Loops give one."""
    part = F.col("part") if "part" in edges.columns else F.lit(None).cast("int")
    way = F.coalesce(F.col("direction"), F.lit(BOTH)) if "direction" in edges.columns else F.lit(BOTH)
    one = F.struct(F.col("src").alias("u"), F.col("dst").alias("v"))
    two = F.struct(F.col("dst").alias("u"), F.col("src").alias("v"))
    ways = F.when((way == BACKWARD) & (F.col("src") != F.col("dst")), F.array(two)).when((way == FORWARD) | (F.col("src") == F.col("dst")), F.array(one)).otherwise(F.array(one, two))
    return edges.select("eid", F.explode(ways).alias("a"), F.col("weight").alias("w"), part.alias("part")).select("eid", "a.u", "a.v", "w", "part")


def implied_nodes(edges: DataFrame) -> DataFrame:
    """The end points of the edges, once each."""
    return edges.select(F.explode(F.array("src", "dst")).alias("nid")).distinct()
