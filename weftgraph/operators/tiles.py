"""Adaptive tiles: a rectangle is split into four while it holds too many edges.

Every edge is in the tile of its midpoint, and neighbours may differ by any
number of levels. Tiles are quad prefixes of one text key, so counts of all
levels come from one pass over prefixes.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from weftgraph.functions.geo import segment_meets_box
from weftgraph.model import Graph
from weftgraph.plans.common import cut

MAX_DEPTH = 24


def quad_key(x, y, box: tuple[float, float, float, float], depth: int):
    """A digit (0 to 3) for each level: bit 0 for the right half, bit 1 for the upper half."""
    x0, y0, x1, y1 = (float(v) for v in box)
    side = 1 << depth
    ix = F.least(F.floor((x - x0) / F.lit((x1 - x0) or 1.0) * side), F.lit(side - 1)).cast("long")
    iy = F.least(F.floor((y - y0) / F.lit((y1 - y0) or 1.0) * side), F.lit(side - 1)).cast("long")
    bit = lambda v, i: F.shiftright(v, depth - 1 - i).bitwiseAND(F.lit(1))
    return F.concat(*[(bit(ix, i) + 2 * bit(iy, i)).cast("string") for i in range(depth)])


def build(edges: DataFrame, max_records: int = 500_000, box: tuple[float, float, float, float] | None = None, depth: int = 12) -> DataFrame:
    """``edges`` (with midpoints mx, my) and column tile, the shortest prefix with at most ``max_records``.

    Edges in a cell of the last level stay there however many they are. The
    root's key is the empty text.
    """
    if not 0 < depth <= MAX_DEPTH:
        raise ValueError(f"depth must lie in 1..{MAX_DEPTH}")
    if box is None:
        b = edges.agg(F.min("mx"), F.min("my"), F.max("mx"), F.max("my")).head()
        box = tuple(v if v is not None else 0.0 for v in b)
    keyed = edges.withColumn("_q", quad_key(F.col("mx"), F.col("my"), box, depth))
    leaves = keyed.groupBy("_q").count()
    levels = leaves.select("count", F.explode(F.transform(F.sequence(F.lit(0), F.lit(depth)), lambda i: F.substring("_q", F.lit(1), i))).alias("prefix"))
    counts = levels.groupBy("prefix").agg(F.sum("count").alias("n"))
    # a tile: small enough (or at the last level), with every longer-lived ancestor too large
    big = cut(counts.where((F.col("n") > max_records) & (F.length("prefix") < depth)).select("prefix"))
    if not big.limit(1).count():
        return keyed.withColumn("tile", F.lit("")).drop("_q")
    split = leaves.select("_q", F.explode(F.transform(F.sequence(F.lit(0), F.lit(depth - 1)), lambda i: F.substring("_q", F.lit(1), i))).alias("prefix")).join(big, "prefix").groupBy("_q").agg(F.max(F.length("prefix")).alias("deep"))
    return keyed.join(split, "_q", "left").withColumn("tile", F.substring("_q", F.lit(1), F.coalesce(F.col("deep") + 1, F.lit(0)))).drop("_q", "deep")


def tile_box(tile: str, box: tuple[float, float, float, float]) -> tuple[float, float, float, float]:
    x0, y0, x1, y1 = box
    for digit in tile:
        mx, my = (x0 + x1) / 2, (y0 + y1) / 2
        x0, x1 = (mx, x1) if int(digit) & 1 else (x0, mx)
        y0, y1 = (my, y1) if int(digit) & 2 else (y0, my)
    return x0, y0, x1, y1


def index(tiled: DataFrame) -> DataFrame:
    """(tile, n, xmin, ymin, xmax, ymax): the extent of each tile's edges, of their midpoints where they have no ends (x1, y1, x2, y2)."""
    ends = {"x1", "y1", "x2", "y2"} <= set(tiled.columns)
    x, y = (("x1", "x2"), ("y1", "y2")) if ends else (("mx", "mx"), ("my", "my"))
    return tiled.groupBy("tile").agg(F.count("*").alias("n"), F.min(F.least(*x)).alias("xmin"), F.min(F.least(*y)).alias("ymin"), F.max(F.greatest(*x)).alias("xmax"), F.max(F.greatest(*y)).alias("ymax"))


def stats(tiled: DataFrame) -> DataFrame:
    """(depth, tiles, records, largest) by level."""
    return index(tiled).groupBy(F.length("tile").alias("depth")).agg(F.count("*").alias("tiles"), F.sum("n").alias("records"), F.max("n").alias("largest"))


def save(tiled: DataFrame, path: str, fmt: str = "csv") -> None:
    """One folder for each tile, and the index as Parquet. Root key: t."""
    flat = tiled.select(*[c for c, t in tiled.dtypes if not t.startswith(("array", "map", "struct"))]).withColumn("tile", F.concat(F.lit("t"), "tile"))
    flat.repartition("tile").write.mode("overwrite").partitionBy("tile").format(fmt).option("header", True).save(f"{path}/edges")
    index(tiled).write.mode("overwrite").parquet(f"{path}/index")


def load(spark: SparkSession, path: str, box: tuple[float, float, float, float], schema: str, fmt: str = "csv") -> DataFrame:
    """Edges of the tiles whose edges' extent meets a box, read from those folders only."""
    x0, y0, x1, y1 = box
    meets = spark.read.parquet(f"{path}/index").where((F.col("xmin") <= x1) & (F.col("xmax") >= x0) & (F.col("ymin") <= y1) & (F.col("ymax") >= y0))
    names = [f"t{r['tile']}" for r in meets.select("tile").collect()]  # tiles of one box
    return spark.read.schema(f"{schema}, tile string").format(fmt).option("header", True).load(f"{path}/edges").where(F.col("tile").isin(names))


def refresh(tiled: DataFrame, path: str, schema: str, fmt: str = "csv") -> None:
    """Overwrite only the tiles that ``tiled`` has rows of."""
    spark = tiled.sparkSession
    before = spark.conf.get("spark.sql.sources.partitionOverwriteMode", "static")
    spark.conf.set("spark.sql.sources.partitionOverwriteMode", "dynamic")
    try:
        flat = tiled.select(*[c for c, t in tiled.dtypes if not t.startswith(("array", "map", "struct"))]).withColumn("tile", F.concat(F.lit("t"), "tile"))
        flat.repartition("tile").write.mode("overwrite").partitionBy("tile").format(fmt).option("header", True).save(f"{path}/edges")
    finally:
        spark.conf.set("spark.sql.sources.partitionOverwriteMode", before)
    now = spark.read.schema(f"{schema}, tile string").format(fmt).option("header", True).load(f"{path}/edges").withColumn("tile", F.substring("tile", 2, 1000))
    cut(index(now)).write.mode("overwrite").parquet(f"{path}/index")


def in_box(tiled: DataFrame, box: tuple[float, float, float, float]) -> DataFrame:
    """Edges (with ends x1, y1, x2, y2) that touch a box, exactly."""
    return tiled.where(segment_meets_box(F.col("x1"), F.col("y1"), F.col("x2"), F.col("y2"), *[F.lit(float(v)) for v in box]))


def graph_of(spark: SparkSession, path: str, box: tuple[float, float, float, float], schema: str, fmt: str = "csv") -> Graph:
    """One graph of the edges that touch a box, stitched from all tiles that hold some.

    Edges carry the node ids of their ends, so edges of different tiles meet in
    the same nodes; nodes take their places from the edges' ends.
    """
    edges = in_box(load(spark, path, box, schema, fmt), box)
    ends = F.array(F.struct(F.col("src").alias("nid"), F.col("x1").alias("x"), F.col("y1").alias("y")), F.struct(F.col("dst").alias("nid"), F.col("x2").alias("x"), F.col("y2").alias("y")))
    nodes = edges.select(F.explode(ends).alias("e")).select("e.nid", "e.x", "e.y").groupBy("nid").agg(F.min(F.struct("x", "y")).alias("p")).select("nid", "p.x", "p.y")
    wanted = [c for c in ("eid", "src", "dst", "weight", "direction", "src_key") if c in edges.columns]
    return Graph.of("tiles", nodes, edges.select(*wanted))
