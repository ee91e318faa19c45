"""Fixture graphs on the given tables, each with the SQL of its twin.

Road lattices are arithmetic on dense keys, so both engines agree to the bit.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from weftgraph.model import Graph
from weftgraph.operators.groups import Groups
from weftgraph.plans.common import table

LON0, LAT0, STEP = -77.5, 38.7, 0.001


def width_of(n: int) -> int:
    """Nodes in a row of the road lattice."""
    return 40 if n <= 2000 else 100


def multiplier_of(n: int) -> int:
    """Scrambles the ids of the lattice; prime to the node counts used."""
    return 797 if n <= 2000 else 7919


def _lattice_edges(nodes: DataFrame, n: int, w: int, attribute: str, base: int) -> DataFrame:
    """Right and upper neighbours; eid is the rank by (src, dst)."""
    nid = F.col("nid")
    has_right = ((nid % w) < w - 1) & (nid + 1 < n)
    rank = F.floor(nid / w).cast("long") * (w - 1) + nid % w + F.least(nid, F.lit(max(0, n - w)))
    ways = F.filter(F.array(F.struct(F.when(has_right, nid + 1).alias("dst"), rank.alias("eid")), F.struct(F.when(nid + w < n, nid + w).alias("dst"), (rank + has_right.cast("long")).alias("eid"))), lambda s: s["dst"].isNotNull())
    out = nodes.select(nid.alias("src"), F.col(attribute).alias("_a"), F.explode(ways).alias("s")).select("src", "_a", "s.dst", "s.eid")
    far = nodes.select(nid.alias("dst"), F.col(attribute).alias("_b"))
    return out.join(far, "dst").select("eid", "src", "dst", (F.lit(base) + F.col("_a") + F.col("_b")).cast("long").alias("weight"))


def road(spark: SparkSession, sf_dir: str) -> Graph:
    """Lattice over part: weights from sizes, labels from brand and type."""
    part = table(spark, sf_dir, "part")
    n = part.count()
    w = width_of(n)
    base = part.select(F.col("p_partkey").alias("nid"), F.col("p_size").cast("long").alias("_size"), F.col("p_name").alias("name"), F.array("p_brand", "p_type").alias("labels"))
    nodes = base.withColumns({"x": (F.col("nid") % w).cast("double"), "y": F.floor(F.col("nid") / w).cast("double")})
    return Graph.of("road", nodes.drop("_size"), _lattice_edges(base, n, w, "_size", 10))


def scrambled_road(spark: SparkSession, sf_dir: str) -> Graph:
    """The same lattice with ids interlaced, as a bad case for id ranges."""
    g = road(spark, sf_dir)
    n = table(spark, sf_dir, "part").count()
    m = multiplier_of(n)
    move = lambda c: (F.col(c) * m) % n
    return Graph("scrambled", g.nodes.withColumn("nid", move("nid")), g.edges.withColumns({"src": move("src"), "dst": move("dst")}), g.options)


def order_grid(spark: SparkSession, sf_dir: str) -> Graph:
    """Lattice over orders, 100 wide: weights from prices, one-way where the order is finished."""
    orders = table(spark, sf_dir, "orders")
    n = orders.count()
    base = orders.select(F.col("o_orderkey").alias("nid"), F.floor(F.col("o_totalprice") / 10000).cast("long").alias("_p"), "o_orderstatus", "o_orderpriority")
    nodes = base.select("nid", (F.col("nid") % 100).cast("double").alias("x"), F.floor(F.col("nid") / 100).cast("double").alias("y"))
    edges = _lattice_edges(base, n, 100, "_p", 10)
    traits = base.select(F.col("nid").alias("src"), F.when(F.col("o_orderstatus") == "F", 1).otherwise(0).alias("direction"), F.array("o_orderpriority").alias("labels"))
    return Graph.of("orders", nodes, edges.join(traits, "src"))


def knows_groups(spark: SparkSession, sf_dir: str) -> Groups:
    """Customers by day and priority of their orders; whoever shares one is acquainted since the first such year."""
    o = table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("c"), F.to_date("o_orderdate").alias("d"), F.col("o_orderpriority").alias("p"), F.year("o_orderdate").cast("long").alias("yr"))
    return Groups.of(o, ["d", "p"], "c", "yr")


def knows_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(a, b, since): customers with an order of one day and priority; since is the first such year."""
    return knows_groups(spark, sf_dir).pairs()


def _known(a: Column, b: Column) -> tuple[Column, Column]:
    """Id and weight of the edge between two customers, the smaller one first."""
    return (a * 1_000_000 + b).alias("eid"), (1 + (a * 31 + b * 17) % 20).alias("weight")


def knows_steps(groups: Groups, since: int | None = None) -> Callable[[DataFrame], DataFrame]:
    """Arcs (eid, v, w) of the social graph that leave the rows' node ``at``, made when they are met, all or those since a year."""

    def steps(rows: DataFrame) -> DataFrame:
        eid, weight = _known(F.least("at", "v"), F.greatest("at", "v"))
        return groups.steps(rows, "at", since).select(*rows.columns, "v", eid, weight.alias("w"))

    return steps


def knows(spark: SparkSession, sf_dir: str, groups: Groups | None = None) -> Graph:
    """Social graph over customer; ``since`` stays in the base table."""
    pairs = (groups or knows_groups(spark, sf_dir)).pairs(None, False)
    edges = pairs.select(*_known(F.col("a"), F.col("b")), F.col("a").alias("src"), F.col("b").alias("dst")).select("eid", "src", "dst", "weight")
    nodes = table(spark, sf_dir, "customer").select(F.col("c_custkey").alias("nid"), F.col("c_name").alias("name"), F.array("c_mktsegment").alias("labels"))
    return Graph.of("knows", nodes, edges)


KIND = 1_000_000_000


def purchases(spark: SparkSession, sf_dir: str) -> Graph:
    """Property graph of customers, parts, suppliers, nations and regions; ids are kind x 10^9 + key."""
    t = lambda n: table(spark, sf_dir, n)
    node = lambda df, kind, key, *labels: df.select((F.lit(kind * KIND) + F.col(key).cast("long")).alias("nid"), F.array(*labels).alias("labels"))
    nodes = node(t("customer"), 1, "c_custkey", F.lit("customer"), "c_mktsegment")
    for other in (node(t("part"), 2, "p_partkey", F.lit("part"), "p_brand"), node(t("supplier"), 3, "s_suppkey", F.lit("supplier"), F.lit("supplier")), node(t("nation"), 4, "n_nationkey", F.lit("nation"), "n_name"), node(t("region"), 5, "r_regionkey", F.lit("region"), "r_name")):
        nodes = nodes.unionByName(other)
    edge = lambda df, label, a, ka, b, kb, w: df.select((F.lit(ka * KIND) + F.col(a).cast("long")).alias("src"), (F.lit(kb * KIND) + F.col(b).cast("long")).alias("dst"), F.lit(label).alias("label"), w.alias("weight"))
    items = t("lineitem").join(t("orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey"), "l_orderkey")
    bought = items.select((F.lit(KIND) + F.col("o_custkey")).alias("src"), (F.lit(2 * KIND) + F.col("l_partkey")).alias("dst"), F.concat(F.lit("bought:"), "l_returnflag").alias("label"), F.floor("l_quantity").cast("long").alias("weight"))
    one = F.lit(1).cast("long")
    edges = bought.unionByName(edge(items, "supplied", "l_partkey", 2, "l_suppkey", 3, F.floor("l_quantity").cast("long")))
    edges = edges.unionByName(edge(t("supplier"), "in_nation", "s_suppkey", 3, "s_nationkey", 4, one)).unionByName(edge(t("customer"), "in_nation", "c_custkey", 1, "c_nationkey", 4, one)).unionByName(edge(t("nation"), "in_region", "n_nationkey", 4, "n_regionkey", 5, one))
    each = edges.groupBy("src", "dst", "label").agg(F.sum("weight").alias("weight"))
    return Graph.of("purchases", nodes, each.select(F.xxhash64("src", "dst", "label").alias("eid"), "src", "dst", "weight", F.array("label").alias("labels")))


def trade(spark: SparkSession, sf_dir: str) -> Graph:
    """Nations, directed from customers' to suppliers', weighed by line items."""
    t = lambda n: table(spark, sf_dir, n)
    items = t("lineitem").select("l_orderkey", "l_suppkey").join(t("orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey"), "l_orderkey")
    flow = items.join(t("customer").select(F.col("c_custkey").alias("o_custkey"), F.col("c_nationkey").cast("long").alias("src")), "o_custkey").join(t("supplier").select(F.col("s_suppkey").alias("l_suppkey"), F.col("s_nationkey").cast("long").alias("dst")), "l_suppkey")
    edges = flow.groupBy("src", "dst").agg(F.count("*").alias("weight")).select((F.col("src") * 1000 + F.col("dst")).alias("eid"), "src", "dst", "weight", F.lit(1).alias("direction"))
    return Graph.of("trade", t("nation").select(F.col("n_nationkey").cast("long").alias("nid"), F.col("n_name").alias("name")), edges)


def turns_chain(spark: SparkSession, sf_dir: str) -> Graph:
    """Conversations as chains of turns; nid is conv x 1000 + turn."""
    c = table(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("nid")).distinct()
    e = c.select(F.col("nid").alias("src"), (F.col("nid") + 1).alias("dst")).join(c.withColumnRenamed("nid", "dst"), "dst", "left_semi")
    return Graph.of("turns", c, e.select(F.col("src").alias("eid"), "src", "dst", F.lit(1).cast("long").alias("weight"), F.lit(1).alias("direction")))


def word_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(w1, w2): distinct consecutive words of all documents, whole texts."""
    words = table(spark, sf_dir, "documents").select(F.regexp_extract_all(F.lower("text"), F.lit("[a-z]+"), F.lit(0)).alias("w"))
    pairs = words.where(F.size("w") > 1).select(F.explode(F.array_distinct(F.arrays_zip(F.slice("w", 1, F.size("w") - 1).alias("w1"), F.slice("w", 2, F.size("w") - 1).alias("w2")))).alias("p"))
    return pairs.select("p.w1", "p.w2").where("w1 <> w2").distinct()


def gps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(trip_id, seq, ts, x, y, true_x, true_y): noisy lattice walks, one per user of events."""
    from pyspark.sql import Window

    n = table(spark, sf_dir, "part").count()
    w = width_of(n)
    cx, cy = w // 2, (n // w) // 2
    e = table(spark, sf_dir, "events")
    kind = F.col("event_type")
    dx = F.when(kind == "click", 1).when(kind == "signup", -1).otherwise(0)
    dy = F.when(kind == "view", 1).when(kind == "purchase", -1).otherwise(0)
    so_far = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    walk = e.select("user_id", "ts", "event_id", F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id")).cast("long").alias("seq"), (F.lit(cx) + F.sum(dx).over(so_far)).cast("long").alias("tx"), (F.lit(cy) + F.sum(dy).over(so_far)).cast("long").alias("ty"), "value")
    ex = (F.floor(F.col("value") * 100) % 41 - 20) / 100.0
    ey = ((F.col("event_id") * 7) % 41 - 20) / 100.0
    return walk.select(F.col("user_id").alias("trip_id"), "seq", "ts", (F.col("tx") + ex).alias("x"), (F.col("ty") + ey).alias("y"), "tx", "ty")


# ---------------------------------------------------------------- SQL twins

ROAD_SQL = """
    road_n AS MATERIALIZED (SELECT count(*) AS n, CASE WHEN count(*) <= 2000 THEN 40 ELSE 100 END AS w, CASE WHEN count(*) <= 2000 THEN 797 ELSE 7919 END AS m FROM part),
    road_nodes AS MATERIALIZED (SELECT p_partkey AS nid, p_size::BIGINT AS size, p_partkey % w AS x, p_partkey // w AS y, n, w, m, p_brand, p_type FROM part, road_n),
    road_edges AS MATERIALIZED (
        SELECT row_number() OVER (ORDER BY src, dst) - 1 AS eid, src, dst, weight FROM (
            SELECT a.nid AS src, b.nid AS dst, 10 + a.size + b.size AS weight FROM road_nodes a JOIN road_nodes b ON b.nid = a.nid + 1 WHERE a.x < a.w - 1
            UNION ALL SELECT a.nid, b.nid, 10 + a.size + b.size FROM road_nodes a JOIN road_nodes b ON b.nid = a.nid + a.w) e)"""
ROAD_ARCS_SQL = "road_arcs AS MATERIALIZED (SELECT eid, src AS u, dst AS v, weight AS w FROM road_edges UNION ALL SELECT eid, dst, src, weight FROM road_edges)"
SCRAMBLED_SQL = """
    scr_nodes AS MATERIALIZED (SELECT (nid * m) % n AS nid, x, y, n FROM road_nodes),
    scr_edges AS MATERIALIZED (SELECT eid, (src * m) % n AS src, (dst * m) % n AS dst, weight FROM road_edges, road_n),
    scr_arcs AS MATERIALIZED (SELECT eid, src AS u, dst AS v, weight AS w FROM scr_edges UNION ALL SELECT eid, dst, src, weight FROM scr_edges)"""
ORDERS_SQL = """
    ord_n AS MATERIALIZED (SELECT count(*) AS n FROM orders),
    ord_nodes AS MATERIALIZED (SELECT o_orderkey AS nid, floor(o_totalprice / 10000)::BIGINT AS p, o_orderstatus, o_orderpriority, o_orderkey % 100 AS x, o_orderkey // 100 AS y FROM orders),
    ord_edges AS MATERIALIZED (
        SELECT row_number() OVER (ORDER BY src, dst) - 1 AS eid, src, dst, weight, direction, label FROM (
            SELECT a.nid AS src, b.nid AS dst, 10 + a.p + b.p AS weight, CASE WHEN a.o_orderstatus = 'F' THEN 1 ELSE 0 END AS direction, a.o_orderpriority AS label
            FROM ord_nodes a JOIN ord_nodes b ON b.nid = a.nid + 1 WHERE a.x < 99
            UNION ALL SELECT a.nid, b.nid, 10 + a.p + b.p, CASE WHEN a.o_orderstatus = 'F' THEN 1 ELSE 0 END, a.o_orderpriority FROM ord_nodes a JOIN ord_nodes b ON b.nid = a.nid + 100) e),
    ord_arcs AS MATERIALIZED (SELECT eid, src AS u, dst AS v, weight AS w FROM ord_edges UNION ALL SELECT eid, dst, src, weight FROM ord_edges WHERE direction = 0)"""
KNOWS_SQL = """
    know_o AS MATERIALIZED (SELECT DISTINCT o_custkey AS c, o_orderdate::DATE AS d, o_orderpriority AS p, year(o_orderdate)::BIGINT AS yr FROM orders),
    know_base AS MATERIALIZED (SELECT l.c AS a, r.c AS b, min(l.yr) AS since FROM know_o l JOIN know_o r ON l.d = r.d AND l.p = r.p AND l.c < r.c GROUP BY l.c, r.c),
    know_edges AS MATERIALIZED (SELECT a * 1000000 + b AS eid, a AS src, b AS dst, 1 + (a * 31 + b * 17) % 20 AS weight FROM know_base),
    know_arcs AS MATERIALIZED (SELECT eid, src AS u, dst AS v, weight AS w FROM know_edges UNION ALL SELECT eid, dst, src, weight FROM know_edges)"""
TRADE_SQL = """
    trade_edges AS MATERIALIZED (SELECT c_nationkey::BIGINT AS src, s_nationkey::BIGINT AS dst, count(*) AS weight
        FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN supplier ON s_suppkey = l_suppkey GROUP BY ALL)"""


def sssp_sql(seed: str, arcs: str, name: str = "dist", bound: str = "") -> str:
    """Keyed recursion for least costs: ``seed`` selects (nid, cost), ``arcs`` has u, v, w."""
    return f"""{name}(nid, cost) USING KEY (nid) AS (
        {seed}
        UNION
        SELECT a.v, min(d.cost + a.w) FROM {name} d JOIN {arcs} a ON a.u = d.nid LEFT JOIN recurring.{name} r ON r.nid = a.v
        {bound} GROUP BY a.v, r.cost HAVING r.cost IS NULL OR min(d.cost + a.w) < r.cost)"""
