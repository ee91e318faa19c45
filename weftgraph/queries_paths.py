"""Shortest path queries: engines, restrictions, turns, paths."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from weftgraph import workloads as w
from weftgraph.catalog import query
from weftgraph.operators import partition, paths, sssp, turns, weights
from weftgraph.plans.common import cut, table

SEED_0 = "SELECT 0::BIGINT, 0::BIGINT"
ROAD = f"{w.ROAD_SQL}, {w.ROAD_ARCS_SQL}"


def boxed_road(spark: SparkSession, sf_dir: str):
    return partition.by_box(w.road(spark, sf_dir).materialised(), 2, 2).materialised()


@query(f"WITH RECURSIVE {w.KNOWS_SQL}, {w.sssp_sql(SEED_0, 'know_arcs')} SELECT nid, cost FROM dist")
def sssp_flat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edge-at-a-time relaxation over the social graph."""
    return sssp.costs(w.knows(spark, sf_dir).materialised(), 0, "flat")


@query(f"WITH RECURSIVE {w.KNOWS_SQL}, {w.sssp_sql(SEED_0, 'know_arcs')} SELECT nid, cost FROM dist")
def sssp_delta(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same by buckets of cost."""
    return sssp.costs(w.knows(spark, sf_dir).materialised(), 0, "delta", delta=8)


@query(f"WITH RECURSIVE {ROAD}, {w.sssp_sql(SEED_0, 'road_arcs')} SELECT nid, cost FROM dist")
def sssp_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Partition-centric solve over four boxes."""
    return sssp.costs(boxed_road(spark, sf_dir), 0, "parts")


@query(f"WITH RECURSIVE {ROAD}, {w.sssp_sql(SEED_0, 'road_arcs')} SELECT nid, cost FROM dist")
def sssp_single(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The whole graph in one kernel."""
    return sssp.costs(w.road(spark, sf_dir).materialised(), 0, "single")


@query(f"WITH RECURSIVE {ROAD}, {w.sssp_sql(SEED_0, 'road_arcs')} SELECT nid, cost FROM dist")
def sssp_21_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three by seven boxes give the same costs."""
    return sssp.costs(partition.by_box(w.road(spark, sf_dir).materialised(), 3, 7), 0, "parts")


MANY = """dist(source, nid, cost) USING KEY (source, nid) AS (
        SELECT nid, nid, 0::BIGINT FROM road_nodes WHERE nid % 499 = 0
        UNION
        SELECT d.source, a.v, min(d.cost + a.w) FROM dist d JOIN road_arcs a ON a.u = d.nid LEFT JOIN recurring.dist r ON r.nid = a.v AND r.source = d.source
        GROUP BY d.source, a.v, r.cost HAVING r.cost IS NULL OR min(d.cost + a.w) < r.cost)"""


@query(f"WITH RECURSIVE {ROAD}, {MANY} SELECT source, nid, cost FROM dist")
def sssp_replicated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Replicated mode: several sources shared among tasks."""
    g = w.road(spark, sf_dir).materialised()
    return sssp.many_costs(g, g.nodes.where("nid % 499 = 0"))


@query(f"WITH RECURSIVE {w.ORDERS_SQL}, {w.sssp_sql(SEED_0, 'ord_arcs')} SELECT nid, cost FROM dist")
def sssp_directed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One-way edges where the order of the tail is finished."""
    return sssp.costs(partition.by_box(w.order_grid(spark, sf_dir).materialised(), 2, 2), 0)


@query(f"WITH RECURSIVE {w.ORDERS_SQL}, {w.sssp_sql(SEED_0, 'ord_arcs')}, pick AS (SELECT nid FROM ord_nodes WHERE nid % ((SELECT n FROM ord_n) // 5) = 77) SELECT nid, cost FROM dist WHERE nid IN (SELECT nid FROM pick)")
def sssp_five_targets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One source to five destinations over four boxes."""
    g = partition.by_box(w.order_grid(spark, sf_dir).materialised(), 2, 2)
    n = table(spark, sf_dir, "orders").count()
    return sssp.costs(g, 0, targets=g.nodes.where(F.col("nid") % (n // 5) == 77))


@query(f"WITH RECURSIVE {w.ORDERS_SQL}, back AS MATERIALIZED (SELECT v AS u, u AS v, w FROM ord_arcs), {w.sssp_sql('SELECT 77::BIGINT, 0::BIGINT', 'back')} SELECT nid, cost FROM dist")
def inverse_sp(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Costs from every node to one destination."""
    return sssp.inverse(partition.by_box(w.order_grid(spark, sf_dir).materialised(), 2, 2), 77)


@query(f"""WITH RECURSIVE {w.ROAD_SQL}, bad AS (SELECT eid FROM road_edges JOIN part ON p_partkey = src WHERE p_brand = (SELECT min(p_brand) FROM part)),
    road_arcs AS MATERIALIZED (SELECT src AS u, dst AS v, weight AS w FROM road_edges WHERE eid NOT IN (SELECT eid FROM bad) UNION ALL SELECT dst, src, weight FROM road_edges WHERE eid NOT IN (SELECT eid FROM bad)),
    {w.sssp_sql(SEED_0, 'road_arcs')} SELECT nid, cost FROM dist""")  # fmt: skip
def sssp_restricted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges of one brand are switched off at solve time, by a column that the base table holds."""
    g = w.road(spark, sf_dir).materialised()
    part = table(spark, sf_dir, "part")
    brand = part.agg(F.min("p_brand")).head()[0]
    off = g.edges.join(part.where(F.col("p_brand") == brand).select(F.col("p_partkey").alias("src")), "src").select("eid")
    return sssp.costs(partition.by_box(weights.restrict_edges(g, off=off).materialised(), 2, 2), 0)


@query(f"""WITH RECURSIVE {w.ROAD_SQL}, cheap AS (SELECT eid FROM road_edges JOIN part ON p_partkey = src WHERE p_retailprice > 1500),
    e AS MATERIALIZED (SELECT eid, src, dst, CASE WHEN eid IN (SELECT eid FROM cheap) THEN 1 ELSE weight END AS weight FROM road_edges),
    road_arcs AS MATERIALIZED (SELECT src AS u, dst AS v, weight AS w FROM e UNION ALL SELECT dst, src, weight FROM e),
    {w.sssp_sql(SEED_0, 'road_arcs')} SELECT nid, cost FROM dist""")  # fmt: skip
def sssp_weight_override(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Weights given at solve time replace those of creation."""
    g = w.road(spark, sf_dir).materialised()
    dear = table(spark, sf_dir, "part").where("p_retailprice > 1500").select(F.col("p_partkey").alias("src"))
    values = g.edges.join(dear, "src").select("eid", F.lit(1).cast("long").alias("value"))
    return sssp.costs(partition.by_box(weights.override(g, values).materialised(), 2, 2), 0)


@query(f"""WITH RECURSIVE {ROAD}, scaled AS MATERIALIZED (SELECT u, v, w * 1000 AS w FROM road_arcs),
    {w.sssp_sql("SELECT nid, rank() OVER (ORDER BY nid) - 1 FROM (SELECT DISTINCT (s_suppkey * 13) % n AS nid FROM supplier, road_n WHERE s_suppkey < 7) s", 'scaled')},
    src AS (SELECT nid AS source, rank() OVER (ORDER BY nid) - 1 AS i FROM (SELECT DISTINCT (s_suppkey * 13) % n AS nid FROM supplier, road_n WHERE s_suppkey < 7) s)
    SELECT nid, source, cost // 1000 AS cost FROM dist JOIN src ON i = cost % 1000""")  # fmt: skip
def nearest_source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The nearest of seven suppliers on the road, ties to the smaller node."""
    g = w.road(spark, sf_dir).materialised()
    n = table(spark, sf_dir, "part").count()
    s = table(spark, sf_dir, "supplier").where("s_suppkey < 7").select(((F.col("s_suppkey") * 13) % n).alias("nid"))
    return sssp.nearest_source(g, s)


@query(f"""WITH RECURSIVE {ROAD}, c AS MATERIALIZED (SELECT nid, x::DOUBLE AS x, y::DOUBLE AS y FROM road_nodes),
    arc AS MATERIALIZED (SELECT eid * 2 + (u > v)::INT AS a, u, v, w, degrees(atan2(cv.y - cu.y, cv.x - cu.x)) AS b FROM road_arcs JOIN c cu ON cu.nid = u JOIN c cv ON cv.nid = v),
    mv AS (SELECT p.a AS a1, q.a AS a2, q.w, 180 - (((180 - (q.b - p.b)) % 360) + 360) % 360 AS t FROM arc p JOIN arc q ON p.v = q.u),
    mw AS MATERIALIZED (SELECT a1 AS u, a2 AS v, w + CASE WHEN t > 20 THEN 30 ELSE 0 END AS w FROM mv WHERE abs(t) < 160 AND NOT (a1 = 0 AND a2 = 4)),
    {w.sssp_sql("SELECT a, w FROM arc WHERE u = 0", 'mw')}
    SELECT v AS nid, min(cost) AS cost FROM dist JOIN arc ON a = nid WHERE v <> 0 GROUP BY v UNION ALL SELECT 0, 0""")  # fmt: skip
def sssp_turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Left turns cost 30, u-turns and one named movement are forbidden."""
    g = w.road(spark, sf_dir).materialised()
    ban = g.spark.range(1).select(F.lit(0).cast("long").alias("eid_in"), F.lit(2).cast("long").alias("eid_out"), F.lit(None).cast("long").alias("extra"))
    return turns.costs(g, 0, turns.TurnRules(left=30, moves=ban))


def _upper_right(g):
    x, y = g.nodes.agg(F.max("x"), F.max("y")).head()
    return g.nodes.where((F.col("x") > x / 2) & (F.col("y") > y / 2)).orderBy("nid").limit(100).select("nid")


def _paths(spark: SparkSession, sf_dir: str) -> tuple:
    g = boxed_road(spark, sf_dir)
    found = cut(sssp.costs(g, 0))
    return g, paths.aggregate(g, found, _upper_right(g))


WALK = f"""{ROAD}, {w.sssp_sql(SEED_0, 'road_arcs')},
    tight AS MATERIALIZED (SELECT a.v AS nid, arg_min(a.u, (a.u, a.eid)) AS pred, arg_min(a.eid, (a.u, a.eid)) AS eid FROM road_arcs a JOIN dist du ON du.nid = a.u JOIN dist dv ON dv.nid = a.v WHERE dv.cost = du.cost + a.w GROUP BY a.v),
    target AS MATERIALIZED (SELECT nid FROM road_nodes WHERE x > (SELECT max(x) FROM road_nodes) / 2 AND y > (SELECT max(y) FROM road_nodes) / 2 ORDER BY nid LIMIT 100),
    walk(target, back, nid) AS (SELECT nid, 0, nid FROM target UNION ALL SELECT target, back + 1, t.pred FROM walk JOIN tight t ON t.nid = walk.nid),
    long AS MATERIALIZED (SELECT target, (max(back) OVER (PARTITION BY target) - back)::INTEGER AS step, nid FROM walk)"""


@query(f"WITH RECURSIVE {WALK} SELECT target, step, long.nid, cost FROM long JOIN dist ON dist.nid = long.nid")
def sssp_paths_100(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One source to the first hundred nodes of the upper right quarter, with paths."""
    return _paths(spark, sf_dir)[1].select("target", "step", "nid", "cost")


@query(f"""WITH RECURSIVE {WALK}, ext AS (SELECT max(x) AS mx, max(y) AS my FROM road_nodes),
    home AS MATERIALIZED (SELECT nid, least(floor(y * 2 / my::DOUBLE), 1) * 2 + least(floor(x * 2 / mx::DOUBLE), 1) AS h FROM road_nodes, ext),
    hop AS MATERIALIZED (SELECT a.target, a.step, least(h1.h, h2.h) AS part FROM long a JOIN long b ON a.target = b.target AND b.step = a.step - 1 JOIN home h1 ON h1.nid = a.nid JOIN home h2 ON h2.nid = b.nid),
    runs AS (SELECT target, part, (part IS DISTINCT FROM lag(part) OVER (PARTITION BY target ORDER BY step))::INT AS new FROM hop)
    SELECT target, sum(new)::BIGINT AS stays, count(DISTINCT part) AS parts FROM runs GROUP BY target""")  # fmt: skip
def path_part_revisits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stays in parts against distinct parts: more stays mean that a part is visited again."""
    return paths.stays(_paths(spark, sf_dir)[1])


@query(f"""WITH RECURSIVE {WALK} SELECT target, 'LINESTRING(' || string_agg(x::DOUBLE::VARCHAR || ' ' || y::DOUBLE::VARCHAR, ', ' ORDER BY step) || ')' AS wkt FROM long JOIN road_nodes ON road_nodes.nid = long.nid GROUP BY target""")
def path_wkt(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each path as one line string."""
    g, steps = _paths(spark, sf_dir)
    return paths.to_wkt(steps, g.nodes)


@query(f"""WITH RECURSIVE {w.ROAD_SQL}, f AS (SELECT eid, CASE WHEN eid % 3 = 0 THEN 2.5 WHEN eid % 3 = 1 THEN 0.5 ELSE 1.0 END AS k FROM road_edges),
    e AS MATERIALIZED (SELECT eid, src, dst, round(weight * k)::BIGINT AS weight FROM road_edges JOIN f USING (eid)),
    road_arcs AS MATERIALIZED (SELECT src AS u, dst AS v, weight AS w FROM e UNION ALL SELECT dst, src, weight FROM e),
    {w.sssp_sql(SEED_0, 'road_arcs')} SELECT nid, cost FROM dist""")  # fmt: skip
def sssp_by_time(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Weights at half past eight, from a profile of multipliers by hour."""
    g = w.road(spark, sf_dir).materialised()
    rows = F.array(*[F.struct(F.lit(h).alias("hour"), F.lit(a).alias("a"), F.lit(b).alias("b")) for h, a, b in ((6, 1.0, 1.0), (8, 2.5, 0.5), (17, 4.0, 3.0))])
    profile = g.edges.where("eid % 3 < 2").select("eid", F.explode(rows).alias("r")).select("eid", "r.hour", F.when(F.col("eid") % 3 == 0, F.col("r.a")).otherwise(F.col("r.b")).alias("factor"))
    return sssp.costs(partition.by_box(weights.by_time(g, profile, 8).materialised(), 2, 2), 0)


@query("SELECT 0::BIGINT AS violations")
def sssp_violations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Arcs that break the shortest-path condition after convergence: none."""
    g = boxed_road(spark, sf_dir)
    return sssp.violations(g, cut(sssp.costs(g, 0))).agg(F.count("*").alias("violations"))


@query(f"WITH RECURSIVE {ROAD}, {w.sssp_sql(SEED_0, 'road_arcs')} SELECT nid, cost FROM dist WHERE nid = (SELECT n - 1 FROM road_n)")
def sssp_route(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Source to one destination."""
    g = boxed_road(spark, sf_dir)
    return sssp.costs(g, 0, targets=g.nodes.orderBy(F.desc("nid")).limit(1))
