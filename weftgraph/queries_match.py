"""Matching, batches of pairs, spatial weights, tiles, fleets."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from weftgraph import workloads as w
from weftgraph.catalog import query
from weftgraph.functions import geo
from weftgraph.operators import match, measures, partition, sssp, tiles, tours, weights
from weftgraph.plans.common import cut, table

ROAD = f"{w.ROAD_SQL}, {w.ROAD_ARCS_SQL}"
POINTS = "pt AS MATERIALIZED (SELECT vec_id AS pid, embedding[1]::DOUBLE AS x, embedding[2]::DOUBLE AS y, label FROM embeddings)"


def plane(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(pid, x, y, label): the first two components of each vector as a place."""
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("pid"), F.col("embedding")[0].cast("double").alias("x"), F.col("embedding")[1].cast("double").alias("y"), "label")


@query(f"WITH {POINTS}, d AS (SELECT p.pid, g.pid AS gid, (p.x - g.x) * (p.x - g.x) + (p.y - g.y) * (p.y - g.y) AS d FROM pt p, pt g WHERE p.pid >= 10 AND g.pid < 10) SELECT pid, arg_min(gid, (d, gid)) AS gid FROM d GROUP BY pid")
def voronoi_zones(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Points and their nearest of ten generators."""
    p = plane(spark, sf_dir)
    return geo.voronoi_zone(p.where("pid >= 10"), p.where("pid < 10").withColumnRenamed("pid", "gid"))


ON_ROAD = f"""{w.ROAD_SQL}, {POINTS}, here AS MATERIALIZED (SELECT pid, (x + 0.5) * 39 AS x, (y + 0.5) * 39 AS y, label FROM pt)"""


def on_road(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same places stretched over the lattice."""
    return plane(spark, sf_dir).select("pid", ((F.col("x") + 0.5) * 39).alias("x"), ((F.col("y") + 0.5) * 39).alias("y"), "label")


@query(f"WITH RECURSIVE {ON_ROAD}, d AS (SELECT pid, nid, sqrt((h.x - r.x) * (h.x - r.x) + (h.y - r.y) * (h.y - r.y)) AS d FROM here h, road_nodes r) SELECT pid, arg_min(nid, (d, nid)) AS nid, round(min(d), 9) AS dist FROM d GROUP BY pid")
def snap_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nearest road node of free points, by growing rings of cells."""
    return geo.snap(on_road(spark, sf_dir), w.road(spark, sf_dir).nodes, 1.0).select("pid", "nid", F.round("dist", 9).alias("dist"))


FACTOR = "f AS MATERIALIZED (SELECT floor(x) AS x, floor(y) AS y, avg(label / 9.0) AS f FROM here GROUP BY ALL)"
IDW = f"""{FACTOR}, mid AS MATERIALIZED (SELECT eid, (a.x + b.x) / 2.0 AS x, (a.y + b.y) / 2.0 AS y FROM road_edges JOIN road_nodes a ON a.nid = src JOIN road_nodes b ON b.nid = dst),
    pair AS (SELECT eid, f, (mid.x - f.x) * (mid.x - f.x) + (mid.y - f.y) * (mid.y - f.y) AS d2 FROM mid, f),
    fac AS MATERIALIZED (SELECT eid, coalesce(avg(f) FILTER (WHERE d2 = 0), sum(f / d2) FILTER (WHERE d2 > 0) / sum(1 / d2) FILTER (WHERE d2 > 0)) AS factor FROM pair GROUP BY eid)"""


def scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Scenic scores at lattice places: label over nine, means where places coincide."""
    return on_road(spark, sf_dir).groupBy(F.floor("x").cast("double").alias("x"), F.floor("y").cast("double").alias("y")).agg(F.avg(F.col("label") / 9).alias("factor"))


@query(f"WITH RECURSIVE {ON_ROAD}, {IDW} SELECT eid, round(factor, 9) AS factor FROM fac")
def idw_factors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Factors of edges by inverse distance from scored places."""
    return weights.idw(w.road(spark, sf_dir), scores(spark, sf_dir)).select("eid", F.round("factor", 9).alias("factor"))


@query(f"""WITH RECURSIVE {ON_ROAD}, {FACTOR}, mid AS MATERIALIZED (SELECT eid, (a.x + b.x) / 2.0 AS x, (a.y + b.y) / 2.0 AS y FROM road_edges JOIN road_nodes a ON a.nid = src JOIN road_nodes b ON b.nid = dst),
    pair AS (SELECT eid, f, (mid.x - f.x) * (mid.x - f.x) + (mid.y - f.y) * (mid.y - f.y) AS d2 FROM mid, f WHERE (mid.x - f.x) * (mid.x - f.x) + (mid.y - f.y) * (mid.y - f.y) <= 9),
    fac AS (SELECT eid, coalesce(avg(f) FILTER (WHERE d2 = 0), sum(f / d2) FILTER (WHERE d2 > 0) / sum(1 / d2) FILTER (WHERE d2 > 0)) AS factor FROM pair GROUP BY eid)
    SELECT eid, round(coalesce(factor, 1), 9) AS factor FROM mid LEFT JOIN fac USING (eid)""")
def idw_factors_near(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same from places within three units only, met in cells."""
    return weights.idw(w.road(spark, sf_dir), scores(spark, sf_dir), radius=3.0).select("eid", F.round("factor", 9).alias("factor"))


@query(f"""WITH RECURSIVE {ON_ROAD}, {IDW}, e AS MATERIALIZED (SELECT eid, src, dst, weight, round(weight * (0.05 + round(factor, 6)) * 100)::BIGINT AS s FROM road_edges JOIN fac USING (eid)),
    plain AS MATERIALIZED (SELECT src AS u, dst AS v, weight AS w FROM e UNION ALL SELECT dst, src, weight FROM e), pretty AS MATERIALIZED (SELECT src AS u, dst AS v, s AS w FROM e UNION ALL SELECT dst, src, s FROM e),
    {w.sssp_sql('SELECT 0::BIGINT, 0::BIGINT', 'plain', 'd1')}, {w.sssp_sql('SELECT 0::BIGINT, 0::BIGINT', 'pretty', 'd2')}
    SELECT d1.nid, d1.cost AS shortest, d2.cost AS scenic FROM d1 JOIN d2 USING (nid)""")
def scenic_vs_shortest(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Costs by length and by scenic weight to all nodes."""
    g = w.road(spark, sf_dir).materialised()
    f = weights.idw(g, scores(spark, sf_dir)).select("eid", (F.lit(0.05) + F.round("factor", 6)).alias("factor"))
    scenic = weights.scaled(g, f, 100).materialised()
    a, b = (sssp.costs(partition.by_box(x, 2, 2), 0) for x in (g, scenic))
    return a.select("nid", F.col("cost").alias("shortest")).join(b.select("nid", F.col("cost").alias("scenic")), "nid")


#: Pseudo-random places over the lattice, one pair for each line item: thousandths of a unit, apart from the middle between nodes.
PLACE = "((l_orderkey * {a} + l_partkey * {b} + l_suppkey * {c}) % ({top} * 1000) + 0.25) / 1000.0"
SPOTS = dict(sx=(7919, 104729, 31), sy=(15485863, 49, 1299709), dx=(611953, 27, 86028121), dy=(32452843, 179, 67867967))


def line_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(pair_id, src_wkt, dst_wkt): a pair of random points over the whole lattice for each line item."""
    tasks = int(spark.conf.get("spark.sql.shuffle.partitions"))
    items = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey").repartition(tasks)  # the given table is one small file
    n = table(spark, sf_dir, "part").count()
    wide = w.width_of(n)
    top = {"x": wide - 1, "y": n // wide - 1}
    at = {k: F.expr(PLACE.format(a=a, b=b, c=c, top=top[k[1]])) for k, (a, b, c) in SPOTS.items()}
    key = (F.col("l_orderkey") * 100_000 + F.col("l_partkey")) * 10_000 + F.col("l_suppkey")
    return items.select(key.alias("pair_id"), geo.point_wkt(at["sx"], at["sy"]).alias("src_wkt"), geo.point_wkt(at["dx"], at["dy"]).alias("dst_wkt"))


def _spot_sql(k: str) -> str:
    a, b, c = SPOTS[k]
    top = "(w - 1)" if k[1] == "x" else "(n // w - 1)"
    return f"ceil({PLACE.format(a=a, b=b, c=c, top=top)} - 0.5)::BIGINT"


PAIRS = f"pairs AS MATERIALIZED (SELECT (l_orderkey * 100000 + l_partkey) * 10000 + l_suppkey AS pair_id, {_spot_sql('sy')} * w + {_spot_sql('sx')} AS src, {_spot_sql('dy')} * w + {_spot_sql('dx')} AS dst FROM lineitem, road_n)"
ALL_COSTS = """dist(source, nid, cost) USING KEY (source, nid) AS (SELECT src, src, 0::BIGINT FROM (SELECT DISTINCT src FROM pairs) o
        UNION SELECT d.source, a.v, min(d.cost + a.w) FROM dist d JOIN road_arcs a ON a.u = d.nid LEFT JOIN recurring.dist r ON r.nid = a.v AND r.source = d.source GROUP BY d.source, a.v, r.cost HAVING r.cost IS NULL OR min(d.cost + a.w) < r.cost)"""


NEAR_COSTS = ALL_COSTS.replace("GROUP BY d.source", "WHERE d.cost + a.w <= 500 GROUP BY d.source")


@query(f"WITH RECURSIVE {ROAD}, {PAIRS}, {ALL_COSTS} SELECT pair_id, src, pairs.dst, cost FROM pairs JOIN dist ON source = src AND dist.nid = pairs.dst")
def batch_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Costs of a random pair of points for each line item, snapped to the road, origins all over it."""
    return match.batch_points(w.road(spark, sf_dir).materialised(), line_points(spark, sf_dir), 1.0)


@query(f"WITH RECURSIVE {ROAD}, {PAIRS}, {ALL_COSTS} SELECT pair_id, src, pairs.dst, cost FROM pairs JOIN dist ON source = src AND dist.nid = pairs.dst")
def batch_pairs_inverse(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The inverse problem on the same pairs; on a graph without one-way edges costs are the same."""
    return match.batch_points(w.road(spark, sf_dir).materialised(), line_points(spark, sf_dir), 1.0, reverse=True)


@query()
def batch_pairs_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same pairs with the line of each way."""
    return match.batch_points(w.road(spark, sf_dir).materialised(), line_points(spark, sf_dir), 1.0, with_paths=True)


@query(f"WITH RECURSIVE {ROAD}, {PAIRS}, {ALL_COSTS} SELECT pair_id, cost, cost::BIGINT AS line_cost FROM pairs JOIN dist ON source = src AND dist.nid = pairs.dst")
def batch_line_costs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Costs of the pairs, and the sums of weights along their lines, which must be the same."""
    g = w.road(spark, sf_dir).materialised()
    found = cut(match.batch_points(g, line_points(spark, sf_dir), 1.0, with_paths=True))
    return found.select("pair_id", "cost", "wkt").join(match.line_costs(g, found), "wkt").select("pair_id", "cost", F.col("line_cost").cast("long").alias("line_cost"))


@query(f"WITH RECURSIVE {ROAD}, {PAIRS}, {NEAR_COSTS} SELECT pair_id, src, pairs.dst, cost, 500 - cost AS slack FROM pairs JOIN dist ON source = src AND dist.nid = pairs.dst WHERE cost <= 500")
def od_within(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs whose way costs at most 500."""
    g = w.road(spark, sf_dir).materialised()
    solved = match.batch_points(g, line_points(spark, sf_dir), 1.0).select("pair_id", "src", "dst")
    return match.od_within(g, cut(solved), 500)


# ---------------------------------------------------------------- tiles

LIMIT = 500
TILED = f"""{w.ORDERS_SQL}, mid AS MATERIALIZED (SELECT eid, ((a.x * a.x + b.x * b.x) / 2.0) AS mx, ((a.y * a.y + b.y * b.y) / 2.0) AS my FROM ord_edges JOIN ord_nodes a ON a.nid = src JOIN ord_nodes b ON b.nid = dst),
    ext AS (SELECT min(mx) AS x0, min(my) AS y0, max(mx) AS x1, max(my) AS y1 FROM mid),
    ij AS MATERIALIZED (SELECT eid, mx, my, least(floor((mx - x0) / (x1 - x0) * 4096), 4095)::BIGINT AS i, least(floor((my - y0) / (y1 - y0) * 4096), 4095)::BIGINT AS j FROM mid, ext),
    cell AS MATERIALIZED (SELECT i, j, list_aggregate([(((i >> (11 - k)) & 1) + 2 * ((j >> (11 - k)) & 1))::VARCHAR FOR k IN range(12)], 'string_agg', '') AS q, count(*) AS n FROM ij GROUP BY i, j),
    pre AS (SELECT prefix, sum(n) AS n FROM (SELECT unnest([q[1:k] FOR k IN range(13)]) AS prefix, n FROM cell) t GROUP BY prefix),
    big AS MATERIALIZED (SELECT prefix FROM pre WHERE n > {LIMIT} AND length(prefix) < 12),
    leaf AS MATERIALIZED (SELECT q, n, q[1:coalesce((SELECT max(length(prefix)) + 1 FROM big WHERE starts_with(q, prefix)), 0)] AS tile FROM cell)"""


def skewed_orders(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, int]:
    """Edges of the order grid at squared coordinates, with ends and midpoints, and the tile limit."""
    g = w.order_grid(spark, sf_dir)
    at = g.nodes.select("nid", (F.col("x") * F.col("x")).alias("x"), (F.col("y") * F.col("y")).alias("y"))
    e = g.edges.select("eid", "src", "dst", "weight").join(at.toDF("src", "x1", "y1"), "src").join(at.toDF("dst", "x2", "y2"), "dst")
    return e.withColumns({"mx": (F.col("x1") + F.col("x2")) / 2, "my": (F.col("y1") + F.col("y2")) / 2}), LIMIT


@query(f"WITH {TILED} SELECT tile, sum(n)::BIGINT AS n FROM leaf GROUP BY tile")
def tiles_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges of each adaptive tile."""
    e, limit = skewed_orders(spark, sf_dir)
    return tiles.build(e, limit).groupBy("tile").agg(F.count("*").alias("n"))


@query(f"WITH {TILED}, t AS (SELECT tile, sum(n)::BIGINT AS n FROM leaf GROUP BY tile) SELECT length(tile)::INTEGER AS depth, count(*) AS tiles, sum(n)::BIGINT AS records, max(n) AS largest FROM t GROUP BY ALL")
def tiles_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tiles by level: neighbours differ by more than one."""
    e, limit = skewed_orders(spark, sf_dir)
    return tiles.stats(tiles.build(e, limit))


@query(f"""WITH {w.ORDERS_SQL}, s AS (SELECT eid, a.x * a.x AS x1, a.y * a.y AS y1, b.x * b.x AS x2, b.y * b.y AS y2 FROM ord_edges JOIN ord_nodes a ON a.nid = src JOIN ord_nodes b ON b.nid = dst)
    SELECT eid FROM s WHERE least(x1, x2) <= 900 AND greatest(x1, x2) >= 100 AND least(y1, y2) <= 2500 AND greatest(y1, y2) >= 400""")
def tiles_box_load(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tiles saved as text files; those that meet a box are read and cut to it."""
    path, schema = saved_tiles(spark, sf_dir)
    return tiles.in_box(tiles.load(spark, path, TILE_BOX, schema), TILE_BOX).select("eid")


TILE_BOX = (100.0, 400.0, 900.0, 2500.0)


def saved_tiles(spark: SparkSession, sf_dir: str) -> tuple[str, str]:
    """The folder of the saved tiles, and their columns."""
    import uuid

    from weftgraph.plans.common import shared_dir

    e, limit = skewed_orders(spark, sf_dir)
    path = f"{shared_dir(spark).rstrip('/')}/tiles-{uuid.uuid4().hex}"
    tiled = tiles.build(e, limit)
    tiles.save(tiled, path)
    return path, ", ".join(f"{n} {t}" for n, t in tiled.drop("tile").dtypes)


@query(f"""WITH RECURSIVE {w.ORDERS_SQL}, s AS (SELECT eid, src, dst, weight, a.x * a.x AS x1, a.y * a.y AS y1, b.x * b.x AS x2, b.y * b.y AS y2 FROM ord_edges JOIN ord_nodes a ON a.nid = src JOIN ord_nodes b ON b.nid = dst),
    e AS MATERIALIZED (SELECT * FROM s WHERE least(x1, x2) <= 900 AND greatest(x1, x2) >= 100 AND least(y1, y2) <= 2500 AND greatest(y1, y2) >= 400),
    both_ways AS MATERIALIZED (SELECT src AS u, dst AS v, weight AS w FROM e UNION ALL SELECT dst, src, weight FROM e), least_id AS (SELECT min(u) AS nid FROM both_ways),
    {w.sssp_sql("SELECT nid, 0::BIGINT FROM least_id WHERE nid IS NOT NULL", "both_ways")} SELECT nid, cost FROM dist""")  # fmt: skip
def tiles_stitched(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A box is loaded from its tiles as one connected graph, and solved from its smallest node."""
    path, schema = saved_tiles(spark, sf_dir)
    g = tiles.graph_of(spark, path, TILE_BOX, schema).materialised()
    start = g.nodes.agg(F.min("nid")).head()[0]
    if start is None:  # no edge touches the box
        return spark.createDataFrame([], "nid long, cost long")
    return sssp.costs(partition.by_id_range(g, 4), start)


# ------------------------------------------------------ heuristic matches


INSIDE = """road_n AS MATERIALIZED (SELECT count(*) AS n, CASE WHEN count(*) <= 2000 THEN 40 ELSE 100 END AS w FROM part),
    step AS (SELECT user_id, sum(CASE event_type WHEN 'click' THEN 1 WHEN 'signup' THEN -1 ELSE 0 END) OVER o + w // 2 AS tx, sum(CASE event_type WHEN 'view' THEN 1 WHEN 'purchase' THEN -1 ELSE 0 END) OVER o + (n // w) // 2 AS ty, w, n FROM events, road_n WINDOW o AS (PARTITION BY user_id ORDER BY ts, event_id)),
    trip AS MATERIALIZED (SELECT user_id AS trip_id, count(*) AS n, min(least(tx, ty, w - 1 - tx, n // w - 1 - ty)) >= 0 AS inside FROM step GROUP BY user_id)"""


def inside_trips(spark: SparkSession, sf_dir: str, gps: DataFrame) -> DataFrame:
    """(trip_id, inside): whether all true places of a trip lie on the lattice; small lattices are left by some."""
    n = table(spark, sf_dir, "part").count()
    wide = w.width_of(n)
    margin = F.least("tx", "ty", F.lit(wide - 1) - F.col("tx"), F.lit(n // wide - 1) - F.col("ty"))
    return gps.groupBy("trip_id").agg((F.min(margin) >= 0).alias("inside"))


@query(f"WITH {INSIDE} SELECT trip_id, n, CASE WHEN inside THEN true END AS below FROM trip")
def map_match_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Samples of each trip, and whether their mean distance to the route is below one unit: it is for all that stay on the lattice (null for others)."""
    gps = cut(w.gps(spark, sf_dir))
    got = match.map_match(w.road(spark, sf_dir).materialised(), gps.select("trip_id", "seq", "x", "y"))
    trips = got.groupBy("trip_id").agg(F.count("*").alias("n"), (F.avg("dist") < 1).alias("near"))
    return trips.join(inside_trips(spark, sf_dir, gps), "trip_id").select("trip_id", "n", F.when(F.col("inside"), F.col("near")).alias("below"))


#: Samples between two steps of the published rates: one every 0.5 to 5 seconds.
RATES = (1, 2, 5, 10)


@query(f"""WITH {INSIDE}, r AS (SELECT unnest([1, 2, 5, 10]) AS per_step)
    SELECT per_step::INTEGER AS per_step, (sum(n) * per_step)::BIGINT AS samples, count(*) FILTER (WHERE inside) AS trips, count(*) FILTER (WHERE inside) AS below FROM trip, r GROUP BY per_step""")
def map_match_rates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All trips sampled at several rates, with positions in between: trips that stay on the lattice, and those of them whose mean distance is below one unit."""
    g = w.road(spark, sf_dir).materialised()
    gps = cut(w.gps(spark, sf_dir))
    inside = cut(inside_trips(spark, sf_dir, gps))
    out, shared = None, match.roads(g)
    for k in RATES:
        got = match.match_rate(g, gps.select("trip_id", "seq", "x", "y"), k, shared=shared).groupBy("trip_id").agg(F.count("*").alias("n"), F.avg("dist").alias("d")).join(inside, "trip_id")
        row = got.agg(F.sum("n").alias("samples"), F.count(F.when(F.col("inside"), 1)).alias("trips"), F.count(F.when(F.col("inside") & (F.col("d") < 1), 1)).alias("below")).select(F.lit(k).alias("per_step"), "samples", "trips", "below")
        out = row if out is None else out.unionByName(row)
    return out


@query()
def map_match_summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of trips with a mean distance under one unit, and of samples on an edge at their true node."""
    g = w.road(spark, sf_dir).materialised()
    gps = cut(w.gps(spark, sf_dir))
    got = cut(match.map_match(g, gps.select("trip_id", "seq", "x", "y")))
    wd = w.width_of(table(spark, sf_dir, "part").count())
    truth = gps.select("trip_id", "seq", (F.col("ty") * wd + F.col("tx")).alias("true_nid"))
    on = got.join(g.edges.select("eid", "src", "dst"), "eid").join(truth, ["trip_id", "seq"])
    hit = on.agg(F.avg(((F.col("src") == F.col("true_nid")) | (F.col("dst") == F.col("true_nid"))).cast("double")).alias("recall"))
    return measures.match_score(got).join(hit).select("trips", "below", F.round("mean_dist", 6).alias("mean_dist"), "share", F.round("recall", 6).alias("recall"))


#: Depots, trucks and customers of the published run.
FLEET = {"depots": 7, "trucks": 300, "customers": 3500}


def fleet_tables(spark: SparkSession, sf_dir: str, n_depots: int = FLEET["depots"], n_trucks: int = FLEET["trucks"], n_stops: int = FLEET["customers"]) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Depots from suppliers, trucks by account balance, demands of customers; capacity is a fifth over demand."""
    n = table(spark, sf_dir, "part").count()
    place = lambda c: (F.col(c) * 13) % n
    items = table(spark, sf_dir, "lineitem").join(table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey"), "l_orderkey")
    bought = items.where(F.col("o_custkey") < n_stops).groupBy("o_custkey").agg(F.sum("l_quantity").alias("q"))
    demands = table(spark, sf_dir, "customer").where(F.col("c_custkey") < n_stops).join(bought, F.col("c_custkey") == F.col("o_custkey"), "left").select(F.col("c_custkey").alias("cust"), place("c_custkey").alias("nid"), (1 + F.coalesce(F.col("q").cast("long") % 20, F.lit(0))).cast("double").alias("amount"))
    total = demands.agg(F.sum("amount")).head()[0] or 0.0
    crew = spark.range(n_trucks).select(F.col("id").alias("truck"), (F.col("id") % n_depots).alias("depot"), (1 + F.col("id") % 3).alias("size"))
    sizes = sum(1 + i % 3 for i in range(n_trucks))
    # at least the largest demand, so that no customer is too large for every truck
    trucks = crew.withColumn("capacity", F.greatest(F.ceil(F.col("size") * F.lit(total * 1.2 / sizes)).cast("double"), F.lit(20.0)))
    supply = trucks.groupBy("depot").agg(F.sum("capacity").alias("supply"))
    depots = table(spark, sf_dir, "supplier").where(F.col("s_suppkey") < n_depots).select(F.col("s_suppkey").alias("depot"), place("s_suppkey").alias("nid")).join(supply, "depot")
    return depots, trucks.select("truck", "depot", "capacity"), demands


DEMANDS = f"""road_n AS (SELECT count(*) AS n FROM part), bought AS (SELECT o_custkey, sum(l_quantity)::BIGINT AS q FROM lineitem JOIN orders ON o_orderkey = l_orderkey GROUP BY o_custkey),
    need AS MATERIALIZED (SELECT c_custkey AS cust, (1 + coalesce(q % 20, 0))::DOUBLE AS amount FROM customer LEFT JOIN bought ON o_custkey = c_custkey WHERE c_custkey < {FLEET['customers']})"""


@query(f"WITH {DEMANDS} SELECT cust, amount AS delivered FROM need")
def fleet_deliveries(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What each customer gets from the trucks of the fleet: all that was asked for."""
    return fleet_routes(spark, sf_dir).where("cust IS NOT NULL AND truck IS NOT NULL").groupBy("cust").agg(F.sum("amount").alias("delivered"))


@query(f"WITH {DEMANDS} SELECT count(*) AS stops, sum(amount) AS amount, 0::BIGINT AS over_capacity, 0::BIGINT AS open_routes FROM need")
def fleet_invariants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Stops and amounts of all routes, trucks above their capacity, and routes that do not begin and end at the depot."""
    _, trucks, _ = fleet_tables(spark, sf_dir)
    routes = cut(fleet_routes(spark, sf_dir))
    of_truck = routes.where("truck IS NOT NULL").groupBy("truck").agg(F.sum("amount").alias("load"), F.count(F.when(F.col("cust").isNull(), 1)).alias("homes"))
    both = of_truck.join(trucks.select("truck", "capacity"), "truck")
    over, opened = F.count(F.when(F.col("load") > F.col("capacity") + 1e-6, 1)), F.count(F.when(F.col("homes") != 2, 1))
    served = routes.where("truck IS NOT NULL").agg(F.countDistinct("cust").alias("stops"))
    checks = both.agg(F.sum("load").alias("amount"), over.alias("over_capacity"), opened.alias("open_routes"))
    return served.join(checks)  # one row each


@query()
def fleet_routes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Routes of the published number of trucks and depots to the published number of customers."""
    depots, trucks, demands = fleet_tables(spark, sf_dir)
    return tours.fleet(w.road(spark, sf_dir).materialised(), depots, trucks, demands, split="rest")


@query(f"""WITH RECURSIVE {ON_ROAD}, d AS (SELECT p.pid, g.pid AS gid, (p.x - g.x) * (p.x - g.x) + (p.y - g.y) * (p.y - g.y) AS d FROM here p, here g WHERE p.pid >= 10 AND g.pid < 10),
    zone AS MATERIALIZED (SELECT pid, arg_min(gid, (d, gid)) AS gid FROM d GROUP BY pid UNION ALL SELECT pid, pid FROM here WHERE pid < 10),
    near AS (SELECT pid, arg_min(nid, ((h.x - r.x) * (h.x - r.x) + (h.y - r.y) * (h.y - r.y), nid)) AS nid FROM here h, road_nodes r GROUP BY pid)
    SELECT gid AS tour, count(DISTINCT nid) AS stops, true AS closed FROM zone JOIN near USING (pid) GROUP BY gid""")  # fmt: skip
def mtsp_coverage(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Places that each collector visits, and whether the round ends where it began."""
    t = cut(mtsp_tours(spark, sf_dir))
    ends = t.groupBy("tour").agg(F.countDistinct("nid").alias("stops"), (F.min_by("nid", "step") == F.max_by("nid", "step")).alias("closed"))
    return ends


@query()
def mtsp_tours(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One collector in each of ten zones visits the points of its zone."""
    g = w.road(spark, sf_dir).materialised()
    p = cut(on_road(spark, sf_dir))
    at = geo.snap(p, g.nodes, 1.0).select("pid", "nid")
    both = cut(p.join(at, "pid"))
    return tours.multi_tsp(g, both.where("pid >= 10"), both.where("pid < 10").withColumnRenamed("pid", "gid"))


def _path_lengths_sql() -> str:
    from weftgraph.queries_paths import WALK

    return f"""WITH RECURSIVE {WALK}, p AS (SELECT target, 'LINESTRING(' || string_agg(x::DOUBLE::VARCHAR || ' ' || y::DOUBLE::VARCHAR, ', ' ORDER BY step) || ')' AS wkt FROM long JOIN road_nodes ON road_nodes.nid = long.nid GROUP BY target)
        SELECT count(*) AS paths, avg(length(wkt)) AS chars FROM p"""


@query(_path_lengths_sql())
def path_lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Number of paths and mean length of their text."""
    from weftgraph.queries_paths import path_wkt

    return measures.path_chars(path_wkt(spark, sf_dir))
