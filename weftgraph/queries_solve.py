"""Generic solvers: components, rank, chains, centralities, trails, tours."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from weftgraph import workloads as w
from weftgraph.catalog import query
from weftgraph.model import Graph
from weftgraph.operators import centrality, query as q, rank, tours
from weftgraph.operators.components import connected_components
from weftgraph.plans.common import table


def _rank_sql(arcs: str, nodes: str, iterations: int) -> str:
    """Rank iterations unrolled, digits rounded as in the query."""
    steps = [f"nn AS (SELECT count(*) AS n FROM ({nodes}) t)", f"oo AS MATERIALIZED (SELECT u, count(*) AS k FROM ({arcs}) a GROUP BY u)", f"mm AS MATERIALIZED (SELECT a.u, a.v, k FROM ({arcs}) a JOIN oo USING (u))", f"r0 AS MATERIALIZED (SELECT nid, 1.0::DOUBLE / n AS s FROM ({nodes}) t, nn)"]
    for i in range(iterations):
        steps.append(f"r{i + 1} AS MATERIALIZED (SELECT p.nid, 0.15::DOUBLE / n + 0.85::DOUBLE * (coalesce(c.s, 0) + d.s / n) AS s FROM r{i} p LEFT JOIN (SELECT v, sum(s / k) AS s FROM r{i} JOIN mm ON u = nid GROUP BY v) c ON c.v = p.nid, nn, (SELECT coalesce(sum(s), 0) AS s FROM r{i} WHERE nid NOT IN (SELECT u FROM oo)) d)")
    return f"{', '.join(steps)} SELECT nid, round(s, 9) AS score FROM r{iterations}"


@query(f"WITH {w.TRADE_SQL}, {_rank_sql('SELECT src AS u, dst AS v FROM trade_edges', 'SELECT n_nationkey::BIGINT AS nid FROM nation', 10)}")
def pagerank_trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rank of nations by trade."""
    g = w.trade(spark, sf_dir)
    return rank.pagerank(g, iterations=10).select("nid", F.round("score", 9).alias("score"))


PAGES = """href AS MATERIALIZED (SELECT DISTINCT 'h:' || regexp_extract(url, '://([^/]+)', 1) AS a, 'p:' || unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS b FROM pages),
    pid AS MATERIALIZED (SELECT name, row_number() OVER (ORDER BY name) - 1 AS nid FROM (SELECT a AS name FROM href UNION SELECT b FROM href) t),
    link AS MATERIALIZED (SELECT x.nid AS u, y.nid AS v FROM href JOIN pid x ON x.name = a JOIN pid y ON y.name = b)"""


def page_links(spark: SparkSession, sf_dir: str) -> Graph:
    """Hosts and the paths they link to."""
    from weftgraph import grammar

    pages = table(spark, sf_dir, "pages")
    links = pages.select(F.concat(F.lit("h:"), F.regexp_extract("url", "://([^/]+)", 1)).alias("a"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("p")).select("a", F.concat(F.lit("p:"), "p").alias("b")).distinct()
    g = grammar.create(spark, "pages", [grammar.Component(links, {"edge.src_name": "a", "edge.dst_name": "b"})])
    return g.with_edges(g.edges.withColumn("direction", F.lit(1)))


@query(f"WITH {PAGES}, {_rank_sql('SELECT u, v FROM link', 'SELECT nid FROM pid', 5)}")
def pagerank_pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rank over the link graph of the pages."""
    return rank.pagerank(page_links(spark, sf_dir).materialised(), iterations=5).select("nid", F.round("score", 9).alias("score"))


KINDS = "CASE event_type WHEN 'click' THEN 0 WHEN 'view' THEN 1 WHEN 'signup' THEN 2 WHEN 'purchase' THEN 3 ELSE 4 END"


def event_chain(spark: SparkSession, sf_dir: str) -> Graph:
    """Transitions between event types of each user."""
    from pyspark.sql import Window

    kind = F.when(F.col("event_type") == "click", 0).when(F.col("event_type") == "view", 1).when(F.col("event_type") == "signup", 2).when(F.col("event_type") == "purchase", 3).otherwise(4).cast("long")
    e = table(spark, sf_dir, "events").select("user_id", "ts", "event_id", kind.alias("src"))
    moves = e.withColumn("dst", F.lead("src").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))).where("dst IS NOT NULL")
    counted = moves.groupBy("src", "dst").agg(F.count("*").alias("weight"))
    return Graph.of("events", e.select(F.col("src").alias("nid")).distinct(), counted.select((F.col("src") * 10 + F.col("dst")).alias("eid"), "src", "dst", "weight", F.lit(1).alias("direction")))


def _markov_sql(steps: int) -> str:
    parts = [f"ev AS (SELECT user_id, ts, event_id, ({KINDS})::BIGINT AS s FROM events)", "mv AS (SELECT s, lead(s) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS t FROM ev)", "cc AS (SELECT s, t, count(*) AS c FROM mv WHERE t IS NOT NULL GROUP BY ALL)", "pp AS MATERIALIZED (SELECT s, t, c / sum(c) OVER (PARTITION BY s)::DOUBLE AS p FROM cc)", "d0 AS (SELECT 0::BIGINT AS s, 1.0::DOUBLE AS q)"]
    parts += [f"d{i + 1} AS (SELECT t AS s, sum(q * p) AS q FROM d{i} JOIN pp USING (s) GROUP BY t)" for i in range(steps)]
    return f"WITH {', '.join(parts)} SELECT s AS nid, round(q, 9) AS p FROM d{steps}"


@query(_markov_sql(3))
def markov_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distribution of event types three steps after a click."""
    return rank.markov(event_chain(spark, sf_dir), 0, 3).select("nid", F.round("p", 9).alias("p"))


@query(_markov_sql(40).replace("round(q, 9)", "round(q, 6)"))
def markov_stationary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The distribution that the chain tends to."""
    return rank.stationary(event_chain(spark, sf_dir)).select("nid", F.round("p", 6).alias("p"))


TRADE_ARCS = "trade_arcs AS MATERIALIZED (SELECT src AS u, dst AS v, weight AS w FROM trade_edges)"
TRADE_ALL = """dist(source, nid, cost) USING KEY (source, nid) AS (
        SELECT n_nationkey::BIGINT, n_nationkey::BIGINT, 0::BIGINT FROM nation
        UNION
        SELECT d.source, a.v, min(d.cost + a.w) FROM dist d JOIN trade_arcs a ON a.u = d.nid LEFT JOIN recurring.dist r ON r.nid = a.v AND r.source = d.source
        GROUP BY d.source, a.v, r.cost HAVING r.cost IS NULL OR min(d.cost + a.w) < r.cost)"""


@query(f"WITH RECURSIVE {w.TRADE_SQL}, {TRADE_ARCS}, {TRADE_ALL}, s AS (SELECT source, count(*) - 1 AS r, sum(cost) AS d FROM dist GROUP BY source) SELECT source AS nid, round(r / d * r / (SELECT count(*) - 1 FROM nation), 9) AS score FROM s")
def closeness_trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Closeness of nations, weights as lengths."""
    return centrality.closeness(w.trade(spark, sf_dir).materialised()).select("nid", F.round("score", 9).alias("score"))


@query(f"""WITH RECURSIVE {w.TRADE_SQL}, {TRADE_ARCS}, {TRADE_ALL},
    cost AS MATERIALIZED (SELECT source AS s, nid AS t, cost AS d FROM dist), tight AS MATERIALIZED (SELECT a.s, x.u, x.v FROM cost a JOIN trade_arcs x ON x.u = a.t JOIN cost b ON b.s = a.s AND b.t = x.v WHERE b.d = a.d + x.w AND x.u <> x.v),
    way(s, t) AS (SELECT n_nationkey::BIGINT, n_nationkey::BIGINT FROM nation UNION ALL SELECT way.s, v FROM way JOIN tight ON tight.s = way.s AND tight.u = way.t),
    k AS MATERIALIZED (SELECT s, t, count(*)::DOUBLE AS k FROM way GROUP BY s, t),
    b AS (SELECT a.t AS nid, sum(ka.k * kb.k / kc.k) AS score FROM cost a JOIN cost b ON b.s = a.t JOIN cost c ON c.s = a.s AND c.t = b.t AND c.d = a.d + b.d
        JOIN k ka ON ka.s = a.s AND ka.t = a.t JOIN k kb ON kb.s = b.s AND kb.t = b.t JOIN k kc ON kc.s = c.s AND kc.t = c.t WHERE a.s <> a.t AND b.t <> a.t AND b.t <> a.s GROUP BY a.t)
    SELECT n_nationkey::BIGINT AS nid, round(coalesce(score, 0), 6) AS score FROM nation LEFT JOIN b ON nid = n_nationkey""")  # fmt: skip
def betweenness_trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Betweenness of nations over all trade arcs, weights as lengths."""
    return centrality.betweenness(w.trade(spark, sf_dir).materialised()).select("nid", F.round("score", 6).alias("score"))


@query("""WITH c AS (SELECT DISTINCT conv_id, turn FROM conversations), e AS (SELECT a.conv_id, a.turn FROM c a JOIN c b ON b.conv_id = a.conv_id AND b.turn = a.turn + 1),
    r AS (SELECT conv_id, turn, turn - row_number() OVER (PARTITION BY conv_id ORDER BY turn) AS run FROM e)
    SELECT conv_id * 1000 + min(turn) AS component, count(*) AS edges, 2::BIGINT AS odd, 'path' AS verdict FROM r GROUP BY conv_id, run""")
def euler_degree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Chains of turns have a trail but no circuit."""
    return rank.euler_degrees(w.turns_chain(spark, sf_dir).materialised())


@query("""WITH c AS (SELECT DISTINCT conv_id, turn FROM conversations), e AS (SELECT a.conv_id, a.turn FROM c a JOIN c b ON b.conv_id = a.conv_id AND b.turn = a.turn + 1),
    r AS (SELECT conv_id, turn, turn - row_number() OVER (PARTITION BY conv_id ORDER BY turn) AS run FROM e)
    SELECT conv_id * 1000 + min(turn) AS component, count(*) + 1 AS nodes FROM r GROUP BY conv_id, run""")
def euler_trails(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Length of the trail of each chain of turns."""
    return rank.euler(w.turns_chain(spark, sf_dir).materialised(), directed=True).groupBy("component").agg(F.count("*").alias("nodes"))


@query("""WITH c AS (SELECT DISTINCT conv_id, turn FROM conversations), r AS (SELECT conv_id, turn, turn - row_number() OVER (PARTITION BY conv_id ORDER BY turn) AS run FROM c),
    k AS (SELECT conv_id * 1000 + turn AS nid, conv_id * 1000 + min(turn) OVER (PARTITION BY conv_id, run) AS component, count(*) OVER (PARTITION BY conv_id, run) AS n FROM r)
    SELECT nid, component FROM k WHERE n > 1""")
def components_turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Components of the turn chains."""
    e = w.turns_chain(spark, sf_dir).edges
    return connected_components(e.select(F.col("src").alias("u"), F.col("dst").alias("v")))


@query(f"""WITH RECURSIVE {w.TRADE_SQL}, walk(here, hops, cost, p) AS (SELECT 3::BIGINT, 0, 0::HUGEINT, [3::BIGINT] UNION ALL SELECT dst, hops + 1, cost + weight, list_append(p, dst) FROM walk JOIN trade_edges ON src = here WHERE hops < 3 AND NOT list_contains(p, dst))
    SELECT hops::INTEGER AS hops, count(*) AS paths, sum(cost)::BIGINT AS cost FROM walk WHERE here = 7 AND hops > 0 AND cost <= 400 GROUP BY hops""")
def all_paths_trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All paths between two nations within three hops and a bound on cost."""
    found = q.all_paths(w.trade(spark, sf_dir).materialised(), 3, 7, 3, 400)
    return found.groupBy("hops").agg(F.count("*").alias("paths"), F.sum("cost").alias("cost"))


def tour_stops(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Twelve parts of the first brand as stops."""
    part = table(spark, sf_dir, "part")
    brand = part.agg(F.min("p_brand")).head()[0]
    return part.where(F.col("p_brand") == brand).orderBy("p_partkey").limit(12).select(F.lit(0).cast("long").alias("tour"), F.col("p_partkey").alias("nid"))


@query()
def tsp_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A round trip through twelve stops of the road graph."""
    return tours.tsp(w.road(spark, sf_dir).materialised(), tour_stops(spark, sf_dir))


@query(f"""WITH RECURSIVE {w.ROAD_SQL}, {w.ROAD_ARCS_SQL}, stop AS MATERIALIZED (SELECT p_partkey AS nid, row_number() OVER (ORDER BY p_partkey) AS i FROM part WHERE p_brand = (SELECT min(p_brand) FROM part) ORDER BY p_partkey LIMIT 5),
    dist(source, nid, cost) USING KEY (source, nid) AS (SELECT nid, nid, 0::BIGINT FROM stop UNION SELECT d.source, a.v, min(d.cost + a.w) FROM dist d JOIN road_arcs a ON a.u = d.nid LEFT JOIN recurring.dist r ON r.nid = a.v AND r.source = d.source GROUP BY d.source, a.v, r.cost HAVING r.cost IS NULL OR min(d.cost + a.w) < r.cost)
    SELECT (a.i - 1)::INTEGER AS leg, a.nid AS src, b.nid AS dst, cost, (sum(cost) OVER (ORDER BY a.i))::BIGINT AS total FROM stop a JOIN stop b ON b.i = a.i + 1 JOIN dist ON dist.source = a.nid AND dist.nid = b.nid""")
def multi_stop_route(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Five stops in a given order."""
    stops = [r["nid"] for r in tour_stops(spark, sf_dir).orderBy("nid").limit(5).collect()]
    return tours.multi_stop(w.road(spark, sf_dir).materialised(), stops)


@query()
def backhaul_route(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Deliver to six stops, then collect from six on the way back."""
    stops = tour_stops(spark, sf_dir).select("nid", (1 + F.col("nid") % 5).alias("amount"))
    return tours.backhaul(w.road(spark, sf_dir).materialised(), 0, stops.where("nid % 2 = 0"), stops.where("nid % 2 = 1"))
