"""Worked examples, invariants and edge cases of the graph engine."""

from __future__ import annotations

import heapq
import itertools
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from weftgraph import grammar, workloads
from weftgraph.functions import geo
from weftgraph.grammar import Component
from weftgraph.model import CreateOptions, Graph
from weftgraph.operators import balance, centrality, match, measures, modify, partition, paths, query, rank, sssp, tiles, topology, tours, turns, weights
from weftgraph.operators.components import connected_components


def edges_of(spark, rows):
    return spark.createDataFrame([(i + 1, a, b, w) for i, (a, b, w) in enumerate(rows)], "eid long, src long, dst long, weight long")


def graph_of(spark, rows, **nodes):
    return Graph.of("g", nodes.get("nodes"), edges_of(spark, rows))


def dijkstra(rows, start):
    ways = {}
    for a, b, w in rows:
        ways.setdefault(a, []).append((b, w))
        ways.setdefault(b, []).append((a, w))
    dist, heap = {start: 0}, [(0, start)]
    while heap:
        d, n = heapq.heappop(heap)
        if d > dist[n]:
            continue
        for m, w in ways.get(n, []):
            if d + w < dist.get(m, float("inf")):
                dist[m] = d + w
                heapq.heappush(heap, (d + w, m))
    return dist


def as_dict(df):
    return {r["nid"]: r["cost"] for r in df.collect()}


RANDOM = [(a, b, random.Random(5).randint(1, 9) + (a * b) % 7) for a, b in {tuple(sorted(random.Random(i).sample(range(40), 2))) for i in range(90)}]


# ------------------------------------------------------------- topology


def test_walk_of_one_node_gives_its_three_edges(spark):
    g = edges_of(spark, [(1, 2, 1), (1, 3, 1), (1, 4, 1), (2, 3, 1), (3, 4, 1), (2, 4, 1)])
    links, heads = topology.build_double_link(g)
    assert {r["nid"]: r["head"] for r in heads.collect()}[1] == 3
    one = spark.createDataFrame([(1,)], "nid long")
    walk = topology.walk_incident(links, heads, one).orderBy("step").collect()
    assert [r["eid"] for r in walk] == [3, 2, 1]
    back = topology.walk_incident(links, heads, one, "next").orderBy("step").collect()
    assert [r["eid"] for r in back] == [1, 2, 3]


def test_deleted_node_queues_its_edges_and_inserts_reuse_them(spark):
    rows = [(1, 2, 1), (2, 3, 1), (1, 4, 1), (3, 4, 1), (4, 5, 1), (3, 5, 1)]
    g = modify.start(edges_of(spark, rows).select("eid", "src", "dst"))
    gone = modify.delete_nodes(g, spark.createDataFrame([(3,)], "nid long"))
    assert sorted(r["id"] for r in gone.free.collect()) == [2, 4, 6]
    new = spark.createDataFrame([(7, 8), (8, 9), (9, 10), (10, 11)], "src long, dst long")
    full = modify.insert_edges(gone, new, ["src"])
    assert sorted(r["eid"] for r in full.edges.collect()) == [1, 2, 3, 4, 5, 6, 7]
    assert full.free.count() == 0
    assert full.edges.where("eid = 2").head()["src"] == 7


def test_bypass_equals_rebuilding(spark):
    g = edges_of(spark, RANDOM)
    links, _ = topology.build_double_link(g)
    gone = g.where("eid % 3 = 0")
    fixed = modify.relink_deleted(links, gone)
    want, _ = topology.build_double_link(g.where("eid % 3 <> 0"))
    assert sorted(map(tuple, fixed.collect())) == sorted(map(tuple, want.collect()))


def test_csr_offsets_and_parallel_and_loop_edges(spark):
    g = edges_of(spark, [(1, 2, 3), (1, 2, 4), (2, 2, 5)])
    rows = {r["nid"]: r for r in topology.to_csr(g).collect()}
    assert rows[1]["offset"] == 0 and rows[1]["degree"] == 2
    assert rows[2]["degree"] == 3 and rows[2]["offset"] == 2
    assert topology.clean(g, allow_loops=False, allow_parallel=False).count() == 1


def test_storage_does_not_depend_on_degrees(spark):
    star = graph_of(spark, [(0, i, 1) for i in range(1, 9)])
    line = graph_of(spark, [(i, i + 1, 1) for i in range(8)])
    size = lambda g: measures.storage_bytes(g).where("layout = 'double_link'").head()["bytes"]
    assert size(star) == size(line) == 8 * 24
    assert measures.storage_model(10, 20)["csr"] == (40 + 11) * 4


def test_upsert_is_independent_of_batching(spark):
    rows = [("upsert", 1, 2, 5, 1, 1), ("upsert", 1, 2, 7, 3, 3), ("delete", 1, 3, 0, 4, 4), ("upsert", 1, 3, 9, 2, 2)]
    ch = spark.createDataFrame(rows, "op string, src long, dst long, weight long, ts long, seq long")
    start = spark.createDataFrame([(1, 3, 1, 0)], "src long, dst long, weight long, ts long")
    whole = sorted(map(tuple, modify.upsert(start, ch).select("src", "dst", "weight").collect()))
    assert whole == [(1, 2, 7)]


# ------------------------------------------------------ partitions, solves


@pytest.mark.parametrize("engine", ["flat", "delta", "single"])
def test_engines_agree_with_dijkstra(spark, engine):
    got = as_dict(sssp.costs(graph_of(spark, RANDOM), RANDOM[0][0], engine, delta=3))
    assert got == dijkstra(RANDOM, RANDOM[0][0])


@pytest.mark.parametrize("parts", [1, 2, 7])
def test_parts_do_not_change_costs(spark, parts):
    g = partition.by_random(graph_of(spark, RANDOM), parts)
    check = measures.check_disjoint(g).head()
    assert check["edges"] == check["distinct_edges"] and check["without_part"] == 0
    found = sssp.costs(g, RANDOM[0][0])
    assert as_dict(found) == dijkstra(RANDOM, RANDOM[0][0])
    assert sssp.violations(g, found).count() == 0


def test_several_sources_inverse_and_replicated(spark):
    g = graph_of(spark, RANDOM)
    a, b = RANDOM[0][0], RANDOM[1][0]
    da, db = dijkstra(RANDOM, a), dijkstra(RANDOM, b)
    both = as_dict(sssp.costs(g, [(a, 2), (b, 0)], "flat"))
    assert both == {n: min(da.get(n, 10**9) + 2, db.get(n, 10**9)) for n in both}
    many = sssp.many_costs(g, spark.createDataFrame([(a,), (b,)], "nid long")).collect()
    assert {(r["source"], r["nid"]): r["cost"] for r in many} == {**{(a, n): c for n, c in da.items()}, **{(b, n): c for n, c in db.items()}}
    one_way = g.with_edges(g.edges.withColumn("direction", F.lit(1)))
    to_b = as_dict(sssp.inverse(one_way, b, "flat"))
    for n, c in to_b.items():
        assert as_dict(sssp.costs(one_way, n, "single"))[b] == c
        break


def test_edge_cases_of_solves(spark):
    g = graph_of(spark, [(1, 2, 0), (2, 2, 4), (3, 4, 1), (1, 2, 7)])
    got = sssp.costs(partition.by_id_range(g, 9), 1, keep_unreached=True)
    assert as_dict(got) == {1: 0, 2: 0, 3: None, 4: None}
    with pytest.raises(ValueError):
        sssp.costs(g, 99)
    with pytest.raises(ValueError):
        sssp.costs(graph_of(spark, [(1, 2, -1)]), 1)
    assert as_dict(sssp.route_cost(graph_of(spark, RANDOM), RANDOM[0][0], RANDOM[3][1])).get(RANDOM[3][1]) == dijkstra(RANDOM, RANDOM[0][0]).get(RANDOM[3][1])


def test_path_revisits_a_part(spark):
    # a line of nodes whose parts go 0, 1, 0: the way back enters part 0 twice
    rows = [(0, 1, 1), (1, 2, 1), (2, 3, 1), (3, 4, 1)]
    g = graph_of(spark, rows)
    g = partition.explicit(g, F.when(F.col("eid").isin(1, 4), 0).otherwise(1))
    found = sssp.costs(g, 0)
    steps = paths.aggregate(g, found, spark.createDataFrame([(4,), (0,)], "nid long"))
    assert [r["nid"] for r in steps.where("target = 4").orderBy("step").collect()] == [0, 1, 2, 3, 4]
    assert steps.where("target = 0").count() == 1
    stay = paths.stays(steps).where("target = 4").head()
    assert (stay["stays"], stay["parts"]) == (3, 2)


def test_explicit_boundary_flags_are_checked(spark):
    g = graph_of(spark, [(1, 2, 1), (2, 3, 1)])
    flags = spark.createDataFrame([(2, True), (1, False)], "nid long, flag boolean")
    assert partition.boundary(partition.explicit(g, F.col("eid").cast("int"), flags).edges).count() == 2
    with pytest.raises(ValueError):
        partition.explicit(g, F.lit(0), flags)


def test_schemes_follow_from_columns(spark):
    flat = graph_of(spark, [(1, 2, 1)])
    assert partition.auto(flat).options.scheme == "id_range"
    named = flat.with_nodes(flat.nodes.withColumn("name", F.lit("a")))
    assert partition.auto(named).options.scheme == "random"
    placed = flat.with_nodes(flat.nodes.withColumns({"x": F.lit(1.0), "y": F.lit(2.0)}))
    assert partition.auto(placed).options.scheme == "box"
    assert partition.auto(flat.with_edges(flat.edges.withColumn("part", F.lit(3)))).options.scheme == "explicit"


def test_balancing_cuts_rounds_and_copies(spark):
    g = workloads.scrambled_road(spark, "/root/testdata/sf0.001").materialised()
    bad = partition.by_id_range(g, 4)
    good = balance.rebalance(g, 4, 0, engine="single").materialised()
    even = balance.rebalance(g, 4, 0, by="edges", engine="single").materialised()
    s1, s2, s3 = sssp.SolveStats(), sssp.SolveStats(), sssp.SolveStats()
    total = sssp.costs(bad, 0, stats=s1).agg(F.sum("cost")).head()[0]
    assert sssp.costs(good, 0, stats=s2).agg(F.sum("cost")).head()[0] == total
    assert sssp.costs(even, 0, stats=s3).agg(F.sum("cost")).head()[0] == total
    assert 2 * s2.supersteps <= s1.supersteps and 3 * s2.messages < s1.messages
    copies = lambda x: measures.partition_score(x).head()["dup_copies"]
    assert copies(good) < 0.5 * copies(bad)
    assert balance.default_source(g) == 0


def test_unreached_nodes_come_last(spark):
    g = graph_of(spark, [(5, 6, 1), (1, 2, 1)])
    ids = balance.renumber(g, sssp.costs(g, 5, "flat")).orderBy("new_id").collect()
    assert [r["old_id"] for r in ids] == [5, 6, 1, 2]


# ------------------------------------------------------------- grammar


@pytest.mark.parametrize("number,roles", list(enumerate([
    "edge.id edge.src_id edge.dst_id", "edge.id edge.src_id edge.dst_id edge.direction", "edge.id edge.src_name edge.dst_name", "edge.id edge.src_point edge.dst_point",
    "edge.id edge.line", "edge.id edge.line edge.direction", "edge.src_id edge.dst_id", "edge.src_name edge.dst_name",
    "edge.src_name edge.dst_name edge.label", "edge.src_point edge.dst_point", "edge.line", "edge.line edge.direction",
], 1)))
def test_permitted_combinations(number, roles):
    assert grammar.resolve(set(roles.split())).number == number


@pytest.mark.parametrize("roles", ["edge.id", "edge.src_id", "edge.line edge.src_id edge.dst_id", "edge.src_id edge.dst_id edge.colour", "edge.src_name edge.dst_name edge.direction"])
def test_other_combinations_are_refused(roles):
    with pytest.raises(ValueError):
        grammar.resolve(set(roles.split()))


def test_create_from_lines_and_constants(spark):
    rows = [("LINESTRING(0 0, 1 0)",), ("LINESTRING(1.000001 0, 1 1, 2 1)",), (None,)]
    t = spark.createDataFrame(rows, "wkt string")
    g = grammar.create(spark, "lines", [Component(t, {"edge.line": "wkt", "edge.label": F.lit("road")})])
    assert g.nodes.count() == 3 and g.edges.count() == 2
    assert sorted(round(r["weight"], 3) for r in g.edges.collect()) == [1.0, 2.0]
    assert g.edges.head()["labels"] == ["road"]
    part = grammar.create(spark, "p", [Component(t, {"edge.line": "wkt"})], options=CreateOptions(mode="partitioned", parts=2))
    assert part.edges.where("part IS NULL").count() == 0


def test_save_and_load(spark, tmp_path):
    g = partition.by_random(graph_of(spark, RANDOM), 3)
    g.save(f"file://{tmp_path}/g")
    back = Graph.load(spark, f"file://{tmp_path}/g")
    assert back.options == g.options
    assert sorted(map(tuple, back.edges.select("eid", "src", "dst", "weight", "part").collect())) == sorted(map(tuple, g.edges.select("eid", "src", "dst", "weight", "part").collect()))


# --------------------------------------------------------------- queries


def test_restricted_query_finds_four_paths(spark):
    """Two sources, a target label, at most three hops, one edge too young."""
    names = {1: "Susan", 2: "Jane", 3: "Tom", 4: "Bill", 5: "Ann", 6: "Rob", 7: "Eve", 8: "Max"}
    nodes = spark.createDataFrame([(i, n, ["FEMALE"] if i < 3 else (["chess"] if i in (5, 7) else ["MALE"])) for i, n in names.items()], "nid long, name string, labels array<string>")
    know = [(1, 3, 1999), (3, 5, 2000), (3, 7, 2001), (2, 4, 1998), (4, 5, 1997), (4, 7, 2001), (2, 5, 2010), (6, 8, 2000)]
    base = spark.createDataFrame([(i + 1, a, b, y) for i, (a, b, y) in enumerate(know)], "eid long, a long, b long, since int")
    g = Graph.of("toy", nodes, base.select("eid", F.col("a").alias("src"), F.col("b").alias("dst"), F.lit(1).cast("long").alias("weight"), F.lit(1).alias("direction")))
    old = query.Restriction.edge(base, F.col("eid"), F.when(F.col("since") <= 2002, True).otherwise(False))
    found = query.paths(g, query.Select(names=["Susan", "Jane"], labels=["FEMALE"]), query.Select(labels=["chess"]), query.Hops(3), [old])
    assert {r["src"]: r["count"] for r in found.groupBy("src").count().collect()} == {1: 2, 2: 2}
    assert found.where(F.array_contains("eids", 7)).count() == 0
    walks = query.paths(g, query.Select(ids=[1]), g.nodes, query.Hops(2, walks=True, direction="both"))
    assert walks.where("size(path) = 3 AND path[2] = 1").count() == 1


def test_pruning_and_rules_do_not_change_results(spark):
    g = graph_of(spark, RANDOM)
    a = query.paths(g, query.Select(ids=[RANDOM[0][0]]), query.Select(ids=[RANDOM[1][1]]), query.Hops(3))
    b = query.paths(g, query.Select(ids=[RANDOM[0][0]]), query.Select(ids=[RANDOM[1][1]]), query.Hops(3), prune=False)
    assert sorted(tuple(r["path"]) for r in a.collect()) == sorted(tuple(r["path"]) for r in b.collect())


# --------------------------------------------------------------- solvers


def test_components_and_loops(spark):
    rows = [(1, 2), (2, 3), (7, 8), (9, 9), (None, 4), (3, 1)]
    got = {r["nid"]: r["component"] for r in connected_components(spark.createDataFrame(rows, "u long, v long")).collect()}
    assert got == {1: 1, 2: 1, 3: 1, 7: 7, 8: 7, 9: 9}
    line = spark.range(300).select(F.col("id").alias("u"), (F.col("id") + 1).alias("v"))
    assert {r["component"] for r in connected_components(line).collect()} == {0}
    assert connected_components(line.limit(0)).count() == 0


def test_rank_and_chain_sum_to_one(spark):
    g = graph_of(spark, RANDOM)
    assert abs(rank.pagerank(g, tolerance=1e-6, iterations=60).agg(F.sum("score")).head()[0] - 1) < 1e-9
    p = rank.markov(g, RANDOM[0][0], 4)
    assert abs(p.agg(F.sum("p")).head()[0] - 1) < 1e-9


def test_betweenness_of_a_line(spark):
    g = graph_of(spark, [(1, 2, 1), (2, 3, 1), (3, 4, 1)])
    got = {r["nid"]: r["score"] for r in centrality.betweenness(g, directed=False).collect()}
    assert got == {1: 0.0, 2: 2.0, 3: 2.0, 4: 0.0}
    close = {r["nid"]: r["score"] for r in centrality.closeness(g).collect()}
    assert abs(close[2] - 3 / 4) < 1e-12


def test_trail_uses_each_edge_once(spark):
    g = graph_of(spark, [(1, 2, 1), (2, 3, 1), (3, 1, 1), (3, 4, 1), (4, 5, 1), (5, 3, 1)])
    trail = rank.euler(g).orderBy("step").collect()
    assert sorted(r["eid"] for r in trail[1:]) == [1, 2, 3, 4, 5, 6]
    assert trail[0]["nid"] == trail[-1]["nid"]
    assert rank.euler_degrees(graph_of(spark, [(1, 2, 1), (1, 3, 1), (1, 4, 1)])).head()["verdict"] == "none"


def test_tours_are_near_the_best(spark):
    rng = np.random.default_rng(1)
    for n in (3, 6, 8):
        xy = rng.random((n, 2))
        m = np.sqrt(((xy[:, None] - xy[None]) ** 2).sum(axis=2))
        order = tours.improve(tours.nearest_neighbour(m), m)
        assert sorted(order) == list(range(n)) and order[0] == 0
        assert tours.tour_cost(order, m) <= 1.1 * tours.exact_tour(m) + 1e-9
        brute = min(tours.tour_cost([0, *p], m) for p in itertools.permutations(range(1, n)))
        assert abs(brute - tours.exact_tour(m)) < 1e-9


def test_fleet_keeps_its_invariants(spark):
    g = workloads.road(spark, "/root/testdata/sf0.001").materialised()
    depots = spark.createDataFrame([(0, 3, 60.0), (1, 150, 60.0)], "depot long, nid long, supply double")
    trucks = spark.createDataFrame([(i, i % 2, 12.0 + 2 * (i % 3)) for i in range(10)], "truck long, depot long, capacity double")
    demands = spark.createDataFrame([(c, (c * 17) % 200, float(1 + c % 7)) for c in range(24)], "cust long, nid long, amount double")
    routes = tours.fleet(g, depots, trucks, demands).toPandas()
    served = routes[routes["cust"].notna() & routes["truck"].notna()]
    assert served["cust"].is_unique and len(routes[routes["cust"].notna()]) == 24
    cap = {r["truck"]: (r["capacity"], r["depot"]) for r in trucks.collect()}
    for t, r in served.groupby("truck"):
        assert r["amount"].sum() <= cap[t][0] and set(r["depot"]) == {cap[t][1]}
    for _, r in routes[routes["truck"].notna()].groupby("truck"):
        r = r.sort_values("stop_seq")
        assert r["cust"].isna().iloc[0] and r["cust"].isna().iloc[-1]
    summary = measures.fleet(spark.createDataFrame(served.astype({"truck": int, "cust": int})[["truck", "cust", "amount", "leg_cost"]]))
    assert summary.head()["stops"] == len(served)


def test_split_loads_and_replanning(spark):
    g = workloads.road(spark, "/root/testdata/sf0.001").materialised()
    depots = spark.createDataFrame([(0, 3, 30.0)], "depot long, nid long, supply double")
    trucks = spark.createDataFrame([(0, 0, 10.0), (1, 0, 10.0), (2, 0, 10.0)], "truck long, depot long, capacity double")
    demands = spark.createDataFrame([(1, 50, 14.0), (2, 60, 7.0), (3, 70, 40.0)], "cust long, nid long, amount double")
    whole = tours.fleet(g, depots, trucks, demands).toPandas()
    assert set(whole[whole["truck"].isna()]["cust"]) == {1, 3}  # too large for a truck, and for the depot
    split = tours.fleet(g, depots, trucks, demands, split=True).toPandas()
    got = split[split["truck"].notna() & split["cust"].notna()]
    assert got[got["cust"] == 1]["amount"].sum() == 14 and got[got["cust"] == 1]["truck"].nunique() >= 2
    assert (got.groupby("truck")["amount"].sum() <= 10).all()
    positions = spark.createDataFrame([(0, 100, 9.0), (1, 20, 0.5)], "truck long, nid long, room double")
    again = tours.replan(g, depots, trucks, demands, spark.createDataFrame([(1,), (3,)], "cust long"), positions).toPandas()
    assert list(again[again["cust"].notna()][["truck", "cust"]].itertuples(index=False, name=None)) == [(0, 2)]


def test_link_walk_equals_rows_and_thinning(spark):
    assert measures.walk_vs_csr(graph_of(spark, [r for r in RANDOM if r[0] != r[1]]), RANDOM[0][0])["equal"]
    gps = spark.createDataFrame([(1, i) for i in range(7)] + [(2, 5)], "trip_id long, seq long")
    assert sorted(map(tuple, match.thinned(gps, 3).collect())) == [(1, 0), (1, 3), (1, 6), (2, 5)]


def test_matching_without_noise_is_exact(spark):
    g = workloads.road(spark, "/root/testdata/sf0.001")
    walk = [(5, 1), (6, 1), (7, 1), (7, 2), (7, 3), (8, 3)]
    gps = spark.createDataFrame([(1, i, float(x) + 0.4 * (i == 1), float(y)) for i, (x, y) in enumerate(walk)] + [(2, 0, 500.0, 500.0), (2, 1, 5.0, 1.0)], "trip_id long, seq long, x double, y double")
    got = match.map_match(g, gps).orderBy("trip_id", "seq").collect()
    assert all(r["dist"] < 1e-9 for r in got[:6])
    assert got[6]["eid"] is None and got[7]["eid"] is not None


def test_turn_rules(spark):
    nodes = spark.createDataFrame([(0, 0.0, 0.0), (1, 1.0, 0.0), (2, 1.0, 1.0), (3, 2.0, 0.0)], "nid long, x double, y double")
    g = Graph.of("t", nodes, edges_of(spark, [(0, 1, 1), (1, 2, 1), (1, 3, 1)]))
    free = as_dict(turns.costs(g, 0, turns.TurnRules()))
    left = as_dict(turns.costs(g, 0, turns.TurnRules(left=10)))
    banned = as_dict(turns.costs(g, 0, turns.TurnRules(left=None)))
    assert free == {0: 0, 1: 1, 2: 2, 3: 2}
    assert left == {0: 0, 1: 1, 2: 12, 3: 2}
    assert banned == {0: 0, 1: 1, 3: 2}


def test_weights_and_geometry(spark):
    g = workloads.road(spark, "/root/testdata/sf0.001")
    same = weights.scaled(g, spark.createDataFrame([(0, 2.0)], "eid long, factor double"))
    a, b = (x.edges.where("eid = 0").head()["weight"] for x in (g, same))
    assert b == 2 * a
    row = spark.range(1).select(
        geo.parse_point(F.lit("POINT(-77.3808 38.7567)")).alias("p"),
        geo.line_length(geo.parse_line(F.lit("LINESTRING(0 0, 3 4, 3 5)"))).alias("n"),
        geo.parse_point(F.lit("LINE")).alias("none"),
        geo.distance_m(F.lit(0.0), F.lit(0.0), F.lit(0.0), F.lit(1.0)).alias("m"),
        geo.turn_angle(F.lit(170.0), F.lit(-170.0)).alias("turn"),
        geo.line_meets_box(geo.parse_line(F.lit("LINESTRING(-1 -1, 2 2)")), F.lit(0.0), F.lit(0.0), F.lit(1.0), F.lit(1.0)).alias("hit"),
        geo.line_meets_box(geo.parse_line(F.lit("LINESTRING(-1 0.5, -1 2)")), F.lit(0.0), F.lit(0.0), F.lit(1.0), F.lit(1.0)).alias("miss"),
    ).head()
    assert (row["p"]["x"], row["p"]["y"]) == (-77.3808, 38.7567) and row["n"] == 6.0 and row["none"] is None
    assert abs(row["m"] - 111195) < 1 and row["turn"] == 20.0 and row["hit"] and not row["miss"]
    pts = spark.createDataFrame([(1, 0.0, 0.0), (2, 0.6, 0.0), (3, 1.2, 0.0), (4, 9.0, 9.0)], "pid long, x double, y double")
    assert {r["pid"]: r["rep"] for r in geo.merge_points(pts, 0.7, "linked").collect()} == {1: 1, 2: 1, 3: 1, 4: 4}
    boxes = spark.createDataFrame([(7, -1.0, -1.0, 1.0, 1.0)], "bid long, xmin double, ymin double, xmax double, ymax double")
    assert sorted(r["pid"] for r in geo.join_within(pts, boxes, 0.5).collect()) == [1, 2]


def test_tiles_hold_every_edge_once(spark, tmp_path):
    e = spark.range(2000).select(F.col("id").alias("eid"), ((F.col("id") % 40) * (F.col("id") % 40)).cast("double").alias("mx"), F.floor(F.col("id") / 40).cast("double").alias("my"))
    tiled = tiles.build(e, 100)
    assert tiled.count() == 2000
    assert tiled.groupBy("tile").count().agg(F.max("count")).head()[0] <= 100
    names = sorted(r["tile"] for r in tiled.select("tile").distinct().collect())
    assert not any(a != b and b.startswith(a) for a in names for b in names)
    tiles.save(tiled, f"file://{tmp_path}/t")
    some = tiles.load(spark, f"file://{tmp_path}/t", (0.0, 0.0, 100.0, 10.0), "eid long, mx double, my double")
    got = some.where("mx <= 100 AND my <= 10").count()
    assert got == e.where("mx <= 100 AND my <= 10").count() and some.count() < 2000
    assert tiles.build(e.limit(0), 5).count() == 0
    tiles.refresh(tiled.where(F.col("tile") == names[0]).limit(1), f"file://{tmp_path}/t", "eid long, mx double, my double")
    assert spark.read.parquet(f"file://{tmp_path}/t/index").agg(F.sum("n")).head()[0] < 2000


# ------------------------------------------------------------- requests


def test_requests_tasks_and_table_functions(spark):
    from weftgraph.plans.tasks import Api, TaskRunner, register_functions

    api = Api(spark)
    edges_of(spark, RANDOM).createOrReplaceTempView("base_edges")
    made = api.run({"endpoint": "create", "graph": "r", "edges": [{"table": "base_edges", "roles": {"edge.id": "eid", "edge.src_id": "src", "edge.dst_id": "dst", "edge.weight": "weight"}}]})
    assert made.head()["edges"] == len(RANDOM)
    with pytest.raises(ValueError):
        api.run({"endpoint": "create", "graph": "r", "edges": [{"table": "base_edges", "roles": {"edge.src_id": "src", "edge.dst_id": "dst"}}]})
    start = RANDOM[0][0]
    runner = TaskRunner(api, 1)
    late = runner.submit({"endpoint": "solve", "graph": "r", "solver": "shortest_path", "source": start, "engine": "single", "into": "costs_r"}, 20)
    soon = runner.submit({"endpoint": "repartition", "graph": "r", "scheme": "random", "parts": 3}, 1)
    bad = runner.submit({"endpoint": "solve", "graph": "r", "solver": "nothing"}, 30)
    runner.close()
    assert soon.result().count() == 3 and late.result().count() > 1
    assert isinstance(bad.exception(), ValueError)
    started = {e["task"]: e["started"] for e in runner.log}
    assert started[1] < started[0]
    assert spark.sql("SELECT min(cost) AS c FROM costs_r").head()["c"] == 0
    api.run({"endpoint": "modify", "graph": "r", "delete_edges": "SELECT eid FROM base_edges WHERE eid = 1"})
    assert api.graphs.get("r").edges.count() == len(RANDOM) - 1
    register_functions(spark, graph_of(spark, RANDOM), "toy")
    got = {r["nid"]: r["cost"] for r in spark.sql(f"SELECT * FROM toy_near({start}, 1000000.0D)").collect()}
    assert got == dijkstra(RANDOM, start)


def test_lattice_source_and_files(spark, tmp_path):
    from weftgraph.sources import files

    spark.dataSource.register(files.LatticeSource)
    e = spark.read.format("lattice").option("width", 5).option("rows", 4).load()
    assert e.count() == 4 * 4 + 5 * 3
    files.write_edges(e, f"file://{tmp_path}/e", "csv")
    assert files.read_edges(spark, f"file://{tmp_path}/e", "csv", "eid long, src long, dst long, weight long").count() == e.count()
    files.write_bucketed(e, "bucketed_edges", 3)
    assert spark.table("bucketed_edges").count() == e.count()
    assert as_dict(sssp.costs(Graph.of("l", None, e), 0, "single"))[19] > 0


# ---------------------------------------------------------------- plans


def plan_of(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans(spark, sf_dir):
    """Filters and columns reach the scans; no cross product in path queries and cells."""
    from weftgraph.plans.common import table

    base = table(spark, sf_dir, "orders").where("o_orderkey < 5").select("o_custkey")
    text = plan_of(base)
    assert "LessThan(o_orderkey,5)" in text and "o_orderdate" not in text.split("ReadSchema")[1]
    g = workloads.knows(spark, sf_dir)
    found = query.paths(g, query.Select(where=F.col("nid") < 3), query.Select(labels=["BUILDING"]), query.Hops(2))
    assert "CartesianProduct" not in plan_of(found) and "BroadcastNestedLoopJoin" not in plan_of(found)
    merged = geo.merge_points(spark.createDataFrame([(1, 0.0, 0.0)], "pid long, x double, y double"), 0.5)
    assert "NestedLoop" not in plan_of(merged)


def test_feed_replay_is_idempotent(spark, tmp_path):
    from weftgraph.streaming.feeds import UpsertFeed, changes

    rows = [(1, 7, "view", 1.5, '{"k": 3}'), (2, 7, "error", 0.0, '{"k": 3}'), (3, 7, "view", 2.5, '{"k": 4}')]
    events = spark.createDataFrame(rows, "event_id long, user_id long, event_type string, value double, props string").withColumn("ts", F.timestamp_seconds("event_id"))
    ch = changes(events)
    feed = UpsertFeed(spark, f"file://{tmp_path}/s")
    feed.apply(ch.where("seq <> 1"), 0)
    feed.apply(ch.where("seq <> 1"), 0)
    feed.apply(ch.where("seq = 1"), 1)  # older than the deletion: stays deleted
    assert sorted(map(tuple, feed.edges().collect())) == [(7, 1000004, 250)]


def test_a_round_that_only_updates_copies_keeps_the_cost_field(spark, sf_dir, monkeypatch):
    from weftgraph import queries_partition

    rows = [(0, 0, 1, 1, 0), (1, 0, 2, 1, 0), (2, 1, 2, 5, 1)]
    edges = spark.createDataFrame(rows, "eid long, src long, dst long, weight long, part int")
    stats = sssp.SolveStats(record_fields=True)
    sssp.costs(Graph.of("copies", None, edges), 0, stats=stats)
    assert [f["sum_cost"] for f in stats.fields] == [2, 2]  # the second round only brings both costs to part 1
    monkeypatch.setattr(queries_partition, "cost_field_rounds", lambda *_: stats.fields)
    assert tuple(queries_partition.sssp_cost_field(spark, sf_dir).head()) == (3, 1, 2, True)
    monkeypatch.setattr(queries_partition, "cost_field_rounds", lambda *_: [{"reached": 3, "max_cost": 1, "sum_cost": 2}, {"reached": 3, "max_cost": 2, "sum_cost": 3}])
    assert not queries_partition.sssp_cost_field(spark, sf_dir).head()["grows"]


def test_a_replicated_graph_reaches_the_driver_as_packed_columns(spark, monkeypatch):
    from pyspark.sql import DataFrame

    g = graph_of(spark, [(0, 1, 300), (1, 2, 400), (0, 2, 900), (2, 3, 500)])
    want = {(0, 0): 0, (0, 1): 300, (0, 2): 700, (0, 3): 1200}
    monkeypatch.setattr(DataFrame, "toPandas", lambda *_: pytest.fail("rows of arcs on the driver"))
    shared = sssp.replicate(g).value
    assert shared.ids.tolist() == [0, 1, 2, 3] and shared.offsets.tolist() == [0, 2, 4, 7, 8]
    got = {(r["source"], r["nid"]): r["cost"] for r in sssp.many_costs(g, spark.createDataFrame([(0,)], "nid long")).collect()}
    assert got == want


def test_arrays_and_lists_of_a_block_settle_alike(monkeypatch):
    from weftgraph.operators import kernels

    u, v, w = np.array([0, 1, 0, 2]), np.array([1, 2, 2, 3]), np.array([300, 400, 900, 500])
    for weights_ in (w, w / 4):
        seen = []
        for most in (10, 0):
            monkeypatch.setattr(kernels, "LIST_ARCS", most)
            block = kernels.Block.of(u, v, weights_)
            dist = [float("inf")] * 4
            kernels.settle(block.lists(), dist, [(0, 0)])
            seen.append((type(block.lists()[1]), dist))
        assert seen[0][0] is list and seen[1][0] is not list and seen[0][1] == seen[1][1] == [0, weights_[0], weights_[0] + weights_[1], weights_.sum() - weights_[2]]


def test_stops_of_a_route_are_not_solved_for_the_whole_graph(spark, monkeypatch):
    g = graph_of(spark, [(0, 1, 3), (1, 2, 4), (2, 3, 5)])
    monkeypatch.setattr(tours, "many_costs", lambda *_: pytest.fail("costs of all nodes"))
    rows = tours.multi_stop(g, [2, 0, 3, 2]).orderBy("leg").collect()
    assert [(r["leg"], r["src"], r["dst"], r["cost"], r["total"]) for r in rows] == [(0, 2, 0, 7, 7), (1, 0, 3, 12, 19), (2, 3, 2, 5, 24)]


def test_fleet_sends_the_graph_once_and_solves_only_its_stops(spark, monkeypatch):
    g = graph_of(spark, [(0, 1, 3), (1, 2, 4), (2, 3, 5), (3, 4, 6)])
    sent, plain = [], sssp.replicate
    for module in (sssp, tours):
        monkeypatch.setattr(module, "replicate", lambda graph: sent.append(1) or plain(graph), raising=False)
    monkeypatch.setattr(tours, "many_costs", lambda *_, **__: pytest.fail("costs of all nodes"))
    depots = spark.createDataFrame([(0, 0, 9.0), (1, 4, 9.0)], "depot long, nid long, supply double")
    trucks = spark.createDataFrame([(0, 0, 9.0), (1, 1, 9.0)], "truck long, depot long, capacity double")
    demands = spark.createDataFrame([(1, 1, 2.0), (2, 3, 4.0), (3, 99, 1.0)], "cust long, nid long, amount double")
    routes = [tuple(r) for r in tours.fleet(g, depots, trucks, demands).select("depot", "truck", "cust", "leg_cost").collect()]
    assert sorted(routes, key=repr) == sorted([(0, 0, None, 0.0), (0, 0, 1, 3.0), (0, 0, None, 3.0), (1, 1, None, 0.0), (1, 1, 2, 6.0), (1, 1, None, 6.0), (None, None, 3, None)], key=repr)
    assert len(sent) == 1


def test_sources_solved_together_are_those_solved_alone():
    import numpy as np

    from weftgraph.operators.kernels import Block, settle, settle_each

    rng = np.random.default_rng(7)
    for kind, low in ((np.int64, 0), (np.int64, 3), (np.float64, 0)):
        u, v = rng.integers(0, 90, 200), rng.integers(0, 90, 200)
        w = (rng.integers(low, 40, 200) / (1 if kind is np.int64 else 7)).astype(kind)
        b = Block.of(u, v, w)
        for limit in (float("inf"), 25):
            found = settle_each(b, np.arange(len(b.ids)), limit)
            for s in range(len(b.ids)):
                dist = [float("inf")] * len(b.ids)
                settle(b.lists(), dist, [(0, s)], limit=limit)
                none = np.inf if kind is np.float64 else np.iinfo(kind).max
                assert [float("inf") if d == none else d for d in found[s].tolist()] == dist
    assert settle_each(Block.of(np.array([1, 2]), np.array([2, 1]), np.array([0, 0])), np.array([0])).tolist() == [[0, 0]]


def test_replicated_sources_are_not_solved_one_by_one(spark, sf_dir, monkeypatch, duck):
    from helpers import same_rows

    from weftgraph.operators import kernels
    from weftgraph.queries import ORACLE_SQL, QUERIES

    monkeypatch.setattr(sssp, "settle", kernels.brandes)  # a call of the queue for one source would fail
    monkeypatch.setattr(sssp, "SETTLED_AT_ONCE", 500)
    same_rows(QUERIES["sssp_replicated"](spark, sf_dir), duck.sql(ORACLE_SQL["sssp_replicated"]))


def test_tasks_share_the_sources_of_a_replicated_graph(spark, sf_dir):
    g = workloads.road(spark, sf_dir)
    found = sssp.many_costs(g, g.nodes.where("nid % 20 = 0").select("nid"), engine="replicated")
    rows = found.select(F.spark_partition_id().alias("p"), "source").distinct().collect()
    assert len({r["source"] for r in rows}) == len(rows) > len({r["p"] for r in rows}) > 1
