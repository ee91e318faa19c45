"""Round trips, back-haul, fleets and several travelling salesmen on network costs.

Costs between stops come from the graph, in replicated mode. Each tour or
depot is one group of rows, so many are improved at once; an instance of a
fleet is bounded by the number of its stops, which is checked.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from weftgraph.functions.geo import voronoi_zone
from weftgraph.model import Graph
from weftgraph.operators.sssp import check_weights, fits_workers, many_costs, pair_costs, replicate
from weftgraph.plans.common import cut

#: Most stops of one tour or of one depot.
TOUR_STOPS = 5_000


def cost_matrix(graph: Graph, stops: DataFrame, tasks: int | None = None, shared=None) -> DataFrame:
    """(tour, a, b, cost): least costs between the stops(tour, nid) of each tour."""
    named = stops.select("tour", "nid").distinct()
    lists = named.groupBy("tour").agg(F.collect_list("nid").alias("dsts"))  # at most TOUR_STOPS each
    # a node may be a stop of several tours; it is solved once for all of them
    wanted = named.join(lists, "tour").groupBy(F.col("nid").alias("src")).agg(F.array_distinct(F.flatten(F.collect_list("dsts"))).alias("dsts"))
    found = pair_costs(graph, wanted, tasks=tasks, shared=shared).where("cost IS NOT NULL")
    a = named.select("tour", F.col("nid").alias("a"))
    b = named.select(F.col("tour").alias("_t"), F.col("nid").alias("b"))
    return a.join(found, F.col("a") == F.col("src")).join(b, (F.col("tour") == F.col("_t")) & (F.col("dst") == F.col("b"))).select("tour", "a", "b", "cost")


def tour_cost(order: list[int], m: np.ndarray, closed: bool = True) -> float:
    legs = sum(m[a, b] for a, b in zip(order[:-1], order[1:], strict=True))
    return float(legs + (m[order[-1], order[0]] if closed and len(order) > 1 else 0))


def nearest_neighbour(m: np.ndarray, start: int = 0) -> list[int]:
    left, order = set(range(len(m))) - {start}, [start]
    while left:
        order.append(min(left, key=lambda j: (m[order[-1], j], j)))
        left.discard(order[-1])
    return order


def improve(order: list[int], m: np.ndarray, closed: bool = True, max_sweeps: int = 50) -> list[int]:
    """2-opt where costs are symmetric, then moves of runs of up to three stops; the first stop stays."""
    symmetric = bool(np.array_equal(m, m.T))
    order = list(order)
    n = len(order)
    for _ in range(max_sweeps):
        better = False
        if symmetric:
            for i in range(n - 1):
                for j in range(i + 2, n + (0 if not closed else 0)):
                    a, b, c = order[i], order[i + 1], order[j]
                    d = order[j + 1] if j + 1 < n else (order[0] if closed else None)
                    if d == a:
                        continue
                    gain = m[a, b] + (m[c, d] if d is not None else 0) - m[a, c] - (m[b, d] if d is not None else 0)
                    if gain > 1e-9:
                        order[i + 1 : j + 1] = order[i + 1 : j + 1][::-1]
                        better = True
        for size in (1, 2, 3):
            for i in range(1, n - size + 1):
                run, rest = order[i : i + size], order[:i] + order[i + size :]
                now = tour_cost(order, m, closed)
                ends = [(tour_cost(rest[:k] + run + rest[k:], m, closed), k) for k in range(1, len(rest) + 1)] if n <= 12 else _places(rest, run, m, closed)
                best, k = min(ends)
                if best < now - 1e-9:
                    order = rest[:k] + run + rest[k:]
                    better = True
        if not better:
            break
    return order


def _places(rest: list[int], run: list[int], m: np.ndarray, closed: bool) -> list[tuple[float, int]]:
    """(cost, place) of putting a run back, by differences."""
    base = tour_cost(rest, m, closed) + sum(m[a, b] for a, b in zip(run[:-1], run[1:], strict=True))
    out = []
    for k in range(1, len(rest) + 1):
        a, b = rest[k - 1], rest[k] if k < len(rest) else (rest[0] if closed else None)
        out.append((base + m[a, run[0]] + (m[run[-1], b] - m[a, b] if b is not None else 0), k))
    return out


def exact_tour(m: np.ndarray, closed: bool = True) -> float:
    """The least cost of a tour from stop 0, by dynamic programming; at most twelve stops."""
    n = len(m)
    if n > 12:
        raise ValueError("too many stops for the exact method")
    if n == 1:
        return 0.0
    best = {(1 << i, i): m[0, i] for i in range(1, n)}
    for size in range(2, n):
        for mask in range(1 << n):
            if mask & 1 or mask.bit_count() != size:
                continue
            for j in range(1, n):
                if mask >> j & 1:
                    best[mask, j] = min(best[mask ^ (1 << j), i] + m[i, j] for i in range(1, n) if i != j and mask >> i & 1)
    full = (1 << n) - 2
    return float(min(best[full, j] + (m[j, 0] if closed else 0) for j in range(1, n)))


def _dense(pdf: pd.DataFrame, first: int | None) -> tuple[list[int], np.ndarray]:
    ids = sorted(set(pdf["a"]) | set(pdf["b"]))
    if first is not None and first in ids:
        ids = [first, *[i for i in ids if i != first]]
    at = {n: i for i, n in enumerate(ids)}
    m = np.full((len(ids), len(ids)), np.inf)
    m[[at[a] for a in pdf["a"]], [at[b] for b in pdf["b"]]] = pdf["cost"].to_numpy(float)
    return ids, m


def _check_stops(stops: DataFrame, key: str) -> None:
    most = stops.groupBy(key).count().agg(F.max("count")).head()[0] or 0
    if most > TOUR_STOPS:
        raise ValueError(f"{most} stops in one group; at most {TOUR_STOPS}")


def tsp(graph: Graph, stops: DataFrame, starts: DataFrame | None = None, closed: bool = True, better: bool = True) -> DataFrame:
    """(tour, step, nid, leg, total): a tour through the stops(tour, nid) of each tour.

    It begins at the start of ``starts(tour, nid)``, else at the smallest stop.
    Ties go to the smaller id. Stops that cannot reach one another are an error.
    """
    _check_stops(stops, "tour")
    all_stops = stops.select("tour", "nid") if starts is None else stops.select("tour", "nid").unionByName(starts.select("tour", "nid"))
    matrix = cost_matrix(graph, all_stops)
    first = (starts.select("tour", F.col("nid").alias("first")) if starts is not None else stops.groupBy("tour").agg(F.min("nid").alias("first"))).withColumnRenamed("tour", "_t")
    rows = matrix.join(first, F.col("tour") == F.col("_t")).select("tour", "a", "b", "cost", "first")

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        ids, m = _dense(pdf, int(pdf["first"].iloc[0]))
        if np.isinf(m).any():
            raise ValueError(f"stops of tour {pdf['tour'].iloc[0]} cannot reach one another")
        order = nearest_neighbour(m)
        if better:
            order = improve(order, m, closed)
        seq = [*order, order[0]] if closed and len(order) > 1 else order
        legs = [0.0, *[m[a, b] for a, b in zip(seq[:-1], seq[1:], strict=True)]]
        return pd.DataFrame({"tour": pdf["tour"].iloc[0], "step": np.arange(len(seq), dtype=np.int32), "nid": [ids[i] for i in seq], "leg": legs, "total": np.cumsum(legs)})

    return rows.groupBy("tour").applyInPandas(one, "tour long, step int, nid long, leg double, total double")


def multi_stop(graph: Graph, stops: list[int]) -> DataFrame:
    """(leg, src, dst, cost, total): a route through stops in the given order."""
    from pyspark.sql import Window

    pairs = graph.spark.range(1).select(F.posexplode(F.array(*[F.struct(F.lit(a).cast("long").alias("src"), F.lit(b).cast("long").alias("dst")) for a, b in zip(stops[:-1], stops[1:], strict=True)])).alias("leg", "p")).select("leg", "p.src", "p.dst")
    kind = "double" if dict(graph.edges.dtypes)["weight"] in ("double", "float") else "long"
    costs = pair_costs(graph, pairs.groupBy("src").agg(F.collect_set("dst").alias("dsts"))).withColumn("cost", F.col("cost").cast(kind))
    legs = pairs.join(costs, ["src", "dst"], "left").select("leg", "src", "dst", "cost")
    return legs.withColumn("total", F.sum("cost").over(Window.partitionBy(F.lit(0)).orderBy("leg")))  # a handful of legs


def _square(graph: Graph, stops: DataFrame, ids: list[int]) -> np.ndarray:
    """Costs between all stops of one tour as a matrix: a packed row for each origin, at most TOUR_STOPS of them."""
    lists = stops.agg(F.sort_array(F.collect_list("nid")).alias("dsts"))
    found = pair_costs(graph, stops.select(F.col("nid").alias("src")).join(F.broadcast(lists)))
    rows = found.groupBy("src").agg(F.array_sort(F.collect_list(F.struct("dst", "cost"))).alias("r")).select("src", F.col("r.cost").alias("c")).collect()
    m, at = np.full((len(ids), len(ids)), np.inf), {n: i for i, n in enumerate(ids)}
    for r in rows:
        m[at[r["src"]]] = [np.inf if c is None else c for c in r["c"]]
    return m


def backhaul(graph: Graph, depot: int, drops: DataFrame, pickups: DataFrame, capacity: float | None = None) -> DataFrame:
    """(step, nid, kind, load, leg, total): depot, all drops, then all pickups, depot.

    Each half goes to the nearest next stop and is then improved with its ends
    held. ``drops(nid, amount)`` leave the vehicle, ``pickups`` enter it; a load
    over ``capacity`` is an error.
    """
    d = drops.select("nid", F.col("amount").cast("double").alias("amount"), F.lit("drop").alias("kind"))
    p = pickups.select("nid", F.col("amount").cast("double").alias("amount"), F.lit("pickup").alias("kind"))
    stops = d.unionByName(p).limit(TOUR_STOPS + 1).toPandas()
    if len(stops) > TOUR_STOPS:
        raise ValueError(f"at most {TOUR_STOPS} stops")
    spark = graph.spark
    ids = sorted({depot, *stops["nid"].tolist()})
    named = spark.createDataFrame([(0, int(i)) for i in ids], "tour long, nid long")
    m, at = _square(graph, named, ids), {n: i for i, n in enumerate(ids)}
    amount = {(r.kind, r.nid): r.amount for r in stops.itertuples()}
    half = {k: sorted(n for kk, n in amount if kk == k) for k in ("drop", "pickup")}
    for kind in half:
        if capacity is not None and sum(amount[kind, n] for n in half[kind]) > capacity:
            raise ValueError(f"the {kind} load is over capacity")
    seq, here = [("depot", depot)], depot
    for kind in ("drop", "pickup"):
        left = set(half[kind])
        while left:
            here = min(left, key=lambda n: (m[at[here], at[n]], n))
            left.discard(here)
            seq.append((kind, here))
    seq.append(("depot", depot))
    # reversing a run of one kind keeps the precedence; only its two ends change where costs are symmetric
    place = np.array([at[n] for _, n in seq])
    symmetric = bool(np.array_equal(m, m.T))
    changed = True
    while changed:
        changed = False
        for i in range(1, len(seq) - 2):
            for j in range(i + 1, len(seq) - 1):
                if seq[j][0] != seq[i][0]:
                    break
                run = place[i : j + 1]
                gain = m[place[i - 1], run[0]] + m[run[-1], place[j + 1]] - m[place[i - 1], run[-1]] - m[run[0], place[j + 1]]
                if not symmetric:
                    gain += m[run[:-1], run[1:]].sum() - m[run[1:], run[:-1]].sum()
                if gain > 1e-9:
                    seq[i : j + 1] = seq[i : j + 1][::-1]
                    place[i : j + 1] = run[::-1].copy()
                    changed = True
    load, rows, total = sum(amount["drop", n] for n in half["drop"]), [], 0.0
    for i, (kind, n) in enumerate(seq):
        leg = 0.0 if i == 0 else float(m[at[seq[i - 1][1]], at[n]])
        total += leg
        load += 0 if kind == "depot" else (-amount[kind, n] if kind == "drop" else amount[kind, n])
        rows.append((i, int(n), kind, float(load), leg, total))
    return spark.createDataFrame(rows, "step int, nid long, kind string, load double, leg double, total double")


# ------------------------------------------------------------------ fleets


def _assign(pdf: pd.DataFrame) -> pd.DataFrame:
    """Customers to depots with supply left, the largest regret first."""
    supply = pdf.groupby("depot")["supply"].first().to_dict()
    rows = []
    for cust, g in pdf.groupby("cust"):
        g = g.sort_values(["cost", "depot"])
        cost = g["cost"].tolist()
        rows.append((cost[1] - cost[0] if len(cost) > 1 else float("inf"), cust, g["amount"].iloc[0], list(zip(g["depot"], cost, strict=True))))
    out = []
    for _, cust, amount, options in sorted(rows, key=lambda r: (-r[0], r[1])):
        for depot, cost in options:
            if supply[depot] >= amount and np.isfinite(cost):
                supply[depot] -= amount
                out.append((cust, depot))
                break
        else:
            out.append((cust, None))
    return pd.DataFrame({"instance": pdf["instance"].iloc[0], "cust": [c for c, _ in out], "depot": pd.array([d for _, d in out], dtype="Int64")})


def _routes(matrix: pd.DataFrame, stops: pd.DataFrame, trucks: pd.DataFrame, split: bool | str) -> pd.DataFrame:
    """Routes of one depot: largest trucks first, each filled by savings from its farthest stop, then improved."""
    depot, home = int(trucks["depot"].iloc[0]), int(trucks["home"].iloc[0])
    ids, m = _dense(matrix, home)
    at = {n: i for i, n in enumerate(ids)}
    need = {int(c): float(a) for c, a in zip(stops["cust"], stops["amount"], strict=True)}
    node = {int(c): at.get(int(n), 0) for c, n in zip(stops["cust"], stops["nid"], strict=True)}
    # several customers may share a node
    rows, planned = [], []
    for t in trucks.sort_values(["capacity", "truck"], ascending=[False, True]).itertuples():
        room, route, got = float(t.capacity), [], {}
        while need and room > 0:
            fits = [c for c in need if need[c] <= room or split is True]
            if not fits:
                break
            if not route:
                c = max(fits, key=lambda c: (m[0, node[c]], -c))
            else:
                ends = (node[route[0]], node[route[-1]])
                save = lambda c: max(m[0, e] + m[0, node[c]] - m[e, node[c]] for e in ends)
                c = max(fits, key=lambda c: (save(c), -c))
            amount = min(need[c], room)
            got[c] = amount
            need[c] -= amount
            room -= amount
            if need[c] <= 0:
                del need[c]
            e0, e1 = (node[route[0]], node[route[-1]]) if route else (0, 0)
            route = [c, *route] if route and m[e0, node[c]] < m[e1, node[c]] else [*route, c]
        planned.append([int(t.truck), room, route, got])
    if split == "rest":  # what fits into no truck is shared by the nearest ones with room
        for c in sorted(need):
            while need[c] > 0 and (open_trucks := [p for p in planned if p[1] > 0]):
                p = min(open_trucks, key=lambda p: (min((m[node[o], node[c]] for o in p[2]), default=m[0, node[c]]), p[0]))
                amount = min(need[c], p[1])
                p[1] -= amount
                need[c] -= amount
                if c not in p[3]:
                    p[2].append(c)
                p[3][c] = p[3].get(c, 0.0) + amount
        need = {c: a for c, a in need.items() if a > 0}
    for truck, _, route, got in planned:
        if not route:
            continue
        local = [0, *[node[c] for c in route]]
        sub = m[np.ix_(local, local)]
        order = improve(list(range(len(local))), sub) if len(local) > 2 else list(range(len(local)))
        order = [*order, 0]
        cost = 0.0
        for k, i in enumerate(order):
            leg = 0.0 if k == 0 else float(sub[order[k - 1], i])
            cost += leg
            c = route[i - 1] if i else None
            rows.append((depot, truck, k, c, got[c] if c is not None else 0.0, leg, cost))
    for c, a in sorted(need.items()):
        rows.append((depot, None, None, c, a, None, None))
    cols = ["depot", "truck", "stop_seq", "cust", "amount", "leg_cost", "arrive_cost"]
    out = pd.DataFrame(rows, columns=cols)
    return out.astype({"depot": "Int64", "truck": "Int64", "stop_seq": "Int32", "cust": "Int64", "amount": "float64", "leg_cost": "float64", "arrive_cost": "float64"})


def fleet(graph: Graph, depots: DataFrame, trucks: DataFrame, demands: DataFrame, split: bool | str = False, tasks: int | None = None) -> DataFrame:
    """(depot, truck, stop_seq, cust, amount, leg_cost, arrive_cost): deliveries of a fleet from several depots.

    depots(depot, nid, supply), trucks(truck, depot, capacity), demands(cust,
    nid, amount). Each route starts and ends at its depot, with a null cust.
    What no truck could take comes back with a null truck; a customer whom no
    depot can supply has a null depot too. ``split=True`` lets several trucks
    share any customer, ``split="rest"`` those only that fit into no truck.
    ``tasks`` bounds how many tasks solve costs at once: one stands for a single
    server, several for replicated ones.
    """
    _check_stops(demands.withColumn("_g", F.lit(0)), "_g")
    check_weights(graph.edges)
    shared = replicate(graph) if fits_workers(graph) else None  # one copy for both kinds of costs
    if shared is None:
        far = many_costs(graph, depots.select("nid"), engine="parts").select("source", F.col("nid").alias("dst"), "cost")
    else:
        ends = demands.agg(F.sort_array(F.collect_set("nid")).alias("dsts"))  # at most TOUR_STOPS
        far = pair_costs(graph, depots.select(F.col("nid").alias("src")).distinct().join(F.broadcast(ends)), shared=shared).where("cost IS NOT NULL").select(F.col("src").alias("source"), "dst", "cost")
    to_depot = demands.select("cust", F.col("nid").alias("at"), F.col("amount").cast("double").alias("amount")).join(far, F.col("at") == F.col("dst")).join(depots.select("depot", F.col("nid").alias("home"), F.col("supply").cast("double").alias("supply")), F.col("source") == F.col("home"))
    options = to_depot.select(F.lit(0).cast("long").alias("instance"), "cust", "amount", "depot", "supply", F.col("cost").cast("double").alias("cost"))
    chosen = cut(options.groupBy("instance").applyInPandas(_assign, "instance long, cust long, depot long"))  # one instance, its size is checked
    lost = demands.join(chosen.where("depot IS NOT NULL").select("cust"), "cust", "left_anti")
    stops = cut(demands.select("cust", "nid", F.col("amount").cast("double").alias("amount")).join(chosen.where("depot IS NOT NULL").select("cust", "depot"), "cust"))
    places = stops.select(F.col("depot").alias("tour"), "nid").unionByName(depots.select(F.col("depot").alias("tour"), "nid"))
    matrix = cost_matrix(graph, places, tasks, shared)
    crew = trucks.select("truck", "depot", F.col("capacity").cast("double").alias("capacity")).join(depots.select("depot", F.col("nid").alias("home")), "depot")
    schema = "depot long, truck long, stop_seq int, cust long, amount double, leg_cost double, arrive_cost double"
    # the matrix and the stops of a depot in one side of the cogroup, told apart by a column
    both = matrix.select(F.col("tour").alias("depot"), "a", "b", F.col("cost").cast("double").alias("cost"), F.lit(None).cast("long").alias("cust"), F.lit(None).cast("double").alias("amount")).unionByName(stops.select("depot", F.col("nid").alias("a"), F.lit(None).cast("long").alias("b"), F.lit(None).cast("double").alias("cost"), "cust", "amount"))

    def one(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        mine = left[left["cust"].notna()].rename(columns={"a": "nid"})
        if not len(right) or not len(mine):
            empty = [(None, None, None, c, a, None, None) for c, a in zip(mine["cust"], mine["amount"], strict=True)]
            return pd.DataFrame(empty, columns=["depot", "truck", "stop_seq", "cust", "amount", "leg_cost", "arrive_cost"])
        grid = left[left["b"].notna()].astype({"b": "int64"})
        return _routes(grid, mine.astype({"cust": "int64"}), right, split)

    done = both.groupBy("depot").cogroup(crew.groupBy("depot")).applyInPandas(one, schema)
    none = lost.select(F.lit(None).cast("long").alias("depot"), F.lit(None).cast("long").alias("truck"), F.lit(None).cast("int").alias("stop_seq"), "cust", F.col("amount").cast("double").alias("amount"), F.lit(None).cast("double").alias("leg_cost"), F.lit(None).cast("double").alias("arrive_cost"))
    return done.unionByName(none)


def replan(graph: Graph, depots: DataFrame, trucks: DataFrame, demands: DataFrame, served: DataFrame, positions: DataFrame, split: bool = False) -> DataFrame:
    """Plan again what is not served, each truck from where it is: trucks become depots of their own.

    ``served(cust)`` are done; ``positions(truck, nid, room)`` tell where trucks
    are and what they still carry.
    """
    open_stops = demands.join(served.select("cust"), "cust", "left_anti")
    own = positions.select(F.col("truck").alias("depot"), "nid", F.col("room").alias("supply"))
    crew = positions.select("truck", F.col("truck").alias("depot"), F.col("room").alias("capacity"))
    return fleet(graph, own, crew, open_stops, split)


def multi_tsp(graph: Graph, points: DataFrame, generators: DataFrame) -> DataFrame:
    """(tour, step, nid, leg, total): a round trip of each generator's collector through the points of its zone.

    points(pid, nid, x, y) and generators(gid, nid, x, y); zones are by straight distance.
    """
    zones = voronoi_zone(points, generators)
    stops = points.join(zones, "pid").select(F.col("gid").alias("tour"), "nid")
    return tsp(graph, stops, generators.select(F.col("gid").alias("tour"), "nid"))
