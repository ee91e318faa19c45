"""Requests on named graphs: create, solve, query, match, modify, repartition.

A request is a dictionary (JSON) with an endpoint and its parameters; the same
requests run as SQL through temporary views. Graph versions are immutable:
modifications of a graph follow one another, solves keep the version they
started with and run side by side. A log of tasks is kept so that none gets
lost.
"""

from __future__ import annotations

import itertools
import json
import queue
import threading
import time
from collections.abc import Callable
from concurrent.futures import Future
from dataclasses import dataclass, field
from typing import Any

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from weftgraph import grammar
from weftgraph.model import CreateOptions, Graph
from weftgraph.operators import balance, centrality, match, partition, paths, query, rank, sssp, tours


class Graphs:
    """Named graphs with versions; readers hold what they got."""

    def __init__(self) -> None:
        self._now: dict[str, Graph] = {}
        self._locks: dict[str, threading.Lock] = {}
        self._guard = threading.Lock()

    def get(self, name: str) -> Graph:
        with self._guard:
            if name not in self._now:
                raise KeyError(f"no graph named {name}")
            return self._now[name]

    def put(self, name: str, graph: Graph, recreate: bool = False) -> None:
        with self._guard:
            if name in self._now and not recreate:
                raise ValueError(f"graph {name} exists; pass recreate")
            self._now[name] = graph

    def change(self, name: str, step: Callable[[Graph], Graph]) -> Graph:
        """Apply one modification after another; readers are not blocked."""
        with self._guard:
            lock = self._locks.setdefault(name, threading.Lock())
        with lock:
            new = step(self.get(name))
            self.put(name, new, recreate=True)
            return new


@dataclass
class Api:
    """Endpoints over a session; tables are given by view name."""

    spark: SparkSession
    graphs: Graphs = field(default_factory=Graphs)

    def run(self, request: dict | str) -> DataFrame | None:
        """Answer one request; ``into`` also registers the result as a view."""
        r = json.loads(request) if isinstance(request, str) else dict(request)
        kind = r.pop("endpoint", None)
        handler = getattr(self, f"_{kind}", None) if kind in ("create", "solve", "query", "match", "modify", "repartition") else None
        if handler is None:
            raise ValueError(f"unknown endpoint {kind}")
        into = r.pop("into", None)
        out = handler(r)
        if into and out is not None:
            out.createOrReplaceTempView(into)
        return out

    def _table(self, source: Any) -> DataFrame:
        return source if isinstance(source, DataFrame) else self.spark.table(source) if " " not in source.strip() else self.spark.sql(source)

    def _component(self, c: dict) -> grammar.Component:
        return grammar.Component(self._table(c["table"]), {k: (F.expr(v) if isinstance(v, str) else v) for k, v in c["roles"].items()})

    def _create(self, r: dict) -> DataFrame:
        options = CreateOptions(**r.get("options", {}))
        g = grammar.create(self.spark, r["graph"], [self._component(c) for c in r["edges"]], [self._component(c) for c in r.get("nodes", [])], options).materialised()
        self.graphs.put(r["graph"], g, options.recreate)
        g.nodes.createOrReplaceTempView(f"{r['graph']}_nodes")
        g.edges.createOrReplaceTempView(f"{r['graph']}_edges")
        return g.nodes.agg(F.count("*").alias("nodes")).join(g.edges.agg(F.count("*").alias("edges")))

    def _solve(self, r: dict) -> DataFrame:
        g, solver = self.graphs.get(r["graph"]), r["solver"]
        if solver == "shortest_path":
            found = sssp.costs(g, r["source"], r.get("engine", "parts"))
            if "targets" in r:
                t = self.spark.range(1).select(F.explode(F.array(*[F.lit(x).cast("long") for x in r["targets"]])).alias("nid"))
                return paths.aggregate(g, found, t) if r.get("paths") else found.join(t, "nid")
            return found
        simple: dict[str, Callable[[], DataFrame]] = {
            "inverse_shortest_path": lambda: sssp.inverse(g, r["source"], r.get("engine", "parts")),
            "page_rank": lambda: rank.pagerank(g, r.get("damping", 0.85), r.get("iterations", 20)),
            "markov": lambda: rank.markov(g, r["source"], r["steps"]),
            "stationary": lambda: rank.stationary(g),
            "closeness": lambda: centrality.closeness(g),
            "betweenness": lambda: centrality.betweenness(g, weighted=r.get("weighted", True)),
            "all_paths": lambda: query.all_paths(g, r["source"], r["target"], r["max_hops"], r.get("max_cost")),
            "euler": lambda: rank.euler(g, r.get("directed", False)),
            "travelling_salesman": lambda: tours.tsp(g, self._table(r["stops"])),
            "multi_stop": lambda: tours.multi_stop(g, r["stops"]),
            "backhaul": lambda: tours.backhaul(g, r["source"], self._table(r["drops"]), self._table(r["pickups"])),
        }
        if solver not in simple:
            raise ValueError(f"unknown solver {solver}")
        return simple[solver]()

    def _query(self, r: dict) -> DataFrame:
        g = self.graphs.get(r["graph"])
        pick = lambda s: query.Select(s.get("ids"), s.get("names"), s.get("labels"), F.expr(s["where"]) if "where" in s else None)
        rules = [query.Restriction.edge(self._table(x["table"]), F.expr(x["key"]), F.expr(x["on"])) if x.get("on") else query.Restriction.not_edge(self._table(x["table"]), F.expr(x["key"]), F.expr(x["off"])) for x in r.get("restrictions", [])]
        hops = query.Hops(r.get("max_hops", 3), r.get("min_hops", 1), [set(h) for h in r["hop_labels"]] if "hop_labels" in r else None, set(r.get("exclude_labels", [])))
        if "targets" not in r:
            return query.neighbours(g, pick(r["sources"]), hops.max_hops, rules, hops)
        return query.paths(g, pick(r["sources"]), pick(r["targets"]), hops, rules)

    def _match(self, r: dict) -> DataFrame:
        g, solver = self.graphs.get(r["graph"]), r["solver"]
        if solver == "map_match":
            return match.map_match(g, self._table(r["gps"]))
        if solver == "batch_pairs":
            return match.batch_pairs(g, self._table(r["pairs"]), r.get("paths", False))
        if solver == "od_within":
            return match.od_within(g, self._table(r["pairs"]), r["max_cost"])
        if solver == "fleet":
            return tours.fleet(g, self._table(r["depots"]), self._table(r["trucks"]), self._table(r["demands"]), r.get("split", False))
        if solver == "multi_tsp":
            return tours.multi_tsp(g, self._table(r["points"]), self._table(r["generators"]))
        raise ValueError(f"unknown solver {solver}")

    def _modify(self, r: dict) -> DataFrame:
        def step(g: Graph) -> Graph:
            edges = g.edges
            if "delete_edges" in r:
                edges = edges.join(self._table(r["delete_edges"]).select("eid").distinct(), "eid", "left_anti")
            if "insert_edges" in r:
                edges = edges.unionByName(self._table(r["insert_edges"]), allowMissingColumns=True).select(*g.edges.columns)
            return g.with_edges(edges).materialised()

        new = self.graphs.change(r["graph"], step)
        return new.edges.agg(F.count("*").alias("edges")).withColumn("version", F.lit(new.version))

    def _repartition(self, r: dict) -> DataFrame:
        schemes = {"id_range": lambda g: partition.by_id_range(g, r.get("parts", 4)), "random": lambda g: partition.by_random(g, r.get("parts", 4)), "box": lambda g: partition.by_box(g, *r.get("box", (2, 2))), "balanced": lambda g: balance.rebalance(g, r.get("parts", 4), r.get("source"))}
        new = self.graphs.change(r["graph"], lambda g: schemes[r["scheme"]](g).materialised())
        return new.edges.groupBy("part").agg(F.count("*").alias("edges"))


@dataclass(order=True)
class _Task:
    order: tuple[int, int]
    request: dict = field(compare=False)
    future: Future = field(compare=False)


class TaskRunner:
    """Requests by priority (the smallest first, then in order of arrival) on a few threads."""

    def __init__(self, api: Api, workers: int = 2):
        self.api, self.log = api, []
        self._queue: queue.PriorityQueue[_Task] = queue.PriorityQueue()
        self._count = itertools.count()
        self._threads = [threading.Thread(target=self._work, daemon=True) for _ in range(workers)]
        self._started = False

    def submit(self, request: dict, priority: int = 10) -> Future:
        n, done = next(self._count), Future()
        self.log.append({"task": n, "priority": priority, "request": request, "state": "queued", "at": time.time()})
        self._queue.put(_Task((priority, n), request, done))
        return done

    def start(self) -> None:
        if not self._started:
            self._started = True
            for t in self._threads:
                t.start()

    def close(self) -> None:
        """End after what is queued."""
        for _ in self._threads:
            self._queue.put(_Task((1 << 30, next(self._count)), {}, Future()))
        self.start()
        for t in self._threads:
            t.join()

    def _work(self) -> None:
        while True:
            task = self._queue.get()
            if not task.request:
                return
            entry = next(e for e in self.log if e["task"] == task.order[1])
            entry |= {"state": "running", "started": time.time()}
            try:
                task.future.set_result(self.api.run(task.request))
                entry |= {"state": "done", "ended": time.time()}
            except Exception as error:  # noqa: BLE001  the error belongs to whoever waits for the result
                entry |= {"state": "failed", "error": str(error)[:500]}
                task.future.set_exception(error)


def register_functions(spark: SparkSession, graph: Graph, name: str) -> None:
    """Table functions ``<name>_route(src, dst)`` and ``<name>_near(src, max_cost)`` for SQL, on a replicated graph."""
    import heapq

    from pyspark.sql.functions import udtf

    shared = sssp.replicate(graph)

    def reach(src: int, limit: float, dst: int | None = None):
        block = shared.value
        offsets, targets, weights = block.lists()
        here = {int(n): i for i, n in enumerate(block.ids)}
        if src not in here:
            return
        dist, heap, done = {here[src]: 0}, [(0, here[src])], set()
        while heap:
            d, i = heapq.heappop(heap)
            if i in done:
                continue
            done.add(i)
            if dst is None or int(block.ids[i]) == dst:
                yield int(block.ids[i]), float(d)
                if dst is not None:
                    return
            for k in range(offsets[i], offsets[i + 1]):
                e = d + weights[k]
                if e <= limit and e < dist.get(targets[k], float("inf")):
                    dist[targets[k]] = e
                    heapq.heappush(heap, (e, targets[k]))

    @udtf(returnType="nid: bigint, cost: double")
    class Route:
        def eval(self, src: int, dst: int):
            yield from reach(src, float("inf"), dst)

    @udtf(returnType="nid: bigint, cost: double")
    class Near:
        def eval(self, src: int, max_cost: float):
            yield from reach(src, max_cost)

    spark.udtf.register(f"{name}_route", Route)
    spark.udtf.register(f"{name}_near", Near)
