"""Costs and accuracies: storage, partitions, solves, matches, fleets."""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from weftgraph.model import Graph
from weftgraph.operators import partition, paths, sssp
from weftgraph.plans.common import cut, running_sum

INT_BYTES = 4
#: Most ascending runs of ids that a task reports, and the widest gaps of a batch that end one.
RUNS, GAPS = 100, 3


def storage_model(n: int, e: int, int_bytes: int = INT_BYTES) -> dict[str, int]:
    """Bytes of each layout: six numbers an edge, compressed rows, a dense matrix of bits in bytes."""
    return {"double_link": 6 * e * int_bytes, "csr": (2 * e + n + 1) * int_bytes, "dense": n * n}


def storage_bytes(graph: Graph, int_bytes: int = INT_BYTES, edges: DataFrame | None = None) -> DataFrame:
    """(layout, nodes, edges, bytes); ``edges(e)``, one row, is their number where it is known without making them."""
    n = graph.nodes.select("nid").distinct().agg(F.count("*").alias("n"))
    e = graph.edges.agg(F.count("*").alias("e")) if edges is None else edges.select("e")
    sizes = F.array(F.struct(F.lit("csr").alias("layout"), ((2 * F.col("e") + F.col("n") + 1) * int_bytes).alias("bytes")), F.struct(F.lit("dense").alias("layout"), (F.col("n") * F.col("n")).alias("bytes")), F.struct(F.lit("double_link").alias("layout"), (6 * F.col("e") * int_bytes).alias("bytes")))
    return n.join(e).select(F.col("n").alias("nodes"), F.col("e").alias("edges"), F.explode(sizes).alias("s")).select("s.layout", "nodes", "edges", "s.bytes")  # one row each


def degree_stats(graph: Graph) -> DataFrame:
    """(nodes, max_degree, sum_degree, sum_square): variance follows from these; storage does not depend on it."""
    d = graph.edges.select(F.explode(F.array("src", "dst")).alias("nid")).groupBy("nid").count()
    return d.agg(F.count("*").alias("nodes"), F.max("count").alias("max_degree"), F.sum("count").alias("sum_degree"), F.sum(F.col("count") * F.col("count")).alias("sum_square"))


def csr_shift_cost(edges: DataFrame, change: DataFrame) -> DataFrame:
    """(eid, moved): slots behind the place of each changed edge in compressed rows, that a change would move.

    ``change`` has (eid, src); moved counts arcs of nodes after ``src``.
    """
    from weftgraph.operators.topology import to_csr

    csr = cut(to_csr(edges).where("chunk = 0").select("nid", "offset", "degree"))
    total = csr.agg(F.coalesce(F.sum("degree"), F.lit(0)).alias("total"))
    at = change.join(csr.select(F.col("nid").alias("src"), "offset", "degree"), "src")
    return at.join(F.broadcast(total)).select("eid", (F.col("total") - F.col("offset") - F.col("degree")).alias("moved"))


def csr_shifts(degrees: DataFrame) -> DataFrame:
    """(nid, moved) from degrees(nid, degree): arcs of nodes after each one."""
    placed = running_sum(degrees.select("nid", "degree"), "nid", "degree", "offset")
    total = placed.agg(F.coalesce(F.sum("degree"), F.lit(0)).alias("total"))
    return placed.join(F.broadcast(total)).select("nid", (F.col("total") - F.col("offset") - F.col("degree")).alias("moved"))


def edge_sets(edges: DataFrame, first: Column, second: Column) -> DataFrame:
    """(kind, n): sizes of intersection, difference and union of two sets of edges, by conditions on edges that each occur once."""
    a, b = F.coalesce(first, F.lit(False)), F.coalesce(second, F.lit(False))
    sizes = edges.agg(F.count_if(a & b).alias("both"), F.count_if(a & ~b).alias("first"), F.count_if(a | b).alias("either"))
    return sizes.select(F.explode(F.array(*[F.struct(F.lit(k).alias("kind"), F.col(c).alias("n")) for k, c in (("both", "both"), ("first only", "first"), ("either", "either"))])).alias("s")).select("s.kind", "s.n")


def partition_score(graph: Graph, scheme: str | None = None) -> DataFrame:
    """(scheme, n_parts, dup_nodes, dup_copies, max_edges, min_edges) over the parts that have edges."""
    seen = partition.copies(graph.edges).groupBy("nid").agg((F.count("*") - 1).alias("more")).agg(F.count(F.when(F.col("more") > 0, 1)).alias("dup_nodes"), F.coalesce(F.sum("more"), F.lit(0)).alias("dup_copies"))
    parts = graph.edges.groupBy("part").count().agg(F.count("*").alias("n_parts"), F.max("count").alias("max_edges"), F.min("count").alias("min_edges"))
    return parts.join(seen).select(F.lit(scheme or graph.options.scheme).alias("scheme"), "n_parts", "dup_nodes", "dup_copies", "max_edges", "min_edges")  # one row each


def balance(graph: Graph) -> DataFrame:
    """(part, edges, share): edges of each part over the mean."""
    c = graph.edges.groupBy("part").agg(F.count("*").alias("edges"))
    return c.join(c.agg(F.avg("edges").alias("m"))).select("part", "edges", (F.col("edges") / F.col("m")).alias("share"))


def interfaces(graph: Graph) -> DataFrame:
    """(p1, p2, shared): nodes that two parts have in common."""
    b = partition.boundary(graph.edges)
    pairs = b.select("nid", F.col("part").alias("p1")).join(b.select("nid", F.col("part").alias("p2")), "nid").where("p1 < p2")
    return pairs.groupBy("p1", "p2").agg(F.count("*").alias("shared"))


def _joined(runs: list[tuple[int, int, int]], most: int) -> list[tuple[int, int, int]]:
    """At most ``most`` of ascending runs (low, high, distinct), which are joined over the smallest gaps; more where ids descend between them."""
    gaps = [b[0] - a[1] for a, b in zip(runs, runs[1:], strict=False)]
    ascents = sorted((k for k, gap in enumerate(gaps) if gap >= 0), key=gaps.__getitem__)
    over = set(ascents[: max(0, len(runs) - most)])
    out = runs[:1]
    for k, (low, high, distinct) in enumerate(runs[1:]):
        if k in over:
            first, last, before = out[-1]
            out[-1] = first, high, before + distinct - (low == last)
        else:
            out.append((low, high, distinct))
    return out


def _id_runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A row for each ascending run of a task's ids in batches (eid, part): counts and ends; a task with too many runs says so in one row.

    Runs end where ids descend and at the widest gaps, since what a task reads
    next may begin far behind, with other tasks' ids in between.
    """
    n = missing = 0
    runs: list[tuple[int, int, int]] = []
    few = True
    for batch in batches:
        n, missing = n + batch.num_rows, missing + batch.column(1).null_count
        ids = batch.column(0).drop_null().to_numpy()
        if not few or not len(ids):
            continue
        ahead = ids[1:] - ids[:-1]
        ends = np.flatnonzero(ids[1:] < ids[:-1])
        few = len(ends) <= RUNS
        if few:
            wide = np.argpartition(ahead, -GAPS)[-GAPS:] if len(ahead) > GAPS else np.arange(len(ahead))
            begins = np.concatenate(([0], np.union1d(ends, wide) + 1)).astype(np.int64)
            other = np.concatenate(([True], ahead != 0))
            other[begins] = True
            found = zip(ids[begins].tolist(), ids[np.append(begins[1:], len(ids)) - 1].tolist(), np.add.reduceat(other, begins, dtype=np.int64).tolist(), strict=True)
            for low, high, distinct in found:
                if runs and runs[-1][1] == low:  # equal ids are counted once
                    runs[-1] = runs[-1][0], high, runs[-1][2] + distinct - 1
                else:
                    runs.append((low, high, distinct))
            if len(runs) > 4 * RUNS:
                runs = _joined(runs, RUNS)
                few = len(runs) <= 2 * RUNS
    runs = _joined(runs, RUNS)
    few = few and len(runs) <= RUNS
    if n:
        rows = [(n, 0, missing, few, None, None), *((0, distinct, 0, True, low, high) for low, high, distinct in (runs if few else []))]
        kinds = [pa.int64(), pa.int64(), pa.int64(), pa.bool_(), pa.int64(), pa.int64()]
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names=["n", "distinct", "missing", "few", "low", "high"])


def check_disjoint(graph: Graph) -> DataFrame:
    """(edges, distinct_edges, without_part): equal counts and no edge without a part.

    A task may read several stretches of ascending ids, in any order. Where no
    two stretches meet, equal ids are neighbours and are counted in place;
    otherwise all ids are shuffled.
    """
    ids = graph.edges.select(F.col("eid").cast("long"), "part")
    runs = ids.mapInArrow(_id_runs, "n long, distinct long, missing long, few boolean, low long, high long").collect()  # at most RUNS + 1 rows a task
    ends = sorted((r["low"], r["high"]) for r in runs if r["low"] is not None)
    if all(r["few"] for r in runs) and all(a[1] < b[0] for a, b in zip(ends, ends[1:], strict=False)):
        total = [sum(r[c] for r in runs) for c in ("n", "distinct", "missing")]
        return graph.spark.createDataFrame([tuple(total)], "edges long, distinct_edges long, without_part long")  # one row
    return graph.edges.agg(F.count("*").alias("edges"), F.countDistinct("eid").alias("distinct_edges"), F.count(F.when(F.col("part").isNull(), 1)).alias("without_part"))


def compare_partitionings(graphs: dict[str, Graph], source: dict[str, int]) -> list[dict]:
    """For each scheme: score, rounds, local solves, messages and seconds of a solve to all nodes, then seconds of all their paths.

    ``targets`` counts the paths, and ``path_cost`` sums the costs at their
    ends as the predecessors' edges add them up, which must equal ``sum_cost``.
    """
    out = []
    for name, g in graphs.items():
        stats = sssp.SolveStats()
        found = cut(sssp.costs(g, source[name], stats=stats))
        total = found.agg(F.sum("cost")).head()[0]
        began = time.time()
        summed, targets = paths.all_path_costs(g, found, source[name])
        stats.path_seconds = time.time() - began
        score = partition_score(g, name).head().asDict()
        out.append(score | {"supersteps": stats.supersteps, "local_solves": stats.local_solves, "messages": stats.messages, "seconds": round(stats.seconds, 2), "path_seconds": round(stats.path_seconds, 2), "sum_cost": total, "targets": targets, "path_cost": summed})
    return out


def speedup_by_parts(graph: Graph, source: int, boxes: list[tuple[int, int]]) -> list[dict]:
    """Rounds and seconds of one solve over several numbers of boxes."""
    out = []
    for nx, ny in boxes:
        g = partition.by_box(graph, nx, ny).materialised()
        stats = sssp.SolveStats()
        n = sssp.costs(g, source, stats=stats).count()
        out.append({"parts": nx * ny, "supersteps": stats.supersteps, "seconds": round(stats.seconds, 2), "reached": n})
    return out


def fleet_by_servers(graph: Graph, depots: DataFrame, trucks: DataFrame, demands: DataFrame, servers: tuple[int, ...] = (1, 4)) -> list[dict]:
    """Seconds and total cost of a fleet's plan when costs are solved by one task, and by several that hold replicas of the graph."""
    from weftgraph.operators import tours

    out = []
    for n in servers:
        began = time.time()
        cost = tours.fleet(graph, depots, trucks, demands, split="rest", tasks=n).agg(F.sum("leg_cost")).head()[0]
        out.append({"servers": n, "seconds": round(time.time() - began, 2), "cost": cost})
    return out


def walk_vs_csr(graph: Graph, source: int) -> dict[str, float]:
    """Seconds of one solve over compressed rows and over double links, in one process, with equal results.

    The link walk follows previous-edge indexes from each node's cached edge.
    The graph's size is checked.
    """
    import heapq

    from weftgraph.operators.kernels import settle

    block = sssp.replicate(graph).value
    lists = block.lists()
    at = int(block.place([source])[0])
    began = time.perf_counter()
    flat = [float("inf")] * len(block.ids)
    settle(lists, flat, [(0, at)])
    csr = time.perf_counter() - began
    rows = graph.edges.select("src", "dst", "weight").toPandas()
    a, b, w = block.place(rows["src"].to_numpy()).tolist(), block.place(rows["dst"].to_numpy()).tolist(), rows["weight"].tolist()
    head, prev1, prev2 = [-1] * len(block.ids), [-1] * len(a), [-1] * len(a)
    for e, (i, j) in enumerate(zip(a, b, strict=True)):
        prev1[e], head[i] = head[i], e
        prev2[e], head[j] = head[j], e
    began = time.perf_counter()
    dist, heap = [float("inf")] * len(block.ids), [(0, at)]
    dist[at] = 0
    while heap:
        d, i = heapq.heappop(heap)
        if d > dist[i]:
            continue
        e = head[i]
        while e >= 0:
            first = a[e] == i
            j, c = (b[e] if first else a[e]), d + w[e]
            if c < dist[j]:
                dist[j] = c
                heapq.heappush(heap, (c, j))
            e = prev1[e] if first else prev2[e]
    links = time.perf_counter() - began
    return {"csr": csr, "links": links, "equal": dist == flat}


def part_pivot(graph: Graph, parts: list[int]) -> DataFrame:
    """(src_part, p0, p1, ...): edges by the parts that the homes of their ends lie in, from boundary copies."""
    c = partition.copies(graph.edges)
    pairs = c.select("nid", F.col("part").alias("src_part")).join(c.select("nid", F.col("part").alias("other")), "nid")
    table = pairs.groupBy("src_part").pivot("other", parts).count().na.fill(0)
    return table.toDF("src_part", *[f"p{p}" for p in parts])


def duplication(tables: dict[str, tuple[DataFrame, list[str]]]) -> DataFrame:
    """(table, attribute_bytes, topology_bytes): what a full copy would repeat, against the topology columns alone."""
    rows = None
    for name, (df, topology) in tables.items():
        size = lambda cols: F.coalesce(F.sum(sum((F.coalesce(F.length(F.col(c).cast("string")), F.lit(0)) for c in cols), F.lit(0))), F.lit(0)).cast("long")
        one = df.agg(size([c for c in df.columns if c not in topology]).alias("attribute_bytes"), size(topology).alias("topology_bytes")).withColumn("table", F.lit(name))
        rows = one if rows is None else rows.unionByName(one)
    return rows.select("table", "attribute_bytes", "topology_bytes")


def path_chars(paths: DataFrame) -> DataFrame:
    """(paths, chars): number of paths and mean length of their text."""
    return paths.agg(F.count("*").alias("paths"), F.avg(F.length("wkt")).alias("chars"))


def match_score(matched: DataFrame, threshold: float = 1.0) -> DataFrame:
    """(trips, below, mean_dist, share): trips whose mean distance to the route is below the threshold."""
    trips = matched.groupBy("trip_id").agg(F.avg("dist").alias("mean_dist"))
    return trips.agg(F.count("*").alias("trips"), F.count(F.when(F.col("mean_dist") < threshold, 1)).alias("below"), F.avg("mean_dist").alias("mean_dist"), F.avg((F.col("mean_dist") < threshold).cast("double")).alias("share"))


def fleet(routes: DataFrame) -> DataFrame:
    """(trucks, stops, amount, cost) of routes(truck, stop_seq, cust, amount, leg_cost)."""
    return routes.agg(F.countDistinct("truck").alias("trucks"), F.count(F.when(F.col("cust").isNotNull(), 1)).alias("stops"), F.sum("amount").alias("amount"), F.sum("leg_cost").alias("cost"))
