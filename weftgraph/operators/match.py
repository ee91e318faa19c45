"""Map matching, origin-destination within limits, and batches of pairs."""

from __future__ import annotations

import heapq
import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from weftgraph.functions.geo import cell, parse_line, parse_point, point_segment, snap, touched_cells
from weftgraph.model import Graph, arcs
from weftgraph.operators import overlay
from weftgraph.operators.sssp import check_weights, pair_costs, replicate, reversed_edges
from weftgraph.plans.common import checked_broadcast, cut


# ------------------------------------------------------------ pairs of ends


def _tree(lists: tuple[list, list, list], start: int, stop: set[int], dist: list, before: list) -> list[int]:
    """Costs and predecessors (ties to the smaller place) until all of ``stop`` are settled; returns the places touched."""
    offsets, targets, weights = lists
    infinite = float("inf")
    dist[start], before[start] = 0, start
    heap, left, touched = [(0, start)], set(stop), [start]
    while heap and left:
        d, i = heapq.heappop(heap)
        if d > dist[i]:
            continue
        left.discard(i)
        for k in range(offsets[i], offsets[i + 1]):
            j, e = targets[k], d + weights[k]
            old = dist[j]
            if e < old:
                if old == infinite:
                    touched.append(j)
                dist[j], before[j] = e, i
                heapq.heappush(heap, (e, j))
            elif e == old and weights[k] > 0 and i < before[j]:
                before[j] = i
    return touched


def batch_pairs(graph: Graph, pairs: DataFrame, with_paths: bool = False, reverse: bool = False) -> DataFrame:
    """(pair_id, src, dst, cost[, wkt]) of pairs(pair_id, src, dst); a null cost where there is no way.

    Costs come from tables of the borders of parts, or, where these would be
    too large, from one search for each origin. With lines each origin is
    searched until its destinations are settled. ``reverse`` solves the inverse
    problem: from the second node to the first, against the edges' directions
    as seen from the first. Tasks share the pairs; a pair that comes often is
    solved once.
    """
    g = graph.with_edges(reversed_edges(graph.edges)) if reverse else graph
    solved = distinct_pairs(g, pairs, with_paths)
    kind = "double" if dict(graph.edges.dtypes)["weight"] in ("double", "float") else "long"
    return pairs.select("pair_id", "src", "dst").join(solved, ["src", "dst"], "left").withColumn("cost", F.col("cost").cast(kind)).select("pair_id", "src", "dst", "cost", *(["wkt"] if with_paths else []))


def distinct_pairs(graph: Graph, pairs: DataFrame, with_paths: bool = False) -> DataFrame:
    """(src, dst, cost[, wkt]) of each distinct pair of nodes in pairs(src, dst), costs as doubles."""
    once = pairs.select("src", "dst").where("src IS NOT NULL AND dst IS NOT NULL").distinct()
    by_origin = once.groupBy("src").agg(F.collect_list("dst").alias("dsts"))
    if with_paths:
        return _pair_lines(graph, by_origin)
    check_weights(graph.edges)
    found = overlay.tables(graph)
    return overlay.pair_table_costs(graph, once, found) if found else pair_costs(graph, by_origin)


def batch_points(graph: Graph, pairs: DataFrame, size: float, with_paths: bool = False, reverse: bool = False) -> DataFrame:
    """(pair_id, src, dst, cost[, wkt]) of pairs(pair_id, src_wkt, dst_wkt): points snap to their nearest nodes.

    ``size`` is a usual distance between nodes. Texts that are no point have a
    null node and cost.
    """
    # texts are read once, and each place is snapped once
    ends = cut(pairs.select("pair_id", parse_point(F.col("src_wkt")).alias("a"), parse_point(F.col("dst_wkt")).alias("b")))
    spots = cut(ends.select(F.explode(F.array("a", "b")).alias("p")).where("p IS NOT NULL").select("p.x", "p.y").distinct().select(F.struct("x", "y").alias("pid"), "x", "y"))
    at = cut(snap(spots, graph.nodes, size).select(F.col("pid.x").alias("x"), F.col("pid.y").alias("y"), "nid"))
    named = ends.select("pair_id", F.col("a.x").alias("ax"), F.col("a.y").alias("ay"), F.col("b.x").alias("bx"), F.col("b.y").alias("by")).join(at.toDF("ax", "ay", "src"), ["ax", "ay"], "left").join(at.toDF("bx", "by", "dst"), ["bx", "by"], "left")
    return batch_pairs(graph, cut(named.select("pair_id", "src", "dst")), with_paths, reverse)


def _pair_lines(graph: Graph, wanted: DataFrame) -> DataFrame:
    """(src, dst, cost, wkt) for rows (src, dsts)."""
    shared = replicate(graph)
    rows = graph.nodes.select("nid", "x", "y").toPandas()  # the graph's size is checked by replicate
    text = dict(zip(rows["nid"].tolist(), [f"{x} {y}" for x, y in zip(rows["x"].tolist(), rows["y"].tolist(), strict=True)], strict=True))
    points = graph.spark.sparkContext.broadcast(text)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        block = shared.value
        lists, at = block.lists(), [points.value.get(n, "") for n in block.ids.tolist()]
        dist, before = [float("inf")] * len(block.ids), [-1] * len(block.ids)
        for batch in batches:
            for src, dsts in zip(batch["src"], batch["dsts"], strict=True):
                dsts = np.asarray(dsts, np.int64)
                start, ends = int(block.place(np.array([src]))[0]), block.place(dsts).tolist()
                if start < 0:
                    yield pd.DataFrame({"src": src, "dst": dsts, "cost": [0.0 if d == src else None for d in dsts], "wkt": None})
                    continue
                touched = _tree(lists, start, {i for i in ends if i >= 0}, dist, before)
                wkt, cost = [], []
                for i in ends:
                    if i < 0 or before[i] < 0:
                        wkt.append(None)
                        cost.append(None)
                        continue
                    cost.append(dist[i])
                    way = [at[i]]
                    while i != start:
                        i = before[i]
                        way.append(at[i])
                    way.reverse()
                    wkt.append("LINESTRING(" + ", ".join(way) + ")")
                for i in touched:  # the lists serve the next origin
                    dist[i], before[i] = float("inf"), -1
                yield pd.DataFrame({"src": src, "dst": dsts, "cost": cost, "wkt": wkt})

    n = int(graph.spark.conf.get("spark.sql.shuffle.partitions"))
    return wanted.select("src", "dsts").repartition(4 * n, "src").mapInPandas(run, "src long, dst long, cost double, wkt string")


def line_costs(graph: Graph, lines: DataFrame) -> DataFrame:
    """(wkt, line_cost) of the distinct lines(wkt): the sum of the least weights along the nodes at a line's points.

    A point that is no node, or a step that is no arc, gives a null cost.
    """
    at = graph.nodes.groupBy("x", "y").agg(F.min("nid").alias("nid"))
    ways = arcs(graph.edges).groupBy("u", "v").agg(F.min("w").alias("w"))
    points = parse_line(F.col("wkt"))
    step = F.arrays_zip(F.slice(points, 1, F.size(points) - 1).alias("a"), F.slice(points, 2, F.size(points) - 1).alias("b"))
    # lines are told apart by two hashes, so that their texts are not repeated for each step
    named = lines.where("wkt IS NOT NULL").select("wkt", F.xxhash64("wkt").alias("h1"), F.xxhash64(F.lit(1), F.col("wkt")).alias("h2")).dropDuplicates(["h1", "h2"])
    each = named.select("h1", "h2", F.explode_outer(F.when(F.size(points) > 1, step)).alias("s")).select("h1", "h2", F.col("s.a.x").alias("x"), F.col("s.a.y").alias("y"), F.col("s.b.x").alias("x2"), F.col("s.b.y").alias("y2"))
    # equal steps of many lines are looked up once
    steps = each.groupBy("x", "y", "x2", "y2").agg(F.lit(1).alias("one")).join(at.withColumnRenamed("nid", "u"), ["x", "y"], "left").join(at.toDF("x2", "y2", "v"), ["x2", "y2"], "left").join(ways, ["u", "v"], "left").select("x", "y", "x2", "y2", "w")
    met = each.join(steps, ["x", "y", "x2", "y2"], "left")
    bad = F.max((F.col("x").isNotNull() & F.col("w").isNull()).cast("int")) > 0
    sums = met.groupBy("h1", "h2").agg(F.when(~bad, F.coalesce(F.sum("w"), F.lit(0))).alias("line_cost"))
    return named.join(sums, ["h1", "h2"]).select("wkt", "line_cost")


def od_within(graph: Graph, pairs: DataFrame, max_cost: int, depart: int = 0, arrive_by: str | None = None) -> DataFrame:
    """(pair_id, src, dst, cost, slack): pairs whose way costs at most ``max_cost``.

    With ``arrive_by``, a column of the pairs, a pair must also arrive in time
    when it leaves at ``depart``; slack is the time left, else the cost left.
    """
    kind = "double" if dict(graph.edges.dtypes)["weight"] in ("double", "float") else "long"
    met = pairs.join(distinct_pairs(graph, pairs).where(F.col("cost") <= max_cost).withColumn("cost", F.col("cost").cast(kind)), ["src", "dst"])
    slack = F.lit(max_cost) - F.col("cost") if arrive_by is None else F.col(arrive_by) - F.lit(depart) - F.col("cost")
    return met.withColumn("slack", slack).where("slack >= 0").select("pair_id", "src", "dst", "cost", "slack")


# ------------------------------------------------------------- map matching


def candidates(graph: Graph, gps: DataFrame, radius: float, keep: int = 4) -> DataFrame:
    """(trip_id, seq, eid, u, v, len, t, px, py, d): the nearest ``keep`` edges of each sample within the radius."""
    best = Window.partitionBy("trip_id", "seq").orderBy("d", "eid")
    return edges_near(graph, gps, radius).withColumn("_r", F.row_number().over(best)).where(F.col("_r") <= keep).drop("_r")


def edges_near(graph: Graph, gps: DataFrame, radius: float) -> DataFrame:
    """(trip_id, seq, eid, u, v, len, t, px, py, d): all edges within the radius of each sample.

    Edges are entered into the cells that they pass: for each column, the rows
    between the ends of the edge's stretch in it. A sample looks into the cells
    that a square of the radius around it touches. Cells are two radii wide. A
    pair that meets in several cells counts in that of the edge's nearest point.
    """
    at = graph.nodes.select("nid", "x", "y")
    segs = graph.edges.select("eid", "src", "dst").join(at.toDF("src", "ax", "ay"), "src").join(at.toDF("dst", "bx", "by"), "dst")
    wide = 2 * radius
    across = F.sequence(F.least(cell(F.col("ax"), wide), cell(F.col("bx"), wide)), F.greatest(cell(F.col("ax"), wide), cell(F.col("bx"), wide)))
    column = segs.withColumn("cx", F.explode(across))
    # the stretch of the edge inside the column, as a range of its parameter
    dx, dy = F.col("bx") - F.col("ax"), F.col("by") - F.col("ay")
    at_x = lambda edge: F.least(F.greatest(((F.col("cx") + edge) * wide - F.col("ax")) / F.when(dx != 0, dx), F.lit(0.0)), F.lit(1.0))
    y1, y2 = (F.col("ay") + dy * F.when(dx != 0, at_x(edge)).otherwise(float(end)) for edge, end in ((-0.5, 0), (0.5, 1)))
    slack = 1e-9 * wide
    entered = column.withColumn("cy", F.explode(F.sequence(cell(F.least(y1, y2) - slack, wide), cell(F.greatest(y1, y2) + slack, wide))))
    # a graph whose size has been checked goes to the samples; otherwise both meet by cells
    near = touched_cells(gps.select("trip_id", "seq", "x", "y"), "x", "y", wide, radius).join(checked_broadcast(cut(entered)), ["cx", "cy"])
    foot = point_segment(F.col("x"), F.col("y"), F.col("ax"), F.col("ay"), F.col("bx"), F.col("by"))
    length = F.sqrt((F.col("ax") - F.col("bx")) * (F.col("ax") - F.col("bx")) + (F.col("ay") - F.col("by")) * (F.col("ay") - F.col("by")))
    scored = near.withColumn("f", foot).where((F.col("f.d") <= radius) & (cell(F.col("f.x"), wide) == F.col("cx")) & (cell(F.col("f.y"), wide) == F.col("cy")))
    return scored.select("trip_id", "seq", "eid", F.col("src").alias("u"), F.col("dst").alias("v"), length.alias("len"), F.col("f.t").alias("t"), F.col("f.x").alias("px"), F.col("f.y").alias("py"), F.col("f.d").alias("d"))


class _Network:
    """Distances between nodes within a limit; searches are remembered by node, for all trips of a worker."""

    MOST = 20_000

    def __init__(self, block):
        self.offsets, self.targets, self.lengths = block.lists()
        self.memory: dict[float, dict[int, dict[int, float]]] = {}
        self.held = 0

    @staticmethod
    def of(block) -> _Network:
        if not hasattr(block, "network"):
            block.network = _Network(block)
        return block.network

    def within(self, limit: float) -> dict[int, dict[int, float]]:
        """Memory of the searches up to a limit, emptied when all of them are too many."""
        if self.held >= self.MOST:
            self.memory, self.held = {}, 0
        return self.memory.setdefault(limit, {})

    def around(self, node: int, limit: float, memory: dict[int, dict[int, float]]) -> dict[int, float]:
        got, heap = {node: 0.0}, [(0.0, node)]
        while heap:
            d, i = heapq.heappop(heap)
            if d > got[i]:
                continue
            for k in range(self.offsets[i], self.offsets[i + 1]):
                e, j = d + self.lengths[k], self.targets[k]
                if e <= limit and e < got.get(j, math.inf):
                    got[j] = e
                    heapq.heappush(heap, (e, j))
        memory[node] = got
        self.held += 1
        return got


def best_chain(network: _Network, x: list, y: list, first: list[int], eid: list, u: list, v: list, length: list, t: list, d: list, sigma: float, beta: float) -> list[int]:
    """The row of the chosen candidate of each sample, -1 without any.

    Candidates of sample i are the rows first[i] to first[i + 1]. Emissions fall
    with the distance, steps with the difference between the way on the network
    and the straight line. A chain breaks where no step is possible.
    """
    n = len(x)
    choice = [-1] * n
    inf = math.inf
    near, far = [a * b for a, b in zip(t, length, strict=True)], [(1 - a) * b for a, b in zip(t, length, strict=True)]
    emit = [-(a * a) / (2 * sigma * sigma) for a in d]
    score: list[float] = []
    back: list[list[int]] = []
    begin = 0

    def finish(end: int) -> None:
        if not score:
            return
        k = max(range(len(score)), key=score.__getitem__)
        for i in range(end, begin - 1, -1):
            choice[i] = first[i] + k
            if i > begin:
                k = back[i - begin][k]

    for i in range(n):
        lo, hi = first[i], first[i + 1]
        if lo == hi:
            finish(i - 1)
            score, back, begin = [], [], i + 1
            continue
        now = emit[lo:hi]
        if not score:
            score, back, begin = now, [[]], i
            continue
        straight = math.hypot(x[i] - x[i - 1], y[i] - y[i - 1])
        limit = 4
        while limit < 2 * straight + 4:
            limit *= 2
        memory = network.within(limit)
        before = first[i - 1]
        pulls = []
        for a in range(before, lo):
            ru, rv = memory.get(u[a]), memory.get(v[a])
            pulls.append((eid[a], near[a], ru if ru is not None else network.around(u[a], limit, memory), far[a], rv if rv is not None else network.around(v[a], limit, memory), a))
        best, origin, possible = [], [], False
        for b in range(lo, hi):
            ub, vb, nb, fb, eb = u[b], v[b], near[b], far[b], eid[b]
            top, at = -inf, 0
            for k, (ea, na, ru, fa, rv, a) in enumerate(pulls):
                if ea == eb:
                    way = abs(t[a] - t[b]) * length[b]
                else:
                    way = min(na + ru.get(ub, inf) + nb, na + ru.get(vb, inf) + fb, fa + rv.get(ub, inf) + nb, fa + rv.get(vb, inf) + fb)
                total = score[k] - abs(way - straight) / beta
                if total > top:
                    top, at = total, k
            possible |= top > -inf
            best.append(top + emit[b])
            origin.append(at)
        if not possible:
            finish(i - 1)
            score, back, begin = now, [[]], i
            continue
        score = best
        back.append(origin)
    finish(n - 1)
    return choice


def denser(gps: DataFrame, per_step: int) -> DataFrame:
    """``per_step`` samples for each one: positions between a sample and the next one of its trip, numbered anew.

    The last sample of a trip is repeated in its place.
    """
    ahead = Window.partitionBy("trip_id").orderBy("seq")
    nxt = gps.select("trip_id", "seq", "x", "y", F.coalesce(F.lead("x").over(ahead), F.col("x")).alias("_x"), F.coalesce(F.lead("y").over(ahead), F.col("y")).alias("_y"))
    i = F.col("_i").cast("double") / per_step
    return nxt.withColumn("_i", F.explode(F.sequence(F.lit(0), F.lit(per_step - 1)))).select("trip_id", (F.col("seq") * per_step + F.col("_i")).alias("seq"), (F.col("x") + (F.col("_x") - F.col("x")) * i).alias("x"), (F.col("y") + (F.col("_y") - F.col("y")) * i).alias("y"))


def match_rate(graph: Graph, gps: DataFrame, per_step: int, **options) -> DataFrame:
    """The match of the trips with ``per_step`` samples for each one given; positions in between are made where their trip lies, and not shuffled."""
    return _matched(graph, denser(_dealt(gps), per_step), **options)


def thinned(gps: DataFrame, keep_every: int) -> DataFrame:
    """Every ``keep_every``-th sample of each trip, for trips sampled more often than needed."""
    place = Window.partitionBy("trip_id").orderBy("seq")
    return gps.withColumn("_n", F.row_number().over(place) - 1).where(F.col("_n") % keep_every == 0).drop("_n")


def _dealt(gps: DataFrame) -> DataFrame:
    """Whole trips over many tasks, however few the bytes: each sample stands for much work."""
    return gps.select("trip_id", "seq", "x", "y").repartition(int(gps.sparkSession.conf.get("spark.sql.shuffle.partitions")), "trip_id")


def _cell(v: np.ndarray, size: float) -> np.ndarray:
    """``geo.cell`` of an array; what has no cell lies beyond all others."""
    with np.errstate(invalid="ignore"):
        at = np.floor(v / size + 0.5)
    return np.where(np.abs(at) < 2.0**53, at, 2.0**53).astype(np.int64)


def _spread(counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(row, place) of each one of so many places of each row."""
    row = np.repeat(np.arange(len(counts)), counts)
    return row, np.arange(len(row)) - np.repeat(np.cumsum(counts) - counts, counts)


@dataclass
class Roads:
    """Edges between places of a block, with the places' coordinates: what a worker needs to look up edges itself."""

    eid: np.ndarray
    u: np.ndarray
    v: np.ndarray
    x: np.ndarray
    y: np.ndarray

    def cells(self, wide: float) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(columns and rows of cells in order, where their edges begin, edges) as ``edges_near`` enters them; made when they are first asked for."""
        if not hasattr(self, "_cells"):
            self._cells = {}
        if wide not in self._cells:
            ax, ay, bx, by = self.x[self.u], self.y[self.u], self.x[self.v], self.y[self.v]
            low, high = _cell(np.minimum(ax, bx), wide), _cell(np.maximum(ax, bx), wide)
            e, k = _spread(high - low + 1)
            cx = low[e] + k
            dx, dy, x0, y0 = (bx - ax)[e], (by - ay)[e], ax[e], ay[e]
            upright = dx == 0
            at_x = lambda edge: np.clip(((cx + edge) * wide - x0) / np.where(upright, 1.0, dx), 0.0, 1.0)
            y1, y2 = (y0 + dy * np.where(upright, float(end), at_x(edge)) for edge, end in ((-0.5, 0), (0.5, 1)))
            slack = 1e-9 * wide
            low, high = _cell(np.minimum(y1, y2) - slack, wide), _cell(np.maximum(y1, y2) + slack, wide)
            row, k = _spread(high - low + 1)
            e, cx, cy = e[row], cx[row], low[row] + k
            order = np.lexsort((cy, cx))
            e, cx, cy = e[order].astype(np.int32), cx[order], cy[order]
            begins = np.flatnonzero(np.concatenate(([True], (cx[1:] != cx[:-1]) | (cy[1:] != cy[:-1])))) if len(e) else np.empty(0, np.int64)
            lowest, rows = (int(cy.min()), int(cy.max() - cy.min()) + 1) if len(e) else (0, 1)
            keys = cx[begins] * rows + (cy[begins] - lowest)
            self._cells[wide] = keys, np.append(begins, len(e)), e, np.array([lowest, rows, *((cx[0], cx[-1]) if len(e) else (1, 0))])
        return self._cells[wide]

    def near(self, x: np.ndarray, y: np.ndarray, radius: float) -> tuple[np.ndarray, ...]:
        """(sample, edge, t, px, py, d) of all edges within the radius of each sample, as ``edges_near`` finds them."""
        wide = 2 * radius
        keys, begins, edges, (lowest, rows, first, last) = self.cells(wide)
        x_low, x_high, y_low, y_high = _cell(x - radius, wide), _cell(x + radius, wide), _cell(y - radius, wide), _cell(y + radius, wide)
        # only cells that hold edges are looked into
        x_low, x_high = np.maximum(x_low, first), np.minimum(x_high, last)
        y_low, y_high = np.maximum(y_low, lowest), np.minimum(y_high, lowest + rows - 1)
        sample, k = _spread(np.maximum(x_high - x_low + 1, 0))
        cx = x_low[sample] + k
        row, k = _spread(np.maximum(y_high - y_low + 1, 0)[sample])
        sample, cx, cy = sample[row], cx[row], y_low[sample[row]] + k
        wanted = cx * rows + (cy - lowest)
        at = np.minimum(np.searchsorted(keys, wanted), max(len(keys) - 1, 0))
        known = keys[at] == wanted if len(keys) else np.zeros(len(wanted), bool)
        sample, cx, cy, at = sample[known], cx[known], cy[known], at[known]
        row, k = _spread(begins[at + 1] - begins[at])
        e = edges[begins[at[row]] + k]
        sample, cx, cy = sample[row], cx[row], cy[row]
        ax, ay, bx, by = self.x[self.u[e]], self.y[self.u[e]], self.x[self.v[e]], self.y[self.v[e]]
        dx, dy, sx, sy = bx - ax, by - ay, x[sample], y[sample]
        square = dx * dx + dy * dy
        t = np.where(square > 0, np.maximum(0.0, np.minimum(1.0, ((sx - ax) * dx + (sy - ay) * dy) / np.where(square > 0, square, 1.0))), 0.0)
        px, py = ax + t * dx, ay + t * dy
        d = np.sqrt((sx - px) * (sx - px) + (sy - py) * (sy - py))
        keep = (d <= radius) & (_cell(px, wide) == cx) & (_cell(py, wide) == cy)
        return sample[keep], e[keep], t[keep], px[keep], py[keep], d[keep]


def _pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """A row of packed columns for each batch (eid, u, v, ax, ay, bx, by)."""
    for batch in batches:
        if batch.num_rows:
            yield pa.RecordBatch.from_arrays([pa.array([c.to_numpy(zero_copy_only=False).tobytes()], pa.binary()) for c in batch.columns], names=batch.schema.names)


def roads(graph: Graph) -> tuple:
    """The graph for matching, as two broadcasts: compressed rows weighed by lengths, and edges with coordinates. Its size is checked first."""
    at = graph.nodes.select("nid", "x", "y")
    ends = graph.edges.join(at.toDF("src", "ax", "ay"), "src").join(at.toDF("dst", "bx", "by"), "dst").withColumn("weight", F.sqrt((F.col("ax") - F.col("bx")) * (F.col("ax") - F.col("bx")) + (F.col("ay") - F.col("by")) * (F.col("ay") - F.col("by"))))
    shared = replicate(graph.with_edges(ends.select(*graph.edges.columns).withColumn("direction", F.lit(0))))
    block = shared.value
    x, y = np.zeros(len(block.ids)), np.zeros(len(block.ids))
    pieces: list[tuple] = [(np.empty(0, np.int64), np.empty(0, np.int32), np.empty(0, np.int32))]
    whole = ends.where("weight IS NOT NULL AND eid IS NOT NULL").select(*[F.col(c).cast("long") for c in ("eid", "src", "dst")], *[F.col(c).cast("double") for c in ("ax", "ay", "bx", "by")])
    for r in whole.mapInArrow(_pack, ", ".join(f"{c} binary" for c in whole.columns)).toLocalIterator():
        eid, u, v = (np.frombuffer(r[c], np.int64) for c in ("eid", "src", "dst"))
        u, v = block.place(u).astype(np.int32), block.place(v).astype(np.int32)
        x[u], y[u], x[v], y[v] = (np.frombuffer(r[c], np.float64) for c in ("ax", "ay", "bx", "by"))
        pieces.append((eid, u, v))
    return shared, graph.spark.sparkContext.broadcast(Roads(*(np.concatenate(c) for c in zip(*pieces, strict=True)), x, y))


def map_match(graph: Graph, gps: DataFrame, **options) -> DataFrame:
    """(trip_id, seq, eid, x, y, dist): samples on the most likely route of their trip.

    A hidden Markov chain of candidate edges: emissions by distance, steps by
    how far the way on the network differs from the straight line. Samples
    without an edge in the radius are looked up again with twice the radius up
    to ``max_radius``; what then has none stays unmatched (null), and the chain
    starts anew behind it. Ways are passed in both directions. Options are
    those of ``_matched``.
    """
    return _matched(graph, _dealt(gps), **options)


def _matched(graph: Graph, gps: DataFrame, radius: float = 0.6, max_radius: float = 2.4, sigma: float = 0.2, beta: float = 0.5, keep: int = 4, shared: tuple | None = None) -> DataFrame:
    """``map_match`` of samples dealt by trip. Candidates are looked up in place, so only samples are shuffled and nothing is stored; ``shared`` are the ``roads`` of the graph, made once for many matches."""
    rows, edges = shared or roads(graph)

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("seq", kind="stable").drop_duplicates("seq")
        x, y = pdf["x"].to_numpy(np.float64), pdf["y"].to_numpy(np.float64)
        block, lines = rows.value, edges.value
        rest, found, r = np.flatnonzero(np.isfinite(x) & np.isfinite(y)), [], radius
        while len(rest):
            got = lines.near(x[rest], y[rest], r)
            found.append((rest[got[0]], *got[1:]))
            if r >= max_radius:
                break
            rest = np.delete(rest, np.unique(got[0]))
            r = min(2 * r, max_radius)
        none = np.empty(0, np.int64)
        sample, e, t, px, py, d = (np.concatenate(c) for c in zip(*found, strict=True)) if found else (none, none, *[np.empty(0)] * 4)
        eid = lines.eid[e]
        order = np.lexsort((eid, d, sample))
        sample = sample[order]
        begins = np.searchsorted(sample, np.arange(len(x)))
        best = np.arange(len(sample)) - begins[sample] < keep  # the nearest edges of each sample
        order, sample = order[best], sample[best]
        first = np.searchsorted(sample, np.arange(len(x) + 1))
        e, eid, t, px, py, d = (c[order] for c in (e, eid, t, px, py, d))
        u, v = lines.u[e], lines.v[e]
        ax, ay, bx, by = lines.x[u], lines.y[u], lines.x[v], lines.y[v]
        length = np.sqrt((ax - bx) * (ax - bx) + (ay - by) * (ay - by))
        picks = np.array(best_chain(_Network.of(block), x.tolist(), y.tolist(), first.tolist(), eid.tolist(), u.tolist(), v.tolist(), length.tolist(), t.tolist(), d.tolist(), sigma, beta), np.int64)
        none = picks < 0
        take = lambda c: np.where(none, np.nan, c[np.maximum(picks, 0)] if len(c) else np.nan)
        on = pd.array(np.where(none, 0, eid[np.maximum(picks, 0)] if len(eid) else 0).astype(np.int64), dtype="Int64")
        on[none] = pd.NA
        return pd.DataFrame({"trip_id": pdf["trip_id"].iloc[0], "seq": pdf["seq"].to_numpy(), "eid": on, "x": take(px), "y": take(py), "dist": take(d)})

    out = gps.groupBy("trip_id").applyInPandas(one, "trip_id long, seq long, eid long, x double, y double, dist double")
    return out.select("trip_id", "seq", "eid", *[F.when(~F.isnan(c), F.col(c)).alias(c) for c in ("x", "y", "dist")])
