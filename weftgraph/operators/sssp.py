"""Shortest paths from one or many sources, by several engines with one answer.

``parts``   each part settles its front with a priority queue, then repeated
            nodes exchange the least cost; rounds go on until nothing improves.
            A part is one packed row, and so are its labels; a round reads the
            rows of busy parts only, and moves costs of repeated nodes only.
``flat``    edge-at-a-time relaxation over the whole graph, no parts.
``delta``   the same, bucket by bucket of cost.
``single``  one task holds the whole graph.
``replicated``  every task holds the whole graph, sources are split.

Weights are whole numbers or doubles and must not be negative. Nodes that are
not reached have no row. Only counts reach the driver in the loops.

Several runs, one for each of many sources, may share the rounds of ``parts``,
which is how many sources are solved on graphs that no worker could hold.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from weftgraph.model import Graph, arcs
from weftgraph.operators.kernels import Block, pack_block, settle, settle_each, unpack_block
from weftgraph.operators.partition import boundary
from weftgraph.plans.common import checked_broadcast, cut, ship, written

#: Largest graph that one task or each worker may hold.
REPLICATED_ARCS = 5_000_000
#: Largest part, in edges, that one task may hold.
PART_ARCS = 10_000_000
#: Costs that a worker holds while it solves many sources together, and costs in a batch that leaves it.
SETTLED_AT_ONCE, COSTS_AT_ONCE = 26_000_000, 100_000


@dataclass
class SolveStats:
    """What a solve did: rounds, rows exchanged, local solves, time, and a row per round."""

    supersteps: int = 0
    messages: int = 0
    local_solves: int = 0
    seconds: float = 0.0
    path_seconds: float = 0.0
    trace: list[dict] = field(default_factory=list)
    record_fields: bool = False
    fields: list[dict] = field(default_factory=list)


def _seeds(graph: Graph, sources) -> DataFrame:
    """(nid, cost) from an id, a list of ids, or pairs of id and start cost."""
    if isinstance(sources, DataFrame):
        return sources.select(F.col("nid").cast("long"), F.col("cost"))
    if not isinstance(sources, (list, tuple)):
        sources = [sources]
    rows = [s if isinstance(s, tuple) else (s, 0) for s in sources]
    if not rows:
        raise ValueError("no source")
    values = F.array(*[F.struct(F.lit(n).cast("long").alias("nid"), F.lit(c).alias("cost")) for n, c in rows])
    return graph.spark.range(1).select(F.explode(values).alias("s")).select("s.nid", "s.cost")


def check_weights(edges: DataFrame) -> None:
    low = edges.agg(F.min("weight")).head()[0]
    if low is not None and low < 0:
        raise ValueError("weights must not be negative")


def costs(graph: Graph, sources=0, engine: str = "parts", targets: DataFrame | None = None, stats: SolveStats | None = None, max_supersteps: int = 10_000, limit: float | None = None, delta: int = 100, keep_unreached: bool = False) -> DataFrame:
    """(nid, cost) of all nodes reached, or of ``targets(nid)`` only.

    A source that the graph does not have is an error, if none of the sources
    is in it. ``limit`` leaves out costs above it. ``keep_unreached`` adds the
    other nodes (or targets) with a null cost.
    """
    stats = stats if stats is not None else SolveStats()
    began = time.time()
    kind = "double" if dict(graph.edges.dtypes)["weight"] in ("double", "float") else "bigint"
    if engine != "parts":  # that one looks when it packs the parts
        check_weights(graph.edges)
    seeds = cut(_seeds(graph, sources).withColumn("cost", F.col("cost").cast(kind)).join(graph.nodes.select("nid"), "nid", "left_semi"))
    if not seeds.limit(1).count():
        raise ValueError("the graph has none of the sources")
    if engine == "parts":
        found = _by_parts(graph, seeds, kind, stats, max_supersteps, limit)
    elif engine in ("flat", "delta"):
        found = _flat(graph, seeds, kind, stats, max_supersteps, limit, delta if engine == "delta" else None)
    elif engine == "single":
        found = _single(graph, seeds, kind, limit)
    else:
        raise ValueError(f"no engine {engine}")
    stats.seconds = time.time() - began
    if targets is not None:
        found = found.join(targets.select("nid").distinct(), "nid", "left_semi")
    if keep_unreached:
        wanted = (targets if targets is not None else graph.nodes).select("nid").distinct()
        found = wanted.join(found, "nid", "left")
    return found


def route_cost(graph: Graph, start: int, end: int, engine: str = "flat") -> DataFrame:
    """(nid, cost) of one destination; relaxation beyond its best cost stops."""
    if engine != "flat":
        return costs(graph, start, engine).where(F.col("nid") == end)
    kind = dict(graph.edges.dtypes)["weight"]
    seeds = cut(_seeds(graph, start).withColumn("cost", F.col("cost").cast("double" if kind == "double" else "bigint")))
    return _flat(graph, seeds, kind, SolveStats(), 10_000, None, None, end).where(F.col("nid") == end)


def _number(kind: str):
    return np.float64 if kind == "double" else np.int64


def _pack(kind: str):
    """cogroup of a part's arcs and of its repeated nodes into one row."""

    def run(rows: pd.DataFrame, shared: pd.DataFrame) -> pd.DataFrame:
        if not len(rows):
            return pd.DataFrame({"part": pd.Series(dtype="int32"), "block": pd.Series(dtype="object")})
        b = Block.of(rows["u"].to_numpy(), rows["v"].to_numpy(), rows["w"].to_numpy(_number(kind)))
        border = np.isin(b.ids, shared["nid"].to_numpy())
        other = np.isin(b.ids, shared["nid"].to_numpy()[~shared["mine"].to_numpy(bool)]) if len(shared) else np.zeros(len(b.ids), bool)
        return pd.DataFrame({"part": [np.int32(rows["part"].iloc[0])], "block": [pack_block(b, border, ~other)]})

    return run


def _solve_rows(kind: str, limit: float | None):
    """Rows (run, part, block, nids, costs, dist): the labels of the part after its front, and what changed at repeated nodes."""
    number = _number(kind)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, block, border, lists = None, None, None, None
        for batch in batches:
            for i in range(batch.num_rows):
                name, part = batch.column(0)[i].as_py(), batch.column(1)[i].as_py()
                if part != held:  # runs that share a part read it once
                    block, border, _ = unpack_block(batch.column(2)[i].as_buffer(), number)
                    held, lists = part, block.lists()
                nids, costs, old = np.array(batch.column(3)[i].as_py(), np.int64), batch.column(4)[i].as_py(), batch.column(5)[i].as_py()
                dist = [float("inf")] * len(block.ids)
                if old is not None:
                    known = np.frombuffer(old, np.float64)
                    dist = [int(x) if number is np.int64 and x != float("inf") else x for x in known.tolist()]
                seeds = [(c, int(j)) for j, c in zip(block.place(nids), costs, strict=True) if j >= 0]
                changed = settle(lists, dist, seeds, limit=float("inf") if limit is None else limit)
                out = [j for j in changed if border[j]]
                yield pa.RecordBatch.from_arrays(
                    [pa.array([name], pa.int64()), pa.array([part], pa.int32()), pa.array([np.array(dist, np.float64).tobytes()], pa.binary()), pa.array([block.ids[out]], pa.list_(pa.int64())), pa.array([[dist[j] for j in out]], pa.list_(pa.float64() if number is np.float64 else pa.int64())), pa.array([len(changed)], pa.int64())],
                    names=["run", "part", "dist", "nids", "costs", "changed"],
                )

    return run


def _unpack_rows(kind: str):
    """Rows (run, block, dist) into (run, nid, cost); a repeated node comes from the smallest of its parts only."""
    number = _number(kind)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                block, _, mine = unpack_block(batch.column(1)[i].as_buffer(), number)
                dist = np.frombuffer(batch.column(2)[i].as_py(), np.float64)
                at = np.flatnonzero(mine & np.isfinite(dist))
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), batch.column(0)[i].as_py()), pa.int64()), pa.array(block.ids[at], pa.int64()), pa.array(dist[at].astype(number), pa.float64() if number is np.float64 else pa.int64())], names=["run", "nid", "cost"])

    return run


def packed_parts(graph: Graph, kind: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    """((part, block), (nid, part) of repeated nodes, (part, src, dst)), all in the shared folder.

    A part must fit one task: more than ``PART_ARCS`` edges in one is an error,
    as is a negative weight.
    """
    edges = written(graph.edges.select(F.coalesce("part", F.lit(0)).alias("part"), "src", "dst", F.col("weight").cast(kind).alias("weight"), "direction", F.lit(0).cast("long").alias("eid")), "edges")
    seen = edges.groupBy("part").agg(F.count("*").alias("n"), F.min("weight").alias("low")).agg(F.max("n").alias("n"), F.min("low").alias("low")).head()
    if (seen["n"] or 0) > PART_ARCS:
        raise ValueError(f"a part has {seen['n']} edges, more than {PART_ARCS}; cut the graph into more parts, or by adaptive tiles")
    if (seen["low"] or 0) < 0:
        raise ValueError("weights must not be negative")
    meet = cut(boundary(edges))
    first = meet.groupBy("nid").agg(F.min("part").alias("_first"))
    shared = meet.join(first, "nid").select("part", "nid", (F.col("part") == F.col("_first")).alias("mine"))
    ways = arcs(edges).select("part", "u", "v", "w")
    blocks = written(ways.groupBy("part").cogroup(shared.groupBy("part")).applyInPandas(_pack(kind), "part int, block binary"), "blocks")
    return blocks, meet, edges.select("part", "src", "dst")


class _Labels:
    """The labels (run, part, dist) after each round: frames in the shared folder, and which rows of each still hold."""

    def __init__(self) -> None:
        self.frames: list[tuple[int, DataFrame]] = []

    def add(self, round_: int, rows: DataFrame) -> None:
        self.frames.append((round_, rows.select("run", "part", "dist").withColumn("round", F.lit(round_))))
        if len(self.frames) > 6:  # rows that a later round replaced go
            self.frames = [(round_, cut(self.now().withColumn("round", F.lit(round_))))]

    def now(self) -> DataFrame | None:
        if not self.frames:
            return None
        if len(self.frames) == 1:
            return self.frames[0][1].drop("round")
        every = self.frames[0][1]
        for _, f in self.frames[1:]:
            every = every.unionByName(f)
        last = every.groupBy("run", "part").agg(F.max("round").alias("round"))
        return every.join(last, ["run", "part", "round"], "left_semi").drop("round")


def solve_parts(graph: Graph, seeds: DataFrame, kind: str, stats: SolveStats, max_supersteps: int = 10_000, limit: float | None = None) -> DataFrame:
    """(run, nid, cost) for seeds(run, nid, cost); the rounds of all runs go on together."""
    ship(graph.spark)
    blocks, meet, ends = packed_parts(graph, kind)
    n = int(graph.spark.conf.get("spark.sql.shuffle.partitions"))
    seeds = checked_broadcast(seeds)
    hits = ends.join(seeds.withColumnRenamed("nid", "src"), "src").select("run", "part", F.col("src").alias("nid"), "cost").unionByName(ends.join(seeds.withColumnRenamed("nid", "dst"), "dst").select("run", "part", F.col("dst").alias("nid"), "cost"))
    least = [F.min("cost").alias("cost")]
    # costs at repeated nodes, and which of them are offers that the part has not seen
    front = border = cut(hits.groupBy("run", "part", "nid").agg(*least).withColumn("fresh", F.lit(True)))
    alone = seeds.join(front.select("run", "nid").distinct(), ["run", "nid"], "left_anti").groupBy("run", "nid").agg(*least)
    labels = _Labels()
    row = f"run long, part int, dist binary, nids array<long>, costs array<{kind}>, changed long"
    while True:
        per_part = front.groupBy("part").agg(F.count("*").alias("front"), F.countDistinct("run").alias("runs")).orderBy("part").collect()  # one row per busy part
        if not per_part:
            break
        if stats.supersteps >= max_supersteps:
            raise RuntimeError(f"no convergence in {max_supersteps} supersteps")
        if stats.supersteps:
            stats.messages += sum(r["front"] for r in per_part)
        stats.supersteps += 1
        stats.local_solves += sum(r["runs"] for r in per_part)
        stats.trace += [{"superstep": stats.supersteps, "part": r["part"], "front": r["front"]} for r in per_part]
        busy = [r["part"] for r in per_part]
        offers = front.groupBy("run", "part").agg(F.collect_list(F.struct("nid", "cost")).alias("o"))
        work = blocks.where(F.col("part").isin(busy)).join(offers, "part")
        before = labels.now()
        if before is None:
            work = work.withColumn("dist", F.lit(None).cast("binary"))
        else:
            work = work.join(before.where(F.col("part").isin(busy)), ["run", "part"], "left")
        dealt = work.select("run", "part", "block", F.col("o.nid").alias("nids"), F.col("o.cost").alias("costs"), "dist").repartition(min(n, len(busy)), "part").sortWithinPartitions("part", "run")
        solved = cut(dealt.mapInArrow(_solve_rows(kind, limit), row))
        labels.add(stats.supersteps, solved)
        if stats.record_fields:
            seen = _costs_now(blocks, labels, kind).agg(F.count("*").alias("reached"), F.max("cost").alias("max_cost"), F.sum("cost").alias("sum_cost")).head()
            stats.fields.append({"superstep": stats.supersteps, **seen.asDict()})
        changed = solved.select("run", "part", F.explode(F.arrays_zip("nids", "costs")).alias("c")).select("run", "part", F.col("c.nids").alias("nid"), F.col("c.costs").alias("cost"))
        sent = changed.join(meet.withColumnRenamed("part", "to"), "nid").select("run", F.col("to").alias("part"), "nid", "cost", (F.col("part") != F.col("to")).alias("offer"))
        both = border.select("run", "part", "nid", "cost", F.lit(False).alias("offer")).unionByName(sent)
        merged = both.groupBy("run", "part", "nid").agg(F.min(F.when(~F.col("offer"), F.col("cost"))).alias("known"), F.min(F.when(F.col("offer"), F.col("cost"))).alias("new"))
        better = F.col("new").isNotNull() & (F.col("known").isNull() | (F.col("new") < F.col("known")))
        border = cut(merged.select("run", "part", "nid", F.when(better, F.col("new")).otherwise(F.col("known")).alias("cost"), better.alias("fresh")))
        front = border.where("fresh")
    if labels.now() is None:
        return alone
    return _costs_now(blocks, labels, kind).unionByName(alone)


def _costs_now(blocks: DataFrame, labels: _Labels, kind: str) -> DataFrame:
    rows = blocks.join(labels.now(), "part").select("run", "block", "dist")
    return rows.mapInArrow(_unpack_rows(kind), f"run long, nid long, cost {kind}")


def _by_parts(graph: Graph, seeds: DataFrame, kind: str, stats: SolveStats, max_supersteps: int, limit: float | None) -> DataFrame:
    return solve_parts(graph, seeds.withColumn("run", F.lit(0).cast("long")), kind, stats, max_supersteps, limit).select("nid", "cost")


def _flat(graph: Graph, seeds: DataFrame, kind: str, stats: SolveStats, max_supersteps: int, limit: float | None, delta: int | None, target: int | None = None) -> DataFrame:
    ways = arcs(graph.edges).groupBy("u", "v").agg(F.min("w").alias("w"))  # parallel arcs: the least
    ways = ways.repartition("u").persist()
    known = cut(seeds.groupBy("nid").agg(F.min("cost").alias("cost")).withColumn("open", F.lit(True)))
    while True:
        # with buckets, only the open nodes of the lowest bucket are expanded
        low, n = known.where("open").agg(F.min("cost"), F.count("*")).head()
        if not n:
            break
        if stats.supersteps >= max_supersteps:
            raise RuntimeError(f"no convergence in {max_supersteps} supersteps")
        stats.supersteps += 1
        stats.messages += n
        ready = F.col("open") if delta is None else F.col("open") & (F.col("cost") < (int(low // delta) + 1) * delta)
        best = None
        if target is not None:
            best = known.where(F.col("nid") == target).agg(F.min("cost")).head()[0]
        reached = known.where(ready).join(ways, F.col("nid") == F.col("u")).select(F.col("v").alias("nid"), (F.col("cost") + F.col("w")).cast(kind).alias("cost"))
        if limit is not None:
            reached = reached.where(F.col("cost") <= limit)
        if best is not None:
            reached = reached.where(F.col("cost") < F.lit(best))
        offers = reached.groupBy("nid").agg(F.min("cost").alias("offer"))
        merged = known.join(offers, "nid", "full_outer")
        better = F.col("offer").isNotNull() & (F.col("cost").isNull() | (F.col("offer") < F.col("cost")))
        known = cut(merged.select("nid", F.when(better, F.col("offer")).otherwise(F.col("cost")).alias("cost"), F.when(better, F.lit(True)).otherwise(F.coalesce("open", F.lit(False)) & ~F.coalesce(ready, F.lit(False))).alias("open")))
    ways.unpersist()
    return known.select("nid", "cost")


def _single(graph: Graph, seeds: DataFrame, kind: str, limit: float | None) -> DataFrame:
    _check_size(graph)
    number = _number(kind)

    def run(rows: pd.DataFrame, offered: pd.DataFrame) -> pd.DataFrame:
        block = Block.of(rows["u"].to_numpy(np.int64), rows["v"].to_numpy(np.int64), rows["w"].to_numpy(number))
        dist = [float("inf")] * len(block.ids)
        at = block.place(offered["nid"].to_numpy(np.int64))
        got = settle(block.lists(), dist, [(c, int(i)) for i, c in zip(at, offered["cost"].tolist(), strict=True) if i >= 0], limit=float("inf") if limit is None else limit)
        return pd.DataFrame({"nid": block.ids[got], "cost": np.array([dist[i] for i in got], number)})

    whole = arcs(graph.edges).select(F.lit(0).alias("k"), "u", "v", F.col("w").cast(kind).alias("w"))
    found = whole.groupBy("k").cogroup(seeds.select(F.lit(0).alias("k"), "nid", "cost").groupBy("k")).applyInPandas(run, f"nid long, cost {kind}")  # one task, its size is checked
    return found.unionByName(seeds.select("nid", "cost")).groupBy("nid").agg(F.min("cost").alias("cost"))


def _check_size(graph: Graph) -> None:
    if graph.edges.limit(REPLICATED_ARCS // 2 + 1).count() > REPLICATED_ARCS // 2:
        raise ValueError(f"the graph has more than {REPLICATED_ARCS // 2} edges, too many for one worker")


def _pack_arcs(number):
    """Batches of (u, v, w) into one row of packed columns for each task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [[column.to_numpy(zero_copy_only=False) for column in batch.columns] for batch in batches if batch.num_rows]
        if held:
            u, v, w = (np.concatenate(c) for c in zip(*held, strict=True))
            yield pa.RecordBatch.from_arrays([pa.array([c.tobytes()], pa.binary()) for c in (u, v, w.astype(number))], names=["u", "v", "w"])

    return run


def replicate(graph: Graph):
    """The whole graph as a broadcast block; its size is checked first.

    Arcs reach the driver as packed columns, one row a task, never as rows of
    their own. Arcs without a weight cannot be passed and stay behind.
    """
    _check_size(graph)
    ship(graph.spark)
    number = _number("double" if dict(graph.edges.dtypes)["weight"] in ("double", "float") else "bigint")
    ways = arcs(graph.edges).select(F.col("u").cast("long"), F.col("v").cast("long"), "w").where("u IS NOT NULL AND v IS NOT NULL AND w IS NOT NULL")
    pieces = [(np.frombuffer(r["u"], np.int64), np.frombuffer(r["v"], np.int64), np.frombuffer(r["w"], number)) for r in ways.mapInArrow(_pack_arcs(number), "u binary, v binary, w binary").toLocalIterator()]
    none = np.empty(0, np.int64)
    u, v, w = (np.concatenate(c) for c in zip(*pieces, strict=True)) if pieces else (none, none, none.astype(number))
    del pieces
    return graph.spark.sparkContext.broadcast(Block.of(u, v, w))


def fits_workers(graph: Graph) -> bool:
    """Whether each worker may hold the whole graph."""
    return graph.edges.limit(REPLICATED_ARCS // 2 + 1).count() <= REPLICATED_ARCS // 2


def many_costs(graph: Graph, sources: DataFrame, limit: float | None = None, reverse: bool = False, engine: str = "auto") -> DataFrame:
    """(source, nid, cost) for every source.

    ``replicated``: tasks hold the whole graph and share the sources. ``parts``:
    the runs of all sources share the rounds of the partition-centric solver.
    ``auto`` takes the first where the graph's size, which is checked, allows it.
    ``reverse`` gives the costs from every node to each source.
    """
    g = graph.with_edges(reversed_edges(graph.edges)) if reverse else graph
    kind = "double" if dict(g.edges.dtypes)["weight"] in ("double", "float") else "bigint"
    if engine == "parts" or engine == "auto" and not fits_workers(g):
        seeds = sources.select("nid").distinct().select(F.col("nid").cast("long").alias("run"), F.col("nid").cast("long").alias("nid"), F.lit(0).cast(kind).alias("cost"))
        return solve_parts(g, cut(seeds), kind, SolveStats(), limit=limit).withColumnRenamed("run", "source")
    check_weights(g.edges)
    shared = replicate(g)

    names, number = ["source", "nid", "cost"], _number(kind)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block = shared.value
        together = max(1, SETTLED_AT_ONCE // max(1, len(block.ids)))
        for batch in batches:
            given = batch.column(0).to_numpy(zero_copy_only=False)
            at = block.place(given)
            alone = given[at < 0]
            if len(alone):
                yield pa.RecordBatch.from_arrays([pa.array(alone), pa.array(alone), pa.array(np.zeros(len(alone), number))], names=names)
            known, at = given[at >= 0], at[at >= 0]
            pieces = max(1, -(-len(at) // together))
            for ours, starts in zip(np.array_split(known, pieces), np.array_split(at, pieces), strict=True):
                found = settle_each(block, starts, float("inf") if limit is None else limit)
                for s, dist in zip(ours.tolist(), found, strict=True):
                    got = np.flatnonzero(dist < (np.inf if number is np.float64 else np.iinfo(number).max))
                    for k in range(0, len(got), COSTS_AT_ONCE):
                        some = got[k : k + COSTS_AT_ONCE]
                        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(some), s)), pa.array(block.ids[some]), pa.array(dist[some])], names=names)

    # dealt evenly: by the key of the distinct rows it would be no exchange of its own, and so few bytes become one task
    n = 2 * int(graph.spark.conf.get("spark.sql.shuffle.partitions"))
    return sources.select(F.col("nid").cast("long")).where("nid IS NOT NULL").distinct().repartition(n).mapInArrow(run, f"source long, nid long, cost {kind}")


def pair_costs(graph: Graph, wanted: DataFrame, limit: float | None = None, tasks: int | None = None, shared=None) -> DataFrame:
    """(src, dst, cost) for rows (src, dsts): each origin is solved once, until its destinations are settled.

    Destinations that cannot be reached, or only at a cost above ``limit``,
    have a null cost. ``tasks`` share the origins (by default four for each
    shuffle partition), and only the pairs asked for leave the workers. Graphs
    that no worker can hold are solved in parts. ``shared`` is the replicated
    graph where the caller has it already.
    """
    if shared is None and not fits_workers(graph):
        pairs = wanted.select("src", F.explode("dsts").alias("dst")).distinct()
        found = many_costs(graph, pairs.select(F.col("src").alias("nid")), limit, engine="parts").select(F.col("source").alias("src"), F.col("nid").alias("dst"), F.col("cost").cast("double").alias("cost"))
        return pairs.join(found, ["src", "dst"], "left")
    shared = shared or replicate(graph)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        block = shared.value
        lists = block.lists()
        for batch in batches:
            for src, dsts in zip(batch["src"], batch["dsts"], strict=True):
                dsts = np.asarray(dsts, np.int64)
                start, ends = int(block.place(np.array([src]))[0]), block.place(dsts)
                if start < 0:
                    yield pd.DataFrame({"src": src, "dst": dsts, "cost": [0.0 if d == src else None for d in dsts]})
                    continue
                dist = [float("inf")] * len(block.ids)
                settle(lists, dist, [(0, start)], {int(i) for i in ends if i >= 0}, float("inf") if limit is None else limit)
                yield pd.DataFrame({"src": src, "dst": dsts, "cost": [dist[i] if i >= 0 and dist[i] < float("inf") else None for i in ends]})

    n = tasks or 4 * int(graph.spark.conf.get("spark.sql.shuffle.partitions"))
    return wanted.select("src", "dsts").repartition(n, "src").mapInPandas(run, "src long, dst long, cost double")


def reversed_edges(edges: DataFrame) -> DataFrame:
    """The same edges passed the other way."""
    return edges.withColumn("direction", F.when(F.col("direction") == 1, 2).when(F.col("direction") == 2, 1).otherwise(F.col("direction")))


def inverse(graph: Graph, destinations, engine: str = "parts", **options) -> DataFrame:
    """(nid, cost): least cost from every node to the nearest destination."""
    return costs(graph.with_edges(reversed_edges(graph.edges)), destinations, engine, **options)


def violations(graph: Graph, found: DataFrame) -> DataFrame:
    """Arcs whose head costs more than their tail and weight; none after convergence."""
    a, d = arcs(graph.edges), found.select(F.col("nid").alias("u"), F.col("cost").alias("du"))
    return a.join(d, "u").join(found.select(F.col("nid").alias("v"), F.col("cost").alias("dv")), "v", "left").where("dv IS NULL OR dv > du + w")


def nearest_source(graph: Graph, sources: DataFrame) -> DataFrame:
    """(nid, source, cost): the source with the least cost to each node, ties to the smaller id."""
    return many_costs(graph, sources).groupBy("nid").agg(F.min(F.struct("cost", "source")).alias("m")).select("nid", "m.source", "m.cost")
