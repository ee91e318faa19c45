"""Costs of many pairs of nodes by a table of costs between the border nodes of parts.

The graph is cut into small parts. Inside each, all costs between its nodes
are found (parts in parallel). The nodes that parts share are the borders: the
least costs between all of them, over any parts, follow from the parts' own
border tables. The cost of a pair is then the least sum of three terms, from
the origin to a border of its part, from there to a border of the other part,
and on to the destination; or the cost inside the part, where both share one.
So work is no more a search for each origin, but a minimum of sums of table
rows, however many origins there are.

The tables are broadcast; their size is checked, and larger graphs are solved
origin by origin.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from weftgraph.model import Graph, arcs
from weftgraph.operators import partition
from weftgraph.operators.kernels import Block
from weftgraph.plans.common import cut, ship

#: Largest part, number of border nodes, and bytes of all tables.
PART_NODES, BORDERS, TABLE_BYTES = 1_200, 4_096, 400 << 20


@dataclass
class Tables:
    """What every task needs: parts of nodes, costs inside parts, and costs between borders."""

    ids: np.ndarray  # all nodes, ascending
    part: np.ndarray  # a part of each node
    row: np.ndarray  # its place in that part
    inside: dict[int, np.ndarray]  # (n, n) of each part
    border: dict[int, np.ndarray]  # places in the part of its border nodes
    places: dict[int, np.ndarray]  # and places of these among all borders
    between: np.ndarray  # (borders, borders)


def close(m: np.ndarray) -> np.ndarray:
    """Least costs between all nodes of a matrix of arcs, in place."""
    for k in range(len(m)):
        np.minimum(m, m[:, k, None] + m[None, k, :], out=m)
    return m


def least_sums(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The least a[i, k] + b[k, j] over k."""
    out = np.full((len(a), b.shape[1]), np.inf)
    for k in range(a.shape[1]):
        np.minimum(out, a[:, k, None] + b[None, k, :], out=out)
    return out


def _inside(rows: pd.DataFrame) -> pd.DataFrame:
    b = Block.of(rows["u"].to_numpy(np.int64), rows["v"].to_numpy(np.int64), rows["w"].to_numpy(float))
    m = np.full((len(b.ids), len(b.ids)), np.inf)
    np.minimum.at(m, (np.repeat(np.arange(len(b.ids)), np.diff(b.offsets)), b.targets), b.weights)
    np.fill_diagonal(m, 0)
    return pd.DataFrame({"part": [rows["part"].iloc[0]], "ids": [b.ids.tobytes()], "costs": [close(m).tobytes()]})


def cut_for_tables(graph: Graph) -> Graph:
    """The graph in parts small enough for tables: boxes where nodes have places, else ranges of ids."""
    n = graph.nodes.count()
    side = max(1, round((n / 500) ** 0.5))
    if graph.nodes.where("x IS NULL").limit(1).count():
        return partition.by_id_range(graph, side * side)
    e = graph.nodes.agg(F.min("x"), F.max("x"), F.min("y"), F.max("y")).head()
    wide, high = (e[1] or 0) - (e[0] or 0) or 1.0, (e[3] or 0) - (e[2] or 0) or 1.0
    nx = max(1, min(side * side, round(side * (wide / high) ** 0.5)))
    return partition.by_box(graph, nx, max(1, round(side * side / nx)))


def tables(graph: Graph) -> Tables | None:
    """The tables of a graph, or None where they would be too large."""
    parts = cut_for_tables(graph)
    edges = cut(parts.edges.select("part", "src", "dst", "weight", "direction", F.lit(0).cast("long").alias("eid")))
    here = partition.copies(edges).groupBy("part").count()
    sizes = [r["count"] for r in here.limit(BORDERS + 1).collect()]
    if not sizes or len(sizes) > BORDERS or max(sizes) > PART_NODES or 8 * sum(s * s for s in sizes) > TABLE_BYTES:
        return None
    shared = partition.boundary(edges).select("nid").distinct()
    if shared.limit(BORDERS + 1).count() > BORDERS:
        return None
    borders = np.sort(np.array([r["nid"] for r in shared.collect()], np.int64))  # at most BORDERS
    ship(graph.spark)
    n = int(graph.spark.conf.get("spark.sql.shuffle.partitions"))
    solved = arcs(edges).select("part", "u", "v", F.col("w").cast("double").alias("w")).repartition(max(n, min(4 * n, len(sizes))), "part").groupBy("part").applyInPandas(_inside, "part int, ids binary, costs binary")
    inside, border, places, ids_of = {}, {}, {}, {}
    between = np.full((len(borders), len(borders)), np.inf)
    np.fill_diagonal(between, 0)
    for r in solved.collect():  # the sum of their sizes is checked above
        ids = np.frombuffer(r["ids"], np.int64)
        m = np.frombuffer(r["costs"], float).reshape(len(ids), len(ids))
        at = np.flatnonzero(np.isin(ids, borders))
        spot = np.searchsorted(borders, ids[at])
        inside[r["part"]], border[r["part"]], places[r["part"]], ids_of[r["part"]] = m, at, spot, ids
        block = between[np.ix_(spot, spot)]
        between[np.ix_(spot, spot)] = np.minimum(block, m[np.ix_(at, at)])
    close(between)
    every = np.concatenate([ids_of[p] for p in sorted(ids_of)])
    owner = np.concatenate([np.full(len(ids_of[p]), p, np.int32) for p in sorted(ids_of)])
    rows = np.concatenate([np.arange(len(ids_of[p])) for p in sorted(ids_of)])
    ids, first = np.unique(every, return_index=True)
    return Tables(ids, owner[first], rows[first], inside, border, places, between)


def solve(t: Tables, src: np.ndarray, dst: np.ndarray) -> np.ndarray:
    """Costs of pairs; infinite where there is no way or a node has no edge."""
    out = np.where(src == dst, 0.0, np.inf)
    i, j = (np.minimum(np.searchsorted(t.ids, x), len(t.ids) - 1) for x in (src, dst))
    known = np.flatnonzero((t.ids[i] == src) & (t.ids[j] == dst))
    p, q = t.part[i], t.part[j]
    for a in np.unique(p[known]):
        mine = known[p[known] == a]
        rows, back = np.unique(t.row[i[mine]], return_inverse=True)
        to_all = least_sums(t.inside[a][np.ix_(rows, t.border[a])], t.between[t.places[a]])
        for b in np.unique(q[mine]):
            some = q[mine] == b
            at, ends = back[some], t.row[j[mine[some]]]
            if len(t.border[b]):
                reach = t.inside[b][t.border[b]]  # from each border to each node
                best = np.empty(len(at))
                for k in range(0, len(at), 4096):
                    best[k : k + 4096] = (to_all[at[k : k + 4096]][:, t.places[b]] + reach[:, ends[k : k + 4096]].T).min(axis=1)
            else:
                best = np.full(len(at), np.inf)
            if a == b:
                best = np.minimum(best, t.inside[a][rows[at], ends])
            out[mine[some]] = np.minimum(out[mine[some]], best)
    return out


def pair_table_costs(graph: Graph, pairs: DataFrame, found: Tables) -> DataFrame:
    """(src, dst, cost) of distinct pairs(src, dst), costs as doubles, null where there is no way."""
    spark = graph.spark
    shared = spark.sparkContext.broadcast(found)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            cost = solve(shared.value, batch["src"].to_numpy(np.int64), batch["dst"].to_numpy(np.int64))
            yield pd.DataFrame({"src": batch["src"], "dst": batch["dst"], "cost": np.where(np.isfinite(cost), cost, np.nan)})

    # pairs of one part side by side, so that a batch holds few parts
    owners = spark.createDataFrame(pd.DataFrame({"nid": found.ids, "_p": found.part}))  # bounded like the tables
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt = pairs.join(F.broadcast(owners), F.col("src") == F.col("nid"), "left").repartitionByRange(4 * n, "_p", "src").sortWithinPartitions("_p", "src").select("src", "dst")
    return dealt.mapInPandas(run, "src long, dst long, cost double").withColumn("cost", F.when(~F.isnan("cost"), F.col("cost")))
