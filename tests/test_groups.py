"""Pairs with a common group, made without a join of the groups with themselves."""

from __future__ import annotations

import itertools

import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from weftgraph.operators import groups as grouped
from weftgraph.operators import measures, topology
from weftgraph.operators.groups import Groups
from weftgraph.plans.common import running_sum

ROWS = [(5, "x", 1), (9, "x", 1), (2, "x", 1), (5, "y", 3), (9, "y", 3), (9, "y", 3), (7, "z", 4), (None, "z", 4), (2, None, 9), (40, "w", 6), (7, "w", 6), (2, "w", 6)]


def _want():
    found = {}
    for (a, g, y), (b, h, _) in itertools.product(ROWS, ROWS):
        if None not in (a, b, g, h) and g == h and a < b:
            found[a, b] = min(found.get((a, b), 99), y)
    return found


@pytest.mark.parametrize("most", [100, 3])
def test_pairs_of_groups_are_those_of_a_join(spark, monkeypatch, most):
    monkeypatch.setattr(grouped, "MEMBERS", most)
    g = Groups.of(spark.createDataFrame(ROWS, "m long, g string, y long"), ["g"], "m", "y")
    assert (len(g.blocks) > 1) == (most == 3)
    want = _want()
    got = [tuple(r) for r in g.pairs().collect()]
    assert sorted(got) == sorted((a, b, y) for (a, b), y in want.items())
    degree = {r["nid"]: (r["degree"], r["ahead"], r["last"]) for r in g.degrees().collect()}
    for n in {2, 5, 7, 9, 40}:
        near = [b if a == n else a for a, b in want if n in (a, b)]
        assert degree[n] == (len(near), sum(x > n for x in near), max((x for x in near if x < n), default=None))


def _walks(n: int, hops: int, least: int = 0) -> list[tuple]:
    """All paths of so many hops from a member, by its pairs."""
    arcs = [x for (a, b), y in _want().items() if y >= least for x in ((a, b), (b, a))]
    found = [(n,)]
    for _ in range(hops):
        found = [(*p, b) for p in found for a, b in arcs if a == p[-1] and b not in p]
    return found


def test_groups_are_walked_without_their_pairs(spark):
    from weftgraph.operators import query as q

    g = Groups.of(spark.createDataFrame(ROWS, "m long, g string, y long"), ["g"], "m", "y")
    start = spark.createDataFrame([(5,), (7,), (2,), (8,)], "nid long")
    got = {(r["src"], r["nid"]): r["hops"] for r in g.within(start, 2).collect()}
    near = {n: {p[-1] for p in _walks(n, 1)} for n in (2, 5, 7, 9, 40)}
    want = {(n, m): 1 if m in near[n] else 2 for n in (5, 7, 2) for m in near[n] | {p[-1] for p in _walks(n, 2)} if m != n}
    assert got == want
    counts = {r["src"]: (r["walks"], r["reached"]) for r in g.two_hops(start).collect()}
    assert counts == {n: (len(_walks(n, 2)), len({p[-1] for p in _walks(n, 2)})) for n in (5, 7, 2)}
    steps = lambda rows: g.steps(rows, "at", 3).select(*rows.columns, "v", F.col("v").alias("eid"), F.col("since").alias("w"))
    for prune in (True, False):
        found = q.paths(None, start, spark.createDataFrame([(7,), (9,)], "nid long"), q.Hops(3), prune=prune, steps=steps)
        assert sorted(tuple(r["path"]) for r in found.collect()) == sorted(p for n in (5, 7, 2) for k in (1, 2, 3) for p in _walks(n, k, 3) if p[-1] in (7, 9))


@pytest.mark.parametrize("name", ["query_knows_since", "query_knows_unpruned", "query_long_form", "query_neighbours", "query_two_hop_counts"])
def test_path_queries_make_only_the_pairs_they_meet(spark, duck, sf_dir, monkeypatch, name):
    from helpers import same_rows

    from weftgraph.queries import ORACLE_SQL, QUERIES

    plain = Groups.pairs
    monkeypatch.setattr(Groups, "pairs", lambda self, *more: plain(self, *more).select(*[F.raise_error(F.lit("all pairs are made")).cast("long").alias(c) for c in ("a", "b", "since")]))
    same_rows(QUERIES[name](spark, sf_dir), duck.sql(ORACLE_SQL[name]))


@pytest.mark.parametrize("name", ["query_long_form", "query_neighbours", "query_two_hop_counts"])
def test_path_queries_over_more_than_one_block(spark, duck, sf_dir, monkeypatch, name):
    from helpers import same_rows

    from weftgraph.queries import ORACLE_SQL, QUERIES

    monkeypatch.setattr(grouped, "MEMBERS", 1000)
    same_rows(QUERIES[name](spark, sf_dir), duck.sql(ORACLE_SQL[name]))


def _plan(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_pairs_are_never_shuffled(spark, sf_dir):
    from weftgraph import workloads

    e = workloads.knows(spark, sf_dir).edges
    for df in (e, topology.incident_edges(e), topology.compact(topology.csr_tombstone(e, F.col("src") % 5 == 0))):
        assert "Exchange" not in _plan(df) and "Join" not in _plan(df)


def test_edges_with_ascending_ids_are_counted_where_they_are(spark):
    from weftgraph.model import Graph

    rows = [(1, 0, 1, 1), (2, 1, 2, 1), (2, 1, 3, 1), (4, 2, 3, None), (4, 2, 3, 0), (9, 3, 4, 0)]
    for order in (rows, rows[::-1]):  # the second order needs the shuffle
        e = spark.createDataFrame(order, "eid long, src long, dst long, part int").coalesce(1)
        assert tuple(measures.check_disjoint(Graph("g", None, e)).head()) == (6, 4, 1)


def test_stretches_of_ids_in_any_order_need_no_shuffle(spark, monkeypatch):
    from weftgraph.model import Graph

    # one task reads 50..59, 10..19, 30..39, as from several files; an id occurs twice inside its stretch
    ids = [*range(50, 60), *range(10, 20), 19, *range(30, 40)]
    e = spark.createDataFrame([(i, 0, 1, None if i == 12 else 0) for i in ids], "eid long, src long, dst long, part int").coalesce(1)
    found = measures.check_disjoint(Graph("g", None, e))
    assert tuple(found.head()) == (31, 30, 1) and "Exchange" not in _plan(found)
    # two tasks read 0..9 with 50..59, and 20..29: the first one's ids ascend across the other's
    apart = spark.sparkContext.parallelize([[*range(10), *range(50, 60)], list(range(20, 30))], 2).flatMap(lambda x: [(i, 0, 1, 0) for i in x]).toDF("eid long, src long, dst long, part int")
    found = measures.check_disjoint(Graph("g", None, apart))
    assert tuple(found.head()) == (30, 30, 0) and "Exchange" not in _plan(found)
    # stretches that meet are shuffled
    again = spark.createDataFrame([(i, 0, 1, 0) for i in [5, 6, 9, 1, 6, 7]], "eid long, src long, dst long, part int").coalesce(1)
    assert tuple(measures.check_disjoint(Graph("g", None, again)).head()) == (6, 5, 0)
    # runs are joined over small gaps, over batches too
    batch = lambda x: pa.RecordBatch.from_arrays([pa.array(x, pa.int64()), pa.array([0] * len(x), pa.int32())], names=["eid", "part"])
    rows = lambda: [tuple(r.values()) for b in measures._id_runs(iter([batch([1, 2, 2]), batch([]), batch([2, 4, 90, 91]), batch([3, 3, 7])])) for r in b.to_pylist()]
    for most, want in ((2, [(1, 91, 5), (3, 7, 2)]), (3, [(1, 4, 3), (90, 91, 2), (3, 7, 2)])):
        monkeypatch.setattr(measures, "RUNS", most)
        assert rows() == [(10, 0, 0, True, None, None), *((0, d, 0, True, low, high) for low, high, d in want)]
    monkeypatch.setattr(measures, "RUNS", 1)
    assert rows() == [(10, 0, 0, False, None, None)]


def test_sizes_of_edge_sets_take_one_pass(spark):
    e = spark.createDataFrame([(0, 1, 3), (0, 2, 30), (1, 2, 4), (3, 4, 50)], "src long, dst long, weight long")
    got = measures.edge_sets(e, F.col("weight") < 10, F.col("src") % 2 == 0)
    assert {r["kind"]: r["n"] for r in got.collect()} == {"both": 1, "first only": 1, "either": 3}


def test_shifts_and_running_sums(spark):
    d = spark.createDataFrame([(7, 2), (1, 3), (4, 5)], "nid long, degree long")
    assert {r["nid"]: r["s"] for r in running_sum(d, "nid", "degree", "s").collect()} == {1: 0, 4: 3, 7: 8}
    assert {r["nid"]: r["moved"] for r in measures.csr_shifts(d).collect()} == {1: 7, 4: 2, 7: 0}


@pytest.mark.parametrize("most", [100, 3])
def test_pairs_of_some_second_members_without_dates(spark, monkeypatch, most):
    monkeypatch.setattr(grouped, "MEMBERS", most)
    g = Groups.of(spark.createDataFrame(ROWS, "m long, g string, y long"), ["g"], "m", "y")
    assert sorted(map(tuple, g.pairs(since=False).collect())) == sorted(_want())
    more = spark.createDataFrame([(2, 20), (5, 50)], "nid long, more long")
    for k in (1, 3, 10):
        got = g.pairs(more, since=False, multiple_of=k).select("a", "b", "more").collect()
        assert sorted(map(tuple, got)) == sorted((a, b, 10 * a) for a, b in _want() if a in (2, 5) and b % k == 0)


def test_shifts_make_only_the_edges_they_return(spark, duck, sf_dir, monkeypatch):
    from helpers import same_rows

    from weftgraph.queries import ORACLE_SQL, QUERIES

    plain, made = Groups.pairs, []
    monkeypatch.setattr(Groups, "pairs", lambda self, *a, **k: made.append(plain(self, *a, **k)) or made[-1])
    same_rows(QUERIES["topo_csr_shift"](spark, sf_dir), duck.sql(ORACLE_SQL["topo_csr_shift"]))
    assert [p.where("b % 10 <> 0").count() for p in made] == [0]


def test_edges_of_the_social_graph_carry_no_dates(spark, sf_dir):
    from weftgraph.queries import QUERIES

    plan = _plan(QUERIES["part_random"](spark, sf_dir))
    assert "since" not in plan and "Exchange" not in plan
