"""Exact, line and near deduplication against brute force and SQL."""

from __future__ import annotations

import hashlib
import random
import re

import numpy as np
import pytest
from helpers import same_rows


from weftgraph.llm import near_dedup
from weftgraph.llm.exact_dedup import drop_exact_duplicates, exact_dedup
from weftgraph.llm.line_dedup import line_dedup
from weftgraph.llm.near_dedup import NearDupParams, drop_near_duplicates, near_dup_groups
from weftgraph.llm.queries import ORACLE_SQL, QUERIES

SCHEMA = "doc_id long, text string, keep_id string, _id int"  # two clashing names besides


def table(spark, rows):
    return spark.createDataFrame([(i, t, "clash", 7) for i, t in rows], SCHEMA)


@pytest.mark.parametrize("name", sorted(ORACLE_SQL))
def test_matches_sql(spark, duck, sf_dir, name):
    same_rows(QUERIES[name](spark, sf_dir), duck.sql(ORACLE_SQL[name]))


# ------------------------------------------------------------------ exact


@pytest.mark.parametrize("limit", [200_000, 0])
def test_exact_cases(spark, limit):
    long = "word " * 50_000
    rows = [(5, "a  b"), (2, "a\tb"), (9, "a b"), (1, None), (3, ""), (7, " "), (4, long + "x"), (6, long + "y"), (8, long + "x"), (None, "a b"), (None, "alone"), (9, "a b")]
    got = sorted(((r["doc_id"], r["keep_id"], r["group_size"], r["kept"]) for r in exact_dedup(table(spark, rows), broadcast_rows=limit).collect()), key=str)
    want = [(5, 2, 5, False), (2, 2, 5, True), (9, 2, 5, False), (9, 2, 5, False), (None, 2, 5, False), (1, 1, 2, True), (3, 1, 2, False), (7, 7, 1, True), (4, 4, 2, True), (8, 4, 2, False), (6, 6, 1, True), (None, None, 1, True)]
    assert got == sorted(want, key=str)
    digest = {r["doc_id"]: r["text_sha256"] for r in exact_dedup(table(spark, rows)).collect()}
    assert digest[5] == hashlib.sha256(b"a b").hexdigest()


def test_exact_empty_and_drop(spark):
    assert exact_dedup(table(spark, [])).count() == 0
    kept = drop_exact_duplicates(table(spark, [(1, "x"), (2, "x"), (3, "y")]))
    assert sorted(r["doc_id"] for r in kept.collect()) == [1, 3]
    assert kept.columns == ["doc_id", "text", "keep_id", "_id"]


def test_exact_drop_keeps_one_row_of_repeated_ids(spark):
    rows = [(1, "a b"), (1, "a b"), (1, "a  b"), (1, "other"), (2, "a b"), (None, "n"), (None, "n"), (None, "a b"), (3, None), (3, "")]
    got = sorted(((r["doc_id"], " ".join((r["text"] or "").split())) for r in drop_exact_duplicates(table(spark, rows)).collect()), key=str)
    assert got == sorted([(1, "a b"), (1, "other"), (None, "n"), (3, "")], key=str)
    assert drop_exact_duplicates(table(spark, [])).count() == 0


# ------------------------------------------------------------------- lines


def brute_lines(rows, min_chars, min_docs):
    low = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    key = lambda line: line.strip(" \t\n\x0b\x0c\r").translate(low)
    holders = {}
    for i, t in rows:
        for line in (t or "").split("\n"):
            if len(key(line)) >= min_chars:
                holders.setdefault(key(line), set()).add(i)
    gone = {k: max(v) for k, v in holders.items() if len(v) >= min_docs}
    out = {}
    for i, t in rows:
        lines = (t or "").split("\n")
        kept = [x for x in lines if key(x) not in gone or gone[key(x)] == i]
        out[i] = ("\n".join(kept), len(lines), len(lines) - len(kept))
    return out


def test_lines_against_brute_force(spark):
    rng = random.Random(3)
    pool = [f"Shared LINE number {k} with É enough characters" for k in range(6)] + ["short"]
    rows = [(i, "\n".join(rng.choice([*pool, f"own line {i} {j}", "  " + pool[0].upper().replace("É", "É") + "\t", ""]) for j in range(rng.randint(0, 7)))) for i in range(40)]
    rows += [(100, None), (101, ""), (102, "\n\n")]
    got = {r["doc_id"]: (r["text"], r["n_lines"], r["n_dropped"]) for r in line_dedup(table(spark, rows), min_chars=20, min_docs=4).collect()}
    assert got == brute_lines(rows, 20, 4)


def test_line_cases(spark):
    line = "x" * 45
    rows = [(i, f"{line}\nown") for i in range(4)] + [(3, f"{line}\nown"), (None, f"{line}\nown")]
    # four ids with equal texts and a null one: five documents
    got = sorted(((r["doc_id"], r["n_dropped"]) for r in line_dedup(table(spark, rows)).collect()), key=str)
    assert got == [(0, 1), (1, 1), (2, 1), (3, 0), (3, 0), (None, 1)]
    assert line_dedup(table(spark, [])).count() == 0
    assert line_dedup(table(spark, rows)).columns == ["doc_id", "text", "keep_id", "_id", "n_lines", "n_dropped"]
    big = line_dedup(table(spark, [(i, (line + "\n") * 20_000) for i in range(6)])).orderBy("doc_id").collect()
    assert [r["n_dropped"] for r in big] == [20_000] * 5 + [0]


# -------------------------------------------------------------------- near


def brute_groups(rows, k, num, den):
    def shingles(t):
        w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        return frozenset(tuple(w[i : i + k]) for i in range(max(1, len(w) - k + 1))) if w else frozenset()

    sets = {i: shingles(t) for i, t in rows}
    parent = {i: i for i in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(sets)
    for a in ids:
        for b in ids:
            if a < b and sets[a] and sets[b] and den * len(sets[a] & sets[b]) >= num * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                parent[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i)) for i in ids}


def family(rng, base, n, first, edits):
    out = []
    for j in range(n):
        words = list(base)
        for _ in range(rng.randint(0, edits)):
            words[rng.randrange(len(words))] = f"w{rng.randrange(10**6)}"
        out.append((first + j, " ".join(words)))
    return out


@pytest.mark.parametrize("block", [64, 8])
def test_near_against_brute_force(spark, monkeypatch, block):
    monkeypatch.setattr(near_dedup, "BLOCK_DOCS", block)  # small blocks: large families take the second round
    rng = random.Random(11)
    rows = family(rng, [f"a{i}" for i in range(80)], 60, 0, 6) + family(rng, [f"b{i}" for i in range(30)], 25, 100, 3) + family(rng, [f"c{i}" for i in range(9)], 10, 200, 1)
    rows += [(300 + i, " ".join(f"u{rng.randrange(500)}" for _ in range(40))) for i in range(30)]
    rows += [(400, ""), (401, None), (402, " \t"), (403, "two words"), (404, "Two  WORDS"), (405, "one"), (406, "ONE"), (407, "É one"), (408, "é one")]
    for params in (NearDupParams(3, 85, 100), NearDupParams(5, 80, 100)):
        got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in near_dup_groups(table(spark, rows), params).collect()}
        assert got == brute_groups(rows, params.words, params.num, params.den)


def test_near_on_documents(spark, documents):
    rows = [(r["doc_id"], r["text"]) for r in documents.select("doc_id", "text").collect()]
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in near_dup_groups(documents, NearDupParams(3, 85, 100)).collect()}
    assert got == brute_groups(rows, 3, 85, 100)


def test_near_cases(spark):
    rows = [(1, "a b c d e f g"), (1, "a b c d e f g"), (1, "quite another text in the same row id"), (None, "a b c d e f g"), (2, "a b c d e f g")]
    got = sorted(((r["doc_id"], r["component_id"], r["kept"]) for r in near_dup_groups(table(spark, rows), NearDupParams(3, 85, 100)).collect()), key=str)
    assert got == [(1, 1, True)] * 3 + [(2, 1, False), (None, None, True)]
    assert near_dup_groups(table(spark, [])).count() == 0
    kept = drop_near_duplicates(table(spark, rows))
    assert sorted((str(r["doc_id"]), r["text"][:5]) for r in kept.collect()) == [("1", "a b c"), ("1", "quite"), ("None", "a b c")]
    assert kept.columns == ["doc_id", "text", "keep_id", "_id"]
    with pytest.raises(ValueError):
        near_dup_groups(table(spark, rows), NearDupParams(3, 0, 100))
    long = " ".join(f"t{i}" for i in range(60_000))
    pair = near_dup_groups(table(spark, [(1, long), (2, long + " end")])).orderBy("doc_id").collect()
    assert [r["component_id"] for r in pair] == [1, 1]


def test_ids_with_several_texts(spark):
    """An id's texts are one document for components, and rows of their own where rows are dropped."""
    a, b = " ".join(f"a{i}" for i in range(40)), " ".join(f"b{i}" for i in range(40))
    rows = [(1, a), (1, b), (2, b + " more"), (3, a + " more"), (4, "alone in the world of words"), (4, ""), (4, None), (2, ""), (5, a), (5, a.upper())]
    got = {(r["doc_id"], r["n_shingles"]): (r["component_id"], r["kept"]) for r in near_dup_groups(table(spark, rows), NearDupParams(3, 85, 100)).collect()}
    assert got == {(1, 38): (1, True), (2, 39): (1, False), (3, 39): (1, False), (4, 4): (4, True), (4, 0): (4, True), (2, 0): (1, False), (5, 38): (1, False)}
    kept = drop_near_duplicates(table(spark, rows), NearDupParams(3, 85, 100)).collect()
    assert sorted((r["doc_id"], len((r["text"] or "").split())) for r in kept) == [(1, 40), (1, 40), (2, 0), (4, 0), (4, 6)]
    # the representative of a set is another id than that of its neighbours
    chain = [(7, a), (7, b), (6, a), (8, b + " x"), (9, "p q r s t u v"), (9, a + " y")]
    got = {r["doc_id"]: r["component_id"] for r in near_dup_groups(table(spark, chain), NearDupParams(3, 85, 100)).collect()}
    assert got == {6: 6, 7: 6, 8: 6, 9: 6}


def test_registers_estimate_similarity():
    rng = np.random.default_rng(0)
    mult = near_dedup._multipliers(210)
    for n, shared in ((400, 300), (30, 24), (5, 4)):
        pool = rng.integers(0, 1 << 63, size=2 * n, dtype=np.uint64)
        a, b = np.unique(pool[:n]), np.unique(np.concatenate([pool[:shared], pool[n : 2 * n - shared]]))
        true = shared / (2 * n - shared)
        got = (near_dedup.registers(a, mult, 210) == near_dedup.registers(b, mult, 210)).mean()
        c = near_dedup.chance_match(n)
        assert abs((got - c) / (1 - c) - true) < 5 * np.sqrt(true * (1 - true) / 210) + 0.01
    a, b = (np.unique(rng.integers(0, 1 << 63, size=500, dtype=np.uint64)) for _ in range(2))
    many = near_dedup._multipliers(4000)
    measured = (near_dedup.registers(a, many, 4000) == near_dedup.registers(b, many, 4000)).mean()
    assert abs(measured - near_dedup.chance_match(500)) < 0.002


def test_bands_follow_from_the_threshold():
    assert NearDupParams(3, 85, 100).bands == 35 and NearDupParams(5, 80, 100).bands > 50
    assert (1 - 0.85**6) ** 35 <= 1e-7


def test_schema_of_queries(spark, sf_dir):
    assert dict(QUERIES["op7_near_dedup"](spark, sf_dir).dtypes) == {"doc_id": "bigint", "n_shingles": "bigint", "component_id": "bigint", "kept": "boolean"}
    out = QUERIES["op3_line_dedup"](spark, sf_dir)
    assert dict(out.dtypes)["n_dropped"] == "bigint"
