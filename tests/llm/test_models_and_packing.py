"""Toxicity, nearest neighbours, packing, mixing, pipeline."""

from __future__ import annotations

import collections
import itertools
import math
import zlib

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from weftgraph.llm import ann, mixing, packing, toxicity
from weftgraph.llm.queries import QUERIES

TINY = toxicity.TrainParams(toxic_docs=60, clean_docs=120, char_epochs=2, window_epochs=3, min_steps=60)


def docs(spark, rows, extra="score int"):
    return spark.createDataFrame([(*r, 1) for r in rows], f"doc_id long, text string, source string, {extra}")


# --------------------------------------------------------------- toxicity


def corpus(n, seed=0):
    rng = np.random.default_rng(seed)
    words = ["".join(rng.choice(list("abcdefgh"), size=rng.integers(2, 6))) for _ in range(300)]
    out = []
    for i in range(n):
        text = list(rng.choice(words, size=rng.integers(5, 150)))
        bad = int(i % 3 == 0)
        if bad:
            for _ in range(3):
                text.insert(int(rng.integers(len(text))), "zot" + "".join(rng.choice(list("xyz"), size=3)))
        out.append((i, " ".join(text), bad))
    return out


@pytest.fixture(scope="module")
def model():
    rows = corpus(240)
    return toxicity.train([t for _, t, _ in rows], [y for _, _, y in rows], TINY)


def test_learns_spellings_it_has_not_seen(model):
    rows = corpus(120, seed=9)
    p = toxicity._Scorer(model).scores([t for _, t, _ in rows])
    assert ((p >= 0.5) == np.array([y for _, _, y in rows])).mean() > 0.95


def test_every_word_of_a_long_text_counts(model):
    calm = " ".join(["abc"] * 5000)
    scorer = toxicity._Scorer(model)
    low, high = scorer.scores([calm, calm + " zotxyz zotzyx zotyyx"])
    assert high > 0.5 > low or high > low + 0.2
    assert [s for s, _ in toxicity.windows_of(130)] == [0, 48, 96] and sum(toxicity.windows_of(130)[-1]) == 130
    assert toxicity.pieces_of(b"..." + b"a" * 60 + b"!") == [b"a" * 24, b"a" * 24, b"a" * 12]


def test_gradients_of_the_recurrent_net():
    rng = np.random.default_rng(1)
    p = {k: v.astype(np.float64) for k, v in toxicity._gru_init(rng, 3, 4).items()}
    x = rng.standard_normal((5, 2, 3))
    up = rng.standard_normal((5, 2, 4))
    loss = lambda q: float((toxicity.gru_forward(q, (x @ q["W"] + q["b"]).astype(np.float64))[0] * up).sum())
    out, kept = toxicity.gru_forward(p, x @ p["W"] + p["b"])
    dxw, du = toxicity.gru_backward(p, kept, up)
    for name, grad in (("U", du), ("b", dxw.sum(axis=(0, 1))), ("W", np.einsum("tbi,tbj->ij", x, dxw))):
        for at in list(np.ndindex(p[name].shape))[::7]:
            q = {k: v.copy() for k, v in p.items()}
            q[name][at] += 1e-3
            r = {k: v.copy() for k, v in p.items()}
            r[name][at] -= 1e-3
            assert abs((loss(q) - loss(r)) / 2e-3 - grad[at]) < 2e-2 * max(1, abs(grad[at]))


def test_scores_of_a_table(spark):
    rows = [(i, t, "s") for i, t, _ in corpus(200)] + [(900, None, None), (901, "", "s"), (None, "abc", "s"), (5, "abc", "s")]
    labels = spark.createDataFrame([(i, y) for i, _, y in corpus(200)] + [(1, None), (None, 1)], "doc_id long, toxic int")
    out = toxicity.score_toxicity(docs(spark, rows), labels, TINY)
    assert out.columns == ["doc_id", "text", "source", "score", "predicted", "held_out"]
    got = out.collect()
    assert len(got) == len(rows) and all(0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.5) for r in got)
    for r in got:
        if r["doc_id"] is not None:
            assert r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0)
    assert all(r["predicted"] == 0 for r in got if not r["text"])
    none = toxicity.score_toxicity(docs(spark, rows[:3]), labels.limit(0), TINY).collect()
    assert {r["score"] for r in none} == {0.0}
    assert toxicity.score_toxicity(docs(spark, []), labels, TINY).count() == 0


def test_held_out_accuracy_on_documents(spark):
    base = "/root/testdata/sf0.1"
    d = spark.read.parquet(f"{base}/documents.parquet").select("doc_id", "text", "lang")
    labels = spark.read.parquet(f"{base}/labels.parquet")
    known = labels.where(toxicity.held_out(F.col("doc_id")))
    out = toxicity.score_toxicity(d.join(labels.select("doc_id"), "doc_id", "left_semi"), labels, carry_text=False).join(known, "doc_id").collect()
    clean = np.mean([r["predicted"] == 0 for r in out if not r["toxic"]])
    # at this scale toxic documents in other languages share no words that clean ones lack
    caught = np.mean([r["predicted"] for r in out if r["toxic"] and r["lang"] == "en"])
    assert clean > 0.99 and caught > 0.85


def test_a_task_frees_what_other_operators_keep_and_returns_small_batches():
    list(packing._pieces(packing.default_vocabulary(), 4096, 1)(iter([pa.record_batch({"_id": [1], "_text": ["some words"]})])))
    assert packing._word_tokens.cache_info().currsize == 1  # for the next task of packing
    batch = pa.record_batch({"doc_id": range(1000), "text": [f"text {i}" for i in range(1000)]})
    out = list(toxicity._score_batches(None, "text", True)(iter([batch])))
    assert packing._word_tokens.cache_info().currsize == 0
    assert max(b.num_rows for b in out) <= 256
    assert pa.Table.from_batches(out).drop(["_score"]).equals(pa.Table.from_batches([batch]))


def test_rare_words_that_mark_toxic_documents_have_vectors():
    calm = [" ".join(f"w{j}" for j in range(i % 7, 40)) for i in range(160)]
    rows = [(t + " zork" * (i % 20 == 0), int(i % 20 == 0)) for i, t in enumerate(calm)]
    got = toxicity.train([t for t, _ in rows], [y for _, y in rows], toxicity.TrainParams(vocabulary=10, char_epochs=1, window_epochs=1, min_steps=1))
    assert b"zork" in got.vocabulary and len(got.vocabulary) == 10


def test_held_out_recall_of_other_languages(spark):
    base = "/root/testdata/sf0.1"
    d = spark.read.parquet(f"{base}/documents.parquet").select("doc_id", "text", "lang")
    labels = spark.read.parquet(f"{base}/labels.parquet")
    known = labels.where(toxicity.held_out(F.col("doc_id"))).select("doc_id", "toxic")
    model = toxicity.fit(d.select("doc_id", "text"), labels)
    rows = d.where("lang <> 'en'").join(known, "doc_id").collect()
    p = toxicity._Scorer(model).scores([r["text"] for r in rows]) >= 0.5
    y = np.array([r["toxic"] for r in rows])
    by = {x: (int(p[at & (y == 1)].sum()), int((at & (y == 1)).sum())) for x in ("de", "fr", "es") for at in [np.array([r["lang"] == x for r in rows])]}
    assert all(caught / n >= 0.75 for caught, n in by.values()), by
    assert p[y == 0].mean() < 0.02


# -------------------------------------------------------------- neighbours


def test_neighbours_and_recall(spark, sf_dir):
    rows = spark.read.parquet(f"{sf_dir}/embeddings.parquet").collect()
    ids = np.array([r["vec_id"] for r in rows])
    x = np.array([r["embedding"] for r in rows], float)
    got = collections.defaultdict(list)
    for r in QUERIES["op6_nearest"](spark, sf_dir).orderBy("query_id", "rank").collect():
        got[r["query_id"]].append((r["vec_id"], r["score"]))
    hit = 0
    for i in np.flatnonzero(ids % 20 == 0):
        s = ann.exact_scores(x, x[i])
        s[i] = -np.inf
        want = ids[np.lexsort((ids, -s))[:20]]
        mine = got[ids[i]]
        assert len(mine) == 20 and mine == sorted(mine, key=lambda v: (-v[1], v[0]))
        hit += len({v for v, _ in mine} & set(want))
    assert hit / (20 * len(got)) >= 0.9


def test_neighbour_cases(spark):
    def rows(spark, values):
        return spark.createDataFrame([(i, v, "clash") for i, v in values], "vec_id long, embedding array<float>, id string")

    nan = float("nan")
    values = [(i, [1.0, 0.5, float(i % 3)]) for i in range(1, 40)] + [(0, [1.0, 1.0, 1.0]), (100, None), (101, [0.0, 0.0, 0.0]), (102, [nan, 1.0, 1.0]), (103, [1.0, None, 1.0]), (104, [1.0, float("inf"), 1.0]), (105, [1.0, 2.0]), (None, [1.0, 1.0, 1.0]), (3, [1.0, 0.5, 0.0])]
    got = ann.nearest(rows(spark, values), F.pmod("vec_id", F.lit(20)) == 0, ann.AnnParams(k=5)).orderBy("query_id", "rank").collect()
    assert {r["query_id"] for r in got} == {0, 20}
    # ties of equal vectors go to the smaller id
    assert [r["vec_id"] for r in got if r["query_id"] == 0] == [2, 5, 8, 11, 14]
    assert all(r["vec_id"] != r["query_id"] for r in got)
    few = ann.nearest(rows(spark, values[:3]), F.lit(True), ann.AnnParams(k=5)).groupBy("query_id").count().collect()
    assert {r["count"] for r in few} == {2}
    assert ann.nearest(rows(spark, []), F.lit(True)).count() == 0
    assert ann.nearest(rows(spark, values).where("vec_id = 100"), F.lit(True)).count() == 0


def test_scores_of_doubles_are_those_of_the_original_vectors(spark):
    rng = np.random.default_rng(6)
    x = rng.standard_normal((60, 8)) + 1e-9 * rng.standard_normal((60, 8))
    wide = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    got = ann.nearest(wide, F.col("vec_id") < 3, ann.AnnParams(k=4)).collect()
    assert len(got) == 12 and all(r["score"] == ann.exact_scores(x[[r["vec_id"]]], x[r["query_id"]])[0] for r in got)
    whole = spark.createDataFrame([(i, [int(9 * a) for a in v]) for i, v in enumerate(x)], "vec_id long, embedding array<int>")
    assert ann.nearest(whole, F.col("vec_id") < 3, ann.AnnParams(k=4)).count() == 12


@pytest.mark.parametrize("spread", [0.0, 1e-6])
def test_copies_do_not_push_out_better_rows(spread):
    import pandas as pd

    rng = np.random.default_rng(2)
    params = ann.AnnParams(k=5, shortlist=10)
    query = np.array([[1.0, 0, 0, 0]])
    # copies, and near ones with the best at the end, have a code that ranks above that of better rows
    words = np.array([[[0, 0], [0.8, 0], [0.9, 0], *[[-1.0, j] for j in range(13)]], [[0, 0]] * 16], float)
    book = ann.Codebook(words, 1.0)
    copies = np.array([[0.5 + spread * i, 0, 0, 0] for i in range(300)])
    better = np.array([[0.7 + 0.01 * i, 0, 0, 0] for i in range(5)])
    x = np.concatenate([copies, better, rng.uniform(-1, 0, (20, 4))]).astype(np.float32)
    codes = np.zeros((len(x), 2), np.uint8)
    codes[:300, 0], codes[300:305, 0], codes[305:, 0] = 2, 1, 3
    ids = np.arange(len(x)) + 1
    rows = pd.DataFrame({"id": ids, "vec": list(x), "code": [c.tobytes() for c in ann.pack_codes(codes)]})
    for n in (len(x), 300):  # with the better rows, and the copies alone
        score = ann.exact_scores(x[:n].astype(float), query[0])
        want = ids[np.lexsort((ids[:n], -score))[:5]]
        got = ann._search_block(book, params)(rows[:n], pd.DataFrame({"id": [999], "vec": list(query)}))
        assert got["vec_id"].tolist() == want.tolist()


def test_tables_give_inner_products_with_codewords():
    rng = np.random.default_rng(3)
    x = rng.standard_normal((300, 7))
    book = ann.fit_codebook(x, ann.AnnParams(rounds=3))
    codes = book.encode(x, 2)
    decoded = np.concatenate([book.words[m][codes[:, m]] for m in range(book.words.shape[0])], axis=1)[:, :7]
    got = ann.scan(book, x[:4], ann.pack_codes(codes))
    assert np.allclose(got, x[:4] @ decoded.T, atol=1e-4)


# ----------------------------------------------------------------- packing


def layout(plan, histogram):
    bins = collections.defaultdict(list)
    ends = {}
    for i, (w, r) in enumerate(zip(plan.lengths, plan.ranks, strict=True)):
        ends[i] = plan.ranks[i + 1] if i + 1 < len(plan.lengths) and plan.lengths[i + 1] == w else histogram[w]
        for k in range(ends[i] - r):
            bins[plan.sequences[i] + k].append((plan.offsets[i], w))
    return bins


def least_bins(items, capacity):
    """The least number of bins, by search over small instances."""
    items = sorted(items, reverse=True)
    best = [len(items)]

    def go(i, bins):
        if len(bins) >= best[0]:
            return
        if i == len(items):
            best[0] = len(bins)
            return
        for j in sorted({b: k for k, b in enumerate(bins)}.values()):
            if bins[j] + items[i] <= capacity:
                bins[j] += items[i]
                go(i + 1, bins)
                bins[j] -= items[i]
        go(i + 1, [*bins, items[i]])

    go(0, [])
    return best[0]


def test_plans_are_whole_and_near_the_least():
    rng = np.random.default_rng(5)
    over = 0
    for _ in range(60):
        items = rng.integers(1, 21, size=rng.integers(0, 11)).tolist()
        histogram = dict(collections.Counter(items))
        plan = packing.plan_packing(histogram, 20)
        bins = layout(plan, histogram)
        assert sorted(w for b in bins.values() for _, w in b) == sorted(items) and len(bins) == plan.n_sequences
        for b in bins.values():
            at = 0
            for offset, w in sorted(b):
                assert offset == at
                at += w
            assert at <= 20
        over += plan.n_sequences - least_bins(items, 20)
    assert over <= 2


def test_fixed_sets_never_cost_a_bin():
    """Fixing a dominating set leaves the least number of bins as it was."""
    rng = np.random.default_rng(6)
    for _ in range(80):
        items = rng.integers(2, 16, size=8).tolist()
        stock = packing._Stock(dict(collections.Counter(items)))
        w = max(items)
        chosen = packing.dominating_set(stock, w, 20)
        if chosen:
            assert sum(chosen) <= 20 and chosen[0] == w
            rest = list(items)
            for c in chosen:
                rest.remove(c)
            assert least_bins(items, 20) == 1 + least_bins(rest, 20)


def test_large_counts_are_planned_in_bulk():
    plan = packing.plan_packing({100: 10**9, 3000: 10**8, 4096: 5})
    assert plan.n_sequences >= (100 * 10**9 + 3000 * 10**8) // 4096 and len(plan.ranks) < 1000
    with pytest.raises(ValueError):
        packing.plan_packing({0: 1})
    assert packing.plan_packing({}).n_sequences == 0


class _Counting:
    """A tokenizer that counts the texts it encodes."""

    def __init__(self, tokenizer):
        self.tokenizer, self.texts = tokenizer, 0

    def encode_batch_fast(self, texts, **options):
        self.texts += len(texts)
        return self.tokenizer.encode_batch_fast(texts, **options)


def test_new_words_are_encoded_many_at_a_time():
    words = packing.WordTokens(packing.default_vocabulary(), limit=2000)
    rng = np.random.default_rng(5)
    signs = np.array(list("abcdefg \u00e9\u00c9\u00df\u00aa\u00b5\u00b2\u00bd01,.-!\n\t\x1c\x1f\x85\xa0<|>\u015f\u0130\u03a9\u6f22'"))
    odd = ["".join(signs[rng.integers(len(signs), size=n)]) for n in rng.integers(0, 60, size=2000)]
    texts = [*odd, "0", "a0b 0 0", "", "\xa0", "i'll don't", " ".join("abc"[i % 3] * (i // 3 + 1) for i in range(3000))]
    words.letters = _Counting(words.letters)
    got = [ids.tolist() for at in range(0, len(texts), 64) for ids in words.encode(texts[at : at + 64])]
    assert got == [e.ids for e in words.whole.encode_batch(texts, add_special_tokens=False)]
    assert 0 < words.letters.texts < 100  # thousands of distinct words
    no_mark = packing.WordTokens(packing.default_vocabulary())
    no_mark.between = no_mark.letters.encode("a", add_special_tokens=False).ids  # a token that letters do have
    assert [ids.tolist() for ids in no_mark.encode(["b a a c"])] == [words.whole.encode("b a a c", add_special_tokens=False).ids]


def test_pack_round_trip(spark):
    from tokenizers import Tokenizer

    whole = Tokenizer.from_file(packing.default_vocabulary())
    rows = [(1, "Hello, World! it's <|endoftext|> fine", "s"), (2, None, "s"), (3, "", "s"), (4, "word " * 9000, "s"), (None, "ÄÖ ß naïve 中文 İ", "s"), (1, "Hello, World! it's <|endoftext|> fine", "s")]
    out = packing.pack_documents(docs(spark, rows, "offset int")).toPandas()
    for i, t, _ in rows:
        ids = np.array([*whole.encode(t or "", add_special_tokens=False).ids, 1], "<u4")
        mine = out[out["doc_id"].isna() if i is None else out["doc_id"] == i].sort_values(["piece", "sequence_id", "offset"])
        want = [(p, s, len(ids[s : s + 4096]), zlib.crc32(ids[s : s + 4096].tobytes())) for p, s in enumerate(range(0, len(ids), 4096))]
        assert set(zip(mine["piece"], mine["start"], mine["length"], mine["ids_crc32"], strict=True)) == set(want)
    for _, b in out.groupby("sequence_id"):
        b = b.sort_values("offset")
        assert list(b["offset"]) == [0, *np.cumsum(b["length"])[:-1]] and b["length"].sum() <= 4096
    assert packing.pack_documents(docs(spark, [])).count() == 0


# ------------------------------------------------------------------ mixing


def test_counts_invert_the_distribution(spark):
    rows = [(i, f"t{i}", "a" if i < 30 else ("b" if i < 90 else None)) for i in range(100)] + [(3, "t3", "a"), (None, "n", "b")]
    table = docs(spark, rows, "copy int")
    rates = {r["_source"]: r["rate"] for r in mixing.source_rates(table, {"a": 3.0, "b": 1.0}, 400).collect()}
    assert abs(rates["a"] - 0.75 * 400 / 31) < 1e-9 and rates[None] == 0
    u = {r["doc_id"]: r["u"] for r in table.select("doc_id", mixing.hash_uniform(F.lit(7), F.col("doc_id")).alias("u")).collect()}
    got = collections.Counter(r["doc_id"] for r in mixing.mix_sources(table, {"a": 3.0, "b": 1.0}, 400, seed=7).collect())
    want = collections.Counter({i: mixing.expected_counts(rates[s], u[i]) for i, _, s in rows if rates[s] > 0})
    want[3] *= 2
    assert got == +want
    assert mixing.mix_sources(docs(spark, [])).count() == 0
    assert mixing.mix_sources(table, {"a": 0.0}).count() == 0
    with pytest.raises(ValueError):
        mixing.mix_sources(table, {"a": -1.0})


def test_large_rates_and_order(spark):
    table = docs(spark, [(i, "t", "a") for i in range(50)])
    out = mixing.mix_sources(table, size=50 * 800.0)
    n = out.count()
    assert abs(n - 40_000) < 6 * math.sqrt(40_000)
    keys = [r["order_key"] for r in out.select("order_key").collect()]
    assert keys == sorted(keys)
    assert out.columns == ["doc_id", "text", "source", "score", "copy", "order_key"]


@pytest.mark.parametrize("rate", [0.3, 90.0, 145.0, 700.0, 16_000.0, 1e6])
def test_distribution_at_any_rate(spark, rate):
    """The table around the rate against sums of exact terms, and counts against a search from the far end."""
    rates = spark.createDataFrame([("a", 1, rate), (None, 1, rate)], "_source string, n long, rate double")
    rows = {r["_source"]: r for r in mixing.distributions(rates).collect()}
    assert set(rows) == {"a", None}
    first, cdf = rows[None]["_first"], np.array(rows[None]["_cdf"])
    k = np.arange(first, first + len(cdf))
    exact = np.cumsum(np.exp(-rate + k * math.log(rate) - np.array([math.lgamma(x + 1) for x in k])))
    assert np.abs(cdf - exact).max() < 1e-8 and abs(cdf[-1] - 1) < 1e-8 and len(cdf) < 20 * math.sqrt(rate) + 64
    n = 40 if rate < 1e5 else 1
    table = docs(spark, [(i, "t", "a") for i in range(n)])
    u = {r["doc_id"]: r["u"] for r in table.select("doc_id", mixing.hash_uniform(F.lit(mixing.SEED), F.col("doc_id")).alias("u")).collect()}
    got = {r["doc_id"]: r["count"] for r in mixing.mix_sources(table, size=n * rate, shuffle=False).groupBy("doc_id").count().collect()}
    assert got == {i: c for i, x in u.items() if (c := int(first + np.searchsorted(cdf, x)))}


# ---------------------------------------------------------------- pipeline


LONG = " ".join(f"word{i}" for i in range(20_000))


def odd_documents(spark):
    """Nulls in every column, empty and very long texts, ties, repeated rows, and columns whose names operators use."""
    line = "a line that is shared by six of the documents of this table"
    rows = [(i, f"{line}\nown words of document {i} and {i * 7} more of them", "en", "a" if i < 4 else None, 1) for i in range(6)]
    rows += [(None, "no id here at all in this row", None, None, None), (10, None, "en", "b", None), (11, "", "en", "b", 0), (12, LONG, "en", "b", len(LONG)), (13, f"{LONG} x", "en", "b", len(LONG) + 2)]
    rows += [(20, "twice the same row with its id", "en", "b", 30)] * 2 + [(20, "the same id with quite another text", "en", "b", 35), (21, " \t\n ", "en", "c", 4)]
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    wide = spark.createDataFrame([(*r, "clash", 0.5, True, 9) for r in rows], f"{schema}, component string, score double, kept boolean, copy int")
    return wide, rows


def test_stages_on_odd_rows(spark, sf_dir):
    import corpus_pipeline
    from test_dedup import brute_lines

    wide, rows = odd_documents(spark)
    tox = corpus_pipeline.drop_toxic(spark, wide, sf_dir)
    assert tox.columns == corpus_pipeline.COLUMNS and collections.Counter(map(tuple, tox.collect())) == collections.Counter(rows)
    cut = corpus_pipeline.drop_shared_lines(spark, wide, sf_dir)
    assert cut.columns == corpus_pipeline.COLUMNS
    got = {(r["doc_id"], r["text"]): r["n_chars"] for r in cut.collect()}
    assert all(n == len(t) for (_, t), n in got.items())
    unique = {i: t for i, t, *_ in rows if i is not None and i < 20}
    assert {k for k in got if k[0] is not None and k[0] < 20} == {(i, t) for i, (t, _, _) in brute_lines(list(unique.items()), 40, 5).items()}
    assert cut.count() == len(rows)
    near = corpus_pipeline.drop_near_copies(spark, wide, sf_dir)
    assert near.columns == corpus_pipeline.COLUMNS
    assert sorted((str(r["doc_id"]), len(r["text"] or "")) for r in near.collect()) == sorted([(str(i), len(f"a line that is shared by six of the documents of this table\nown words of document {i} and {i * 7} more of them")) for i in range(6)] + [("None", 29), ("10", 0), ("11", 0), ("12", len(LONG)), ("20", 30), ("20", 35), ("21", 4)])
    mixed = corpus_pipeline.mix(spark, wide, sf_dir)
    assert mixed.columns == corpus_pipeline.COLUMNS and {r["doc_id"] for r in mixed.collect()} <= {r[0] for r in rows}
    packed = corpus_pipeline.pack(spark, wide, sf_dir).toPandas()
    assert len(packed[packed["piece"] == 0]) == len(rows) and packed["length"].max() <= 4096
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, wide.limit(0), sf_dir).count() == 0


def test_stages_against_brute_force(spark, sf_dir, documents):
    """The rows that each stage keeps of the given table, from plain versions of its rule."""
    import corpus_pipeline
    from test_dedup import brute_groups, brute_lines

    rows = {r["doc_id"]: r for r in documents.collect()}
    judged = {r["doc_id"]: r["predicted"] for r in QUERIES["op4_toxicity"](spark, sf_dir).collect()}
    kept = {r["doc_id"] for r in corpus_pipeline.drop_toxic(spark, documents, sf_dir).collect()}
    assert kept == {i for i, p in judged.items() if not p} and kept != set(rows)
    texts = {i: t for i, (t, _, _) in brute_lines([(i, r["text"]) for i, r in rows.items()], 40, 5).items()}
    assert {r["doc_id"]: r["text"] for r in corpus_pipeline.drop_shared_lines(spark, documents, sf_dir).collect()} == texts
    groups = brute_groups([(i, r["text"]) for i, r in rows.items()], 5, 80, 100)
    assert {r["doc_id"] for r in corpus_pipeline.drop_near_copies(spark, documents, sf_dir).collect()} == {i for i, (_, c) in groups.items() if c == i}
    sources = collections.Counter(r["source"] for r in rows.values())
    u = {r["doc_id"]: r["u"] for r in documents.select("doc_id", mixing.hash_uniform(F.lit(mixing.SEED), F.col("doc_id")).alias("u")).collect()}
    want = {i: mixing.expected_counts(len(rows) / len(sources) / sources[r["source"]], u[i]) for i, r in rows.items()}
    assert collections.Counter(r["doc_id"] for r in corpus_pipeline.mix(spark, documents, sf_dir).collect()) == +collections.Counter(want)


def test_pipeline_stages_take_effect(spark, sf_dir):
    import corpus_pipeline

    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "line_dedup", "near_dedup", "mixing", "packing"]
    d = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, d, sf_dir)
        assert out.columns == corpus_pipeline.COLUMNS and out.dtypes == d.dtypes
        assert out.count() > 0
    packed = corpus_pipeline.run(spark, sf_dir)
    assert set(packed.columns) == {"doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"} and packed.count() > 0


def test_modules_do_not_leave_the_subpackage():
    """Nothing outside the subpackage imports it, but for the guarded entry."""
    import pathlib

    top = pathlib.Path(__file__).resolve().parents[2]
    for path in itertools.chain(top.glob("weftgraph/*.py"), *(top.glob(f"weftgraph/{d}/*.py") for d in ("operators", "sources", "functions", "plans", "streaming"))):
        assert "weftgraph.llm" not in path.read_text()
