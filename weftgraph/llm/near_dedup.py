"""Near-duplicate groups by compressed min-hash registers and exact checks.

1. Every whole text becomes a set of 64-bit shingle hashes. Each of K hash
   functions keeps its least value, compressed to a register: the count of
   leading zeros and ten mantissa bits. Bands of six registers are hashed.
   The number of bands follows from the threshold, so that a pair exactly at
   the threshold shares no band with a chance of at most ``MISS``.
2. Texts with equal sets are represented by their smallest id. Within each
   band bucket every representative is tied to the smallest one, and the
   components of those ties are families: a true link never leaves one.
3. Families are cut into blocks of bounded size. Inside a block, together
   with a few pivots of the family, pairs that are not yet connected are
   compared: first by the Jaccard estimate of their registers, corrected for
   chance collisions, then on their full sets. Of large families, members
   outside the largest component are then compared with every block. Only
   links that connect something new are emitted, so no group is expanded
   into its pairs and none is capped.
4. Components of the links are the groups.

Work inside a family grows with (members outside its main component) x
(members), spread over tasks of bounded size.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from weftgraph.llm.memory import give_back
from weftgraph.llm.rows import one_row_each
from weftgraph.operators.components import connected_components
from weftgraph.plans.common import cut, ordinal, other_key, written

BAND_ROWS, MISS, MANTISSA = 6, 1e-7, 10
BLOCK_DOCS, BLOCK_SHINGLES, PIVOTS = 64, 1 << 20, 8
_CACHE_WORDS = 150_000


@dataclass(frozen=True)
class NearDupParams:
    """Words in a shingle, and the threshold num/den of the Jaccard similarity."""

    words: int = 5
    num: int = 80
    den: int = 100

    @property
    def bands(self) -> int:
        return math.ceil(math.log(MISS) / math.log1p(-((self.num / self.den) ** BAND_ROWS)))


class _WordHashes(dict):
    """Word to 64-bit hash, bounded: it forgets all when it is full."""

    def __missing__(self, word: bytes) -> int:
        if len(self) >= _CACHE_WORDS:
            self.clear()
        value = self[word] = xxhash.xxh3_64_intdigest(word)
        return value


def _mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    h = (h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return h ^ (h >> np.uint64(32))


def shingle_set(text: str | None, words: int, cache: dict) -> np.ndarray:
    """Sorted distinct hashes of the text's shingles; empty without words."""
    parts = (text or "").encode("utf-8", "surrogatepass").lower().split()  # bytes: ASCII case and white space only
    if not parts:
        return np.empty(0, np.uint64)
    w = np.fromiter(map(cache.__getitem__, parts), np.uint64, len(parts))
    k = min(words, len(parts))
    n = len(parts) - k + 1
    h = np.full(n, k, np.uint64)
    for j in range(k):
        h = h * np.uint64(0x100000001B3) + w[j : j + n]
        h ^= h >> np.uint64(27)
    return np.unique(_mix(h))


def _multipliers(k: int) -> np.ndarray:
    return np.random.Generator(np.random.PCG64(20240229)).integers(0, 1 << 63, size=(k + 1) // 2, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def registers(shingles: np.ndarray, mult: np.ndarray, k: int) -> np.ndarray:
    """K registers: leading zeros and mantissa of each function's least 32-bit value."""
    least = np.full(2 * len(mult), 0xFFFFFFFF, np.uint32)
    for at in range(0, len(shingles), 1024):
        product = shingles[at : at + 1024, None] * mult[None, :]
        np.minimum(least, product.view(np.uint32).min(axis=0), out=least)
    m, e = np.frexp(least[:k].astype(np.float64))
    zero = least[:k] == 0
    mantissa = np.where(zero, 0, ((m * 2 - 1) * (1 << MANTISSA)).astype(np.int64))
    return (((32 - e) << MANTISSA) + mantissa).astype(np.uint16)


def band_keys(reg: np.ndarray, bands: int) -> np.ndarray:
    r = reg.reshape(bands, BAND_ROWS).astype(np.uint64)
    h = np.arange(bands, dtype=np.uint64) + np.uint64(1)
    for j in range(BAND_ROWS):
        h = _mix(h * np.uint64(0x100000001B3) + r[:, j])
    return h.view(np.int64)


def chance_match(n: int) -> float:
    """Chance that two unrelated registers of sets of about n shingles agree.

    The least of n uniform values has a density near n exp(-n v); the chance is
    the sum over register cells of the squared cell probability.
    """
    lz = np.arange(0, 33)
    lo = np.where(lz < 32, 2.0 ** (31 - lz), 0.0) / 2.0**32
    frac = np.arange(1 << MANTISSA) / (1 << MANTISSA)
    a = lo[:, None] * (1 + frac)[None, :]
    width = lo[:, None] / (1 << MANTISSA)
    p = np.exp(-n * a) - np.exp(-n * (a + width))
    return float((p * p).sum())


def _signatures(params: NearDupParams):
    bands, words = params.bands, params.words
    k = bands * BAND_ROWS

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache, mult = _WordHashes(), _multipliers(k)
        for batch in batches:
            ids, n, digest, keys = batch.column(0), [], [], []
            for text in batch.column(1).to_pylist():
                s = shingle_set(text, words, cache)
                n.append(len(s))
                digest.append(xxhash.xxh3_128_digest(s.tobytes()))
                keys.append(band_keys(registers(s, mult, k), bands) if len(s) else np.empty(0, np.int64))
            offsets = np.concatenate(([0], np.cumsum([len(x) for x in keys]))).astype(np.int32)
            flat = np.concatenate(keys) if keys else np.empty(0, np.int64)
            yield pa.RecordBatch.from_arrays([ids.cast(pa.int64()), batch.column(2), pa.array(n, pa.int64()), pa.array(digest, pa.binary()), pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(flat, pa.int64()))], names=["_id", "_row", "n", "digest", "bands"])
        give_back()

    return run


def _sets(params: NearDupParams):
    words, k = params.words, params.bands * BAND_ROWS

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache, mult = _WordHashes(), _multipliers(k)
        for batch in batches:
            nid, text, digest, rest = batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2).to_pylist(), batch.columns[3:]
            good, sets, regs = [], [], []
            for row, (t, d) in enumerate(zip(text, digest, strict=True)):
                s = shingle_set(t, words, cache)
                if xxhash.xxh3_128_digest(s.tobytes()) == d:  # else another row with the same id
                    good.append(row)
                    sets.append(s.tobytes())
                    regs.append(registers(s, mult, k).tobytes())
            at = pa.array(good, pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array([nid[i] for i in good], pa.int64()), pa.array(sets, pa.binary()), pa.array(regs, pa.binary()), *[c.take(at) for c in rest]], names=["nid", "shingles", "regs", *batch.schema.names[3:]])
        give_back()

    return run


def _find(parent: np.ndarray, x: int) -> int:
    while parent[x] != x:
        parent[x] = parent[parent[x]]
        x = parent[x]
    return x


def link_block(nids: np.ndarray, sets: list[np.ndarray], regs: np.ndarray, num: int, den: int, active: np.ndarray | None = None) -> list[tuple[int, int]]:
    """Links that connect the members of one block, each confirmed on full sets.

    ``active`` marks members of which pairs are wanted; None: all. Pairs that
    are already connected, or whose corrected estimate is five standard
    deviations under the threshold, are not compared.
    """
    m = len(nids)
    sizes = np.array([len(s) for s in sets], np.int64)
    vocabulary, ids = np.unique(np.concatenate(sets), return_inverse=True)
    ends = np.cumsum(sizes)
    starts = ends - sizes
    mark = np.zeros(len(vocabulary), bool)
    t, k = num / den, regs.shape[1]
    chance = chance_match(int(max(1, np.median(sizes))))
    floor = t - 5 * math.sqrt(t * (1 - t) / k)
    parent = np.arange(m)
    root = np.arange(m)
    links = []
    for x in range(m):
        if active is not None and not active[x]:
            continue
        others = np.arange(m) > x if active is None else (np.arange(m) > x) | ~active
        others &= root != root[x]
        # sizes alone rule out many pairs
        others &= (den * np.minimum(sizes, sizes[x]) >= num * np.maximum(sizes, sizes[x]))
        cand = np.flatnonzero(others)
        if not len(cand):
            continue
        estimate = ((regs[cand] == regs[x]).mean(axis=1) - chance) / (1 - chance)
        cand = cand[estimate >= floor]
        if not len(cand):
            continue
        mark[ids[starts[x] : ends[x]]] = True
        for y in cand:
            if root[y] == root[x]:
                continue
            common = int(np.count_nonzero(mark[ids[starts[y] : ends[y]]]))
            if den * common >= num * (int(sizes[x]) + int(sizes[y]) - common):
                links.append((int(nids[x]), int(nids[y])))
                a, b = _find(parent, x), _find(parent, int(y))
                parent[max(a, b)] = min(a, b)
                root = np.where(root == root[y], root[x], root)
        mark[ids[starts[x] : ends[x]]] = False
    return links


def _link_groups(params: NearDupParams):
    """mapInArrow over rows sorted by (g1, g2, g3): links of each group in turn."""
    num, den, k = params.num, params.den, params.bands * BAND_ROWS

    def emit(rows: list[tuple]) -> pa.RecordBatch:
        nids = np.array([r[0] for r in rows], np.int64)
        _, first = np.unique(nids, return_index=True)  # a pivot may come twice
        active = np.array([rows[i][3] for i in first], bool)
        sets = [np.frombuffer(rows[i][1], np.uint64) for i in first]
        regs = np.stack([np.frombuffer(rows[i][2], np.uint16)[:k] for i in first])
        links = link_block(nids[first], sets, regs, num, den, None if active.all() else active)
        return pa.RecordBatch.from_arrays([pa.array([a for a, _ in links], pa.int64()), pa.array([b for _, b in links], pa.int64())], names=["u", "v"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, rows = None, []
        for batch in batches:
            cols = [batch.column(i).to_pylist() for i in range(7)]
            for *group, nid, s, r, active in zip(*cols, strict=True):
                if group != key and rows:
                    yield emit(rows)
                    rows = []
                key = group
                rows.append((nid, s, r, active))
        if rows:
            yield emit(rows)
        give_back()

    return run


def _grouped(rows: DataFrame, params: NearDupParams) -> DataFrame:
    n = int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    dealt = rows.select("g1", "g2", "g3", "nid", "shingles", "regs", "active").repartition(n, "g1", "g2", "g3").sortWithinPartitions("g1", "g2", "g3", "nid")
    return dealt.mapInArrow(_link_groups(params), "u long, v long")


def _named(sig: DataFrame) -> DataFrame | None:
    """(_id, digest, name): a number for each id and set, in the order of ids; None if no id has two sets.

    Rows that repeat an id may differ in their texts. Then ids cannot stand
    for sets, and these numbers do.
    """
    with_set = sig.where("n > 0 AND _id IS NOT NULL")
    several = with_set.groupBy("_id").agg(F.min("digest").alias("a"), F.max("digest").alias("b")).where("a <> b")
    if not several.limit(1).count():
        return None
    return ordinal(with_set.select("_id", "digest").distinct(), ["_id", "digest"], "name")


def _components(base: DataFrame, sig: DataFrame, names: DataFrame | None, params: NearDupParams, tie_ids: bool) -> DataFrame:
    """(digest, name, component): the least name that links reach, for one name of each set.

    A name is an id, or a number of ``names``. ``tie_ids`` joins the sets of
    one id.
    """
    if names is None:
        whose = sig.where("n > 0 AND _id IS NOT NULL").withColumn("name", F.col("_id"))
    else:
        whose = sig.where("n > 0").join(names, ["_id", "digest"])
    # a text is fetched again by the id of its representative
    first = F.min(F.struct("name", "_id")).alias("r")
    reps = written(whose.groupBy("digest").agg(first, F.any_value("n").alias("n"), F.any_value("bands").alias("bands")).select("digest", F.col("r.name").alias("rep"), F.col("r._id").alias("rid"), "n", "bands"), "reps")
    spread = reps.select("rep", F.explode("bands").alias("band"))
    leads = spread.groupBy("band").agg(F.min("rep").alias("lead"), F.count("*").alias("c")).where("c > 1").select(other_key(F.col("band")).alias("jb"), "lead")
    ties = spread.withColumn("jb", other_key(F.col("band"))).join(leads, "jb").where("rep <> lead").select(F.col("rep").alias("u"), F.col("lead").alias("v")).distinct()
    family = connected_components(ties).withColumnsRenamed({"component": "family"})
    # members of families, dealt into blocks of bounded size
    member = cut(family.join(reps.select(F.col("rep").alias("nid"), "rid", "n", "digest"), "nid"))
    sizes = member.groupBy("family").agg(F.greatest(F.ceil(F.count("*") / BLOCK_DOCS), F.ceil(F.sum("n") / BLOCK_SHINGLES)).cast("int").alias("s"))
    sized = member.join(sizes.select(other_key(F.col("family")).alias("jf"), "s"), other_key(F.col("family")) == F.col("jf")).drop("jf")
    spot = F.xxhash64("nid", F.lit(7))
    few = F.pmod(F.shiftright(spot, 40), F.col("s") * BLOCK_DOCS) < PIVOTS  # about PIVOTS of a family
    sized = sized.withColumns({"block": F.pmod(spot, F.col("s")).cast("int"), "pivot": (F.col("s") > 1) & few})
    texts = base.join(sized, F.col("_id") == F.col("rid")).select("nid", "_text", "digest", "family", "s", "block", "pivot")
    full = written(texts.mapInArrow(_sets(params), "nid long, shingles binary, regs binary, family long, s int, block int, pivot boolean"), "sets")
    homes = F.when(F.col("pivot"), F.sequence(F.lit(0), F.col("s") - 1)).otherwise(F.array("block"))
    first = full.withColumns({"g1": F.col("family"), "g2": F.explode(homes), "g3": F.lit(0), "active": F.lit(True)})
    links = cut(_grouped(first, params))
    large = full.where("s > 1")
    if large.limit(1).count():
        links = links.unionByName(_outside_main(large, links, params))
    if names is not None:
        # equal sets of several ids, and with tie_ids the sets of one id, hold together
        links = links.unionByName(names.join(reps.select("digest", "rep"), "digest").where("name <> rep").select(F.col("name").alias("u"), F.col("rep").alias("v")))
        if tie_ids:
            leads = names.groupBy("_id").agg(F.min("name").alias("lead"))
            links = links.unionByName(names.join(leads, "_id").where("name <> lead").select(F.col("name").alias("u"), F.col("lead").alias("v")))
    found = connected_components(links)
    return reps.select("digest", F.col("rep").alias("name")).join(found, F.col("name") == F.col("nid"), "left").select("digest", "name", F.coalesce("component", "name").alias("component"))


def near_dup_groups(docs: DataFrame, params: NearDupParams = NearDupParams(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: id, n_shingles, component_id, kept.

    ``component_id`` is the smallest id that links reach. Texts without words
    (null, empty, white space) have an empty set and are linked with nothing.
    A text with fewer words than a shingle has one shingle, all its words.
    Rows that repeat an id stay separate rows of one document: what any of
    their texts is linked with is in its component. Rows whose id is null are
    linked with nothing, have a null component and are kept. An empty table
    gives an empty result; extra columns are ignored.
    """
    base, sig = _signed(docs, params, id_col, text_col)
    names = _named(sig)
    placed = _components(base, sig, names, params, tie_ids=True)
    if names is None:
        of_id = None
        named = placed.select("digest", F.col("component").alias("component_id"))
    else:
        back = names.select(F.col("name").alias("component"), F.col("_id").alias("component_id"))
        named = placed.join(back, "component").select("digest", "component_id")
        # a row without words shares the component of its id
        of_id = names.join(named, "digest").groupBy("_id").agg(F.min("component_id").alias("of_id"))
    out = sig.select("_id", "n", "digest").join(named, "digest", "left")
    component = F.when(F.col("n") > 0, F.col("component_id")).otherwise(F.col("_id"))
    if of_id is not None:
        out = out.join(of_id, "_id", "left")
        component = F.coalesce("of_id", component)
    component = F.when(F.col("_id").isNotNull(), component)
    return out.select(F.col("_id").alias(id_col), F.col("n").alias("n_shingles"), component.alias("component_id"), F.coalesce(F.col("_id") == component, F.lit(True)).alias("kept"))


def _signed(docs: DataFrame, params: NearDupParams, id_col: str, text_col: str) -> tuple[DataFrame, DataFrame]:
    """The texts by id, and the written signatures of all rows."""
    if not 0 < params.num / params.den <= 1:
        raise ValueError("the threshold must lie in (0, 1]")
    base = docs.select(F.col(id_col).cast("long").alias("_id"), F.col(text_col).alias("_text"), F.xxhash64(text_col).alias("_row"))
    return base, written(base.mapInArrow(_signatures(params), "_id long, _row long, n long, digest binary, bands array<long>"), "sig")


def _outside_main(large: DataFrame, links: DataFrame, params: NearDupParams) -> DataFrame:
    """Links of members outside their family's largest component, looked for in every block."""
    place = connected_components(links)
    state = cut(large.select("nid", "family", "s", "block").join(place, "nid", "left").withColumn("component", F.coalesce("component", "nid")))
    counted = state.groupBy("family", "component").count()
    main = counted.groupBy("family").agg(F.max(F.struct("count", (-F.col("component")).alias("least"))).alias("m")).select(other_key(F.col("family")).alias("jf"), (-F.col("m")["least"]).alias("main"))
    joined = state.join(main, other_key(F.col("family")) == F.col("jf")).drop("jf")
    outside = cut(joined.where("component <> main").select("nid", "family"))
    strays = outside.groupBy("family").agg(F.ceil(F.count("*") / BLOCK_DOCS).cast("int").alias("u"))
    strays = strays.select(other_key(F.col("family")).alias("jf"), "u")
    with_u = large.join(strays, other_key(F.col("family")) == F.col("jf")).drop("jf").join(outside.select(F.col("nid").alias("oid")), F.col("nid") == F.col("oid"), "left")
    with_u = written(with_u, "strays")
    ahead = with_u.withColumns({"g1": F.col("family"), "g3": F.col("block"), "g2": F.explode(F.sequence(F.lit(0), F.col("u") - 1)), "active": F.lit(False)})
    stray = with_u.where("oid IS NOT NULL").withColumns({"g1": F.col("family"), "g2": F.pmod(F.xxhash64("nid", F.lit(11)), F.col("u")).cast("int"), "g3": F.explode(F.sequence(F.lit(0), F.col("s") - 1)), "active": F.lit(True)})
    cols = ["g1", "g2", "g3", "nid", "shingles", "regs", "active"]
    return cut(_grouped(ahead.select(*cols).unionByName(stray.select(*cols)), params))


def drop_near_duplicates(docs: DataFrame, params: NearDupParams = NearDupParams(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The input rows that stay: of each group of linked texts one row, that of the smallest id.

    Rows are judged by their texts: rows that repeat an id and whose texts are
    not alike all stay, and of rows that repeat an id with equal sets of
    shingles (the empty set as well) one stays. All rows whose id is null
    stay. Columns pass unchanged, whatever their names; an empty table gives
    an empty result.
    """
    base, sig = _signed(docs, params, id_col, text_col)
    known = sig.where("_id IS NOT NULL")
    if not known.groupBy("_id").count().where("count > 1").limit(1).count():
        placed = _components(base, sig, None, params, tie_ids=False)
        gone = known.join(placed, "digest").where("_id <> component").select(F.col("_id").alias("_gone"))
        return docs.join(gone, docs[id_col].cast("long") == gone["_gone"], "left_anti")
    names = ordinal(known.where("n > 0").select("_id", "digest").distinct(), ["_id", "digest"], "name")
    placed = _components(base, sig, names, params, tie_ids=False)
    # the first name of each set, if it is also the first of its group
    stay = placed.where("name = component").select("digest", "name").join(names, ["digest", "name"]).select("_id", "digest")
    alive = known.join(stay.unionByName(known.where("n = 0").select("_id", "digest").distinct()), ["_id", "digest"]).groupBy("_id", "digest").agg(F.min("_row").alias("_stay")).select(F.col("_id").alias("_alive"), "_stay")
    kept = docs.join(alive, (docs[id_col].cast("long") == alive["_alive"]) & (F.xxhash64(docs[text_col]) == alive["_stay"]), "left_semi")
    return one_row_each(kept, id_col, text_col).unionByName(docs.where(F.col(id_col).isNull()))
