"""Packing documents into sequences: dominance reduction, then best fit.

Texts are tokenised once, in Arrow batches, and become pieces of at most
``capacity`` tokens. Only the histogram of piece lengths, which has at most
``capacity`` rows, reaches the driver. There, sets of lengths that provably
dominate every alternative for their largest member are fixed in bulk, again
and again, until no rule applies; best fit in decreasing order places what
remains, also in bulk. The plan is a table of runs (length, first rank, ranks,
first sequence, offset). Each piece gets its rank among pieces of its length
from a range sort with two passes and takes its place from the plan.
"""

from __future__ import annotations

import bisect
import functools
import os
import re
import struct
import zlib
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import compress
from operator import not_

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from weftgraph.llm.memory import give_back, keep, make_room
from weftgraph.plans.common import ordinal, written

CAPACITY, END_ID = 4096, 1
_CACHE_WORDS, _CACHE_TEXTS = 400_000, 20_000


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


#: Letters of Latin-1 in lower case, and what the tokenizer takes as white space there.
_LETTERS, _WHITE = "a-z\u00aa\u00b5\u00ba\u00df-\u00f6\u00f8-\u00ff", "\t-\r \u0085\u00a0"
_RUNS = re.compile(f"[{_LETTERS}]+|[^{_LETTERS}{_WHITE}]+")
#: Stands between words that are encoded as one text; it is no letter, so it is a token of its own.
_BETWEEN = "0"


class WordTokens:
    """Token ids of whole texts, with a bounded memory of their parts.

    The tokenizer drops white space, and no token crosses it or the border of
    letters and other characters. A text's ids are therefore those of its
    parts one after another. Texts in Latin-1 without apostrophes (which join
    letters) and special tokens are put in lower case and cut into runs of
    letters and of other characters; there, the tokenizer's normalisation
    changes nothing more, so letters are encoded by one that has the same
    model without it, many runs in one text with ``_BETWEEN`` between them.
    Other texts are cut at spaces and newlines only. Each distinct part is
    encoded once until the memory is full and starts anew.
    """

    def __init__(self, vocabulary: str, limit: int = _CACHE_WORDS):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # one task, one core
        from tokenizers import Tokenizer
        from tokenizers.pre_tokenizers import ByteLevel, Sequence, Split

        self.whole, self.limit = Tokenizer.from_file(vocabulary), limit
        self.letters = Tokenizer(self.whole.model)  # the same model, not a copy
        self.letters.pre_tokenizer = Sequence([Split(_BETWEEN, "isolated"), ByteLevel(add_prefix_space=False, use_regex=False)])
        self.between = self.letters.encode(_BETWEEN, add_special_tokens=False).ids
        self.known: dict[str, bytes] = {}
        self.texts: dict[bytes, list[tuple]] = {}

    @staticmethod
    def cut(text: str) -> tuple[bool, list[str]]:
        if "'" not in text and "<|" not in text:
            try:
                text.encode("latin-1")
            except UnicodeEncodeError:
                pass
            else:
                return True, _RUNS.findall(text.lower())
        return False, text.replace("\n", " ").split(" ")

    def _learn(self, tokenizer, parts: list[str]) -> None:
        for at in range(0, len(parts), 4096):
            some = parts[at : at + 4096]
            for part, code in zip(some, tokenizer.encode_batch_fast(some, add_special_tokens=False), strict=True):
                ids = code.ids
                self.known[part] = struct.pack(f"<{len(ids)}I", *ids)

    def _learn_letters(self, parts: list[str]) -> None:
        for at in range(0, len(parts), 1024):
            some = parts[at : at + 1024]
            ids = np.array(self.letters.encode_batch_fast([_BETWEEN.join(some)], add_special_tokens=False)[0].ids, "<u4")
            ends = np.flatnonzero(ids == self.between[0]).tolist() if len(self.between) == 1 else []
            if len(ends) != len(some) - 1:  # not a token that letters never have
                self._learn(self.letters, some)
                continue
            raw = ids.tobytes()
            for part, start, end in zip(some, [0, *[e + 1 for e in ends]], [*ends, len(ids)], strict=True):
                self.known[part] = raw[4 * start : 4 * end]

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        if len(self.known) > self.limit:
            self.known = {}
        split = [self.cut(t) for t in texts]
        found = [list(map(self.known.get, parts)) for _, parts in split]
        gaps = [list(compress(range(len(f)), map(not_, f))) for f in found]
        runs, words = set(), set()
        for (simple, parts), at in zip(split, gaps, strict=True):
            (runs if simple else words).update([parts[i] for i in at])
        self._learn_letters([p for p in runs if p[0].isalpha()])
        self._learn(self.whole, list(words.union(p for p in runs if not p[0].isalpha())))
        for (_, parts), f, at in zip(split, found, gaps, strict=True):
            for i in at:
                f[i] = self.known[parts[i]]
        return [np.frombuffer(b"".join(f), "<u4") for f in found]


@functools.lru_cache(maxsize=2)
def _word_tokens(vocabulary: str) -> WordTokens:
    """One encoder for all tasks of a worker process, until another operator needs the room."""
    keep("packing", _word_tokens.cache_clear)
    return WordTokens(vocabulary)


def pieces_of(ids: np.ndarray, capacity: int) -> list[tuple[int, int, int, int]]:
    """(piece, start, length, checksum) of a document's ids."""
    out = []
    for piece, start in enumerate(range(0, len(ids), capacity)):
        part = ids[start : start + capacity]
        out.append((piece, start, len(part), zlib.crc32(part.tobytes())))
    return out


def _pieces(vocabulary: str, capacity: int, end_id: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make_room("packing")
        words = _word_tokens(vocabulary)
        end = np.array([end_id], "<u4")
        for batch in batches:
            ids, rows = batch.column(0).to_pylist(), []
            for at in range(0, len(ids), 64):  # bounds the words held at once
                some = [t or "" for t in batch.column(1).slice(at, 64).to_pylist()]
                # copies of a text that is remembered are not cut again
                keys = [xxhash.xxh3_128_digest(t.encode("utf-8", "surrogatepass")) for t in some]
                new = {k: t for k, t in zip(keys, some, strict=True) if k not in words.texts}
                done = dict(zip(new, (pieces_of(np.concatenate([tokens, end]), capacity) for tokens in words.encode(list(new.values()))), strict=True))
                for doc_id, k in zip(ids[at : at + 64], keys, strict=True):
                    rows += [(doc_id, *p) for p in done.get(k) or words.texts[k]]
                if len(words.texts) > _CACHE_TEXTS:
                    words.texts.clear()
                words.texts.update((k, p) for k, p in done.items() if len(p) == 1)
            cols = list(zip(*rows, strict=True)) if rows else [[]] * 5
            kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names=["_id", "piece", "start", "length", "ids_crc32"])
        batch = ids = rows = cols = some = keys = new = done = words = None  # else they outlive this
        give_back()

    return run


@dataclass
class Plan:
    """Runs of equal placements, sorted by (length, first rank)."""

    lengths: list[int]
    ranks: list[int]
    sequences: list[int]
    offsets: list[int]
    n_sequences: int
    n_fixed: int


class _Stock:
    """Counts by length, with the distinct lengths still in stock in order."""

    def __init__(self, counts: dict[int, int]):
        self.counts = {k: v for k, v in counts.items() if v > 0}
        self.order = sorted(self.counts)

    def take(self, length: int, n: int) -> None:
        self.counts[length] -= n
        if not self.counts[length]:
            del self.counts[length]
            self.order.remove(length)

    def largest_up_to(self, bound: int, used: list[int]) -> int:
        """The largest length <= bound of which more are in stock than in ``used``; 0 if none."""
        i = bisect.bisect_right(self.order, bound)
        while i:
            i -= 1
            if self.counts[self.order[i]] > used.count(self.order[i]):
                return self.order[i]
        return 0

    def smallest(self, n: int, used: list[int]) -> list[int]:
        """The n smallest pieces in stock besides ``used``."""
        out: list[int] = []
        for w in self.order:
            free = self.counts[w] - used.count(w)
            out += [w] * min(max(free, 0), n - len(out))
            if len(out) == n:
                break
        return out


def dominating_set(stock: _Stock, w: int, capacity: int) -> list[int] | None:
    """A set holding one piece of length w that dominates every other such set.

    A feasible set dominates another if the other's pieces can be dealt into
    groups, each no longer than one piece of the first. Provable cases:
    nothing fits beside w; a single piece fills the rest exactly; at most one
    more piece fits, then the largest; at most two more fit and the largest
    single is as long as the best pair together; at most two more fit and the
    largest single, with the best partner it leaves room for, is in no place
    shorter than any other pair.
    """
    rest = capacity - w
    low = stock.smallest(3, [w])
    if not low or low[0] > rest:
        return [w]
    k = stock.largest_up_to(rest, [w])
    if k == rest or len(low) < 2 or low[0] + low[1] > rest:
        return [w, k]
    if len(low) == 3 and sum(low) <= rest:
        return None
    # at most two more fit: the best pair, and the longest shorter member of a pair
    best, longest_second = 0, 0
    for a in stock.order:
        if a + low[0] > rest or stock.counts[a] <= [w].count(a):
            continue
        b = stock.largest_up_to(min(rest - a, a), [w, a])
        if b:
            best, longest_second = max(best, a + b), max(longest_second, b)
    if k >= best:
        return [w, k]
    partner = stock.largest_up_to(rest - k, [w, k])
    if partner and partner >= longest_second:
        return [w, k, partner]
    return None


def plan_packing(histogram: dict[int, int], capacity: int = CAPACITY) -> Plan:
    """Place ``histogram`` (pieces by length) into few sequences."""
    if any(not 0 < w <= capacity for w in histogram):
        raise ValueError("lengths must lie in 1..capacity")
    stock, used = _Stock(dict(histogram)), dict.fromkeys(histogram, 0)
    runs: list[tuple[int, int, int, int]] = []
    sequences = 0

    def place(length: int, n: int, first: int, offset: int) -> None:
        runs.append((length, used[length], first, offset))
        used[length] += n

    changed = True
    while changed:  # reduction: longest first, until no rule applies
        changed = False
        for w in sorted(stock.order, reverse=True):
            while w in stock.counts:
                chosen = dominating_set(stock, w, capacity)
                if chosen is None:
                    break
                times = min(stock.counts[x] // chosen.count(x) for x in set(chosen))
                offset = 0
                for x in chosen:
                    place(x, times, sequences, offset)
                    offset += x
                for x in set(chosen):
                    stock.take(x, times * chosen.count(x))
                sequences += times
                changed = True
    fixed = sequences
    # best fit decreasing on what is left: groups of sequences by the room they have
    room: dict[int, list[tuple[int, int]]] = {}
    rooms: list[int] = []

    def put(space: int, first: int, n: int) -> None:
        if space not in room:
            room[space] = []
            bisect.insort(rooms, space)
        room[space].append((first, n))

    for w in sorted(stock.order, reverse=True):
        left = stock.counts[w]
        while left:
            i = bisect.bisect_left(rooms, w)
            if i < len(rooms):
                space = rooms[i]
                first, n = room[space].pop()
                if not room[space]:
                    del room[space]
                    rooms.pop(i)
            else:
                space, first, n = capacity, sequences, -(-left // (capacity // w))
                sequences += n
            each = min(space // w, left)
            whole = min(n, left // each)
            for j in range(each):
                place(w, whole, first, capacity - space + j * w)
            left -= whole * each
            put(space - each * w, first, whole)
            if whole < n:
                put(space, first + whole, n - whole)
    runs.sort()
    return Plan([r[0] for r in runs], [r[1] for r in runs], [r[2] for r in runs], [r[3] for r in runs], sequences, fixed)


def _placed(plan: Plan, starts: dict[int, int]):
    """mapInArrow: the place of each piece from its length and global ordinal."""
    at = np.array([starts[w] + r for w, r in zip(plan.lengths, plan.ranks, strict=True)], np.int64)
    sequence, offset = np.array(plan.sequences, np.int64), np.array(plan.offsets, np.int64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            i = batch.schema.get_field_index("ordinal")
            place = batch.column(i).to_numpy(zero_copy_only=False)
            slot = np.searchsorted(at, place, side="right") - 1
            yield pa.RecordBatch.from_arrays([*batch.columns[:i], pa.array(sequence[slot] + place - at[slot]), pa.array(offset[slot])], names=[*batch.schema.names[:i], "sequence_id", "offset"])

    return run


def pack_documents(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", vocabulary: str | None = None, capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """One row per piece: id, piece, start, length, ids_crc32, sequence_id, offset.

    A document is its token ids and ``end_id``; null and empty texts are that
    one id. Only documents longer than ``capacity`` are cut. Repeated rows and
    null ids are packed like any other row. An empty table gives an empty
    result; extra columns are ignored. ``vocabulary`` is a path that every
    executor can open, as the tokenizer files are installed with Python.
    """
    vocabulary = vocabulary or default_vocabulary()
    base = docs.select(F.col(id_col).cast("long").alias("_id"), F.col(text_col).alias("_text"))
    pieces = written(base.mapInArrow(_pieces(vocabulary, capacity, end_id), "_id long, piece int, start long, length long, ids_crc32 long"), "pieces")
    histogram = {r["length"]: r["count"] for r in pieces.groupBy("length").count().collect()}  # at most `capacity` rows
    plan = plan_packing(histogram, capacity)
    starts, total = {}, 0
    for w in sorted(histogram):
        starts[w], total = total, total + histogram[w]
    ranked = ordinal(pieces, ["length", "_id", "piece", "ids_crc32"]).select("_id", "piece", "start", "length", "ids_crc32", "ordinal")
    out = ranked.mapInArrow(_placed(plan, starts), "_id long, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
    return out.withColumnRenamed("_id", id_col)
