"""Exact deduplication by progressive refinement.

Three passes, each over what the pass before could not tell apart:

1. rows are grouped by the length of their normalised text;
2. rows whose length is shared get a 64-bit hash of a prefix, and are grouped
   by length and prefix hash;
3. rows whose pair is shared get a SHA-256 of the whole normalised text, and
   only those rows are grouped by it.

Only lengths, hashes and ids are shuffled, never texts, as long as the set of
surviving pairs passes the size check of a broadcast; beyond it the digest is
computed before the shuffle, so texts stay where they are read in that case
too. Aggregates combine before each shuffle, and the last join is one that
adaptive execution can split, so a group may hold any share of the rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from weftgraph.llm.rows import one_row_each
from weftgraph.plans.common import BROADCAST_ROWS, checked_broadcast, cut

PREFIX_CHARS = 256


def normalised(text: Column) -> Column:
    """Every run of ASCII white space as one space; null as empty.

    The pattern leaves single spaces alone, which is the common case.
    """
    return F.regexp_replace(F.coalesce(text, F.lit("")), r"[\x09-\x0D][\x20\x09-\x0D]*|\x20[\x20\x09-\x0D]+", " ")


def exact_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", carry: dict[str, Column] | None = None, prefix_chars: int = PREFIX_CHARS, broadcast_rows: int = BROADCAST_ROWS) -> DataFrame:
    """One row per input row: id, keep_id, group_size, kept, text_sha256.

    ``text_sha256`` is the digest of the normalised text. ``carry`` names
    further columns, computed from the input row.

    Null text counts as empty text. Of equal texts the smallest id stays. A
    null id is never the one that stays unless its group has no other; rows
    that repeat both id and text count separately in ``group_size`` and share
    ``kept``. An empty table gives an empty result. Extra columns of the input
    are ignored.
    """
    norm = normalised(F.col(text_col))
    base = docs.select(F.col(id_col).alias("_id"), norm.alias("_t"))
    lengths = cut(base.groupBy(F.length("_t").alias("_n")).agg(F.count("*").alias("c")).where("c > 1").select("_n"))
    hinted_lengths = checked_broadcast(lengths, broadcast_rows)
    prefix = F.xxhash64(F.substring("_t", 1, prefix_chars))
    if hinted_lengths is lengths:  # hashes first, for the same reason
        shared = base.select(F.length("_t").alias("_n"), prefix.alias("_p")).join(lengths, "_n", "left_semi")
    else:
        shared = base.withColumn("_n", F.length("_t")).join(hinted_lengths, "_n", "left_semi").select("_n", prefix.alias("_p"))
    pairs = cut(shared.groupBy("_n", "_p").agg(F.count("*").alias("c")).where("c > 1").select("_n", "_p"))
    hinted = checked_broadcast(pairs, broadcast_rows)
    wide = base.select("_id", "_t", F.length("_t").alias("_n"), prefix.alias("_p"))
    if hinted is pairs:  # digests first, so that the shuffle of the join carries no texts
        rows = wide.select("_id", "_n", "_p", F.unhex(F.sha2("_t", 256)).alias("_h")).join(pairs, ["_n", "_p"], "left_semi")
    else:
        rows = wide.join(hinted, ["_n", "_p"], "left_semi").select("_id", "_n", "_p", F.unhex(F.sha2("_t", 256)).alias("_h"))
    groups = rows.groupBy("_n", "_p", "_h").agg(F.min("_id").alias("keep_id"), F.count("*").alias("group_size")).where("group_size > 1").select(F.hex("_h").alias("_k"), "keep_id", "group_size")
    out = docs.select(F.col(id_col).alias("_id"), F.upper(F.sha2(norm, 256)).alias("_k"), *[c.alias(k) for k, c in (carry or {}).items()])
    joined = out.join(groups, "_k", "left")
    keep = F.when(F.col("group_size").isNull(), F.col("_id")).otherwise(F.col("keep_id"))
    return joined.select(F.col("_id").alias(id_col), keep.alias("keep_id"), F.coalesce("group_size", F.lit(1).cast("long")).alias("group_size"), F.col("_id").eqNullSafe(keep).alias("kept"), F.lower("_k").alias("text_sha256"), *(carry or {}))


def drop_exact_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The input rows that stay: one row of each group of equal texts, that of the smallest id.

    Rows are judged by their texts: of rows that repeat an id those with other
    texts are not affected. Null text is empty text; a row whose id is null
    stays where no row of its group has an id. Of rows that repeat both id and
    text one stays, any of them. Columns pass unchanged, whatever their names;
    an empty table gives an empty result.
    """
    kept = exact_dedup(docs, id_col, text_col).where("kept").select(F.col(id_col).alias("_keep"), F.col("text_sha256").alias("_sha")).distinct()
    repeats = docs.groupBy(id_col).count().where("count > 1").limit(1).count()
    if not repeats:
        return docs.join(kept, docs[id_col].eqNullSafe(kept["_keep"]), "left_semi")
    same = docs[id_col].eqNullSafe(kept["_keep"]) & (F.sha2(normalised(docs[text_col]), 256) == kept["_sha"])
    # texts that differ in white space only are equal, so rows are told apart by the normalised text
    shown = docs.join(kept, same, "left_semi").withColumn("_equal_text", normalised(F.col(text_col)))
    return one_row_each(shown, id_col, "_equal_text").drop("_equal_text")
