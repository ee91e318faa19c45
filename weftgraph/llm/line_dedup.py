"""Deletion of lines that many documents share.

Lines are exploded, normalised and hashed to 128 bits; documents are counted
per hash; lines of hashes over the threshold go, except in one document; what
stays is joined again by position. Texts move once, to meet the positions
their document loses; the counts move only hashes and ids.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from weftgraph.plans.common import other_key, written

MIN_CHARS, MIN_DOCS = 40, 5
_SPACE = " \t\n\x0b\x0c\r"
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def line_key(line: Column) -> Column:
    """ASCII white space stripped at both ends, A-Z lower-cased."""
    return F.translate(F.btrim(line, F.lit(_SPACE)), _UPPER, _LOWER)


def _lines(docs: DataFrame, id_col: str, text_col: str) -> Column:
    return F.split(F.coalesce(F.col(text_col), F.lit("")), "\n", -1)


def _eligible(docs: DataFrame, id_col: str, text_col: str, min_chars: int) -> DataFrame:
    """(_id, _row, _pos, h1, h2) of each line long enough to be dropped."""
    lines = docs.select(F.col(id_col).alias("_id"), F.xxhash64(text_col).alias("_row"), F.posexplode(_lines(docs, id_col, text_col)).alias("_pos", "_line"))
    trimmed = lines.where(F.length("_line") >= min_chars).withColumn("_k", line_key(F.col("_line"))).where(F.length("_k") >= min_chars)
    return trimmed.select("_id", "_row", "_pos", F.xxhash64("_k").alias("h1"), F.xxhash64(F.lit("second"), F.col("_k")).alias("h2"))


def shared_lines(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = MIN_CHARS, min_docs: int = MIN_DOCS) -> DataFrame:
    """(h1, h2, n_docs, keep_id) of the line keys in ``min_docs`` documents or more.

    A document is a distinct pair of id and text, so that repeated rows and
    lines that recur inside a text count once.
    """
    return _shared(_eligible(docs, id_col, text_col, min_chars), min_docs)


def _shared(lines: DataFrame, min_docs: int) -> DataFrame:
    once = lines.groupBy("h1", "h2", "_id", "_row").agg(F.lit(1).alias("x"))
    return once.groupBy("h1", "h2").agg(F.count("*").alias("n_docs"), F.max("_id").alias("keep_id")).where(F.col("n_docs") >= min_docs)


def line_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", min_chars: int = MIN_CHARS, min_docs: int = MIN_DOCS) -> DataFrame:
    """The input rows with ``text`` cut, and n_lines and n_dropped beside it.

    Lines end at ``\\n``; a null or empty text is one empty line, and comes
    back as empty. Of a shared line only the document with the largest id
    keeps its lines. A null id is smaller than any other; a repeated row is
    treated as the row it repeats. Extra columns stay as they are, except
    columns named n_lines or n_dropped, which are replaced.
    """
    hashed = written(_eligible(docs, id_col, text_col, min_chars), "lines")  # hashes and places, read twice
    gone = _shared(hashed, min_docs).select(other_key(F.col("h1")).alias("j1"), other_key(F.col("h2")).alias("j2"), "keep_id")
    lines = hashed.withColumns({"j1": other_key(F.col("h1")), "j2": other_key(F.col("h2"))})
    hits = lines.join(gone, ["j1", "j2"]).where(~F.col("_id").eqNullSafe(F.col("keep_id")))
    cuts = hits.groupBy("_id", "_row").agg(F.collect_set("_pos").alias("_cuts")).withColumnsRenamed({"_id": "_cid", "_row": "_crow"})
    rows = docs.drop("n_lines", "n_dropped").withColumn("_row", F.xxhash64(text_col))
    met = rows.join(cuts, rows[id_col].eqNullSafe(cuts["_cid"]) & (rows["_row"] == cuts["_crow"]), "left")
    # columns of their own: inside the lambda they must not be computed for each line
    split = met.withColumn("_parts", _lines(docs, id_col, text_col))
    placed = split.withColumn("_keep", F.when(F.col("_cuts").isNotNull(), F.array_except(F.sequence(F.lit(0), F.size("_parts") - 1), "_cuts")))
    kept = F.when(F.col("_cuts").isNull(), F.coalesce(F.col(text_col), F.lit(""))).otherwise(F.array_join(F.transform("_keep", lambda i: F.get("_parts", i)), "\n"))
    return placed.withColumns({text_col: kept, "n_lines": F.size("_parts").cast("long"), "n_dropped": F.coalesce(F.size("_cuts"), F.lit(0)).cast("long")}).drop("_row", "_cid", "_crow", "_cuts", "_parts", "_keep")
