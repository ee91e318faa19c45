"""Rows of tables that may repeat ids and texts."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from weftgraph.plans.common import cut


def one_row_each(rows: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """One row of those that repeat both id and text; only repeated rows are shuffled with their texts.

    Rows whose id is null are told apart by their texts alone. Which of
    several rows stays, where other columns differ, is not defined.
    """
    seen = rows.groupBy(F.col(id_col).alias("_i"), F.xxhash64(text_col).alias("_t")).count().where("count > 1")
    seen = cut(seen.select("_i", "_t"))
    if not seen.limit(1).count():
        return rows
    same = rows[id_col].eqNullSafe(seen["_i"]) & (F.xxhash64(rows[text_col]) == seen["_t"])
    return rows.join(seen, same, "left_anti").unionByName(rows.join(seen, same, "left_semi").dropDuplicates([id_col, text_col]))
