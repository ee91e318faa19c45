"""Training-data pipeline over ``documents``: five stages, each one operator.

Each stage gets what the stage before kept, written as Parquet and read again.
Stages but the last return the columns of ``documents``, whatever further
columns their input has; nulls of other columns pass unchanged.
An empty table gives an empty result in every stage.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from weftgraph.llm.line_dedup import line_dedup
from weftgraph.llm.mixing import mix_sources
from weftgraph.llm.near_dedup import NearDupParams, drop_near_duplicates
from weftgraph.llm.packing import pack_documents
from weftgraph.llm.toxicity import score_toxicity
from weftgraph.plans.common import forget, table, tables_made, written

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose toxicity score is below one half.

    Rows without a text get the score of an empty one, which is below one half
    unless most of the labelled sample is toxic. Repeated rows and null ids are
    judged like any other. Without labels of both classes all rows stay.
    """
    scored = score_toxicity(docs.select(*COLUMNS), table(spark, sf_dir, "labels"))
    return scored.where("predicted = 0").select(*COLUMNS)


def drop_shared_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without lines that five or more of them share; n_chars follows the text.

    No row goes: a document all of whose lines are shared stays with an empty
    text, as does one whose text is null or empty. Rows that repeat an id are
    one document where holders of a line are counted; null ids count by text.
    """
    return line_dedup(docs).withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group linked by five-word shingles at 0.8 or more, that of the smallest id.

    Texts without words are linked with nothing and stay. Of rows that repeat
    an id, those with unlike texts stay and of those with equal ones one does.
    Rows whose id is null stay.
    """
    return drop_near_duplicates(docs, NearDupParams(words=5, num=80, den=100)).select(*COLUMNS)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Equal weight for each source, as many documents as before in expectation.

    A null source is a source of its own. Each row comes as often as its count
    says, also never; rows that repeat an id, and all null ids, share a count.
    """
    return mix_sources(docs).select(*COLUMNS)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces and their places in sequences of 4096 tokens.

    A null or empty text is one piece of one token, the end mark. Repeated rows
    are packed each; a very long text is cut into full pieces and a rest.
    """
    return pack_documents(docs)


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("toxicity", drop_toxic),
    ("line_dedup", drop_shared_lines),
    ("near_dedup", drop_near_copies),
    ("mixing", mix),
    ("packing", pack),
]

#: SQL can express neither the learned scores nor the tokens.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the whole of ``documents``."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        before = tables_made()
        docs = written(stage(spark, docs, sf_dir), name)
        forget(spark, before, docs)  # what the stage wrote for itself is not read again
    return STAGES[-1][1](spark, docs, sf_dir)
