"""Helpers shared by the operators: table access, lineage cuts, checked
broadcasts and global ordinals.

Nothing here changes a setting that is fixed when the session starts.
"""

from __future__ import annotations

import re
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: Largest number of rows that a checked broadcast may carry.
BROADCAST_ROWS = 200_000


def ship(spark: SparkSession) -> None:
    """Send this package to the executors, once for each Spark context.

    Python workers import it by name; where it is not installed or on their
    path, this is how they find it.
    """
    sc = spark.sparkContext
    if getattr(sc, "_weftgraph_shipped", False):
        return
    top = Path(__file__).resolve().parents[1]
    archive = Path(tempfile.mkdtemp(prefix="weft-")) / "weftgraph.zip"
    with zipfile.ZipFile(archive, "w") as z:
        for path in sorted(top.rglob("*.py")):
            z.write(path, path.relative_to(top.parent))
    sc.addPyFile(str(archive))
    sc._weftgraph_shipped = True


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables, read by Spark from any store it knows."""
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share, from ``spark.checkpoint.dir``.

    Where the session names none, a temporary one is set if driver and
    executors are one process (tests); on a cluster it is an error.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        if not named and not re.fullmatch(r"local(\[.*\])?", sc.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        sc.setCheckpointDir(named or f"file://{tempfile.mkdtemp(prefix='weft-ckpt-')}")
    return named or sc._jsc.sc().getCheckpointDir().get()


_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def _release_shuffles(spark: SparkSession) -> None:
    """Let Spark delete the shuffle files of an execution when it ends, from now on in this session.

    What is materialised in the shared folder does not need them any more, and
    loops would otherwise keep the files of every round. The setting stays on,
    since threads of one session would else see one another's switching.
    """
    if spark.conf.get(_CLEANUP) != "true":
        spark.conf.set(_CLEANUP, "true")


def cut(df: DataFrame) -> DataFrame:
    """Cut the lineage with a reliable checkpoint in the shared folder."""
    ship(df.sparkSession)
    shared_dir(df.sparkSession)
    _release_shuffles(df.sparkSession)
    return _without_estimate(df.checkpoint(eager=True))


def _without_estimate(df: DataFrame) -> DataFrame:
    """The same rows as a plan of its own, without the size that Spark estimates for what they came from.

    A checkpoint keeps the estimate of its plan. Loops multiply it in every
    round, until the planner spends its time and memory on numbers of millions
    of digits; adaptive execution measures real sizes anyway.
    """
    spark = df.sparkSession
    rows = df._jdf.queryExecution().toRdd()
    return DataFrame(spark._jsparkSession.internalCreateDataFrame(rows, df._jdf.schema(), False), spark)


def written(df: DataFrame, label: str = "t") -> DataFrame:
    """Write ``df`` as Parquet into the shared folder and read it again.

    Smaller than a checkpoint (columnar, compressed) and prunable. The files
    go when the driver ends, or by ``forget``.
    """
    spark = df.sparkSession
    ship(spark)
    path = f"{shared_dir(spark).rstrip('/')}/{label}-{uuid.uuid4().hex}"
    _release_shuffles(spark)
    df.write.parquet(path)
    place = spark._jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(place)
    _made.append(path)
    return spark.read.schema(df.schema).parquet(path)


#: Paths of the tables that ``written`` made in this process and that still stand.
_made: list[str] = []


def tables_made() -> int:
    """How many tables ``written`` has made so far, as a mark for ``forget``."""
    return len(_made)


def forget(spark: SparkSession, since: int, keep: DataFrame | None = None) -> None:
    """Delete the tables made after a mark, but for the files of ``keep``.

    For callers that have materialised what they need of them.
    """
    held = set() if keep is None else {f.split("://")[-1].replace("file:", "").rsplit("/", 1)[0].lstrip("/") for f in keep.inputFiles()}
    stay = []
    for path in _made[since:]:
        if path.split("://")[-1].replace("file:", "").lstrip("/") in held:
            stay.append(path)
            continue
        place = spark._jvm.org.apache.hadoop.fs.Path(path)
        place.getFileSystem(spark._jsc.hadoopConfiguration()).delete(place, True)
    _made[since:] = stay


def checked_broadcast(df: DataFrame, limit: int = BROADCAST_ROWS) -> DataFrame:
    """``df`` with a broadcast hint if it has at most ``limit`` rows.

    The count stops at ``limit + 1`` rows. Beyond it the frame comes back
    without a hint, and Spark joins it by a shuffle.
    """
    few = df.limit(limit + 1).count() <= limit
    return F.broadcast(df) if few else df


def ordinal(df: DataFrame, keys: list[str], name: str = "ordinal", parts: int | None = None) -> DataFrame:
    """Add the 0-based place of each row in the order of ``keys``.

    A range shuffle and a sort inside each partition, then one offset per
    partition: no window over the whole table. The sorted rows are
    checkpointed so that both passes see the same partitions. Rows that tie
    in all keys get neighbouring places in any order.
    """
    n = parts or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    placed = cut(df.repartitionByRange(n, *keys).sortWithinPartitions(*keys).withColumn("_mono", F.monotonically_increasing_id()))
    part = F.shiftright("_mono", 33)
    sizes = placed.groupBy(part.alias("p")).count().collect()  # one row per partition
    offsets, total = {}, 0
    for r in sorted(sizes, key=lambda r: r["p"]):
        offsets[r["p"]], total = total, total + r["count"]
    if not offsets:
        return placed.withColumn(name, F.lit(0).cast("long")).drop("_mono")
    # one literal per partition that has rows, looked up by position
    lookup = F.array(*[F.lit(offsets.get(p, 0)).cast("long") for p in range(max(offsets) + 1)])
    place = F.element_at(lookup, (part + 1).cast("int")) + F.col("_mono").bitwiseAND(F.lit((1 << 33) - 1))
    return placed.withColumn(name, place).drop("_mono")


def running_sum(df: DataFrame, key: str, value: str, name: str) -> DataFrame:
    """Add the sum of ``value`` over all rows before each one in the order of ``key``, which must not repeat.

    As for ``ordinal``: a range shuffle, sums inside each partition, one offset per partition.
    """
    n = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    placed = cut(df.repartitionByRange(n, key).withColumn("_p", F.spark_partition_id()))
    sums = placed.groupBy("_p").agg(F.sum(value).alias("s")).collect()  # one row per partition
    offsets, total = {}, 0
    for r in sorted(sums, key=lambda r: r["_p"]):
        offsets[r["_p"]], total = total, total + (r["s"] or 0)
    lookup = F.array(*[F.lit(offsets.get(p, 0)).cast("long") for p in range(max(offsets, default=0) + 1)])
    before = F.coalesce(F.sum(value).over(Window.partitionBy("_p").orderBy(key).rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    return placed.withColumn(name, F.element_at(lookup, F.col("_p") + 1) + before).drop("_p")


def other_key(c: Column) -> Column:
    """A one-to-one image of a long key.

    Joining on it instead of the key makes Spark shuffle an aggregate that is
    already partitioned by the key once more, so that both sides of the join
    have an exchange of their own and adaptive execution can split a hot key.
    """
    return c.bitwiseXOR(F.lit(0x5DEECE66D2B79F31))
