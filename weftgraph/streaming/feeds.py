"""Streams: edge upserts from tables, windows, sessions, stateful degrees, joins, deduplication.

Sources are files that Spark reads, replayed in order; sinks are versions of a
Parquet table in the shared folder. Every function works alike on a batch
frame where that makes sense, which is how results are checked.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from weftgraph.operators.modify import upsert
from weftgraph.plans.common import shared_dir, ship


def changes(events: DataFrame) -> DataFrame:
    """(op, src, dst, weight, ts, seq): errors delete an edge from a user to a key, all else sets its weight."""
    k = F.get_json_object("props", "$.k").cast("long")
    return events.select(F.when(F.col("event_type") == "error", "delete").otherwise("upsert").alias("op"), F.col("user_id").alias("src"), (F.lit(1_000_000) + k).alias("dst"), F.floor(F.col("value") * 100).cast("long").alias("weight"), "ts", F.col("event_id").alias("seq"))


def replay(spark: SparkSession, table: DataFrame, files: int = 4, ts: str = "ts") -> str:
    """Write a table as files by time, one after another, so that a stream meets them in this order.

    Returns the folder to stream from. Cuts are at quantiles of the time.
    """
    import uuid

    path = f"{shared_dir(spark).rstrip('/')}/replay-{uuid.uuid4().hex}"
    at = F.unix_micros(F.col(ts).cast("timestamp"))
    cuts = table.agg(F.percentile_approx(at, [i / files for i in range(1, files)], 1000)).head()[0] or []
    place = sum((F.when(at > c, 1).otherwise(0) for c in cuts), F.lit(0))
    for i in range(files):
        table.where(place == i).coalesce(1).write.mode("append").parquet(path)
    return path


def stream(spark: SparkSession, path: str, schema, files_per_batch: int = 1) -> DataFrame:
    """A file stream; ``ts`` becomes an instant, as watermarks need one."""
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def _empty(spark: SparkSession) -> DataFrame:
    return spark.range(0).select(F.col("id").alias("src"), F.col("id").alias("dst"), F.col("id").alias("weight"), F.lit(None).cast("timestamp").alias("ts"))


class UpsertFeed:
    """Apply change batches to a versioned edge table; a batch that comes again changes nothing.

    The state of a batch is written under its number, so a batch that was cut
    short is simply written over. A new feed on the same folder goes on from
    the last batch that was written whole; a folder therefore belongs to one
    stream checkpoint. The state before the last one is kept, older ones go.
    Deleted keys stay known as tombstones, so that late changes older than a
    deletion do not bring an edge back.
    """

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")
        self.done = max((n for n, whole in self._batches() if whole), default=-1)

    def _batches(self) -> list[tuple[int, bool]]:
        """Numbers of the states in the folder, and whether each was written whole."""
        place = self.spark._jvm.org.apache.hadoop.fs.Path(self.path)
        store = place.getFileSystem(self.spark._jsc.hadoopConfiguration())
        if not store.exists(place):
            return []
        names = [f.getPath() for f in store.listStatus(place) if f.getPath().getName().startswith("batch=")]
        return [(int(p.getName()[6:]), store.exists(self.spark._jvm.org.apache.hadoop.fs.Path(p, "_SUCCESS"))) for p in names]

    def _forget(self, before: int) -> None:
        for n, _ in self._batches():
            if n < before:
                place = self.spark._jvm.org.apache.hadoop.fs.Path(f"{self.path}/batch={n}")
                place.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(place, True)

    def state(self, batch_id: int | None = None) -> DataFrame:
        at = self.done if batch_id is None else batch_id
        if at < 0:
            return _empty(self.spark).withColumns({"gone": F.lit(False), "seq": F.lit(None).cast("long")})
        return self.spark.read.parquet(f"{self.path}/batch={at}")

    def edges(self) -> DataFrame:
        return self.state().where("NOT gone").select("src", "dst", "weight")

    def apply(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id <= self.done:
            return
        new = batch.groupBy("src", "dst").agg(F.max(F.struct("ts", "seq", "weight", "op")).alias("c")).select("src", "dst", "c.weight", "c.ts", (F.col("c.op") == "delete").alias("gone"), "c.seq")
        both = self.state().select("src", "dst", "weight", "ts", "gone", "seq").unionByName(new)
        last = both.groupBy("src", "dst").agg(F.max(F.struct("ts", "seq", "weight", "gone")).alias("c")).select("src", "dst", "c.weight", "c.ts", "c.gone", "c.seq")
        last.write.mode("overwrite").parquet(f"{self.path}/batch={batch_id}")
        before, self.done = self.done, batch_id
        self._forget(before)

    def run(self, source: DataFrame, checkpoint: str) -> None:
        """Drain a change stream."""
        q = source.writeStream.foreachBatch(self.apply).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
        q.awaitTermination()


def final_state(edges: DataFrame | None, all_changes: DataFrame) -> DataFrame:
    """(src, dst, weight): what the whole feed leaves, as one batch."""
    start = _empty(all_changes.sparkSession) if edges is None else edges
    return upsert(start, all_changes).select("src", "dst", "weight")


def windowed_counts(events: DataFrame, width: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """(start, event_type, n): edge changes in tumbling or sliding windows; rows later than ``late`` are dropped in streams."""
    win = F.window("ts", width, slide) if slide else F.window("ts", width)
    marked = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    return marked.groupBy(win.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "event_type", "n")


def trips(events: DataFrame, gap: str = "2 hours", late: str = "1 hour") -> DataFrame:
    """(user_id, start, end, n): sessions without a pause longer than ``gap``."""
    marked = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    return marked.groupBy("user_id", F.session_window("ts", gap).alias("s")).agg(F.count("*").alias("n")).select("user_id", F.col("s.start").cast("timestamp_ntz").alias("start"), F.col("s.end").cast("timestamp_ntz").alias("end"), "n")


def interval_pairs(origins: DataFrame, destinations: DataFrame, within: str = "6 hours", late: str = "1 hour") -> DataFrame:
    """(user_id, origin_id, dest_id): a user's destination events after an origin event, in a bound of time."""
    a = origins.select(F.col("user_id"), F.col("event_id").alias("origin_id"), F.col("ts").alias("t0")).withWatermark("t0", late)
    b = destinations.select(F.col("user_id").alias("u2"), F.col("event_id").alias("dest_id"), F.col("ts").alias("t1")).withWatermark("t1", late)
    return a.join(b, F.expr(f"user_id = u2 AND t1 > t0 AND t1 <= t0 + INTERVAL {within}")).select("user_id", "origin_id", "dest_id")


def once(events: DataFrame, key: str = "event_id", late: str = "1 hour") -> DataFrame:
    """Each key once while it is remembered."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark([key]) if events.isStreaming else events.dropDuplicates([key])


def degrees(all_changes: DataFrame) -> DataFrame:
    """(src, degree, head): running degree and latest key of each node, kept as state."""
    ship(all_changes.sparkSession)

    def step(key: tuple, rows: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        known = set(state.get[0].split(",")) - {""} if state.exists else set()
        head = state.get[1] if state.exists else 0
        for pdf in rows:
            for r in pdf.sort_values(["ts", "seq"]).itertuples():
                if r.op == "delete":
                    known.discard(str(r.dst))
                else:
                    known.add(str(r.dst))
                    head = int(r.dst)
        state.update((",".join(sorted(known)), head))
        yield pd.DataFrame({"src": [key[0]], "degree": [len(known)], "head": [head]})

    from pyspark.sql.streaming.state import GroupStateTimeout

    return all_changes.groupBy("src").applyInPandasWithState(step, "src long, degree long, head long", "known string, head long", "update", GroupStateTimeout.NoTimeout)


def drain(df: DataFrame, name: str, mode: str, checkpoint: str) -> DataFrame:
    """Run a streaming query over what is there and return its rows as a table."""
    spark = df.sparkSession
    if mode == "append":
        path = f"{checkpoint}-out"
        q = df.writeStream.format("parquet").outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start(path)
        q.awaitTermination()
        return spark.read.schema(df.schema).parquet(path)
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)
