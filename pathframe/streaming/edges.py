"""Edges that arrive over time: counts of use in tumbling, sliding and session windows, two-hop paths by interval joins,
paths of k hops by state of each node, and counts merged into a table batch by batch.

Rows later than the watermark are dropped by Spark and show in the progress of the query. Results go to Parquet in the
session's shared folder, with the batch that wrote them, so a batch that runs again replaces its own rows.
"""

from __future__ import annotations

import json
import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from ..sources.shared import shared_top


def events_stream(spark: SparkSession, folder: str, late: str = "1 hour") -> DataFrame:
    """The event table read as a stream, with its watermark; times without a zone are read in the session's."""
    schema = spark.read.parquet(f"{folder}/events.parquet").schema
    return spark.readStream.schema(schema).parquet(f"{folder}/events.parquet*").withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)


def windowed_edges(events: DataFrame, width: str = "1 day") -> DataFrame:
    """window_start, user, type, n: how often a user's edge to an event type was used in each tumbling window."""
    return events.groupBy(F.window("ts", width), "user_id", "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("window_start"), F.col("user_id").alias("user"), F.col("event_type").alias("type"), "n")


def two_hops(events: DataFrame, first: str = "click", then: str = "purchase", within: str = "1 day") -> DataFrame:
    """user, a, b: paths user -> event -> event, a first event and a later one of the same user within a span."""
    a = events.filter(F.col("event_type") == first).select(F.col("user_id").alias("user"), F.col("event_id").alias("a"), F.col("ts").alias("a_ts"))
    b = events.filter(F.col("event_type") == then).select(F.col("user_id").alias("b_user"), F.col("event_id").alias("b"), F.col("ts").alias("b_ts"))
    on = (F.col("user") == F.col("b_user")) & (F.col("b_ts") > F.col("a_ts")) & (F.col("b_ts") <= F.col("a_ts") + F.expr(f"INTERVAL {within}"))
    return a.join(b, on).select("user", "a", "b")


def sliding_edges(events: DataFrame, width: str = "1 day", slide: str = "12 hours") -> DataFrame:
    """window_start, user, type, n: uses of a user's edge to an event type in windows that overlap."""
    return events.groupBy(F.window("ts", width, slide), "user_id", "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").cast("timestamp_ntz").alias("window_start"), F.col("user_id").alias("user"), F.col("event_type").alias("type"), "n")


def session_edges(events: DataFrame, gap: str = "1 hour") -> DataFrame:
    """session_start, session_end, user, n: a user's events without a pause of `gap`, each session when it is over."""
    own = events.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return own.select(F.col("w.start").cast("timestamp_ntz").alias("session_start"), F.col("w.end").cast("timestamp_ntz").alias("session_end"), F.col("user_id").alias("user"), "n")


def k_hops(events: DataFrame, types: tuple[str, ...] = ("view", "click", "purchase"), within_s: int = 3600) -> DataFrame:
    """user, hops: paths of one user's events of the given types in order of time, the last within a span of the first.

    State holds, for each user, the begun paths that may still go on: those whose first event is within the span of the
    newest event. Events of a batch are taken in order of time; one that comes in a later batch than a newer event of its
    path's end doesn't extend that path.
    """
    k = len(types)

    def run(key, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        open_: list[list] = json.loads(state.get[0]) if state.exists else []  # [first time, last time, ids]
        rows = pd.concat(list(batches)).sort_values(["at", "event_id"])
        done = []
        for at, event, kind in zip(rows["at"].tolist(), rows["event_id"].tolist(), rows["event_type"].tolist(), strict=True):
            open_ = [p for p in open_ if at - p[0] <= within_s * 1_000_000]
            grown = [[p[0], at, [*p[2], event]] for p in open_ if types[len(p[2])] == kind and p[1] < at]
            done += [p[2] for p in grown if len(p[2]) == k]
            open_ += [p for p in grown if len(p[2]) < k]
            if types[0] == kind:
                if k == 1:
                    done.append([event])
                else:
                    open_.append([at, at, [event]])
        state.update((json.dumps(open_),))
        yield pd.DataFrame({"user": [key[0]] * len(done), "hops": pd.Series(done, dtype=object)})

    own = events.filter(F.col("event_type").isin(*types)).select("user_id", "event_id", "event_type", F.unix_micros("ts").alias("at"))
    return own.groupBy("user_id").applyInPandasWithState(run, "user long, hops array<long>", "open string", "append", GroupStateTimeout.NoTimeout)


def drained(stream: DataFrame, keys: list[str] | None = None, progress: list[dict] | None = None) -> DataFrame:
    """Run a stream until its input is used up and give its rows. With keys, rows are updates: the last of each counts.
    progress, if given, takes the reports of all batches (late_rows() reads them)."""
    spark = stream.sparkSession
    where = f"{shared_top(spark)}/stream-{uuid.uuid4().hex}"

    def write(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{where}/rows/part={number}")

    _ran(stream.writeStream.outputMode("update" if keys else "append").foreachBatch(write).option("checkpointLocation", f"{where}/state"), progress)
    rows = spark.read.schema(_with_batch(stream)).parquet(f"{where}/rows")
    if not keys:
        return rows.select(*stream.columns)
    return rows.groupBy(*keys).agg(*[F.max_by(c, "batch").alias(c) for c in stream.columns if c not in keys]).select(*stream.columns)


def _ran(writer, progress: list[dict] | None) -> None:
    query = writer.trigger(availableNow=True).start()
    query.awaitTermination()
    if progress is not None:
        progress += [json.loads(p.json) for p in query.recentProgress]


def late_rows(progress: list[dict]) -> int:
    """Rows that came after the watermark and were dropped, by the reports of a stream's batches."""
    return sum(op.get("numRowsDroppedByWatermark", 0) for p in progress for op in p.get("stateOperators", []))


def merged_counts(events: DataFrame, table: str, progress: list[dict] | None = None, state: str | None = None) -> DataFrame:
    """user, type, n in `table`, after each batch's counts are merged into those of the batches before.

    A batch writes version b + 1 from version b; its number is the batch's, so one that runs again writes the same
    version again, and the last whole version is the table. Give the same state folder to go on where a stream ended.
    """
    spark = events.sparkSession

    def merge(batch: DataFrame, number: int) -> None:
        own = batch.groupBy(F.col("user_id").alias("user"), F.col("event_type").alias("type")).agg(F.count(F.lit(1)).alias("n"))
        if number:
            own = own.unionByName(spark.read.schema(own.schema).parquet(f"{table}/v{number:08d}")).groupBy("user", "type").agg(F.sum("n").alias("n"))
        own.write.mode("overwrite").parquet(f"{table}/v{number + 1:08d}")

    where = state or f"{table}-state"
    _ran(events.writeStream.foreachBatch(merge).option("checkpointLocation", where), progress)
    jvm = spark.sparkContext._jvm
    top = jvm.org.apache.hadoop.fs.Path(table)
    fs = top.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    versions = sorted(s.getPath().getName() for s in fs.listStatus(top) if fs.exists(jvm.org.apache.hadoop.fs.Path(s.getPath(), "_SUCCESS")))
    return spark.read.parquet(f"{table}/{versions[-1]}")


def _with_batch(stream: DataFrame):
    from pyspark.sql.types import IntegerType, StructType

    return StructType([*stream.schema.fields]).add("batch", IntegerType())
