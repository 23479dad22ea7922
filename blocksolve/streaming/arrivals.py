"""Structured Streaming over events: observations that arrive, windows that are observations, late data, state and joins.

Every function takes a stream (or reads files as one) and returns a streaming DataFrame; ``drain`` runs it to the
end of what is there and returns the result as a table, so a stream can be compared with its batch.
"""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator
from typing import Any

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from blocksolve.operators import step
from blocksolve.sources.store import shared_dir

EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"



def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream of files."""
    if _is_folder(spark, f"{sf_dir}/events.parquet"):
        return spark.readStream.schema(EVENTS).parquet(f"{sf_dir}/events.parquet")
    return spark.readStream.schema(EVENTS).option("pathGlobFilter", "events.parquet").parquet(sf_dir)


def _is_folder(spark: SparkSession, path: str) -> bool:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(p).isDirectory()


def drain(stream: DataFrame, mode: str = "append", keys: list[str] | None = None) -> DataFrame:
    """Process all that is available, into files in the shared folder. Complete mode keeps the last batch; update mode keeps the last
    version of each of ``keys``."""
    if mode == "update" and not keys:
        raise ValueError("update mode needs the keys whose last version counts")
    spark = stream.sparkSession
    path = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")  # the same batch again writes the same place

    q = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{path}-state").trigger(availableNow=True).foreachBatch(put).start()
    q.awaitTermination()
    made = spark.read.option("basePath", path).parquet(f"{path}/batch=*")
    if mode == "complete":
        made = made.where(F.col("batch") == made.agg(F.max("batch")).first()[0])
    if mode == "update":
        rest = [c for c in made.columns if c not in (*keys, "batch")]
        return made.groupBy(*keys).agg(F.max_by(F.struct(*rest), "batch").alias("last")).select(*keys, "last.*")
    return made.drop("batch")


def in_turns(rows: DataFrame, turns: list[str], path: str) -> DataFrame:
    """A stream that delivers the rows that meet each condition of ``turns``, one micro-batch after the other. Files are taken by their time of writing."""
    for i, condition in enumerate(turns):
        rows.where(condition).coalesce(1).write.mode("append").parquet(f"{path}/turn={i:04d}")
    return rows.sparkSession.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).parquet(f"{path}/turn=*")


def tumbling(events: DataFrame, width: str = "1 day", slide: str | None = None, late: str = "2 hours") -> DataFrame:
    """start, n, total of tumbling or sliding windows; rows later than ``late`` are dropped once their window is closed."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.withWatermark("ts", late).groupBy(w).agg(F.count("*").alias("n"), F.sum("value").alias("total")).select(F.col("window.start").alias("start"), "n", "total")


def sessions(events: DataFrame, gap: str = "12 hours", late: str = "2 hours") -> DataFrame:
    """user_id, start, stop, n of sessions that end after a gap."""
    s = events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))
    return s.select("user_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("stop"), "n")


def purchases_after_views(events: DataFrame, within: str = "1 hour", late: str = "2 hours", first: str = "view", then: str = "purchase") -> DataFrame:
    """Pairs of one user's events of two types, the second within an hour of the first."""
    a = events.where(F.col("event_type") == first).select(F.col("event_id").alias("a"), F.col("ts").alias("ta"), F.col("user_id").alias("ua")).withWatermark("ta", late)
    b = events.where(F.col("event_type") == then).select(F.col("event_id").alias("b"), F.col("ts").alias("tb"), F.col("user_id").alias("ub")).withWatermark("tb", late)
    return a.join(b, F.expr(f"ua = ub AND tb >= ta AND tb <= ta + INTERVAL {within}")).select("a", "b", F.col("ua").alias("user_id"))


def labelled(events: DataFrame, labels: DataFrame) -> DataFrame:
    """A stream joined with a table: event_id, event_type, label."""
    return events.join(labels, "event_type").select("event_id", "event_type", "label")


def deduplicated(events: DataFrame, late: str = "2 hours") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


class _Counters(StatefulProcessor):
    """Visits and the sum of values of each row block, kept as state; emits the running numbers of each batch."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("counters", "visits bigint, total double")

    def handleInputRows(self, key: Any, rows: Iterator[pd.DataFrame], timerValues: Any) -> Iterator[pd.DataFrame]:
        visits, total = self.state.get() if self.state.exists() else (0, 0.0)
        for df in rows:
            visits, total = visits + len(df), total + float(df["value"].sum())
        self.state.update((visits, total))
        yield pd.DataFrame({"rb": [key[0]], "visits": [visits], "total": [total]})

    def close(self) -> None:
        pass


ROCKSDB = "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def counters(events: DataFrame, parts: int = 8) -> DataFrame:
    """rb, visits, total of each row block (users modulo ``parts``). State of this kind needs the RocksDB store, a setting of the session's streams."""
    events.sparkSession.conf.set("spark.sql.streaming.stateStore.providerClass", ROCKSDB)
    keyed = events.withColumn("rb", F.pmod("user_id", F.lit(parts)).cast("int")).select("rb", "value")
    return keyed.groupBy("rb").transformWithStateInPandas(_Counters(), outputStructType="rb int, visits bigint, total double", outputMode="Update", timeMode="None")


def _latest(spark: SparkSession, path: str) -> int:
    """The number of the last complete version under ``path``, -1 if there is none."""
    root = spark._jvm.org.apache.hadoop.fs.Path(path)
    fs = root.getFileSystem(spark._jsc.hadoopConfiguration())
    done = fs.globStatus(spark._jvm.org.apache.hadoop.fs.Path(f"{path}/batch=*/_SUCCESS")) or []
    return max((int(f.getPath().getParent().getName().removeprefix("batch=")) for f in done), default=-1)


def descend_on_arrival(observations: DataFrame, entries: DataFrame, x: DataFrame, beta: float = 1.0, path: str | None = None) -> tuple[DataFrame, Callable[[], DataFrame]]:
    """One block step for each micro-batch of observations (row_id, y): (the stream's query, a function that gives the x reached).

    The iterate is written with the number of its batch beside the stream's checkpoint, under ``path``. A stream that is started
    again there goes on from it; a batch that is delivered again is recognised by its number and skipped.
    """
    spark = observations.sparkSession
    path = path or f"{shared_dir(spark)}/arrivals-{uuid.uuid4().hex}"

    def reached() -> DataFrame:
        last = _latest(spark, f"{path}/x")
        return x if last < 0 else spark.read.schema(x.schema).parquet(f"{path}/x/batch={last}")

    def take(batch: DataFrame, number: int) -> None:
        if number <= _latest(spark, f"{path}/x") or batch.isEmpty():
            return
        now = reached()
        e = entries.join(batch.select("row_id"), "row_id", "left_semi").withColumn("grp", F.lit(0))
        r = step.true_residual(e.drop("grp"), batch.withColumn("rb", F.lit(0)).select("rb", "row_id", "y"), now)
        xg = step.with_x(step.back_project(e, r), now)
        f = step.forward_pair(e, xg)
        b = xg.select("cb", "grp").distinct().withColumn("beta", F.lit(beta))
        mu = step.step_length(xg, f, b)
        step.average(now, xg, mu, b.groupBy("cb").agg(F.count("*").alias("visits"))).write.mode("overwrite").parquet(f"{path}/x/batch={number}")

    q = observations.writeStream.option("checkpointLocation", f"{path}/stream").trigger(availableNow=True).foreachBatch(take).start()
    return q, reached
