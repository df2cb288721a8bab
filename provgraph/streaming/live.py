"""Live auditing with Structured Streaming. Inputs are event rows as in the event table; times become instants for watermarks."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.stateful_processor import StatefulProcessor, StatefulProcessorHandle

from provgraph.operators import versioning
from provgraph.plans.iterate import materialize, shared_dir
from provgraph.sources.carriers import accesses_of

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def audit_source(spark: SparkSession, folder: str, files_per_trigger: int = 1) -> DataFrame:
    """A stream of the Parquet files of a folder, with ``at``, the event time as an instant."""
    s = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)
    return s.withColumn("at", F.col("ts").cast("timestamp"))


def dedup_events(events: DataFrame, delay: str = "10 minutes") -> DataFrame:
    return events.withWatermark("at", delay).dropDuplicatesWithinWatermark(["event_id"])


def _accesses(events: DataFrame) -> DataFrame:
    return accesses_of(events).withColumn("at", F.col("ts").cast("timestamp"))


def open_close_intervals(events: DataFrame, gap: str = "1 hour", delay: str | None = "10 minutes") -> DataFrame:
    """(actor, op, object, t_begin, t_last, n): accesses no more than ``gap`` apart are one session; rows past the watermark are dropped.

    Without a ``delay`` no row is dropped; drained in complete mode, sessions that are still open are there too.
    """
    a = _accesses(events)
    a = a.withWatermark("at", delay) if delay else a
    s = a.groupBy(F.session_window("at", gap), "actor", "op", "object").agg(F.min("at").alias("t_begin"), F.max("at").alias("t_last"), F.count(F.lit(1)).alias("n"))
    return s.select("actor", "op", "object", "t_begin", "t_last", "n")


def access_counts(events: DataFrame, size: str = "1 day", slide: str | None = None, delay: str = "10 minutes") -> DataFrame:
    w = F.window("at", size, slide) if slide else F.window("at", size)
    return events.withWatermark("at", delay).groupBy(w, "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("begun"), "event_type", "n")


def live_hazards(events: DataFrame, horizon: str | None = "1 day", delay: str = "10 minutes") -> DataFrame:
    """(reader, file, writer, read_at, written_at): reads and later writes by others within ``horizon``; both sides are held that long.

    Without a horizon every access is held and none is dropped as late, so that no pair is missed.
    """
    a = _accesses(events)
    a = a.withWatermark("at", delay) if horizon else a
    r = a.filter("op = 'read'").select(F.col("actor").alias("reader"), F.col("object").alias("file"), F.col("at").alias("read_at"))
    w = a.filter("op = 'written'").select(F.col("actor").alias("writer"), F.col("object").alias("written_file"), F.col("at").alias("written_at"))
    cond = F.expr("file = written_file and written_at > read_at" + (f" and written_at <= read_at + interval {horizon}" if horizon else ""))
    return r.join(w, cond).filter("reader <> writer").select("reader", "file", "writer", "read_at", "written_at")


def hazard_ends(events: DataFrame) -> DataFrame:
    """(actor, file, read_at, written_at): a process's first read and last write of a file in the rows of one batch; what hazards are judged by."""
    a = _accesses(events).filter("op in ('read', 'written') and object is not null")
    at = lambda op: F.when(F.col("op") == op, F.col("at"))
    return a.groupBy("actor", F.col("object").alias("file")).agg(F.min(at("read")).alias("read_at"), F.max(at("written")).alias("written_at"))


def count_hazards(events: DataFrame) -> DataFrame:
    """(file, n): the hazards of each file over a whole stream, each (reader, writer) once, without a pair being made.

    Each batch is cut to ``hazard_ends``, which the table of batches holds; their least and greatest times are the stream's.
    """
    ends = drain(events, each=hazard_ends).groupBy("actor", "file").agg(F.min("read_at").alias("read_at"), F.max("written_at").alias("written_at"))
    ends = materialize(ends, "ends")
    r, w = (ends.select(F.lit(0).cast("long").alias("run_id"), "file", F.col("actor").alias("p"), F.col(x).alias("t")).filter("t is not null") for x in ("read_at", "written_at"))
    return versioning.counts_of(r, w).select("file", "n")


class VersionCounter(StatefulProcessor):
    """A counter of writes for each file; emits the version that every access sees or makes."""

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.count = handle.getValueState("count", "n long")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        n = self.count.get()[0] if self.count.exists() else 0
        pdf = pd.concat(list(rows)).sort_values(["at", "op", "seq"])  # 'read' sorts before 'written'
        out = []
        for at, op, seq, actor in pdf[["at", "op", "seq", "actor"]].itertuples(index=False):
            n += op == "written"
            out.append((key[0], actor, op, seq, n))
        self.count.update((int(n),))
        yield pd.DataFrame(out, columns=["object", "actor", "op", "seq", "version"])

    def close(self) -> None:
        pass


def live_versions(events: DataFrame) -> DataFrame:
    """(object, actor, op, seq, version) of reads and writes, in arrival order of the batches; needs the RocksDB state store."""
    a = _accesses(events).filter("op in ('read', 'written') and object is not null").select("object", "at", "op", "seq", "actor")
    return a.groupBy("object").transformWithStateInPandas(VersionCounter(), "object string, actor string, op string, seq long, version long", "append", "none")


def sink_runs(stream: DataFrame, path: str, checkpoint: str, mode: str = "append", each: Callable[[DataFrame], DataFrame] | None = None):
    """Writes each batch, or what ``each`` makes of it, under its own number, so that a batch that runs again replaces itself; in complete
    mode the last one stays."""

    def put(df: DataFrame, batch: int) -> None:
        (each(df) if each else df).write.mode("overwrite").parquet(f"{path}/batch={0 if mode == 'complete' else batch}")

    return stream.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def drain(stream: DataFrame, mode: str = "append", then: Callable | None = None, each: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """Runs a stream over all that is there, into a table in the shared folder, and returns the table; ``each`` as in ``sink_runs``."""
    path = f"{shared_dir(stream.sparkSession)}/stream-{uuid.uuid4().hex}"
    schema = each(stream).schema if each else stream.schema
    stream.sparkSession.createDataFrame([], schema).write.parquet(f"{path}/rows/none")  # if there is no batch
    q = sink_runs(stream, f"{path}/rows", f"{path}/state", mode, each)
    q.awaitTermination()
    if then:
        then(q)
    return stream.sparkSession.read.schema(schema).parquet(f"{path}/rows/*")


def late_rows(query) -> int:
    """Rows that a finished query dropped for coming after the watermark."""
    return sum(op.get("numRowsDroppedByWatermark", 0) for p in query.recentProgress for op in p["stateOperators"])
