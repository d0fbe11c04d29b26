"""Edges from a stream of events, and windows over it."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from regpath.operators.scratch import Scratch
from regpath.sources.builders import seconds_of
from regpath.sources.graph import LabeledGraph

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string"
EDGES = "src long, label string, dst long, part long, late long"


def stream_events(spark: SparkSession, path: str, files_a_batch: int = 1) -> DataFrame:
    """Events from files as they arrive."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_a_batch).parquet(path)


def linked(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState, forget_after_ms: int | None = None) -> Iterator[pd.DataFrame]:
    """Edges from a user's last event to each new one in the order of (ts, event_id), and how many events came late.

    The state is the last event alone.  An event behind it is late, or was seen
    already: no edge leads to it, and it is counted in a row without ends.  A user's state goes when the
    watermark has passed the last event by the time that `stream_edges` is given.
    """
    if state.hasTimedOut:
        state.remove()
        return
    rows = pd.concat(list(batches)).drop_duplicates("event_id").sort_values(["ts", "event_id"])
    last = state.get if state.exists else None
    out, late = [], 0
    for ts, event, label in zip(rows.ts, rows.event_id, rows.event_type, strict=True):
        now = (ts.value // 1000, int(event))
        if last is not None and now <= (last[0], last[1]):
            late += 1
            continue
        if last is not None:
            out.append((last[1], label, now[1], key[0], 0))
        last = now
    if last is not None:
        state.update(tuple(last))
    if forget_after_ms and last is not None:
        state.setTimeoutTimestamp(max(last[0] // 1000, state.getCurrentWatermarkMs()) + forget_after_ms)
    if late:
        out.append((None, None, None, key[0], late))
    yield pd.DataFrame(out, columns=["src", "label", "dst", "part", "late"]).astype({"src": "Int64", "dst": "Int64"})


def stream_edges(events: DataFrame, forget_after_ms: int | None = None, lateness: str = "1 hour") -> DataFrame:
    """Edges (src, label, dst, part, late) of a stream of events; state is one row a user.

    forget_after_ms: how far the watermark, `lateness` behind the latest event, passes a user's last event before the
    state goes, None to keep it; an event that comes then starts the user's timeline anew, and events behind the watermark are
    dropped by Spark, which counts them in the query's progress.  Rows without ends count a batch's other late or repeated events of a user.
    """

    def run(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        yield from linked(key, batches, state, forget_after_ms)

    timeout = GroupStateTimeout.NoTimeout
    if forget_after_ms:
        events, timeout = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", lateness), GroupStateTimeout.EventTimeTimeout
    return events.groupBy("user_id").applyInPandasWithState(run, EDGES, "ts long, event_id long", "append", timeout)


def append_to_graph(edges: DataFrame, path: str, checkpoint: str):
    """Writes a stream of edges, and its counts of late events, to a graph table, a folder for each batch: a batch run again replaces its own."""

    def put(df: DataFrame, batch: int) -> None:
        df.write.mode("overwrite").parquet(f"{path}/batch={batch}")

    return edges.writeStream.foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def graph_of(spark: SparkSession, path: str) -> LabeledGraph:
    return LabeledGraph.from_edges(spark.read.schema(EDGES + ", batch int").parquet(path), part=F.col("part"))


def late_events(spark: SparkSession, path: str) -> DataFrame:
    """(part, late): events of each user that came late, or again, so far."""
    return spark.read.schema(EDGES + ", batch int").parquet(path).where("late > 0").groupBy("part").agg(F.sum("late").alias("late"))


def windowed(events: DataFrame, kind: str, size: str, slide: str | None = None, lateness: str = "1 hour") -> DataFrame:
    """Events with the windows they fall in, behind a watermark: 'tumbling', 'sliding' or 'session'."""
    marked = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", lateness)
    w = F.session_window("ts", size) if kind == "session" else F.window("ts", size, slide) if kind == "sliding" else F.window("ts", size)
    return marked.select("*", w.alias("span"))


def deduplicated(events: DataFrame, lateness: str = "1 hour") -> DataFrame:
    """Each event once, if its repetitions come within the watermark."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", lateness).dropDuplicatesWithinWatermark(["event_id"])


def evaluated_windows(events: DataFrame, evaluate: Callable[[LabeledGraph], DataFrame], path: str, checkpoint: str, kind: str = "tumbling", size: str = "1 day", slide: str | None = None, lateness: str = "1 hour"):
    """Writes the result of a query over each window's timeline, once the watermark has closed it.

    A window's events are grouped by user in the stream's state until it closes; then
    its edges, from event to event of a user within the window, are the graph that
    `evaluate` is given.  Result rows carry the window's start and end, in a folder for each batch: a batch run again replaces its own.
    """
    held = windowed(events, kind, size, slide, lateness).groupBy("span", "user_id").agg(F.collect_set(F.struct("ts", "event_id", "event_type")).alias("held"))

    def put(df: DataFrame, batch: int) -> None:
        spark = df.sparkSession
        scratch = Scratch(spark, "windows")
        closed = scratch.table(df.select(F.col("span.start").alias("start"), F.col("span.end").alias("end"), "user_id", F.sort_array("held").alias("held")))
        steps = F.transform(F.sequence(F.lit(1), F.size("held") - 1), lambda i: F.struct(F.col("held")[i - 1]["event_id"].alias("src"), F.col("held")[i]["event_type"].alias("label"), F.col("held")[i]["event_id"].alias("dst")))
        edges = closed.where(F.size("held") > 1).select("start", "end", "user_id", F.explode(steps).alias("e")).select("start", "end", "user_id", "e.*")
        edges = scratch.table(edges)
        # a batch closes few windows: one evaluation each, over that window's edges alone
        for span in closed.select("start", "end").distinct().orderBy("start").toLocalIterator():
            own = edges.where((F.col("start") == F.lit(span["start"])) & (F.col("end") == F.lit(span["end"])))
            found = evaluate(LabeledGraph.from_edges(own, part=F.col("user_id")))
            found.withColumns({"window_start": F.lit(span["start"]), "window_end": F.lit(span["end"])}).write.mode("overwrite").parquet(f"{path}/batch={batch}/start={int(span['start'].timestamp())}")

    return held.writeStream.outputMode("append").foreachBatch(put).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def replayed_timeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The timeline's edges, from a stream over the events sorted by time in one file a batch."""
    scratch = Scratch(spark, "stream")
    events = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", "ts", "user_id", "event_type")
    source, graph = f"{scratch.root}/events", f"{scratch.root}/graph"
    t = seconds_of("ts")
    cuts = events.agg(*[F.percentile_approx(t, q).alias(f"q{i}") for i, q in enumerate((0.34, 0.67))]).first()
    for i, part in enumerate((t <= cuts[0], (t > cuts[0]) & (t <= cuts[1]), t > cuts[1])):
        events.where(part).coalesce(1).write.mode("append" if i else "overwrite").parquet(source)
    append_to_graph(stream_edges(stream_events(spark, source)), graph, f"{scratch.root}/checkpoint").awaitTermination()
    return graph_of(spark, graph).edges.select("src", "label", "dst")


def windowed_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events a day and type, counted by a stream with tumbling windows."""
    scratch = Scratch(spark, "stream")
    events = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", "ts", "user_id", "event_type")
    events.write.parquet(f"{scratch.root}/events")
    counts = stream_events(spark, f"{scratch.root}/events", 1_000).groupBy(F.window("ts", "1 day").alias("span"), "event_type").agg(F.count(F.lit(1)).alias("n"))

    def put(df: DataFrame, batch: int) -> None:
        df.select(F.col("span.start").alias("start"), "event_type", "n").write.mode("overwrite").parquet(f"{scratch.root}/counts")

    counts.writeStream.outputMode("complete").foreachBatch(put).option("checkpointLocation", f"{scratch.root}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{scratch.root}/counts")
