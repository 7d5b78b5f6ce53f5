"""Streams of edge updates: batches into versions, windows, sessions, expiry."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from motifjoin.operators.delta import DeltaEngine
from motifjoin.operators.static_join import static_join
from motifjoin.plans.query import JoinQuery
from motifjoin.sources.graphs import event_pairs
from motifjoin.workspace import new_path

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, path: str, max_files: int = 1) -> DataFrame:
    """A file stream of events with event time as a timestamp."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", max_files).parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))


def run_changes(events: DataFrame, engine: DeltaEngine, sink: str, checkpoint: str, relation: str = "e", delay: str = "2 days") -> None:
    """Feed an event stream through a delta engine until it is drained.

    Every micro-batch becomes one version: purchases insert, errors delete, the last
    operation on an edge in the batch counts. Signed changes of the result are written
    under the version; a batch that is replayed after a failure finds its version committed,
    or stages it anew, and overwrites its own output.
    """
    pairs = event_pairs(events).filter("event_type in ('purchase', 'error')").withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])

    def batch(df: DataFrame, number: int) -> None:
        version = number + 1
        w = F.when(F.col("event_type") == "purchase", 1).otherwise(-1)
        changes = df.groupBy("src", "dst").agg(F.max_by(w, F.struct("ts", "event_id")).cast("int").alias("w"))
        if all(s.version >= version for s in engine.stores.values()):
            return
        out = engine.stage(version, {relation: changes})
        out.write.mode("overwrite").parquet(f"{sink}/ver={version}")
        engine.commit(version)

    pairs.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start().awaitTermination()


def windowed_counts(events: DataFrame, length: str = "1 day", slide: str | None = None, delay: str = "2 days") -> DataFrame:
    """Distinct-free activity per event-time window: operations and net insertions."""
    pairs = event_pairs(events).filter("event_type in ('purchase', 'error')")
    pairs = pairs.withWatermark("ts", delay) if events.isStreaming else pairs
    win = F.window("ts", length, slide) if slide else F.window("ts", length)
    return pairs.groupBy(win.alias("w")).agg(F.count(F.lit(1)).alias("n_ops"), F.sum(F.when(F.col("event_type") == "purchase", 1).otherwise(-1)).alias("net")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n_ops", "net")


def sessions(events: DataFrame, gap: str = "12 hours", delay: str = "2 days") -> DataFrame:
    """Bursts of one user's events."""
    pairs = event_pairs(events)
    pairs = pairs.withWatermark("ts", delay) if events.isStreaming else pairs
    return pairs.groupBy("src", F.session_window("ts", gap).alias("w")).agg(F.count(F.lit(1)).alias("n")).select("src", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def drain(df: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a stream until it is drained into a table in memory, for tests and small reports."""
    df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", new_path(df.sparkSession, "stream")).trigger(availableNow=True).start().awaitTermination()
    return df.sparkSession.table(name)


def expiring_edges(pairs: DataFrame, days: int = 7) -> DataFrame:
    """Signed changes of the set of edges seen in the last ``days``: an edge's first event inserts it, silence deletes it.

    Stateful per edge, with event-time timers; the watermark drives expiry.
    """
    span = pd.Timedelta(days=days)

    def edge(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            last = pd.Timestamp(state.get[0], unit="us")
            state.remove()
            yield pd.DataFrame({"src": [key[0]], "dst": [key[1]], "at": [last + span], "w": [-1]})
            return
        times = sorted(t for f in frames for t in f["ts"])
        out, last = [], pd.Timestamp(state.get[0], unit="us") if state.exists else None
        for t in times:
            if last is not None and t > last + span:
                out.append((last + span, -1))
                last = None
            if last is None:
                out.append((t, 1))
            last = t if last is None else max(t, last)
        state.update((int(last.value // 1000),))
        state.setTimeoutTimestamp(max(int((last + span).timestamp() * 1000), state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame({"src": key[0], "dst": key[1], "at": [t for t, _ in out], "w": [w for _, w in out]})

    return pairs.groupBy("src", "dst").applyInPandasWithState(edge, "src long, dst long, at timestamp, w int", "last long", "append", "EventTimeTimeout")


def batch_expiry(pairs: DataFrame, days: int = 7) -> DataFrame:
    """The same changes over a finished table: gaps between an edge's events, by a window."""
    w = Window.partitionBy("src", "dst").orderBy("ts")
    span = F.expr(f"interval {days} days")
    seen = pairs.select("src", "dst", "ts").distinct().withColumn("before", F.lag("ts").over(w)).withColumn("after", F.lead("ts").over(w))
    starts = seen.filter(F.col("before").isNull() | (F.col("ts") > F.col("before") + span)).select("src", "dst", F.col("ts").alias("at"), F.lit(1).alias("w"))
    ends = seen.filter(F.col("after").isNull() | (F.col("after") > F.col("ts") + span)).select("src", "dst", (F.col("ts") + span).alias("at"), F.lit(-1).alias("w"))
    return starts.unionByName(ends)


def lifetimes(ops: DataFrame) -> DataFrame:
    """``(src, dst, since, until)`` from at most one operation ``(day, src, dst, w)`` per edge and day; ``until`` is null while an edge lives."""
    w = Window.partitionBy("src", "dst").orderBy("day")
    flips = ops.withColumn("before", F.coalesce(F.lag("w").over(w), F.lit(-1))).filter("w <> before")
    return flips.withColumn("until", F.lead("day").over(w)).filter("w > 0").select("src", "dst", F.col("day").alias("since"), "until")


def pattern_changes(query: JoinQuery, alive: DataFrame) -> DataFrame:
    """``(attrs.., day, w)``: when every match of a pattern over one edge relation came and went.

    The pattern is matched once over all edges that ever lived; a match lives while the
    lifetimes of its edges overlap. One plan for a history that is at hand, where a stream
    would apply batch after batch; the signed rows are the same.
    """
    out = static_join(query, {query.atoms[0].relation: alive.select("src", "dst").distinct()})
    for i, atom in enumerate(query.atoms):
        a, b = atom.attrs
        out = out.join(alive.select(F.col("src").alias(a), F.col("dst").alias(b), F.col("since").alias(f"__s{i}"), F.col("until").alias(f"__u{i}")), [a, b])
    n, attrs = range(len(query.atoms)), query.order or query.attrs
    since = F.greatest(*(F.col(f"__s{i}") for i in n))
    until = F.least(*(F.col(f"__u{i}") for i in n))  # nulls are passed over
    spans = out.select(*attrs, since.alias("since"), until.alias("until")).filter("until is null or since < until")
    came = spans.select(*attrs, F.col("since").alias("day"), F.lit(1).alias("w"))
    return came.unionByName(spans.filter("until is not null").select(*attrs, F.col("until").alias("day"), F.lit(-1).alias("w")))
