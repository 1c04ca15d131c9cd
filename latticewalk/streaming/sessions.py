"""Click sessions and monitors from a stream of events (H)."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from latticewalk.sources.builders import CLICK, SESSIONS, label


#: Ids of events that are put in order together.
ARRIVALS = 100_000


def timed(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Watermarks need an instant, so the column without a zone becomes one."""
    return events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def stream_sessions(events: DataFrame, gap: str = "12 hours", delay: str = "1 hour") -> DataFrame:
    """user_id, began, ended, n: sessions that the watermark has closed; an event exactly `gap` later starts a new one."""
    return timed(events, delay).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("began"), F.col("w.end").alias("ended"), "n")


def event_counts(events: DataFrame, width: str = "1 day", slide: str | None = None, delay: str = "1 hour") -> DataFrame:
    """Tumbling or sliding counts of each type of event."""
    return timed(events, delay).groupBy(F.window("ts", width, slide or width).alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("began"), "event_type", "n")


def late_events(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """day, n, late: events by day, and those that came more than `delay` after the newest one before them in order of event_id.

    A batch count of what a stream with this delay may drop: order of arrival is taken to be that of ids. The newest
    time so far is carried from one range of ids to the next by its maximum, so ranges are looked at in parallel.
    """
    e = events.select(F.col("ts").cast("timestamp").alias("ts"), "event_id", F.floor(F.col("event_id") / ARRIVALS).alias("part"))
    ends = e.groupBy("part").agg(F.max("ts").alias("newest"))
    before = ends.select("part", F.max("newest").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)).alias("carried"))
    so_far = F.max("ts").over(Window.partitionBy("part").orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1))
    newest = F.greatest("carried", so_far)
    e = e.join(before, "part").withColumn("late", (F.col("ts") < newest - F.expr(f"interval {delay}")).cast("int"))
    return e.groupBy(F.to_date("ts").cast("string").alias("day")).agg(F.count("*").alias("n"), F.sum(F.coalesce("late", F.lit(0))).cast("long").alias("late"))


def run_to_table(stream: DataFrame, folder: str) -> DataFrame:
    """Runs a stream over what there is and gives what it wrote: files and checkpoint lie in a shared folder."""
    query = stream.writeStream.format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/checkpoint").outputMode("append").trigger(availableNow=True).start()
    query.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(f"{folder}/out")


def upsert_sessions(stream: DataFrame, path: str, checkpoint: str):
    """Writes closed sessions of each micro-batch to a folder of its own, so that a repeated batch replaces itself."""
    return stream.writeStream.foreachBatch(lambda df, n: df.write.mode("overwrite").parquet(f"{path}/batch={n}")).outputMode("append").option("checkpointLocation", checkpoint)


def stream_click_graphs(events: DataFrame, gap_hours: int = 12, delay: str = "1 hour") -> DataFrame:
    """gid, vlabel, src, dst: the packed tree of each session that the watermark has closed, as the batch builder makes it.

    A user's state holds the number of closed sessions and the events of open ones. Events within the delay may come in
    any order; later ones are dropped by the watermark. Sessions of one event count in the numbering and give no graph.
    """
    view, gap = CLICK.index("view"), gap_hours * 3_600_000_000

    def close(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, *held = state.get if state.exists else (0, [], [], [])
        rows = [*zip(*held)]
        for batch in batches:
            rows += [(int(t), int(e), None if pd.isna(l) else int(l)) for t, e, l in batch[["at", "event_id", "label"]].itertuples(index=False)]
        rows.sort(key=lambda t: t[:2])
        groups: list[list[tuple]] = []
        for row in rows:
            if groups and row[0] - groups[-1][-1][0] <= gap:
                groups[-1].append(row)
            else:
                groups.append([row])
        now, out = state.getCurrentWatermarkMs() * 1000, []
        while groups and groups[0][-1][0] + gap < now:
            done, n, parents, last = groups.pop(0), n + 1, [], 0
            for i, row in enumerate(done):
                parents += [last] if i else []
                last = i if row[2] == view else last
            if len(done) > 1:
                out.append((key[0] * SESSIONS + n, [row[2] for row in done], parents, [*range(1, len(done))]))
        left = [row for g in groups for row in g]
        state.update((n, [t for t, _, _ in left], [e for _, e, _ in left], [l for _, _, l in left]))
        if left:
            state.setTimeoutTimestamp((groups[0][-1][0] + gap) // 1000 + 2)
        yield pd.DataFrame(out, columns=["gid", "vlabel", "src", "dst"])

    rows = timed(events, delay).select("user_id", "ts", "event_id", F.unix_micros("ts").alias("at"), label(F.col("event_type"), CLICK).alias("label"))
    return rows.groupBy("user_id").applyInPandasWithState(close, "gid long, vlabel array<int>, src array<int>, dst array<int>", "n long, at array<long>, event_id array<long>, label array<int>", "append", GroupStateTimeout.EventTimeTimeout)
