"""Event graphs as they stream in: windows with watermarks, transitions by keyed state, trees per closed window."""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import DataStreamWriter, StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..kernels.solve import Options, solutions
from ..operators.enumerate import directed_steiner_trees
from ..sources.graphs import EVENT_TYPES

EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


def event_stream(spark: SparkSession, folder: str, files_per_batch: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_batch).parquet(folder)


def without_repeats(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each event once; an id that comes again within the watermark is dropped."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def window_counts(events: DataFrame, width: str, slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """(window_start, event_type, n) for tumbling or sliding windows; in append mode a window comes once, when the watermark has passed it."""
    windows = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.withWatermark("ts", late).groupBy(windows.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("window_start"), "event_type", "n")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """(user_id, session_start, session_end, n)."""
    out = events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"))
    return out.select("user_id", F.col("w.start").alias("session_start"), F.col("w.end").alias("session_end"), "n")


def closed_windows(events: DataFrame, width: str = "7 days", late: str = "1 hour") -> DataFrame:
    """(window_start, user_id, steps): a user's events of a window in order, once the watermark has passed the window."""
    keyed = events.withWatermark("ts", late).groupBy(F.window("ts", width).alias("w"), "user_id")
    steps = F.transform(F.array_sort(F.collect_list(F.struct("ts", "event_id", "event_type"))), lambda e: e["event_type"])
    return keyed.agg(steps.alias("steps")).select(F.unix_timestamp(F.col("w.start")).alias("window_start"), "user_id", "steps")


def transitions_of(closed: DataFrame) -> DataFrame:
    """Edges of one digraph for each window: (graph_id, edge_id, src, dst)."""
    types = F.array(*map(F.lit, EVENT_TYPES))
    pairs = F.zip_with(F.slice("steps", 1, F.greatest(F.size("steps") - 1, F.lit(0))), F.slice("steps", 2, F.size("steps")), lambda a, b: F.struct(a.alias("a"), b.alias("b")))
    arcs = closed.where(F.size("steps") > 1).select(F.col("window_start").alias("graph_id"), F.explode(pairs).alias("p")).where("p.a <> p.b")
    ids = arcs.select("graph_id", (F.array_position(types, F.col("p.a")) - 1).cast("bigint").alias("src"), (F.array_position(types, F.col("p.b")) - 1).cast("bigint").alias("dst")).distinct()
    return ids.select("graph_id", (F.col("src") * 5 + F.col("dst")).alias("edge_id"), "src", "dst")


def trees_per_window(events: DataFrame, path: str, root: str = "signup", wanted: str = "purchase", width: str = "7 days", late: str = "1 hour") -> DataStreamWriter:
    """Directed trees of every closed window, one folder a batch: a batch that is run again overwrites its own folder, so each window's trees are there once."""

    def one_batch(closed: DataFrame, batch: int) -> None:
        edges = transitions_of(closed)
        starts = edges.select("graph_id").distinct()
        jobs = starts.select(F.col("graph_id").alias("instance_id"), "graph_id", F.lit(EVENT_TYPES.index(root)).cast("bigint").alias("root"))
        ends = starts.select(F.col("graph_id").alias("instance_id"), F.lit(EVENT_TYPES.index(wanted)).cast("bigint").alias("vertex_id"))
        directed_steiner_trees(jobs, ends, edges).select(F.col("instance_id").alias("window_start"), "solution_key", "n_edges").write.mode("overwrite").parquet(f"{path}/batch={batch}")

    return closed_windows(events, width, late).writeStream.outputMode("append").foreachBatch(one_batch)


def late_rows(query: StreamingQuery) -> int:
    """How many rows a stream's operators have dropped as later than the watermark, over the progress that the query still holds."""
    return sum(int(s.get("numRowsDroppedByWatermark", 0)) for p in query.recentProgress for s in p["stateOperators"])


def trees_at_window_end(events: DataFrame, root: str = "signup", wanted: str = "purchase", width: str = "7 days", late: str = "1 hour") -> DataFrame:
    """(window_start, solution_key, n_edges): the directed trees of a window's transitions, found by a timer when the watermark passes its end.

    A window's state holds its events, each once, as they may come out of order until then; it is given up with the answer.
    """

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        start, end = key
        held = json.loads(state.get[0]) if state.exists else []
        if not state.hasTimedOut:
            seen = {e[1] for e in held}
            for frame in frames:
                for user, ts, event_id, kind in zip(frame["user_id"], frame["ts"], frame["event_id"], frame["event_type"], strict=True):
                    if int(event_id) not in seen:
                        seen.add(int(event_id))
                        held.append((ts.isoformat(), int(event_id), int(user), kind))
            state.update((json.dumps(held),))
            state.setTimeoutTimestamp(int(end) * 1000)
            return
        steps, last = set(), {}
        for _, _, user, kind in sorted(map(tuple, held)):
            if user in last and last[user] != kind:
                steps.add((EVENT_TYPES.index(last[user]), EVENT_TYPES.index(kind)))
            last[user] = kind
        state.remove()
        edges = [(5 * a + b, a, b) for a, b in sorted(steps)]
        found = list(solutions(edges, [[EVENT_TYPES.index(wanted)]], EVENT_TYPES.index(root), Options(flavour="directed"))) if edges else []
        yield pd.DataFrame([(int(start), s.key, len(s.edges)) for s in found], columns=["window_start", "solution_key", "n_edges"])

    keyed = events.withWatermark("ts", late).withColumn("w", F.window("ts", width)).withColumn("window_start", F.unix_timestamp(F.col("w.start"))).withColumn("window_end", F.unix_timestamp(F.col("w.end")))
    rows = keyed.select("window_start", "window_end", "user_id", "ts", "event_id", "event_type")
    return rows.groupBy("window_start", "window_end").applyInPandasWithState(step, "window_start bigint, solution_key string, n_edges int", "held string", "append", GroupStateTimeout.EventTimeTimeout)


def running_transitions(events: DataFrame) -> DataFrame:
    """(user_id, src_type, dst_type, n): transitions counted by a user's state, which is the last event's time, id and type; updates as they happen.

    Events of a batch are put in order first; one that is not newer than the state's, a repeated one too, is left out.
    """
    out = "user_id bigint, src_type string, dst_type string, n bigint"

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        last = state.get if state.exists else None
        counts: dict[tuple[str, str], int] = {}
        new = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        for ts, event_id, kind in zip(new["ts"], new["event_id"], new["event_type"], strict=True):
            now = (ts.to_pydatetime(), int(event_id), kind)
            if last is not None and now[:2] <= tuple(last)[:2]:
                continue
            if last is not None and last[2] != kind:
                counts[last[2], kind] = counts.get((last[2], kind), 0) + 1
            last = now
        if last is not None:
            state.update(tuple(last))
        yield pd.DataFrame([(key[0], a, b, n) for (a, b), n in counts.items()], columns=["user_id", "src_type", "dst_type", "n"])

    return events.groupBy("user_id").applyInPandasWithState(step, out, "ts timestamp, event_id bigint, event_type string", "update", GroupStateTimeout.NoTimeout)
