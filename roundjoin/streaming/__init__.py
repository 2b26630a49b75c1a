"""Streaming forms: a hub stream on reduced static arms, windows, interval joins, duplicate removal, paths in event sequences, joins per micro-batch."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.query import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..operators.decomposition import decomposition_join
from ..plans.query import Atom, JoinQuery


def stream_star(stream: DataFrame, arms: list[tuple[DataFrame, list[str]]]) -> DataFrame:
    """Each arm (static, with the stream's key columns) joins the hub stream; append mode, no state."""
    for arm, on in arms:
        stream = stream.join(arm.dropDuplicates(), on)
    return stream


def stream_windows(stream: DataFrame, ts: str, keys: list[str], kind: str = "tumbling", size: str = "1 hour", slide: str | None = None, gap: str = "30 minutes", watermark: str = "1 hour") -> DataFrame:
    """Counts by window; rows later than the watermark are dropped."""
    w = F.session_window(ts, gap) if kind == "session" else F.window(ts, size, slide) if kind == "sliding" else F.window(ts, size)
    return stream.withWatermark(ts, watermark).groupBy(w.alias("w"), *keys).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *keys, "n")


def stream_interval_join(a: DataFrame, b: DataFrame, a_ts: str, b_ts: str, a_key: str, b_key: str, after: str = "10 minutes", watermark: str = "1 hour") -> DataFrame:
    """Pairs with equal keys where b comes within `after` of a. Both sides have watermarks, so state is bounded."""
    a, b = a.withWatermark(a_ts, watermark), b.withWatermark(b_ts, watermark)
    return a.join(b, F.expr(f"{a_key} = {b_key} AND {b_ts} >= {a_ts} AND {b_ts} <= {a_ts} + INTERVAL {after}"))


def stream_distinct(stream: DataFrame, ts: str, keys: list[str], watermark: str = "1 hour") -> DataFrame:
    return stream.withWatermark(ts, watermark).dropDuplicatesWithinWatermark(keys)


def stream_paths(stream: DataFrame, key: str, item: str, ts: str, length: int, watermark: str = "1 hour") -> DataFrame:
    """Paths of `length` consecutive events of a key in time order, whatever micro-batches they come in.

    An event waits until the watermark has reached its time and then takes its place; an event that comes later than that is dropped, and counted in the query's
    numRowsDroppedByWatermark. Events of one time stand by item. State of a key: its waiting events and the last length - 1 items; any state store does."""

    def run(k, parts, state: GroupState):
        held, times, items = state.get if state.exists else ([], [], [])
        waiting = list(zip(times, items, strict=True))
        if not state.hasTimedOut:
            for pdf in parts:
                waiting += zip(pdf["__us"].tolist(), pdf[item].tolist(), strict=True)
        waiting.sort()
        mark = state.getCurrentWatermarkMs()
        ready = [x for x in waiting if x[0] // 1000 <= mark]
        waiting = waiting[len(ready) :]
        run_of = [*held, *(x[1] for x in ready)]
        state.update((run_of[len(run_of) - length + 1 :] if len(run_of) >= length else run_of, [x[0] for x in waiting], [x[1] for x in waiting]))
        if waiting:
            state.setTimeoutTimestamp(max(mark, waiting[0][0] // 1000 - 1, 1))
        paths = [run_of[i : i + length] for i in range(len(run_of) - length + 1)]
        yield pd.DataFrame({key: [k[0]] * len(paths), "path": paths})

    rows = stream.withWatermark(ts, watermark).select(F.col(key).cast("long").alias(key), F.col(item).cast("long").alias(item), ts, F.unix_micros(ts).alias("__us")).groupBy(key)
    return rows.applyInPandasWithState(run, f"{key} long, path array<long>", "items array<long>, times array<long>, waiting array<long>", "append", GroupStateTimeout.EventTimeTimeout)


def batch_paths(df: DataFrame, key: str, item: str, ts: str, length: int, rows: Callable | None = None) -> DataFrame:
    """The same on a table, by a window. The events of a key are one task's; a path has no other bound."""
    from pyspark.sql import Window

    w = Window.partitionBy(key).orderBy(ts, item)
    items = [F.col(item), *[F.lead(item, k).over(w) for k in range(1, length)]]
    return df.select(key, F.array(*items).alias("path")).where(F.col("path")[length - 1].isNotNull())


def stream_batches(stream: DataFrame, q: JoinQuery, hub: str, path: str, checkpoint: str) -> StreamingQuery:
    """Runs the decomposition join on each micro-batch in place of the hub atom and appends the answers to path."""

    def one(batch: DataFrame, epoch: int) -> None:
        atoms = [Atom(a.name, batch.select(*a.attrs), a.attrs) if a.name == hub else a for a in q.atoms]
        decomposition_join(JoinQuery(atoms)).write.mode("overwrite").parquet(f"{path}/epoch={epoch}")

    return stream.writeStream.foreachBatch(one).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
