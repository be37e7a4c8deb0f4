"""Streams of edges and events."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..language.fsm import Fsm
from ..operators.index import PathIndex


class Maintained:
    """An index that follows a stream of edges (src, label, dst): each batch is one delta."""

    def __init__(self, index: PathIndex, then: Callable[[PathIndex, int], None] | None = None):
        self.index, self.then = index, then

    def batch(self, edges: DataFrame, number: int) -> None:
        self.index = self.index.insert(edges)
        if self.then:
            self.then(self.index, number)

    def start(self, stream: DataFrame, checkpoint: str | None = None, trigger: dict | None = None):
        w = stream.writeStream.foreachBatch(self.batch)
        if checkpoint:
            w = w.option("checkpointLocation", checkpoint)
        return w.trigger(**(trigger or {"availableNow": True})).start()


def dedup(edges: DataFrame, delay: str = "1 hour", time: str = "ts") -> DataFrame:
    """Repeated edges within the watermark once."""
    return edges.withWatermark(time, delay).dropDuplicatesWithinWatermark(["src", "label", "dst"])


def windowed_labels(events: DataFrame, size: str = "1 hour", slide: str | None = None, delay: str | None = None) -> DataFrame:
    """Events of each type per window; batch or stream (with ``delay`` as the watermark)."""
    e = events.withWatermark("ts", delay) if delay else events
    win = F.window("ts", size, slide) if slide else F.window("ts", size)
    return e.groupBy(win.alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.col("w.start").alias("window_start"), "event_type", "n")


def session_trails(events: DataFrame, gap: str = "30 minutes", delay: str | None = None) -> DataFrame:
    """Sessions of each user: start, end and number of events."""
    e = events.withWatermark("ts", delay) if delay else events
    s = e.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"), F.max("ts").alias("last_ts"))
    return s.select("user_id", F.col("w.start").alias("session_start"), "last_ts", "n")


def dfa_match(events: DataFrame, machine: Fsm, delay: str | None = None) -> DataFrame:
    """Online matches of a deterministic automaton along each user's events, in order of (ts, event_id): one row
    (user_id, src, dst) per walk begun at src that is accepted when dst arrives.

    The state of a user is, per automaton state, the starts that stand in it; it grows with the user's open
    walks.  With a watermark, events are held back until it has passed them, so late but not too late events keep their
    place."""
    m = machine.determinize()
    step = {(q, s): p for q, s, p in m.edges}
    start, finals = next(iter(m.starts)), set(m.finals)
    out_schema, state_schema = "user_id long, src long, dst long", "last_event long, last_label string, open string, held string"

    def advance(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        import json

        last, label, open_, held = state.get if state.exists else (-1, "", "{}", "[]")
        places: dict[int, list[int]] = {int(k): v for k, v in json.loads(open_).items()}
        waiting = [tuple(x) for x in json.loads(held)]
        for f in frames:
            waiting += list(zip(f["ts"].astype("int64").tolist(), f["event_id"].tolist(), f["event_type"].tolist(), strict=True))
        if delay:
            limit = state.getCurrentWatermarkMs() * 1_000_000
            unit = 1 if waiting and waiting[0][0] > 10**17 else 1000
            ready = sorted(x for x in waiting if x[0] * unit <= limit or state.hasTimedOut)
            waiting = sorted(x for x in waiting if x not in set(ready))
        else:
            ready, waiting = sorted(waiting), []
        rows = []
        for _, event, kind in ready:
            if last >= 0:
                moved: dict[int, list[int]] = {}
                places.setdefault(start, []).append(last)
                for q, froms in places.items():
                    p = step.get((q, label))
                    if p is not None:
                        moved.setdefault(p, []).extend(froms)
                places = moved
                rows += [(key[0], s, event) for q in finals for s in places.get(q, ())]
            last, label = event, kind
        state.update((last, label, json.dumps(places), json.dumps(waiting)))
        if delay and waiting:
            state.setTimeoutTimestamp(max(state.getCurrentWatermarkMs() + 1, 1 + waiting[-1][0] // (1_000_000 if waiting[0][0] > 10**17 else 1000)))
        yield pd.DataFrame(rows, columns=["user_id", "src", "dst"])

    e = events.withWatermark("ts", delay) if delay else events
    timeout = GroupStateTimeout.EventTimeTimeout if delay else GroupStateTimeout.NoTimeout
    return e.select("user_id", "ts", "event_id", "event_type").groupBy("user_id").applyInPandasWithState(advance, out_schema, state_schema, "append", timeout)


def trail_edges(events: DataFrame) -> DataFrame:
    """Edges of one finished batch of events, for :class:`Maintained`."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = events.withColumn("nxt", F.lead("event_id").over(w)).where("nxt is not null")
    return e.select(F.col("event_id").cast("long").alias("src"), F.col("event_type").alias("label"), F.col("nxt").cast("long").alias("dst"))
