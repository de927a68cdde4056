"""Matching over streams: chunks in any order of arrival, windows of events, state at a time.

Chunks are scanned to small maps before anything is shuffled; only maps travel to the state store. A word's state is
its segments, one for each gap at most. When the last gap closes, the verdict is emitted and the state dropped; when the
watermark passes the word's last event by the lateness, the word is emitted as undecided.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout
from pyspark.sql.window import Window

from ..functions.sqlapi import map_function
from ..operators.fold import Segments
from ..operators.match import Compiled, compiled

_STATE = "lo array<int>, hi array<int>, image array<array<int>>, chunks int"


def match_stream(chunks: DataFrame, p: str | Compiled, lateness: str = "10 minutes", time: str = "ts") -> DataFrame:
    """word_id, status (accepted, rejected or undecided) from a stream of word_id, chunk_ix, chunks, payload and a time."""
    c = compiled(p)
    maps = chunks.withWatermark(time, lateness).select("word_id", F.col("chunk_ix").cast("int").alias("chunk_ix"), F.col("chunks").cast("int").alias("chunks"), F.col(time).alias("_ts"), map_function(c)("payload").alias("image"))
    final = [bool(f) for f in c.dfa.final]

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            yield pd.DataFrame({"word_id": [key[0]], "status": ["undecided"]})
            return
        held, total, last = Segments(), 0, 0
        if state.exists:
            lo, hi, image, total = state.get
            held.parts = [(a, b, list(i)) for a, b, i in zip(lo, hi, image, strict=True)]
        for rows in batches:
            for ix, n, ts, image in zip(rows["chunk_ix"], rows["chunks"], rows["_ts"], rows["image"], strict=True):
                total, last = int(n), max(last, int(ts.timestamp() * 1000))
                if not any(a <= ix <= b for a, b, _ in held.parts):  # a chunk that comes again changes nothing
                    held.add(int(ix), int(ix), [int(q) for q in image])
        whole = held.complete(total)
        if whole is not None:
            if state.exists:
                state.remove()
            yield pd.DataFrame({"word_id": [key[0]], "status": ["accepted" if final[whole[0]] else "rejected"]})
            return
        state.update(([a for a, _, _ in held.parts], [b for _, b, _ in held.parts], [i for _, _, i in held.parts], total))
        state.setTimeoutTimestamp(max(last, state.getCurrentWatermarkMs() + 1))

    kind = chunks.schema["word_id"].dataType.simpleString()
    return maps.groupBy("word_id").applyInPandasWithState(update, f"word_id {kind}, status string", _STATE, "append", GroupStateTimeout.EventTimeTimeout)


def windowed(events: DataFrame, key: str, time: str, order: str, symbol: Column, kind: str, size: str, slide: str | None = None) -> DataFrame:
    """key, start, stop, word of every tumbling, sliding or session window; size is the gap of a session."""
    window = F.session_window(time, size) if kind == "session" else F.window(time, size, slide if kind == "sliding" else None)
    parts = F.array_sort(F.collect_list(F.struct(F.col(time).alias("t"), F.col(order).alias("o"), symbol.alias("s"))))
    made = events.groupBy(window.alias("w"), key).agg(F.array_join(F.transform(parts, lambda x: x["s"]), "").alias("word"))
    return made.select(key, F.col("w.start").alias("start"), F.col("w.end").alias("stop"), "word")


class TwoStacks:
    """The composition of the last n maps of a sequence; maps have no inverse, so two stacks share the work."""

    def __init__(self, n: int, states: int):
        self.n, self.identity = n, list(range(states))
        self.front: list[list[int]] = []  # suffix compositions, the oldest on top
        self.back: list[list[int]] = []
        self.back_all = self.identity

    def push(self, image: list[int]) -> list[int]:
        if len(self.front) + len(self.back) == self.n:
            if not self.front:
                whole = self.identity
                for m in reversed(self.back):
                    whole = [whole[q] for q in m]
                    self.front.append(whole)
                self.back, self.back_all = [], self.identity
            self.front.pop()
        self.back.append(image)
        self.back_all = [image[q] for q in self.back_all]
        first = self.front[-1] if self.front else self.identity
        return [self.back_all[q] for q in first]


def state_asof(states: DataFrame, probes: DataFrame, key: str, time: str) -> DataFrame:
    """Every probe with the last known state at or before its time (null if none): both sides are sorted together once."""
    both = states.select(key, time, "state", F.lit(0).alias("probe")).unionByName(probes.select(key, time, F.lit(None).cast(states.schema["state"].dataType).alias("state"), F.lit(1).alias("probe")))
    before = Window.partitionBy(key).orderBy(time, "probe").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("state", F.last("state", ignorenulls=True).over(before)).where("probe = 1").drop("probe")
