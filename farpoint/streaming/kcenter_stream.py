"""k-center over streams (an extension: the methods compose, so a micro-batch is a block).

Center sets are kept by level, as the digits of a binary counter: two sets of one level make one of
the next. The factor grows by 2 with each level, so with the logarithm of the batches.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from farpoint.operators import kernels
from farpoint.operators.blocked import blocked_farthest_first


class CenterLevels:
    """At most one set of k centers (ids, coordinates) on each level."""

    def __init__(self, k: int, levels: list | None = None):
        self.k, self.levels = k, levels or []

    def add(self, ids: np.ndarray, x: np.ndarray) -> None:
        if not len(ids):
            return
        level = 0
        while level < len(self.levels) and self.levels[level] is not None:
            other_ids, other_x = self.levels[level]
            ids, x = self.reduced(np.concatenate([ids, other_ids]), np.concatenate([x, other_x]))
            self.levels[level] = None
            level += 1
        if level == len(self.levels):
            self.levels.append(None)
        self.levels[level] = (ids, x)

    def reduced(self, ids: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        ids, x = kernels.by_id(ids, x)
        picks, _, _ = kernels.farthest_first(x, self.k)
        return ids[picks], x[picks]

    def centers(self) -> tuple[np.ndarray, np.ndarray]:
        held = [s for s in self.levels if s is not None]
        if not held:
            return np.empty(0, np.int64), np.empty((0, 1))
        return self.reduced(np.concatenate([i for i, _ in held]), np.concatenate([x for _, x in held]))

    @property
    def guarantee(self) -> int:
        """Twice the rounds that a point of the highest level has been through, the last one included."""
        return 2 * (len(self.levels) + 1)

    def dump(self) -> str:
        return json.dumps([None if s is None else [s[0].tolist(), s[1].tolist()] for s in self.levels])

    @classmethod
    def load(cls, k: int, text: str) -> CenterLevels:
        return cls(k, [None if s is None else (np.array(s[0], np.int64), np.array(s[1])) for s in json.loads(text)])


class StreamKCenter:
    """For foreachBatch: each micro-batch is reduced on the cluster to k centers and joins the levels."""

    def __init__(self, k: int, blocks: int = 8):
        self.levels, self.k, self.blocks, self.seen = CenterLevels(k), k, blocks, -1

    def __call__(self, batch: DataFrame, epoch: int) -> None:
        if epoch <= self.seen:
            return  # a batch that is run again after a restart counts once
        rows = blocked_farthest_first(batch, self.k, self.blocks).centers.collect()  # k rows
        if rows:
            self.levels.add(np.array([r.id for r in rows]), np.array([list(r.coords) for r in rows]))
        self.seen = epoch


def stream_kcenter(points: DataFrame, k: int, checkpoint: str, blocks: int = 8) -> tuple[StreamKCenter, StreamingQuery]:
    """Starts a query that keeps centers of all points (id, coords) of a stream so far."""
    sink = StreamKCenter(k, blocks)
    return sink, points.writeStream.foreachBatch(sink).option("checkpointLocation", checkpoint).start()


WINDOWED = "window_start timestamp, rank int, id long, coords array<double>, points long"


def windowed_kcenter(points: DataFrame, k: int, window: str, watermark: str, slide: str | None = None) -> DataFrame:
    """Centers of each event-time window (ts, id, coords), emitted when the watermark has passed it.

    Rows later than the watermark are dropped; the state of a window is its center levels. ``slide`` makes
    windows overlap.
    """

    def step(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            text, seen = state.get
            ids, x = CenterLevels.load(k, text).centers()
            state.remove()
            yield pd.DataFrame({"window_start": [key[0]] * len(ids), "rank": np.arange(1, len(ids) + 1, dtype=np.int32), "id": ids, "coords": x.tolist(), "points": [seen] * len(ids)})
            return
        end, passed = int(pd.Timestamp(key[1]).timestamp() * 1000), state.getCurrentWatermarkMs()
        if end <= passed:  # too late for this window
            if state.exists:
                state.setTimeoutTimestamp(passed + 1)
            return
        text, seen = state.get if state.exists else ("[]", 0)
        levels = CenterLevels.load(k, text)
        for batch in batches:
            levels.add(*levels.reduced(batch["id"].to_numpy(np.int64), np.array(batch["coords"].tolist(), float)))
            seen += len(batch)
        state.update((levels.dump(), seen))
        state.setTimeoutTimestamp(end)

    timed = points.withWatermark("ts", watermark)
    w = F.window("ts", window, slide) if slide else F.window("ts", window)
    keyed = timed.select(w.alias("w"), "ts", "id", "coords").select(F.col("w.start").alias("window_start"), F.col("w.end").alias("window_end"), "ts", "id", "coords")
    grouped = keyed.groupBy("window_start", "window_end")
    return grouped.applyInPandasWithState(step, WINDOWED, "levels string, seen long", "append", GroupStateTimeout.EventTimeTimeout)
