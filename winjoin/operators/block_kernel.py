"""The block nested-loop join of one (mini-)partition, on NumPy blocks.

A stream's window is a queue of full blocks and one head block. Arrivals go to
the head; a counter tells how many of its tuples have not probed yet. Probing
skips opposite tuples that have not probed themselves: these will do it later,
so a pair is found once. A block whose newest tuple has left the window first
meets the opposite tuples that have not probed, then goes. Every pair is
tested with the exact condition; blocks only bound what is read.
"""

from __future__ import annotations

from collections import deque
from collections.abc import Iterable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from winjoin.functions.hashing import partition_id

PAIR = "l_id long, r_id long, key long, l_t long, r_t long, newer_t long"


class BlockWindow:
    """Both windows of a partition. Streams are 0 and 1; ``windows`` their lengths.

    ``skip_unprobed`` and ``meet_before_expiry`` are the two rules for exact
    results; they can be switched off to see what each is for.
    """

    def __init__(self, windows: tuple[int, int], block: int = 64, skip_unprobed: bool = True, meet_before_expiry: bool = True):
        self.windows, self.block = windows, block
        self.skip_unprobed, self.meet_before_expiry = skip_unprobed, meet_before_expiry
        self.full: tuple[deque, deque] = (deque(), deque())
        self.head: tuple[list, list] = ([], [])
        self.unprobed = [0, 0]
        self.pairs: list[np.ndarray] = []
        self.blocks_read = self.compared = 0

    def arrive(self, stream: int, key: int, t: int, ident: int) -> None:
        self.expire(t)
        self.head[stream].append((key, t, ident))
        self.unprobed[stream] += 1
        if len(self.head[stream]) == self.block:
            self.probe(stream)
            self.full[stream].append(np.array(self.head[stream], np.int64))
            self.head[stream].clear()

    def end_of_run(self) -> None:
        """The buffer is empty: partly filled heads probe now rather than wait."""
        for stream in (0, 1):
            self.probe(stream)

    def probe(self, stream: int) -> None:
        n = self.unprobed[stream]
        if not n:
            return
        mine = np.array(self.head[stream][-n:], np.int64)
        other = 1 - stream
        for b in self.full[other]:
            self._meet(stream, mine, b)
        head = self.head[other]
        seen = head[: len(head) - self.unprobed[other]] if self.skip_unprobed else head
        if seen:
            self._meet(stream, mine, np.array(seen, np.int64))
        self.unprobed[stream] = 0

    def expire(self, now: int) -> None:
        for stream in (0, 1):
            queue, other = self.full[stream], 1 - stream
            while queue and queue[0][-1, 1] + self.windows[stream] < now:
                n = self.unprobed[other]
                if n and self.meet_before_expiry:
                    self._meet(other, np.array(self.head[other][-n:], np.int64), queue[0])
                queue.popleft()

    def _meet(self, stream: int, mine: np.ndarray, block: np.ndarray) -> None:
        self.blocks_read += 1
        self.compared += len(mine) * len(block)
        a, b = np.nonzero(mine[:, None, 0] == block[None, :, 0])
        l, r = (mine[a], block[b]) if stream == 0 else (block[b], mine[a])
        ok = (r[:, 1] >= l[:, 1] - self.windows[1]) & (r[:, 1] <= l[:, 1] + self.windows[0])
        if ok.any():
            self.pairs.append(np.stack([l[ok, 2], r[ok, 2], l[ok, 0], l[ok, 1], r[ok, 1], np.maximum(l[ok, 1], r[ok, 1])], axis=1))

    def take(self) -> np.ndarray:
        out = np.concatenate(self.pairs) if self.pairs else np.zeros((0, 6), np.int64)
        self.pairs = []
        return out

    def held(self) -> int:
        return sum(len(h) for h in self.head) + sum(len(b) for q in self.full for b in q)


def run_tuples(rows: Iterable[tuple[int, int, int, int, int]], windows: tuple[int, int], block: int = 64, flush: str = "epoch", **rules) -> tuple[np.ndarray, BlockWindow]:
    """Feed (epoch, stream, key, t, id) in order of (t, stream, id). flush 'epoch': heads probe at the end of each epoch; 'block': when full or at the end."""
    w, last = BlockWindow(windows, block, **rules), None
    for epoch, stream, key, t, ident in rows:
        if flush == "epoch" and last is not None and epoch != last:
            w.end_of_run()
        last = epoch
        w.arrive(stream, key, t, ident)
    w.end_of_run()
    return w.take(), w


def replay_join(left: DataFrame, right: DataFrame, w1: int, w2: int, n_part: int = 60, td: int = 2_000_000, block: int = 64, flush: str = "epoch", leaves: DataFrame | None = None, max_depth: int = 12) -> DataFrame:
    """The kernel over all partitions, or over all leaves of a directory: rows as the window join's."""
    from winjoin.operators.window_join import locate

    by = ["pid"] if leaves is None else ["pid", "depth", "suffix"]
    merged = left.select(F.lit(0).alias("stream"), "id", "key", "t").unionByName(right.select(F.lit(1).alias("stream"), "id", "key", "t"))
    if leaves is None:
        placed = merged.withColumn("pid", partition_id(F.col("key"), n_part))
    else:
        renamed = merged.select("stream", F.col("id").alias("x_id"), F.col("key").alias("x_key"), F.col("t").alias("x_t"))
        placed = locate(renamed, "x", leaves, n_part, max_depth).select("stream", F.col("x_id").alias("id"), F.col("x_key").alias("key"), F.col("x_t").alias("t"), F.col("x_pid").alias("pid"), F.col("x_depth").alias("depth"), F.col("x_suffix").alias("suffix"))

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values(["t", "stream", "id"])
        feed = zip((rows.t // td).tolist(), rows.stream.tolist(), rows.key.tolist(), rows.t.tolist(), rows.id.tolist())
        pairs, _ = run_tuples(feed, (w1, w2), block, flush)
        return pd.DataFrame(pairs, columns=["l_id", "r_id", "key", "l_t", "r_t", "newer_t"])

    return placed.groupBy(*by).applyInPandas(run, PAIR)
