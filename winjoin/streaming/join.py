"""Window joins of live streams.

``builtin`` is Spark's own stream-stream join. ``partitioned`` keeps both windows of
a partition in state and joins each micro-batch (a distribution epoch) in
order of (t, stream, id); its state is keyed by partition, so a partition moves between
executors as Spark schedules it.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle, StreamingQueryListener

from winjoin.functions.hashing import partition_id
from winjoin.plans.balance import PPM, reorganise, start
from winjoin.plans.model import ClusterSpec

PAIR = "l_id long, r_id long, key long, l_t long, r_t long, newer_t long"


def with_event_time(stream: DataFrame) -> DataFrame:
    """Adds ts, the microseconds t as a timestamp, for watermarks."""
    return stream.withColumn("ts", F.timestamp_micros("t"))


def builtin(left: DataFrame, right: DataFrame, w1: int, w2: int, delay: str = "0 seconds", how: str = "inner") -> DataFrame:
    """Stream-stream join in append mode; ``delay`` is the watermark's, at least the streams' unevenness."""
    l = with_event_time(left).withWatermark("ts", delay).select(F.col("id").alias("l_id"), F.col("key").alias("l_key"), F.col("t").alias("l_t"), F.col("ts").alias("l_ts"))
    r = with_event_time(right).withWatermark("ts", delay).select(F.col("id").alias("r_id"), F.col("key").alias("r_key"), F.col("t").alias("r_t"), F.col("ts").alias("r_ts"))
    cond = (F.col("l_key") == F.col("r_key")) & (F.col("r_ts") >= F.col("l_ts") - F.expr(f"INTERVAL {w2} MICROSECONDS")) & (F.col("r_ts") <= F.col("l_ts") + F.expr(f"INTERVAL {w1} MICROSECONDS"))
    return l.join(r, cond, {"inner": "inner", "left": "leftOuter", "right": "rightOuter", "full": "fullOuter", "left_semi": "leftSemi"}[how])


class WindowProcessor(StatefulProcessor):
    """State of one partition: the tuples of both windows in blocks, one state row a block, and how far time has come.

    Within a micro-batch tuples are handled in order of (t, stream, id); a batch
    may only bring tuples that are not older than those of earlier batches.
    """

    def __init__(self, w1: int, w2: int, block: int = 64, most: int = 1_000_000):
        self.windows, self.block, self.most = (w1, w2), block, most

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.held = handle.getListState("blocks", "stream int, newest long, tuples binary")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        new = pd.concat(list(rows)).sort_values(["t", "stream", "id"])
        blocks: dict[int, list[np.ndarray]] = {0: [], 1: []}
        for stream, _, data in self.held.get():
            blocks[stream].append(np.frombuffer(data, np.int64).reshape(-1, 3))
        fresh = {s: new.loc[new.stream == s, ["key", "t", "id"]].to_numpy(np.int64) for s in (0, 1)}
        out = []
        # old against new on both sides, then new against new once: the first stream's new tuples probe all, the second's only old ones
        for s in (0, 1):
            others = blocks[1 - s] + ([fresh[1]] if s == 0 else [])
            for b in others:
                # a block out of reach of the oldest new tuple is not read
                if len(fresh[s]) and len(b) and b[:, 1].max() + self.windows[1 - s] >= fresh[s][0, 1]:
                    out.append(self._pairs(s, fresh[s], b))
        now = int(new.t.max())
        keep = []
        for s in (0, 1):
            tuples = np.concatenate([*blocks[s], fresh[s]]) if blocks[s] or len(fresh[s]) else np.zeros((0, 3), np.int64)
            tuples = tuples[tuples[:, 1] + self.windows[s] >= now]
            keep += [(s, int(tuples[a : a + self.block, 1].max()), tuples[a : a + self.block].tobytes()) for a in range(0, len(tuples), self.block)]
        self.held.put(keep) if keep else self.held.clear()
        found = np.concatenate(out) if out else np.zeros((0, 6), np.int64)
        yield pd.DataFrame(found, columns=["l_id", "r_id", "key", "l_t", "r_t", "newer_t"])

    def _pairs(self, s: int, mine: np.ndarray, block: np.ndarray) -> np.ndarray:
        """Pairs of equal keys within the windows: both sides sorted by key, so space follows the pairs and not the product of both sizes."""
        block = block[np.argsort(block[:, 0], kind="stable")]
        lo, hi = (np.searchsorted(block[:, 0], mine[:, 0], side) for side in ("left", "right"))
        out = []
        # a hot key meets in pieces of at most this many pairs
        cut = np.searchsorted(np.cumsum(hi - lo), np.arange(self.most, int((hi - lo).sum()) + self.most, self.most), side="left") + 1
        for p, q in zip([0, *cut[:-1]], cut):
            out.append(self._within(s, mine[p:q], block, lo[p:q], hi[p:q]))
        return np.concatenate(out) if out else np.zeros((0, 6), np.int64)

    def _within(self, s: int, mine: np.ndarray, block: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        n = hi - lo
        a = np.repeat(np.arange(len(mine)), n)
        b = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n) + np.repeat(lo, n)
        l, r = (mine[a], block[b]) if s == 0 else (block[b], mine[a])
        ok = (r[:, 1] >= l[:, 1] - self.windows[1]) & (r[:, 1] <= l[:, 1] + self.windows[0])
        return np.stack([l[ok, 2], r[ok, 2], l[ok, 0], l[ok, 1], r[ok, 1], np.maximum(l[ok, 1], r[ok, 1])], axis=1)

    def close(self) -> None:
        pass


def partitioned(merged: DataFrame, w1: int, w2: int, n_part: int = 60, block: int = 64) -> DataFrame:
    """Join of one merged stream (stream 1 or 2, id, key, t). Needs the RocksDB state store; n_part is fixed with the first checkpoint."""
    placed = merged.select((F.col("stream") - 1).cast("int").alias("stream"), "id", "key", "t", partition_id(F.col("key"), n_part).alias("pid"))
    return placed.groupBy("pid").transformWithStateInPandas(WindowProcessor(w1, w2, block), outputStructType=PAIR, outputMode="Append", timeMode="None")


def use_rocksdb(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")


def collect(query: DataFrame, name: str, path: str, checkpoint: str, available_now: bool = True, td: str = "2 seconds"):
    """Collector: results of a query below its own name, each batch written under its number, so a replayed batch replaces itself."""

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/query_id={name}/batch={number}")

    out = query.writeStream.queryName(name).option("checkpointLocation", checkpoint).foreachBatch(write)
    return (out.trigger(availableNow=True) if available_now else out.trigger(processingTime=td)).start()


def reassign(cluster: ClusterSpec, pids: list[int], held: Callable[[], dict[int, int]] = dict) -> Callable[[list, int], dict]:
    """A decision for ``controller``: the master's reorganisation, with its pairing, random groups and changing degree, on mean occupancies."""
    state = start(cluster, pids)

    def decide(loads: list[tuple[int, float]], rep: int) -> dict[int, int]:
        state.samples = {int(v): [int(f * PPM)] for v, f in loads if int(v) in state.active}
        reorganise(state, rep, held())
        return dict(state.assignment)

    return decide


def latest_assignment(spark: SparkSession, path: str, n_part: int, n_nodes: int) -> dict[int, int]:
    """What the controller wrote last, one row a partition; before that partitions go round the nodes."""
    out = {p: p % n_nodes for p in range(n_part)}
    try:
        rows = spark.read.parquet(f"{path}/assignment")
    except AnalysisException:  # nothing is written yet
        return out
    last = rows.agg(F.max("rep_epoch").alias("r")).first().r
    return out | {r.pid: r.node for r in rows.where(F.col("rep_epoch") == last).select("pid", "node").collect()}


def load_by_node(path: str, n_part: int, n_nodes: int, capacity: int) -> Callable[[DataFrame], DataFrame]:
    """For ``controller``: (node, f) of a batch of merged tuples under the assignment that holds now; f is what a node gets over its buffer of ``capacity`` tuples."""

    def load_of(batch: DataFrame) -> DataFrame:
        spark = batch.sparkSession
        now = spark.createDataFrame(list(latest_assignment(spark, path, n_part, n_nodes).items()), "pid int, node int")
        came = batch.withColumn("pid", partition_id(F.col("key"), n_part)).groupBy("pid").agg(F.count(F.lit(1)).alias("n"))
        return now.join(came, "pid", "left").groupBy("node").agg(F.least(F.lit(1.0), F.coalesce(F.sum("n"), F.lit(0)) / F.lit(float(capacity))).alias("f"))

    return load_of


def controller(load_of: Callable[[DataFrame], DataFrame], decide: Callable[[list, int], dict], path: str, every: int) -> Callable[[DataFrame, int], None]:
    """For foreachBatch: writes the batch's load rows and, every ``every`` batches, what ``decide`` makes of those of the
    last reorganisation epoch: the next assignment. Loads are a row a node, so a round trip is a few hundred rows."""

    def step(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        load_of(batch).withColumn("epoch", F.lit(number)).write.mode("overwrite").parquet(f"{path}/load/epoch_no={number}")
        if (number + 1) % every == 0:
            rep = (number + 1) // every
            files = [f"{path}/load/epoch_no={k}" for k in range(number + 1 - every, number + 1)]
            rows = spark.read.parquet(*files).groupBy("node").agg(F.avg("f").alias("f")).collect()
            chosen = decide([(r.node, r.f) for r in rows], rep)
            spark.createDataFrame([(rep, int(p), int(v)) for p, v in chosen.items()], "rep_epoch long, pid int, node int").write.mode("overwrite").parquet(f"{path}/assignment/rep_epoch={rep}")

    return step


class Progress(StreamingQueryListener):
    """Rows in, rows dropped behind the watermark and batch times of all queries."""

    def __init__(self):
        self.rows: list[tuple] = []

    def onQueryStarted(self, event) -> None:
        pass

    def onQueryProgress(self, event) -> None:
        p = event.progress
        late = sum(s.numRowsDroppedByWatermark for s in p.stateOperators)
        self.rows.append((p.name, p.batchId, p.numInputRows, late, p.durationMs.get("triggerExecution", 0)))

    def onQueryTerminated(self, event) -> None:
        pass


def windowed_counts(results: DataFrame, length: str, slide: str | None = None, delay: str = "0 seconds") -> DataFrame:
    """Results per tumbling or sliding window of their newer time."""
    timed = results.withColumn("ts", F.timestamp_micros("newer_t")).withWatermark("ts", delay)
    return timed.groupBy(F.window("ts", length, slide) if slide else F.window("ts", length)).agg(F.count(F.lit(1)).alias("n"))


def sessions(stream: DataFrame, gap: str, delay: str = "0 seconds") -> DataFrame:
    """Sessions of arrivals per key."""
    return with_event_time(stream).withWatermark("ts", delay).groupBy(F.session_window("ts", gap), "key").agg(F.count(F.lit(1)).alias("n"))


def once_only(stream: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Tuples without replays of the same id."""
    return with_event_time(stream).withWatermark("ts", delay).dropDuplicatesWithinWatermark(["id"])
