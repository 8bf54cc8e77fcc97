"""Counts over windows without joining: what an arrival finds, what a window holds, how arrivals are spaced."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from winjoin.functions.hashing import floor_div


def arrival_counts(left: DataFrame, right: DataFrame, w1: int, w2: int, by: Sequence[str], match: str = "n_opposite") -> DataFrame:
    """For each arrival the number of opposite tuples of its group in the opposite window: (stream, id, *by, t, n_opposite).

    A pair counts once, for its newer member; of equal times for the first stream's.
    A running count is looked up at both ends of the window, so the cost does not
    depend on the window's size: one sort of three rows per tuple, and one sum per arrival.
    """
    both = left.select(F.lit(1).alias("stream"), "id", *by, "t").unionByName(right.select(F.lit(2).alias("stream"), "id", *by, "t"))
    # order within an instant: 0 looks before its tuples, 1 is a tuple, 2 looks after them
    at = F.when(F.col("stream") == 1, F.struct((F.col("t") - F.lit(w2)).alias("low"), F.lit(2).alias("o"))).otherwise(F.struct((F.col("t") - F.lit(w1)).alias("low"), F.lit(0).alias("o")))
    rows = F.array(
        F.struct(F.col("t").alias("at"), F.lit(1).alias("o"), F.lit(0).alias("sign")),
        F.struct(F.col("t").alias("at"), at["o"].alias("o"), F.lit(1).alias("sign")),
        F.struct(at["low"].alias("at"), F.lit(0).alias("o"), F.lit(-1).alias("sign")),
    )
    looks = both.withColumn("x", F.explode(rows)).select("stream", "id", *by, "t", "x.at", "x.o", "x.sign")
    running = Window.partitionBy(*by).orderBy("at", "o").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    # lookups with sign 0 are the tuples themselves
    for s in (1, 2):
        looks = looks.withColumn(f"n{s}", F.sum(F.when((F.col("sign") == 0) & (F.col("stream") == s), 1).otherwise(0)).over(running))
    seen = F.col("sign") * F.when(F.col("stream") == 1, F.col("n2")).otherwise(F.col("n1"))
    return looks.where("sign <> 0").groupBy("stream", "id", *by, "t").agg(F.sum(seen).cast("long").alias(match))


def window_sizes(stream: DataFrame, w: int, by: Sequence[str]) -> DataFrame:
    """Tuples of the group in [t - w, t] at each arrival, by a range frame: (id, *by, t, n)."""
    frame = Window.partitionBy(*by).orderBy("t").rangeBetween(-w, 0)
    return stream.select("id", *by, "t", F.count(F.lit(1)).over(frame).alias("n"))


def held_at(stream: DataFrame, w: int, by: Sequence[str], t0: int, td: int) -> DataFrame:
    """Window size of each group at the end of each epoch in which it changed: (*by, epoch, n).

    A tuple adds one in its epoch and takes one away in the epoch after its window; sums run over those few rows.
    """
    epoch = lambda t: floor_div(t - F.lit(t0), td)
    steps = stream.withColumn("x", F.explode(F.array(F.struct(epoch(F.col("t")).alias("epoch"), F.lit(1).alias("d")), F.struct((epoch(F.col("t") + F.lit(w)) + 1).alias("epoch"), F.lit(-1).alias("d")))))
    moved = steps.groupBy(*by, F.col("x.epoch").alias("epoch")).agg(F.sum("x.d").alias("d"))
    running = Window.partitionBy(*by).orderBy("epoch").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return moved.select(*by, "epoch", F.sum("d").over(running).alias("n"))


def arrival_gaps(stream: DataFrame, by: Sequence[str]) -> DataFrame:
    """Time since the group's previous tuple: (id, *by, t, gap_us)."""
    order = Window.partitionBy(*by).orderBy("t", "id")
    return stream.select("id", *by, "t", (F.col("t") - F.lag("t").over(order)).alias("gap_us"))


def block_numbers(stream: DataFrame, block: int, by: Sequence[str]) -> DataFrame:
    """Place of each tuple in its group's blocks: (id, *by, block_no, pos)."""
    n = F.row_number().over(Window.partitionBy(*by).orderBy("t", "id")) - 1
    return stream.select("id", *by, n.alias("_n")).select("id", *by, (F.col("_n") / F.lit(block)).cast("long").alias("block_no"), (F.col("_n") % block).cast("int").alias("pos"))


def membership(stream: DataFrame, at: int, w: int) -> DataFrame:
    """Tuples inside the window at an instant."""
    return stream.where(F.col("t").between(at - w, at))
