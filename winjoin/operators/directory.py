"""Extendible-hash directories that keep partition-groups between theta and 2 theta tuples.

Slots are addressed by the reversed low bits of the hash: a bucket of local
depth d' in a directory of depth d then owns the 2^(d-d') slots that follow its
first one, and its buddy stands next to it.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass, field

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from winjoin.functions.hashing import mini_bits, partition_id, reversed_bits_int, two_to


def buddy(first: int, depth: int, local: int) -> int | None:
    """First slot of the buddy of the bucket that starts at ``first``; None at local depth 0."""
    if local == 0:
        return None
    width = 1 << (depth - local)
    return first ^ width


@dataclass
class Bucket:
    local: int
    first: int
    hashes: Counter = field(default_factory=Counter)

    @property
    def size(self) -> int:
        return sum(self.hashes.values())


class Directory:
    """One group's directory. Splits above 2 theta, merges buddies below theta whose sum stays below 2 theta; all tests are strict."""

    def __init__(self, theta: int, max_depth: int = 12):
        self.theta, self.max_depth, self.depth = theta, max_depth, 0
        self.slots = [Bucket(0, 0)]

    def buckets(self) -> list[Bucket]:
        return [b for i, b in enumerate(self.slots) if b.first == i]

    def locate(self, h: int) -> Bucket:
        return self.slots[reversed_bits_int(h, self.depth)]

    def add(self, h: int, n: int = 1) -> None:
        self.locate(h).hashes[h] += n

    def remove(self, h: int, n: int = 1) -> None:
        bucket = self.locate(h)
        bucket.hashes[h] -= n
        if bucket.hashes[h] <= 0:
            del bucket.hashes[h]

    def double(self) -> None:
        self.slots = [b for b in self.slots for _ in (0, 1)]
        self.depth += 1
        for b in {id(b): b for b in self.slots}.values():
            b.first *= 2

    def split(self, bucket: Bucket) -> bool:
        """Halve a bucket; False where the depth is used up."""
        if bucket.local >= self.max_depth:
            return False
        if bucket.local == self.depth:
            self.double()
        bit, width = bucket.local, 1 << (self.depth - bucket.local)
        other = Bucket(bucket.local + 1, bucket.first + width // 2)
        bucket.local += 1
        for h in [h for h in bucket.hashes if h >> bit & 1]:
            other.hashes[h] = bucket.hashes.pop(h)
        self.slots[other.first : other.first + width // 2] = [other] * (width // 2)
        return True

    def merge(self, bucket: Bucket) -> bool:
        """Unite a bucket below theta with its buddy of equal depth if both stay below 2 theta."""
        at = buddy(bucket.first, self.depth, bucket.local)
        if at is None or bucket.size >= self.theta:
            return False
        other = self.slots[at]
        if other.local != bucket.local or bucket.size + other.size >= 2 * self.theta:
            return False
        left, right = sorted((bucket, other), key=lambda b: b.first)
        left.hashes.update(right.hashes)
        left.local -= 1
        width = 1 << (self.depth - left.local)
        self.slots[left.first : left.first + width] = [left] * width
        while self.depth and all(b.local < self.depth for b in self.slots):
            self.slots = self.slots[::2]
            self.depth -= 1
            for b in {id(b): b for b in self.slots}.values():
                b.first //= 2
        return True

    def tune(self) -> None:
        """Split and merge until no bucket asks for it."""
        work = True
        while work:
            work = False
            for b in self.buckets():
                if b.size > 2 * self.theta and self.split(b):
                    work = True
                    break
                if b.size < self.theta and self.merge(b):
                    work = True
                    break

    def unsplittable(self) -> list[Bucket]:
        return [b for b in self.buckets() if b.size > 2 * self.theta]


def static_directory(tuples: DataFrame, n_part: int, theta: int, max_depth: int, key: str = "key") -> DataFrame:
    """Leaves (pid, depth, suffix, n, unsplittable) of all groups at once.

    A node (pid, depth, low bits) is a leaf if it holds at most 2 theta tuples (or has
    the greatest depth) and its parent holds more; counts only fall with depth, so the parent speaks for all ancestors.
    """
    kind = dict(tuples.dtypes)[key]
    fine = tuples.groupBy(partition_id(F.col(key), n_part, kind).alias("pid"), mini_bits(F.col(key), max_depth, kind).alias("bits")).agg(F.count(F.lit(1)).alias("c"))
    nodes = fine.withColumn("depth", F.explode(F.sequence(F.lit(0), F.lit(max_depth)))).groupBy("pid", "depth", F.pmod(F.col("bits"), two_to(F.col("depth"))).cast("int").alias("suffix")).agg(F.sum("c").alias("n"))
    parents = nodes.where(F.col("n") > 2 * theta).select(F.col("pid").alias("p_pid"), (F.col("depth") + 1).alias("p_depth"), F.col("suffix").alias("p_suffix"))
    stops = nodes.where((F.col("n") <= 2 * theta) | (F.col("depth") == max_depth))
    roots = stops.where("depth = 0")
    below = stops.where("depth > 0").join(
        parents, (F.col("pid") == F.col("p_pid")) & (F.col("depth") == F.col("p_depth")) & (F.pmod(F.col("suffix"), two_to(F.col("depth") - 1)) == F.col("p_suffix")), "left_semi")
    leaves = roots.unionByName(below)
    return leaves.select("pid", "depth", "suffix", "n", (F.col("n") > 2 * theta).alias("unsplittable"))


def directory_stats(leaves: DataFrame, theta: int) -> DataFrame:
    """(leaves, tuples, smallest, largest, deepest, in_range, unsplittable)."""
    return leaves.agg(
        F.count(F.lit(1)).alias("leaves"), F.sum("n").cast("long").alias("tuples"), F.min("n").cast("long").alias("smallest"), F.max("n").cast("long").alias("largest"), F.max("depth").cast("int").alias("deepest"),
        F.sum(F.when(F.col("n").between(theta, 2 * theta), 1).otherwise(0)).cast("long").alias("in_range"), F.sum(F.col("unsplittable").cast("long")).cast("long").alias("unsplittable"),
    )


def directory_trace(sizes: DataFrame, theta: int, max_depth: int) -> DataFrame:
    """A group's directory through time, with its memory: rows (pid, epoch, buckets, depth, tuples, largest, unsplittable).

    ``sizes``: (pid, bits, epoch, n), the window's tuples per hash suffix whenever they
    change. Groups are independent; the history of one is a few rows per suffix and epoch.
    """

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        d, out, last = Directory(theta, max_depth), [], {}
        for epoch, changed in rows.sort_values(["epoch", "bits"]).groupby("epoch"):
            for h, n in zip(changed.bits.tolist(), changed.n.tolist()):
                was = last.get(h, 0)
                if n > was:
                    d.add(h, n - was)
                elif n < was:
                    d.remove(h, was - n)
                last[h] = n
            d.tune()
            bs = d.buckets()
            out.append((int(rows.pid.iloc[0]), int(epoch), len(bs), d.depth, sum(b.size for b in bs), max(b.size for b in bs), len(d.unsplittable())))
        return pd.DataFrame(out, columns=["pid", "epoch", "buckets", "depth", "tuples", "largest", "unsplittable"])

    return sizes.groupBy("pid").applyInPandas(run, "pid int, epoch long, buckets long, depth int, tuples long, largest long, unsplittable long")
