import random
from collections import Counter

import pytest
from pyspark.sql import functions as F

from winjoin.functions.hashing import bmodel_key, buddy_slot, mini_bits, mix32, mix32_int, partition_id, reversed_bits_int
from winjoin.operators.directory import Bucket, Directory, buddy, directory_stats, directory_trace, static_directory
from winjoin.sources.streams import events, merge_tagged, table


def check(d, sizes):
    """Slots are covered by contiguous buckets of one suffix; tuples are where their hash says; sizes obey the thresholds."""
    at = 0
    for b in d.buckets():
        width = 1 << (d.depth - b.local)
        assert b.first == at and all(s is b for s in d.slots[at : at + width])
        at += width
        suffixes = {h & ((1 << b.local) - 1) for h in b.hashes}
        assert len(suffixes) <= 1 and all(d.locate(h) is b for h in b.hashes)
        assert b.size <= 2 * d.theta or b.local == d.max_depth
        other = buddy(b.first, d.depth, b.local)
        if other is not None:
            assert d.slots[other].local != b.local or buddy(d.slots[other].first, d.depth, b.local) == b.first
            mergeable = b.size < d.theta and d.slots[other].local == b.local and b.size + d.slots[other].size < 2 * d.theta
            assert not mergeable
    assert at == 1 << d.depth and not (d.depth and all(b.local < d.depth for b in d.buckets()))
    assert Counter({h: n for b in d.buckets() for h, n in b.hashes.items()}) == sizes


def test_random_histories():
    for seed in range(20):
        rnd, d, sizes = random.Random(seed), Directory(10, 6), Counter()
        for _ in range(400):
            h = rnd.randrange(64)
            if rnd.random() < 0.6 or not sizes[h]:
                d.add(h)
                sizes[h] += 1
            else:
                d.remove(h)
                sizes[h] -= 1
            sizes += Counter()
            if rnd.random() < 0.2:
                d.tune()
                check(d, sizes)


def test_thresholds_are_strict():
    def of(*sizes):
        d = Directory(10, 4)
        d.depth, d.slots = len(sizes) // 2, []
        for k, n in enumerate(sizes):
            d.slots.append(Bucket(d.depth, k, Counter({reversed_bits_int(k, d.depth): n}) if n else Counter()))
        return d

    d = Directory(10, 4)
    d.add(0, 10)
    d.add(1, 10)
    d.tune()
    assert d.depth == 0
    d.add(1)
    d.tune()
    assert d.depth == 1 and [b.size for b in d.buckets()] == [10, 11] and all(b.local == 1 for b in d.buckets())
    assert not of(10, 5).merge(of(10, 5).slots[0])
    x = of(9, 11)
    assert not x.merge(x.slots[0])
    x = of(9, 10)
    assert x.merge(x.slots[0]) and x.depth == 0
    one = Directory(10, 4)
    one.add(5, 30)
    one.tune()
    assert [b.size for b in one.unsplittable()] == [30]


def test_buddies(spark):
    assert buddy(4, 3, 2) == 6 and buddy(6, 3, 2) == 4 and buddy(0, 3, 0) is None
    assert [reversed_bits_int(b, 3) for b in (0b001, 0b101)] == [4, 5]
    rows = [(d, l, f) for d in range(6) for l in range(d + 1) for f in range(0, 1 << d, 1 << (d - l))]
    for d in range(6):
        df = spark.createDataFrame([(l, f) for dd, l, f in rows if dd == d], "l int, f int").withColumn("b", buddy_slot(F.col("f"), F.col("l"), d))
        assert all(r.b == buddy(r.f, d, r.l) for r in df.collect())


def test_hashes(spark):
    df = spark.range(-500, 1500).select("id", mix32(F.col("id")).alias("h"))
    assert all(r.h == mix32_int(r.id) for r in df.collect())
    cells = table(spark, "/root/testdata/sf0.1", "events").select(partition_id(F.col("user_id"), 60).alias("p"), mini_bits(F.col("user_id"), 2).alias("m")).distinct().count()
    assert cells == 240
    keys = spark.range(400_000).select(bmodel_key(F.col("id"), 0.7).alias("k")).groupBy("k").count()
    r = keys.agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("count") / 400_000) ** 2).alias("p2"), (F.max("count") / 400_000).alias("top")).first()
    # the expected share of equal pairs: without pairs of a tuple with itself
    assert r.n == 305_535 and r.p2 - 1 / 400_000 == pytest.approx(3.05e-6, rel=0.01) and r.top == pytest.approx(2.325e-4, rel=0.001)


def test_static_directory(spark):
    both = merge_tagged([events(spark, "/root/testdata/sf0.1", k) for k in ("click", "view")])
    s = directory_stats(static_directory(both, 60, 182, 8), 182).first()
    assert (s.leaves, s.tuples, s.smallest, s.largest, s.deepest, s.unsplittable) == (168, 39804, 74, 363, 3, 0)
    hot = spark.createDataFrame([(1,)] * 50 + [(2,)], "key long")
    assert directory_stats(static_directory(hot, 1, 10, 5), 10).first().unsplittable == 1


def test_trace_grows_and_shrinks(spark):
    up, down = [(0, b, e, e * 2) for b in range(8) for e in range(1, 6)], [(0, b, e, 20 - e * 2) for b in range(8) for e in range(6, 11)]
    t = directory_trace(spark.createDataFrame(up + down, "pid int, bits int, epoch long, n int"), 10, 3).orderBy("epoch").collect()
    sizes = [r.buckets for r in t]
    assert sizes[0] == 1 and max(sizes) == 4 and sizes[-1] == 1 and all(r.largest <= 20 for r in t)
