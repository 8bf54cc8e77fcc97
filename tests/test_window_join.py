"""Results against brute force, at the edges of windows, and how plans look."""

import random

import pytest
from pyspark.sql import functions as F

from winjoin.operators.block_kernel import run_tuples
from winjoin.operators.frames import arrival_counts
from winjoin.operators.window_join import STRATEGIES, asof_latest, choose, nested_loop_window_join, window_join, window_join_multi, window_self_join
from winjoin.plans.model import HOUR, MINUTE
from winjoin.sources.streams import as_stream, decode_punctuated, events, merge_tagged, punctuated, rejected, save_bucketed, table, write_layout

SCHEMA = "id long, key long, t long"


def frame(spark, rows):
    return spark.createDataFrame(rows, SCHEMA)


def brute(left, right, w1, w2):
    return sorted((a[0], b[0]) for a in left for b in right if a[1] is not None and a[1] == b[1] and a[2] - w2 <= b[2] <= a[2] + w1)


def ids(df):
    return sorted((r.l_id, r.r_id) for r in df.collect())


@pytest.mark.parametrize("strategy", [s for s in STRATEGIES])
def test_all_strategies_on_random_streams(spark, strategy):
    rnd = random.Random(7)
    left, right = ([(i, rnd.randrange(6), rnd.randrange(-50, 200)) for i in range(120)] for _ in (0, 1))
    left += left[:3]  # a bag
    for w1, w2 in ((0, 0), (10, 3), (3, 40)):
        got = window_join(frame(spark, left), frame(spark, right), w1, w2, strategy, heavy=10, salts=3, slab_us=17)
        assert ids(got) == brute(left, right, w1, w2)


def test_closed_ends_ties_nulls_and_asymmetry(spark):
    l = frame(spark, [(1, 7, 100)])
    r = frame(spark, [(1, 7, 100 - 5), (2, 7, 100 - 6), (3, 7, 100 + 9), (4, 7, 100 + 10)])
    for s in ("naive", "cells", "partitioned", "slabs"):
        assert ids(window_join(l, r, 9, 5, s)) == [(1, 1), (1, 3)]
        assert ids(window_join(frame(spark, [(1, 1, 5)]), frame(spark, [(2, 1, 5)]), 0, 0, s)) == [(1, 2)]
        assert ids(window_join(frame(spark, [(1, 1, 0)]), frame(spark, [(2, 1, 8)]), 10, 2, s)) == [(1, 2)]
        assert ids(window_join(frame(spark, [(1, 1, 8)]), frame(spark, [(2, 1, 0)]), 10, 2, s)) == []
        assert ids(window_join(frame(spark, [(1, None, 5)]), frame(spark, [(2, None, 5)]), 9, 9, s)) == []
        assert ids(window_join(l, r.limit(0), 9, 9, s)) == []


def test_streams_without_key_or_time_go_aside(spark):
    df = spark.createDataFrame([(1, 1, 5), (2, None, 5), (3, 1, None)], SCHEMA)
    assert [r.id for r in as_stream(df, "key", "t", "id").collect()] == [1]
    assert sorted(r.id for r in rejected(df, "key", "t").collect()) == [2, 3]


def test_three_streams(spark):
    one = lambda *ts: [frame(spark, [(k, 1, t)]) for k, t in enumerate(ts)]
    assert window_join_multi(one(0, 3, 6), [5, 5, 5]).collect() == []
    assert window_join_multi(one(1, 3, 6), [5, 5, 5]).count() == 1
    rnd = random.Random(3)
    streams = [[(i, rnd.randrange(3), rnd.randrange(60)) for i in range(25)] for _ in range(3)]
    w = (9, 4, 14)
    want = sorted((a[0], b[0], c[0]) for a in streams[0] for b in streams[1] for c in streams[2] if a[1] == b[1] == c[1] and all(max(a[2], b[2], c[2]) - x[2] <= w[k] for k, x in enumerate((a, b, c))))
    got = window_join_multi([frame(spark, s) for s in streams], w).collect()
    assert sorted((r.id_1, r.id_2, r.id_3) for r in got) == want


def test_latest_partner_and_self_join(spark):
    l, r = frame(spark, [(1, 1, 10), (2, 1, 4), (3, 2, 10)]), frame(spark, [(7, 1, 10), (8, 1, 10), (9, 1, 3)])
    assert sorted((x.l_id, x.r_id) for x in asof_latest(l, r, 5).collect() if x.r_id is not None) == [(1, 8), (2, 9)]
    assert ids(window_self_join(frame(spark, [(1, 1, 0), (2, 1, 3), (3, 1, 9)]), 5)) == [(1, 2)]


def test_counts_of_arrivals_equal_the_join(spark):
    rnd = random.Random(5)
    left, right = ([(i, rnd.randrange(4), rnd.randrange(40)) for i in range(80)] for _ in (0, 1))
    n = arrival_counts(frame(spark, left), frame(spark, right), 7, 3, ["key"]).agg(F.sum("n_opposite")).first()[0]
    assert n == len(brute(left, right, 7, 3))


@pytest.mark.parametrize("flush", ["epoch", "block"])
def test_kernel_rules(flush):
    wrong = {"skip_unprobed": 0, "meet_before_expiry": 0}
    for seed in range(30):
        rnd = random.Random(seed)
        rows = [(s, i, rnd.randrange(4), rnd.randrange(600)) for s in (0, 1) for i in range(80)]
        feed = sorted(((t // 50, s, k, t, i) for s, i, k, t in rows), key=lambda r: (r[3], r[1], r[4]))
        want = brute([(i, k, t) for s, i, k, t in rows if s == 0], [(i, k, t) for s, i, k, t in rows if s == 1], 60, 90)
        run = lambda **rules: sorted((int(p[0]), int(p[1])) for p in run_tuples(feed, (60, 90), 8, flush, **rules)[0])
        assert run() == want
        for rule in wrong:
            wrong[rule] += run(**{rule: False}) != want
    # each rule is needed: without it some run has too many or too few pairs
    assert wrong["skip_unprobed"] and wrong["meet_before_expiry"]


def test_kernel_micro_cases():
    pairs = lambda rows, w, **k: len(run_tuples(rows, w, **k)[0])
    assert pairs([(0, 0, 1, 5, 1), (0, 1, 1, 5, 2)], (9, 9), block=2) == 1
    assert pairs([(0, 0, 1, 5, 1), (0, 1, 1, 5, 2)], (9, 9), block=2, skip_unprobed=False) == 2
    assert pairs([(0, 0, 1, 0, 1), (0, 0, 1, 0, 2), (0, 1, 1, 1, 3), (0, 0, 1, 3, 4)], (1, 1), block=2, flush="block") == 2
    _, w = run_tuples([(0, s, k, t, t) for t in range(1000) for s, k in ((0, t % 5), (1, t % 5))], (20, 20), 8)
    assert w.held() < 120


def test_punctuation(spark):
    rows = spark.createDataFrame([(0, 1, 1, None, None, None), (0, 2, None, 10, 1, 1), (0, 3, None, 11, 1, 2), (0, 4, 2, None, None, None), (0, 5, None, 12, 1, 3)], "g int, seq int, mark int, id long, key long, t long")
    assert [(r.id, r.stream) for r in decode_punctuated(rows, ["g"]).orderBy("id").collect()] == [(10, 1), (11, 1), (12, 2)]
    merged = merge_tagged([frame(spark, [(1, 1, 1), (2, 1, 5)]), frame(spark, [(3, 1, 2), (4, 1, 3)])]).withColumn("g", F.lit(0))
    marks = punctuated(merged, ["g"])
    assert marks.where("mark IS NOT NULL").count() == 3
    assert sorted(map(tuple, decode_punctuated(marks, ["g"]).drop("g").collect())) == sorted(map(tuple, merged.drop("g").collect()))


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans(spark, tmp_path):
    l, r = events(spark, "/root/testdata/sf0.01", "click"), events(spark, "/root/testdata/sf0.01", "view")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", -1)
    try:
        for s in ("naive", "cells", "partitioned"):
            p = plan(window_join(l, r, 6 * HOUR, 6 * HOUR, s))
            assert p.count("Exchange hashpartitioning") == 2 and "Cartesian" not in p and "NestedLoop" not in p
            assert "EqualTo(event_type,click)" in p and "props" not in p and "Python" not in p
        save_bucketed(l, "clicks_bucketed", 4)
        save_bucketed(r, "views_bucketed", 4)
        p = plan(window_join(spark.table("clicks_bucketed"), spark.table("views_bucketed"), 6 * HOUR, 6 * HOUR, "naive"))
        assert "Exchange hashpartitioning" not in p
        assert window_join(spark.table("clicks_bucketed"), spark.table("views_bucketed"), 6 * HOUR, 6 * HOUR, "naive").count() == 477
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        spark.sql("DROP TABLE IF EXISTS clicks_bucketed")
        spark.sql("DROP TABLE IF EXISTS views_bucketed")
    write_layout(l, str(tmp_path / "laid"), 12, 24 * HOUR)
    back = spark.read.parquet(str(tmp_path / "laid"))
    slab = back.agg(F.min("slab")).first()[0]
    assert "PartitionFilters: [isnotnull(slab" in plan(back.where(F.col("slab") == slab)) and back.count() == l.count()


def test_choice_of_strategy(spark):
    hot = frame(spark, [(i, 1, i * 10) for i in range(400)])
    cold = frame(spark, [(i, i, i * 10) for i in range(400)])
    assert choose(hot, hot, 5, 5) == "cells" and choose(cold, cold, 5, 5) == "naive" and choose(hot, hot, None, 5) == "naive"
    assert table(spark, "/root/testdata/sf0.001", "nation").count() == 25


def test_every_kind_of_join_by_cells_equals_the_naive_one(spark):
    l, r = events(spark, "/root/testdata/sf0.01", "click"), events(spark, "/root/testdata/sf0.01", "view")
    few = [x.withColumn("key", F.col("key") % 7) for x in (l, r)]
    w1, w2 = 20 * MINUTE, 50 * MINUTE
    for how in ("inner", "left_semi", "left_anti", "left", "right", "full"):
        for direction in ("both", "left_newer", "right_newer"):
            a, b = (window_join(*few, w1, w2, s, direction, how) for s in ("cells", "naive"))
            assert a.columns == b.columns and sorted(map(str, a.collect())) == sorted(map(str, b.collect())), (how, direction)
    a, b = (sorted(map(tuple, window_self_join(few[0], HOUR, strategy=s).collect())) for s in ("cells", "naive"))
    assert a == b and a
    third = events(spark, "/root/testdata/sf0.01", "purchase").withColumn("key", F.col("key") % 7)
    a, b = (sorted(map(tuple, window_join_multi([*few, third], [HOUR, 3 * HOUR, 2 * HOUR], s).collect())) for s in ("cells", "naive"))
    assert a == b and a


def test_cells_are_exact_for_nanosecond_clocks(spark):
    base = (1 << 60) + 1
    l = spark.createDataFrame([(1, 5, base), (2, 5, base + 10)], "id long, key long, t long")
    r = spark.createDataFrame([(k, 5, base + k) for k in range(-6, 20)], "id long, key long, t long")
    got = sorted((x.l_id, x.r_id) for x in window_join(l, r, 3, 2, "cells").collect())
    assert got == sorted((i, k) for i, at in ((1, 0), (2, 10)) for k in range(-6, 20) if at - 2 <= k <= at + 3)


def test_nested_loop_takes_any_size_in_blocks(spark):
    """More tuples on the right than one block holds: an equal result, and no join of everything with everything."""
    rnd = random.Random(11)
    left, right = ([(i, rnd.choice([None, *range(6)]), rnd.randrange(-50, 200)) for i in range(120)] for _ in (0, 1))
    for w1, w2 in ((0, 0), (10, 3), (3, 40), (1000, 1000)):
        got = nested_loop_window_join(frame(spark, left), frame(spark, right), w1, w2, block=5, most=50)
        assert ids(got) == brute(left, right, w1, w2)
        assert "NestedLoop" not in got._jdf.queryExecution().executedPlan().toString()
        assert ids(nested_loop_window_join(frame(spark, left), frame(spark, right), w1, w2)) == brute(left, right, w1, w2)
