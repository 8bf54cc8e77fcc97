import pytest
from pyspark.sql import functions as F

from winjoin.functions.udtf import register_window_pairs
from winjoin.operators.window_join import window_join
from winjoin.plans.model import DAY, HOUR, JoinSpec
from winjoin.sources.streams import events, merge_tagged, replay, write_replay_files
from winjoin.sources.synth import BModelSource
from winjoin.functions.hashing import partition_id
from winjoin.streaming import join as S
from winjoin.streaming.service import JoinService

SF = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def pair(spark):
    return events(spark, SF, "click"), events(spark, SF, "view")


def rows(df):
    return sorted(tuple(r) for r in df.select("l_id", "r_id").collect())


def test_stateful_join_equals_batch_and_survives_a_restart(spark, pair, tmp_path):
    S.use_rocksdb(spark)
    want = rows(window_join(*pair, 6 * HOUR, 6 * HOUR, "naive"))
    merged = merge_tagged(pair)
    write_replay_files(merged, str(tmp_path / "in"), 5)
    live = replay(spark, str(tmp_path / "in"), merged.schema, 2)
    query = S.partitioned(live, 6 * HOUR, 6 * HOUR, 12, 16)
    S.collect(query, "q", str(tmp_path / "out"), str(tmp_path / "cp")).awaitTermination()
    got = rows(spark.read.parquet(str(tmp_path / "out")))
    assert got == want and len(got) == 477
    # more input after a restart from the checkpoint: only what is new comes out, and it meets the old state
    last = merged.agg(F.max("t")).first()[0]
    extra = merged.where(F.col("t") > last - 3 * HOUR).withColumn("id", F.col("id") + 10_000_000).withColumn("t", F.lit(last + 1))
    both = merged.unionByName(extra)
    write_replay_files(extra, str(tmp_path / "in"), 1)
    S.collect(S.partitioned(replay(spark, str(tmp_path / "in"), merged.schema, 2), 6 * HOUR, 6 * HOUR, 12, 16), "q", str(tmp_path / "out"), str(tmp_path / "cp")).awaitTermination()
    l, r = (both.where(F.col("stream") == k).select("id", "key", "t") for k in (1, 2))
    assert rows(spark.read.parquet(str(tmp_path / "out"))) == rows(window_join(l, r, 6 * HOUR, 6 * HOUR, "naive"))


def test_builtin_join_equals_batch(spark, pair, tmp_path):
    for name, df in zip("lr", pair):
        write_replay_files(df, str(tmp_path / name), 1)
    l, r = (replay(spark, str(tmp_path / n), pair[0].schema) for n in "lr")
    q = S.builtin(l, r, 6 * HOUR, 6 * HOUR).writeStream.format("memory").queryName("b").option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
    q.awaitTermination()
    assert rows(spark.table("b")) == rows(window_join(*pair, 6 * HOUR, 6 * HOUR, "naive"))


def test_table_function(spark, pair):
    register_window_pairs(spark, DAY, DAY, 8)
    merge_tagged(pair).withColumn("pid", partition_id(F.col("key"), 7)).createOrReplaceTempView("merged")
    got = spark.sql("SELECT l_id, r_id FROM window_pairs(TABLE(merged) PARTITION BY pid ORDER BY (t, stream, id))")
    assert rows(got) == rows(window_join(*pair, DAY, DAY, "naive"))


def test_service_and_controller(spark, pair, tmp_path):
    service = JoinService()
    service.register("a", "click", "view", JoinSpec(HOUR, HOUR))
    service.register("b", "click", "view", JoinSpec(6 * HOUR, 6 * HOUR))
    with pytest.raises(ValueError):
        service.register("a", "x", "y", JoinSpec())
    got = service.answer(dict(zip(("click", "view"), pair)))
    assert (got["a"].count(), got["b"].count()) == (76, 477)
    step = S.controller(lambda b: b.select("node", "f"), lambda loads, rep: {0: min(loads, key=lambda x: x[1])[0]}, str(tmp_path), 2)
    for k, f in enumerate(([(0, 0.9), (1, 0.1)], [(0, 0.7), (1, 0.3)])):
        step(spark.createDataFrame(f, "node int, f double"), k)
    assert [tuple(r) for r in spark.read.parquet(str(tmp_path / "assignment")).select("pid", "node").collect()] == [(0, 1)]


def test_sources(spark, tmp_path):
    spark.dataSource.register(BModelSource)
    df = spark.read.format("bmodel").option("n", 300).load()
    assert df.count() == 300 and df.select("id").distinct().count() == 300
    q = spark.readStream.format("bmodel").option("n", 300).option("rowsPerBatch", 100).load().writeStream.format("memory").queryName("gen").option("checkpointLocation", str(tmp_path / "c")).trigger(processingTime="100 milliseconds").start()
    for _ in range(100):
        if spark.table("gen").count() == 300:
            break
        q.processAllAvailable()
    q.stop()
    assert sorted(map(tuple, spark.table("gen").collect())) == sorted(map(tuple, df.collect()))


def stream(spark, rows, path, schema="id long, key long, t long"):
    write_replay_files(spark.createDataFrame(rows, schema), path, 4)
    return replay(spark, path, schema, 1)


def answers(df, tmp_path, name, mode="append"):
    q = df.writeStream.format("memory").queryName(name).outputMode(mode).option("checkpointLocation", str(tmp_path / f"cp_{name}")).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.table(name).collect()


def test_windows_over_results_sessions_and_replays(spark, tmp_path):
    second = 1_000_000
    rows = [(k, k % 2, t * second) for k, t in enumerate([0, 1, 2, 8, 9, 25, 26, 27, 100])]
    results = stream(spark, [(i, k, t, t) for i, k, t in rows], str(tmp_path / "r"), "id long, key long, t long, newer_t long")
    counts = {r.window.start.timestamp(): r.n for r in answers(S.windowed_counts(results, "10 seconds"), tmp_path, "tumbling")}
    assert counts == {0: 5, 20: 3}  # the last window is still open
    slid = {r.window.start.timestamp(): r.n for r in answers(S.windowed_counts(results, "10 seconds", "5 seconds"), tmp_path, "sliding")}
    assert slid[0] == 5 and slid[5] == 2 and slid[20] == 3 and slid[25] == 3
    gaps = sorted((r.key, r.n) for r in answers(S.sessions(stream(spark, rows, str(tmp_path / "s")), "5 seconds"), tmp_path, "session"))
    assert gaps == [(0, 1), (0, 1), (0, 2), (1, 1), (1, 1), (1, 2)]
    later = [(i, k, t + 7200 * second) for i, k, t in rows]  # a watermark begins at 0
    once = answers(S.once_only(stream(spark, later + [later[3], later[4]], str(tmp_path / "o"))), tmp_path, "once")
    assert sorted(r.id for r in once) == list(range(9))


def test_listener_counts_rows_and_late_ones(spark, tmp_path):
    progress = S.Progress()
    spark.streams.addListener(progress)
    try:
        rows = [(k, 1, k * 1_000_000, k * 1_000_000) for k in range(40)]
        df = stream(spark, rows, str(tmp_path / "in"), "id long, key long, t long, newer_t long")
        answers(S.windowed_counts(df, "10 seconds"), tmp_path, "heard")
        for _ in range(100):
            if sum(r[2] for r in progress.rows if r[0] == "heard") == 40:
                break
            import time

            time.sleep(0.1)
        assert sum(r[2] for r in progress.rows if r[0] == "heard") == 40
    finally:
        spark.streams.removeListener(progress)


def test_live_controller_moves_groups_and_its_assignment_is_read(spark, tmp_path):
    from winjoin.plans.model import ClusterSpec

    path, cluster = str(tmp_path), ClusterSpec(4, 1000, 2000, adaptive=False)
    hot = [p for p in range(400) if p]
    keys = spark.createDataFrame([(k,) for k in hot], "key long").withColumn("pid", partition_id(F.col("key"), 12)).collect()
    busy = [r.key for r in keys if r.pid in (1, 5, 9)]  # all at node 1
    step = S.controller(S.load_by_node(path, 12, 4, 40), S.reassign(cluster, list(range(12))), path, 2)
    assert S.latest_assignment(spark, path, 12, 4) == {p: p % 4 for p in range(12)}
    for number in range(4):
        step(spark.createDataFrame([(k, busy[k % len(busy)], k) for k in range(120)], "id long, key long, t long"), number)
    now = S.latest_assignment(spark, path, 12, 4)
    assert sum(now[p] != p % 4 for p in range(12)) >= 2 and {now[p] for p in (1, 5, 9)} != {1}
    f = {r.node: r.f for r in S.load_by_node(path, 12, 4, 1000)(spark.createDataFrame([(0, busy[0], 0)], "id long, key long, t long")).collect()}
    assert len(f) == len(set(now.values())) and sum(f.values()) == pytest.approx(0.001)


def test_a_large_first_batch_is_probed_in_bounded_space(spark):
    import numpy as np

    rnd = np.random.default_rng(3)
    p = S.WindowProcessor(50, 20, most=700)
    l, r = (np.stack([rnd.integers(0, 30, 2000), np.sort(rnd.integers(0, 1000, 2000)), np.arange(2000)], axis=1) for _ in (0, 1))
    got = sorted(map(tuple, p._pairs(0, l, r)[:, :2].tolist()))
    want = sorted((int(a[2]), int(b[2])) for a in l for b in r if a[0] == b[0] and a[1] - 20 <= b[1] <= a[1] + 50)
    assert got == want and len(want) > 700
    assert sorted(map(tuple, p._pairs(1, r, l)[:, :2].tolist())) == want
