"""Epochs, balance, costs, and the shapes of the experiments."""

import random

import pandas as pd
import pytest
from pyspark.sql import functions as F

from winjoin.plans import balance as B
from winjoin.plans import cost as C
from winjoin.plans import epochs as E
from winjoin.plans import experiments as X
from winjoin.plans.model import ClusterSpec, CostSpec, JoinSpec, tuples_in


def test_parameters_are_checked():
    for bad in ({"th_con": 0.5}, {"th_sup": 1.0}, {"beta": 0}, {"beta": 1}, {"tr_us": 1}, {"n_groups": 9}, {"n_groups": 0}, {"order": "x"}, {"initial_nodes": 9}):
        with pytest.raises(ValueError):
            ClusterSpec(**bad)
    for bad in ({"theta_tuples": 1}, {"w1_us": -1}, {"n_part": 0}, {"max_depth": 99}):
        with pytest.raises(ValueError):
            JoinSpec(**bad)
    assert tuples_in(3 << 19) == 24576


def test_classes_pairs_and_degree(spark):
    load = spark.createDataFrame([(1, k, f) for k, f in enumerate((0.01, 0.0099, 0.5, 0.5001))], "rep_epoch long, node int, f double")
    assert [r["class"] for r in B.classify(load, ClusterSpec()).orderBy("node").collect()] == ["neutral", "consumer", "neutral", "supplier"]
    assert B.classify(load.withColumn("m", F.lit(0.9)), ClusterSpec(), "m").where("class = 'supplier'").count() == 4
    many = spark.createDataFrame([(1, k, f) for k, f in enumerate((0.9, 0.8, 0.7, 0.0, 0.001))], "rep_epoch long, node int, f double")
    pairs = B.pair_nodes(B.classify(many, ClusterSpec()))
    assert sorted((r.supplier, r.consumer) for r in pairs.collect()) == [(0, 3), (1, 4)]
    assignment = spark.createDataFrame([(p, p % 5) for p in range(20)], "pid int, node int")
    moves = B.plan_moves(pairs, assignment)
    assert moves.count() == 2 and moves.select("supplier").distinct().count() == 2
    after = B.apply_moves(assignment, moves)
    assert after.count() == 20 and after.exceptAll(assignment).count() == 2
    cases = {(0, 3): "shrink", (2, 3): "grow", (1, 3): "keep", (1, 0): "grow", (0, 0): "shrink"}
    rows = [(k, v, 0.9 if v < s else 0.0 if v < s + c else 0.2) for k, (s, c) in enumerate(cases) for v in range(6)]
    got = B.decide_degree(B.classify(spark.createDataFrame(rows, "rep_epoch long, node int, f double"), ClusterSpec()), 0.5).orderBy("rep_epoch").collect()
    assert [r.decision for r in got] == list(cases.values())


def test_backlog_and_delay(spark):
    work = spark.createDataFrame([(0, e, w) for e, w in enumerate((7, 1, 9, 0))], "node int, epoch int, work int")
    assert [r.backlog for r in E.lindley(work, ["node"], 5).orderBy("epoch").collect()] == [2, 0, 4, 0]
    sparse = spark.createDataFrame([(0, 0, 7), (0, 3, 1), (0, 9, 9), (0, 10, 1)], "node int, epoch int, work int")
    assert [r.backlog for r in E.lindley(sparse, ["node"], 3).orderBy("epoch").collect()] == [4, 0, 6, 4]
    rnd = random.Random(1)
    rows = [(v, e, rnd.randrange(12)) for v in range(3) for e in range(60)]
    got = {(r.node, r.epoch): r.backlog for r in E.lindley(spark.createDataFrame(rows, "node int, epoch int, work int"), ["node"], 5).collect()}
    for v in range(3):
        b = 0
        for _, e, w in (r for r in rows if r[0] == v):
            b = max(0, b + w - 5)
            assert got[v, e] == b
    one = spark.createDataFrame([(9, 12)], "newer_t long, emit_us long")
    assert C.production_delay(one).first().avg_us == 3


def test_buffer(spark):
    assert [E.buffer_bound(1500, 2, n) for n in (1, 2, 4, 10)] == pytest.approx([3000, 2250, 1875, 1650])
    stream = spark.range(60_000).select("id", (F.col("id") * 7919).alias("key"), (F.col("id") * 1000).alias("t"))
    for g in (1, 2, 4):
        peak = E.buffer_trace(E.route(stream, ClusterSpec(4, 2_000_000, 20_000_000, n_groups=g), 60, 0)).agg(F.max("waiting")).first()[0]
        assert 0.9 * E.buffer_bound(1000, 2, g) <= peak <= 1.06 * E.buffer_bound(1000, 2, g)


def loads(n_pid, epochs, hot=None, weight=1):
    return [{"epoch": e, "pid": p, "tuples": 10 * (weight if p == hot else 1), "comparisons": 100, "held": 50, "matches": 1, "wait_us": 1000} for e in range(epochs) for p in range(n_pid)]


def test_reorganisation_keeps_its_invariants():
    for seed in range(5):
        rnd = random.Random(seed)
        rows = [{**r, "tuples": rnd.randrange(60)} for r in loads(12, 80)]
        cluster = ClusterSpec(5, 1000, 5000, buffer_bytes=2000, adaptive=True, initial_nodes=3, seed=seed)
        trace = pd.DataFrame(B.simulate(rows, "s", cluster, CostSpec(ns_per_tuple=9000, ns_per_compare=10, ns_per_message=1000, ns_per_byte=1)), columns=[c.split(" ")[0] for c in B.TRACE.split(", ")])
        assert trace.groupby("epoch").tuples.sum().tolist() == [sum(r["tuples"] for r in rows if r["epoch"] == e) for e in range(80)]
        assert trace.groupby("epoch").node.nunique().equals(trace.groupby("epoch").active.first())
        assert trace.active.between(1, 5).all() and (trace.groupby("epoch").held.sum() == 600).all() and trace.moved_groups.sum() > 0
        again = pd.DataFrame(B.simulate(rows, "s", cluster, CostSpec(ns_per_tuple=9000, ns_per_compare=10, ns_per_message=1000, ns_per_byte=1)), columns=trace.columns)
        assert trace.equals(again)


def test_moves_shift_load_from_a_hot_node():
    cost = CostSpec(ns_per_tuple=20_000, ns_per_compare=1, ns_per_message=1000, ns_per_byte=1)
    rows = [{**r, "tuples": 30 if r["pid"] % 3 == 0 else 2} for r in loads(12, 200)]
    runs = {}
    for name, tr in (("static", None), ("moving", 5000)):
        runs[name] = list(B.simulate(rows, name, ClusterSpec(3, 1000, tr, buffer_bytes=40_000, adaptive=False), cost))
    last = {name: sum(r[9] for r in run if r[1] == 199) for name, run in runs.items()}
    assert last["moving"] < 0.5 * last["static"] and sum(r[14] for r in runs["static"]) == 0


def test_a_move_takes_buffered_tuples_and_directory_along_and_delays_those_who_take_part():
    cost = CostSpec(ns_per_tuple=1000, ns_per_compare=0, ns_per_message=10, ns_per_byte=1, tuple_bytes=10)
    rows = [{"epoch": e, "pid": p, "tuples": 150 if p < 2 and e < 4 else 0, "comparisons": 0, "held": 7, "matches": 1, "wait_us": 0, "buckets": 3} for e in range(8) for p in (0, 1, 3, 5)]
    rows = [{**r, "pid": {0: 0, 1: 2, 3: 1, 5: 3}[r["pid"]]} for r in rows]  # node 0 has the busy groups 0 and 2
    cluster = ClusterSpec(2, 100, 400, buffer_bytes=400, adaptive=False)
    trace = pd.DataFrame(B.simulate(rows, "s", cluster, cost), columns=B.COLUMNS)
    before, after = (trace[trace.epoch == e].set_index("node") for e in (3, 4))
    moved = after.moved_tuples[1]
    assert after.moved_groups.tolist() == [0, 1] and moved > 7
    # the queue has gone with the group: what both have left is what was there less one epoch's work of each
    price = 10 + (moved * 10 + 8 * 3)
    room = 100_000 - (10 + price)
    assert (after.comm_ns == 10 + price).all() and before.backlog_ns[1] == 0
    assert abs(after.backlog_ns.sum() - (before.backlog_ns.sum() - 2 * room)) <= 4 and after.backlog_ns[1] > 0
    # results of nodes that take part wait for the acknowledgement
    half = [before.backlog_ns[0] * k for k in (0.49, 0.51)]
    for v in (0, 1):
        assert half[0] < after.delay_us[v] * 1000 / after.matches[v] - price - 10 * (v + 1) < half[1]


def test_degree_grows_under_load_and_shrinks_after(spark):
    cost = CostSpec(ns_per_tuple=2000, ns_per_compare=0, ns_per_message=1000, ns_per_byte=1)
    rows = [{**r, "tuples": 30 if r["epoch"] < 150 else 1} for r in loads(12, 400)]
    trace = pd.DataFrame(B.simulate(rows, "s", ClusterSpec(6, 200_000 // 1000, 1000, buffer_bytes=20_000, initial_nodes=1), cost), columns=B.COLUMNS)
    active = trace.groupby("epoch").active.first()
    assert active[0] == 1 and active[:150].max() >= 4 and active[399] == 1


def test_placement_and_channels():
    assert B.place_operators({"a": 5, "b": 4, "c": 3, "d": 3}, 2) == {"a": 0, "b": 1, "c": 1, "d": 0}
    assert E.channels(5) == 10 and E.channels(5, "all") == 20


@pytest.fixture(scope="module")
def setting(spark):
    return X.generated(spark, base_rate=30, window_s=40, n_part=10)


def values(df, measure):
    out = {}
    for r in df.where(F.col("measure") == measure).collect():
        variant = r.scenario.split("/")[1] if r.scenario.count("/") > 1 else ""
        out.setdefault(variant, {})[r.param_value] = r.value
    return {k: [v[x] for x in sorted(v)] for k, v in out.items()}


def test_tuning_saves_cpu_and_delay_but_no_communication(setting):
    df = X.run("w2_cpu_vs_rate", setting, rates=(1.0, 2.7, 4.0)).cache()
    cpu, delay, comm, idle = (values(df, m) for m in ("cpu_avg_ns", "delay_avg_us", "comm_avg_ns", "idle_avg_ns"))
    gaps = [u / t for u, t in zip(cpu["untuned"], cpu["tuned"])]
    assert gaps[0] < 1.2 and gaps[1] > 1.15 and gaps[2] > 1.5 and gaps == sorted(gaps)
    assert delay["untuned"][2] > 10 * delay["tuned"][2] and delay["untuned"][0] < 2 * delay["tuned"][0]
    # tuning sends nothing of its own; near saturation moved groups come on top
    assert comm["tuned"][0] == comm["untuned"][0]
    # the untuned system has no idle time left at 2.7 (4000 a second), the tuned one at 4 (6000 a second)
    assert idle["untuned"][1] < 0.12 * idle["untuned"][0] and idle["tuned"][1] > 2 * idle["untuned"][1] and idle["tuned"][2] < 0.12 * idle["tuned"][0]


def test_more_nodes_move_the_knee(setting):
    df = X.run("w1_delay_vs_rate", setting, rates=(1.0, 4.0), nodes=(2, 8)).cache()
    delay = values(df, "delay_avg_us")
    assert delay["nodes2"][1] > 20 * delay["nodes2"][0] and delay["nodes8"][1] < 3 * delay["nodes8"][0]


def test_communication_against_nodes(setting):
    df = X.run("w6_comm_vs_nodes", setting, nodes=(2, 4, 6), rate=0.7).cache()
    each, all_, degree = values(df, "comm_avg_ns"), values(df, "comm_all_ns"), values(df, "degree_avg")
    assert each["fixed"] == sorted(each["fixed"], reverse=True)
    steps = [b - a for a, b in zip(all_["fixed"], all_["fixed"][1:])]
    assert steps[0] > 0 and steps[0] == pytest.approx(steps[1], rel=0.05)
    assert all(a < f for a, f in zip(all_["adaptive"], all_["fixed"])) and degree["adaptive"][2] < 6


def test_spread_epochs_windows_and_buffers(spark, setting):
    spread = X.run("w7_comm_spread", setting, rates=(1.0, 4.0)).cache()
    low, high = values(spread, "comm_min_ns"), values(spread, "comm_max_ns")
    assert high["blocking"][1] - low["blocking"][1] > high["blocking"][0] - low["blocking"][0] > high["fixed"][0] - low["fixed"][0]
    epochs = X.run("w8_delay_vs_epoch", setting, factors=(0.5, 1, 2)).cache()
    assert values(epochs, "delay_avg_us")[""] == sorted(values(epochs, "delay_avg_us")[""])
    assert values(epochs, "comm_avg_ns")[""] == sorted(values(epochs, "comm_avg_ns")[""], reverse=True)
    window = values(X.run("w10_window_vs_rate", setting, rates=(1.0, 2.0)), "window_avg")[""]
    assert window[1] == pytest.approx(2 * window[0], rel=0.15)
    peaks = values(X.buffer_vs_groups(setting), "buffer_peak")[""]
    assert peaks == sorted(peaks, reverse=True)


def test_grid_finds_the_cheapest_within_a_delay(setting):
    found = X.run("grid", setting, epochs=(0.5, 2)).cache()
    delay = values(found, "delay_avg_us")
    top = X.best(found, max(max(v) for v in delay.values())).first().scenario
    assert top.endswith("td=2")
    assert X.best(found, min(min(v) for v in delay.values())).first().scenario.endswith("td=0.5")
    assert X.best(found, 0).collect() == []


def test_arrivals_are_poisson(spark):
    from winjoin.sources.synth import poisson_stream

    s = poisson_stream(spark, 500, 60, seed=3).cache()
    n = s.count()
    assert abs(n - 30_000) < 5 * 30_000**0.5
    per_s = [r["count"] for r in s.groupBy((F.col("t") / 1_000_000).cast("int").alias("s")).count().collect()]
    mean = sum(per_s) / len(per_s)
    var = sum((x - mean) ** 2 for x in per_s) / (len(per_s) - 1)
    assert 0.5 < var / mean < 1.7
    assert s.agg(F.countDistinct("id")).first()[0] == n and s.exceptAll(poisson_stream(spark, 500, 60, seed=3).repartition(7)).count() == 0


def test_measured_time_grows(spark):
    from winjoin.plans.cost import measured_cpu

    was = measured_cpu(spark)
    spark.range(3_000_000).selectExpr("sum(sqrt(id))").collect()
    now = measured_cpu(spark)
    assert now["cpu_ms"] > was["cpu_ms"] and now["run_ms"] >= was["run_ms"]


def test_delays_beyond_64_bits(spark):
    """Matches times backlog of an overloaded node: the sum of delays is exact where it leaves 64 bits."""
    n = 4 * 10**9
    rows = [(e, 0, n, n, n, n, 0, 0, "s") for e in range(3)]
    loads = spark.createDataFrame(rows, "epoch long, pid int, tuples long, comparisons long, held long, matches long, wait_us long, buckets long, scenario string")
    cluster = ClusterSpec(1, 1000, None, buffer_bytes=40_000, adaptive=False)
    trace = B.simulate_all(loads, {"s": (cluster, CostSpec(ns_per_tuple=9000))})
    want = [r[B.COLUMNS.index("delay_us")] for r in B.simulate([r.asDict() for r in loads.collect()], "s", cluster, CostSpec(ns_per_tuple=9000))]
    assert max(want) > 1 << 63 and [int(r.delay_us) for r in trace.orderBy("epoch").collect()] == want
    found = {r.measure: r.value for r in C.summary(trace, 0).collect()}
    assert found["delay_avg_us"] == sum(want) // (3 * n)


def test_a_sweep_leaves_no_plans_of_its_streams_behind(spark):
    """The driver holds one aggregation's plan at a time: what is left of a sweep reads rows, not streams."""
    one = spark.range(400).selectExpr("id", "id % 7 AS key", "id * 50000 AS t")
    setting = X.Setting(lambda m, b: (one, one), JoinSpec(5_000_000, 5_000_000, 4, 2, 8, True, 4), ClusterSpec(2, 500_000, 5_000_000, adaptive=False), CostSpec())
    plan = X.run("w12_ablations", setting, n_part=4)._jdf.queryExecution().optimizedPlan().toString()
    assert "InMemoryRelation" not in plan and "Range" not in plan and len(plan) < 100_000
