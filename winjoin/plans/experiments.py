"""Workloads: parameter sweeps of the modelled cluster over real or generated streams.

One aggregation per (rate, tuning) turns tuples into loads per (epoch,
partition); every scenario after that is a fold over those rows. Results are
(workload, scenario, param, param_value, measure, value).

The scaled defaults keep the ratios of window, epochs and group size to the
threshold: run = 2 W, warm-up = W, td = W / 300, tr = W / 30, a mean group of
1.22 thresholds at rate multiple 1 (1500 tuples a second in the full-size setting).
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from winjoin.functions.hashing import partition_id
from winjoin.operators.directory import static_directory
from winjoin.operators.frames import arrival_counts, held_at
from winjoin.operators.window_join import locate, small_directory
from winjoin.plans.balance import simulate_all
from winjoin.plans.cost import summary
from winjoin.plans.epochs import floor_div
from winjoin.plans.model import ClusterSpec, CostSpec, JoinSpec

#: At this rate multiple the mean partition-group is 1.22 thresholds.
GROUP_TO_THETA = 1.22


@dataclass(frozen=True)
class Setting:
    """A pair of streams as a function of the rate multiple and the skew of keys (None: the setting's own), and the scaled parameters."""

    streams: Callable[..., tuple[DataFrame, DataFrame]]
    join: JoinSpec
    cluster: ClusterSpec
    cost: CostSpec
    t0: int = 0


def loads(left: DataFrame, right: DataFrame, join: JoinSpec, td: int, t0: int = 0) -> DataFrame:
    """(epoch, pid, tuples, comparisons, held, matches, wait_us, buckets) of a pair of streams.

    Comparisons are those of whole partitions, or of the leaves of a static
    directory over the last window if the spec is tuned; buckets are a partition's leaves (0 untuned).
    """
    n = join.n_part

    def place(df: DataFrame) -> DataFrame:
        return df.withColumn("pid", partition_id(F.col("key"), n))

    pl, pr = place(left), place(right)
    scanned_by = ["pid"]
    cl, cr = pl, pr
    if join.tuned:
        last = left.select("t").unionByName(right.select("t")).agg(F.max("t")).first()[0] or 0
        recent = left.where(F.col("t") > last - join.w1_us).select("key").unionByName(right.where(F.col("t") > last - join.w2_us).select("key"))
        leaves = small_directory(static_directory(recent, n, join.theta_tuples, join.max_depth))

        def leaf(df: DataFrame) -> DataFrame:
            side = df.select(F.col("id").alias("x_id"), F.col("key").alias("x_key"), F.col("t").alias("x_t"))
            found = locate(side, "x", leaves, n, join.max_depth)
            return found.select(F.col("x_id").alias("id"), F.col("x_t").alias("t"), F.col("x_pid").alias("pid"), F.coalesce("x_depth", F.lit(-1)).alias("depth"), F.coalesce("x_suffix", F.lit(0)).alias("suffix"))

        cl, cr, scanned_by = leaf(left), leaf(right), ["pid", "depth", "suffix"]
    epoch = floor_div(F.col("t") - F.lit(t0), td)
    scanned = arrival_counts(cl, cr, join.w1_us, join.w2_us, scanned_by, "comparisons").groupBy(epoch.alias("epoch"), "pid").agg(F.count(F.lit(1)).alias("tuples"), F.sum("comparisons").alias("comparisons"))
    matched = arrival_counts(pl, pr, join.w1_us, join.w2_us, ["pid", "key"], "m").groupBy(epoch.alias("epoch"), "pid").agg(F.sum("m").alias("matches"), F.sum(F.col("m") * (F.lit(t0) + (epoch + 1) * F.lit(td) - F.col("t"))).alias("wait_us"))
    sizes = held_at(pl, join.w1_us, ["pid"], t0, td).select("pid", "epoch", F.col("n").alias("n1")).join(held_at(pr, join.w2_us, ["pid"], t0, td).select("pid", "epoch", F.col("n").alias("n2")), ["pid", "epoch"], "full")
    from pyspark.sql import Window

    run = Window.partitionBy("pid").orderBy("epoch").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    held = sizes.select("pid", "epoch", (F.coalesce(F.last("n1", True).over(run), F.lit(0)) + F.coalesce(F.last("n2", True).over(run), F.lit(0))).alias("held"))
    joined = scanned.join(matched, ["epoch", "pid"]).join(held, ["epoch", "pid"], "left")
    joined = joined.join(leaves.groupBy("pid").agg(F.count(F.lit(1)).alias("buckets")), "pid", "left") if join.tuned else joined.withColumn("buckets", F.lit(0).cast("long"))
    return joined.select("epoch", "pid", "tuples", F.coalesce("comparisons", F.lit(0)).alias("comparisons"), F.coalesce("held", F.lit(0)).alias("held"), "matches", "wait_us", F.coalesce("buckets", F.lit(0)).alias("buckets"))


@dataclass(frozen=True)
class Case:
    """One scenario of a sweep: what differs from the setting. ``tr`` counts distribution epochs (0: nothing ever moves); ``over`` names fields of the cluster."""

    param: str
    value: float
    rate: float = 1.0
    tuned: bool = True
    variant: str = ""
    nodes: int = 4
    td_factor: float = 1.0
    tr: int | None = None
    n_part: int | None = None
    theta_factor: float = 1.0
    skew: float | None = None
    over: tuple[tuple[str, object], ...] = ()

    def name(self, workload: str) -> str:
        return f"{workload}/{self.variant + '/' if self.variant else ''}{self.param}={self.value:g}"

    def join_of(self, s: Setting) -> JoinSpec:
        return replace(s.join, tuned=self.tuned, n_part=self.n_part or s.join.n_part, theta_tuples=max(s.join.block_tuples, int(s.join.theta_tuples * self.theta_factor)))

    def cluster_of(self, s: Setting) -> ClusterSpec:
        td = int(s.cluster.td_us * self.td_factor)
        tr = s.cluster.tr_us if self.tr is None else self.tr * td or None
        return replace(s.cluster, n_nodes=self.nodes, td_us=td, tr_us=tr, **{"adaptive": False, "initial_nodes": None, **dict(self.over)})


def run_cases(workload: str, setting: Setting, cases: list[Case]) -> DataFrame:
    """Every case's measures; cases with the same streams, tuning and epoch share one aggregation, and streams (id, key, t) are made once for all of these.

    Aggregations run one after the other and leave (epoch, partition) rows without their plans: the driver never holds
    the plans of all cases at once. The trace of all cases is kept in the same way, as its measures read it several times.
    """
    keys: dict[tuple, list[Case]] = {}
    for c in cases:
        keys.setdefault((c.rate, c.skew), []).append(c)
    shared: dict[tuple, DataFrame] = {}
    for (rate, skew), own in keys.items():
        made = tuple(x.select("id", "key", "t").persist() for x in setting.streams(rate, skew))
        for c in own:
            key = (rate, skew, c.join_of(setting), c.cluster_of(setting).td_us)
            if key not in shared:
                shared[key] = loads(*made, key[2], key[3], setting.t0).localCheckpoint()
        for x in made:
            x.unpersist()
    frames, specs, notes = [], {}, []
    for c in cases:
        join, cluster = c.join_of(setting), c.cluster_of(setting)
        name = c.name(workload)
        specs[name] = (cluster, setting.cost)
        notes.append((name, c.param, float(c.value), join.w1_us // cluster.td_us))
        frames.append(shared[c.rate, c.skew, join, cluster.td_us].withColumn("scenario", F.lit(name)))
    trace = simulate_all(reduce(DataFrame.unionByName, frames), specs).localCheckpoint()
    spark = frames[0].sparkSession
    known = spark.createDataFrame(notes, "scenario string, param string, param_value double, warm long")
    marked = trace.join(F.broadcast(known), "scenario").where(F.col("epoch") >= F.col("warm"))
    measures = summary(marked.drop("param", "param_value", "warm"), 0)
    return measures.join(F.broadcast(known.drop("warm")), "scenario").select(F.lit(workload).alias("workload"), "scenario", "param", "param_value", "measure", "value")


RATES = (0.5, 1.0, 2.0, 2.7, 4.0)
TUNING = (("tuned", True), ("untuned", False))


def delay_vs_rate(rates=RATES, nodes=(2, 4, 8)) -> list[Case]:
    """Average delay and rise of the backlog against the rate, for several numbers of nodes."""
    return [Case("rate", r, r, nodes=n, variant=f"nodes{n}") for n in nodes for r in rates]


def cpu_vs_rate(rates=RATES) -> list[Case]:
    """CPU time with and without tuning."""
    return [Case("rate", r, r, t, v) for v, t in TUNING for r in rates]


def delay_untuned(rates=RATES) -> list[Case]:
    """Delay without tuning, beside the tuned one."""
    return [Case("rate", r, r, t, v) for v, t in TUNING[::-1] for r in rates]


def idle_untuned(rates=RATES) -> list[Case]:
    """Idle and communication time without tuning."""
    return [Case("rate", r, r, False) for r in rates]


def idle_tuned(rates=RATES) -> list[Case]:
    """Idle and communication time with tuning."""
    return [Case("rate", r, r, True) for r in rates]


def comm_vs_nodes(nodes=(2, 3, 4, 5, 6), rate: float = 1.0) -> list[Case]:
    """Communication against the number of nodes, fixed and adaptive."""
    return [Case("nodes", n, rate, nodes=n, variant=v, over=(("adaptive", a),)) for v, a in (("fixed", False), ("adaptive", True)) for n in nodes]


def comm_spread(rates=RATES) -> list[Case]:
    """Least, mean and greatest communication of four nodes, in agreed order and blocking."""
    return [Case("rate", r, r, variant=o, over=(("order", o),)) for o in ("fixed", "blocking") for r in rates]


def delay_vs_epoch(factors=(0.5, 1, 2, 4)) -> list[Case]:
    """Delay against the distribution epoch, three nodes."""
    return [Case("td", f, nodes=3, td_factor=f) for f in factors]


def comm_vs_epoch(factors=(0.5, 1, 2, 4)) -> list[Case]:
    """Communication against the distribution epoch, three nodes."""
    return delay_vs_epoch(factors)


def window_vs_rate(rates=RATES) -> list[Case]:
    """Tuples held by a node against the rate."""
    return [Case("rate", r, r) for r in rates]


def ablations(rate: float = 2.7, n_part: int = 20, b: float | None = None) -> list[Case]:
    """One parameter at a time, at a rate that overloads some nodes: threshold, partitions, one partition a node, skew of keys,
    class thresholds, beta (with a changing degree), reorganisation epoch and no reorganisation, load shedding."""
    more = {"rate": rate, "skew": b}
    cases = [Case("theta", f, theta_factor=f, **more) for f in (0.25, 1, 4)]
    cases += [Case("n_part", n, tuned=False, n_part=n, variant="per_node" if n == 4 else "", **more) for n in (4, n_part, 4 * n_part)]
    cases += [Case("b", x, rate, skew=x) for x in (0.5, 0.6, 0.7, 0.8)]
    cases += [Case("th_sup", v, over=(("th_sup", v),), **more) for v in (0.05, 0.5, 0.95)]
    cases += [Case("th_con", v, over=(("th_con", v),), **more) for v in (0.0, 0.01, 0.3)]
    cases += [Case("beta", v, nodes=6, over=(("beta", v), ("adaptive", True), ("initial_nodes", 2)), **more) for v in (0.1, 0.5, 0.9)]
    cases += [Case("tr_over_td", k, tr=k, variant="" if k else "static", **more) for k in (2, 10, 0)]
    return cases + [Case("kept", k, rate * k, skew=b, variant="shedding") for k in (0.5, 0.75)]


def grid(epochs=(0.5, 1, 2), groups=(1, 2), rate: float = 1.0) -> list[Case]:
    """Offline search over the epoch's length and the number of sub-groups."""
    return [Case("td", f, rate, td_factor=f, variant=f"groups{g}", over=(("n_groups", g),)) for g in groups for f in epochs]


def buffer_vs_groups(s: Setting, groups=(1, 2, 4), rate: float = 1.0, td_factor: float = 1.0) -> DataFrame:
    """Greatest number of tuples of a stream at the master against the number of sub-groups, with the bound for even arrivals.

    ``td_factor`` makes the epoch long enough to hold hundreds of tuples where arrivals are sparse.
    """
    from winjoin.plans.epochs import buffer_bound, buffer_trace, route

    left, _ = s.streams(rate)
    span = left.agg(F.min("t").alias("a"), F.max("t").alias("b"), F.count(F.lit(1)).alias("n")).first()
    rate = span.n / max(1e-9, (span.b - span.a) / 1e6)
    out = []
    for g in groups:
        td = int(s.cluster.td_us * td_factor)
        c = replace(s.cluster, n_nodes=max(g, s.cluster.n_nodes), n_groups=g, td_us=td, tr_us=None)
        peak = buffer_trace(route(left, c, s.join.n_part, s.t0)).agg(F.max("waiting").cast("double").alias("buffer_peak"), F.lit(round(buffer_bound(rate, c.td_us / 1e6, g), 3)).alias("buffer_bound"))
        out.append(peak.unpivot([], ["buffer_peak", "buffer_bound"], "measure", "value").select(F.lit("w11").alias("workload"), F.lit(f"w11/groups={g}").alias("scenario"), F.lit("groups").alias("param"), F.lit(float(g)).alias("param_value"), "measure", "value"))
    return reduce(DataFrame.unionByName, out)


def best(measures: DataFrame, delay_limit_us: float) -> DataFrame:
    """Of a grid's scenarios within a limit on delay the one of least communication."""
    wide = measures.groupBy("scenario").pivot("measure", ["delay_avg_us", "comm_all_ns"]).agg(F.first("value"))
    return wide.where(F.col("delay_avg_us") <= delay_limit_us).orderBy("comm_all_ns", "scenario").limit(1)


def generated(spark: SparkSession, base_rate: float = 60, window_s: float = 60, n_part: int = 20, b: float = 0.7, domain: int = 10_000_001) -> Setting:
    """Two independent Poisson streams; rate multiple 1 stands for 1500 tuples a second of the full-size setting.

    Half of an epoch for comparisons, 0.47 for tuples and the rest for messages at multiple 2.7, untuned, saturate four nodes there; with
    two levels of splitting at multiple 4 (a quarter of 16 / 7.3 of the comparisons, 1.5 times the tuples) the same prices saturate them there.
    """
    from winjoin.sources.synth import poisson_stream

    w, td = int(window_s * 1e6), int(window_s * 1e6 / 300)
    theta = max(8, int(2 * base_rate * window_s / n_part / GROUP_TO_THETA))

    def streams(m: float, skew: float | None = None) -> tuple[DataFrame, DataFrame]:
        return tuple(poisson_stream(spark, base_rate * m, 2 * window_s, skew or b, seed, domain) for seed in (1, 2))

    # per epoch of four nodes: 2 * rate * td / 4 arrivals, each with rate * W / n_part comparisons untuned
    per_epoch, found = 2 * 2.7 * base_rate * window_s / 300 / 4, 2.7 * base_rate * window_s / n_part
    budget = window_s / 300 * 1e9 / per_epoch
    cost = CostSpec(ns_per_compare=max(1, int(0.5 * budget / found)), ns_per_tuple=int(0.47 * budget), ns_per_message=int(window_s / 300 * 1e9 / 200), ns_per_byte=max(1, int(window_s / 300 * 1e9 / 50 / per_epoch / 64)))
    return Setting(streams, JoinSpec(w, w, n_part, 8, theta, True, 8), ClusterSpec(4, td, 10 * td, buffer_bytes=int(per_epoch * 64 * 20), adaptive=False), cost)


#: Of the registered runs over the table events.
EVENT_SKEW = (6, 50)  # levels and keys of the b-model


def on_events(spark: SparkSession, sf_dir: str, n_part: int = 12, skew: float | None = None) -> Setting:
    """Clicks and views of the table events: W = 10 days, td = 48 minutes, tr = 8 hours; rates by thinning, multiple 4 is every tuple.

    ``skew`` replaces users by b-model keys. All parameters are whole-number functions of the number of tuples n.
    """
    from winjoin.functions.hashing import bmodel_key
    from winjoin.plans.model import DAY, MINUTE
    from winjoin.sources.streams import events
    from winjoin.sources.synth import thin

    both = [events(spark, sf_dir, kind) for kind in ("click", "view")]
    span = both[0].unionByName(both[1]).agg(F.min("t").alias("a"), F.count(F.lit(1)).alias("n")).first()
    n, t0 = span.n or 1, span.a or 0
    w, td = 10 * DAY, 48 * MINUTE
    # thousandths of arrivals per epoch and node of four at multiple 2.7, and what one of them finds
    per, found = max(1, n * 27 // 144), max(1, n * 27 // 2880)
    budget = td * 1_000_000 // per
    cost = CostSpec(ns_per_compare=max(1, 6 * budget // (10 * found)), ns_per_tuple=3 * budget // 10, ns_per_message=td * 1000 // 200, ns_per_byte=max(1, td * 1_000_000 // 50 // per // 64))

    def streams(m: float, b: float | None = None) -> tuple[DataFrame, DataFrame]:
        b = b or skew
        keyed = (x if b is None else x.withColumn("key", bmodel_key(F.col("id"), b, *EVENT_SKEW)) for x in both)
        return tuple(thin(x.withColumn("t", F.col("t") - F.lit(t0)), m / 4) for x in keyed)

    return Setting(streams, JoinSpec(w, w, n_part, 4, max(4, n // 176), True, 8), ClusterSpec(4, td, 10 * td, buffer_bytes=max(256, per * 64 * 20 // 1000), adaptive=False), cost)


WORKLOADS: dict[str, Callable[..., list[Case]]] = {
    "w1_delay_vs_rate": delay_vs_rate, "w2_cpu_vs_rate": cpu_vs_rate, "w3_delay_untuned": delay_untuned, "w4_idle_untuned": idle_untuned, "w5_idle_tuned": idle_tuned,
    "w6_comm_vs_nodes": comm_vs_nodes, "w7_comm_spread": comm_spread, "w8_delay_vs_epoch": delay_vs_epoch, "w9_comm_vs_epoch": comm_vs_epoch, "w10_window_vs_rate": window_vs_rate,
    "w12_ablations": ablations,
}


def run(workload: str, setting: Setting, **options) -> DataFrame:
    """A workload by its name, or 'grid'; W11 is ``buffer_vs_groups``."""
    cases = grid if workload == "grid" else WORKLOADS[workload]
    return run_cases(workload.split("_")[0], setting, cases(**options))
