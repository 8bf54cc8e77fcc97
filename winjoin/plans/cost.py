"""Measures over results, deliveries and traces. Modelled times say so in their names."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def production_delay(results: DataFrame, emit: str = "emit_us", by: list[str] | None = None) -> DataFrame:
    """Time from the newer partner's arrival to emission: (*by, n, sum_us, avg_us, max_us)."""
    delay = F.col(emit) - F.col("newer_t")
    return results.groupBy(*(by or [])).agg(F.count(F.lit(1)).alias("n"), F.sum(delay).cast("long").alias("sum_us"), F.avg(delay).alias("avg_us"), F.percentile_approx(delay, 0.5).alias("p50_us"), F.percentile_approx(delay, 0.95).alias("p95_us"), F.max(delay).alias("max_us"))


def blocks_scanned(counts: DataFrame, block: int, by: list[str], n: str = "n_opposite") -> DataFrame:
    """Opposite blocks that the arrivals of a group read: (*by, blocks)."""
    return counts.groupBy(*by).agg(F.sum(F.ceil(F.col(n) / F.lit(block))).cast("long").alias("blocks"))


def imbalance(work: DataFrame, value: str = "work") -> DataFrame:
    """Greatest and mean work over nodes and their ratio: (max_work, mean_work, ratio)."""
    return work.agg(F.max(value).alias("max_work"), F.avg(value).alias("mean_work"), (F.max(value) / F.avg(value)).alias("ratio"))


def occupancy(trace: DataFrame, per_rep: int) -> DataFrame:
    """Mean occupancy f of each node in each reorganisation epoch."""
    return trace.groupBy("scenario", F.floor(F.col("epoch") / per_rep).cast("long").alias("rep_epoch"), "node").agg((F.avg("occupancy_ppm") / 1e6).alias("f"))


#: Measures of a run, and how they follow from its rows; whole numbers but for shares and ratios.
MEASURES = (
    "backlog_rise_ns", "comm_all_ns", "comm_avg_ns", "comm_max_ns", "comm_min_ns", "comparisons", "cpu_avg_ns", "degree_avg", "delay_avg_us", "idle_avg_ns", "imbalance",
    "moved_groups", "moved_tuples", "occupancy_max", "results", "window_avg", "window_max",
)


def summary(trace: DataFrame, warm_epoch: int) -> DataFrame:
    """Measures of each run after its warm-up, long form (scenario, measure, value).

    Averages are whole-number quotients of exact sums, shares have three decimals. backlog_rise_ns is what the backlog of
    all nodes grows by from the first to the last of these epochs, per epoch: above zero for long in an overloaded system.
    """
    own = trace.where(F.col("epoch") >= warm_epoch)

    def total(c: str) -> Column:
        return F.sum(F.col(c).cast("decimal(20,0)"))

    def ratio(a: Column, b: Column) -> Column:
        return F.round(a.cast("double") / F.greatest(b.cast("double"), F.lit(1.0)), 3)

    def whole(a: Column, b: Column) -> Column:
        return F.floor(a.cast("double") / F.greatest(b.cast("double"), F.lit(1.0))).cast("double")

    node = own.groupBy("scenario", "node").agg(F.sum("comm_ns").alias("comm"), F.sum("idle_ns").alias("idle"), F.sum("work_ns").alias("work"))
    n = F.count(F.lit(1))
    per_node = node.groupBy("scenario").agg(
        whole(total("comm"), n).alias("comm_avg_ns"), F.min("comm").cast("double").alias("comm_min_ns"), F.max("comm").cast("double").alias("comm_max_ns"), total("comm").cast("double").alias("comm_all_ns"),
        whole(total("idle"), n).alias("idle_avg_ns"), whole(total("work"), n).alias("cpu_avg_ns"), ratio(F.max("work") * n, total("work")).alias("imbalance"))
    ends = own.groupBy("scenario", "epoch").agg(F.sum("backlog_ns").alias("b"))
    ends = ends.groupBy("scenario").agg(F.min_by("b", "epoch").alias("a"), F.max_by("b", "epoch").alias("b"), F.count(F.lit(1)).alias("k"))
    ends = ends.select("scenario", F.floor((F.col("b") - F.col("a")).cast("double") / F.greatest(F.col("k") - 1, F.lit(1))).cast("double").alias("backlog_rise_ns"))
    overall = own.groupBy("scenario").agg(
        whole(F.sum(F.col("delay_us").cast("decimal(38,0)")), total("matches")).alias("delay_avg_us"), total("matches").cast("double").alias("results"), total("comparisons").cast("double").alias("comparisons"),
        ratio(F.sum("active"), n).alias("degree_avg"), F.max("held").cast("double").alias("window_max"), whole(total("held"), n).alias("window_avg"), F.round(F.max("occupancy_ppm") / 1e6, 6).alias("occupancy_max"),
        F.sum("moved_groups").cast("double").alias("moved_groups"), F.sum("moved_tuples").cast("double").alias("moved_tuples"))
    return per_node.join(overall, "scenario").join(ends, "scenario").unpivot("scenario", list(MEASURES), "measure", "value")


def capacity(runs: DataFrame, limit_ns: float) -> DataFrame:
    """(group, capacity): the greatest rate whose backlog slope stays within the limit. ``runs``: (group, rate, slope)."""
    return runs.where(F.col("slope") <= limit_ns).groupBy("group").agg(F.max("rate").alias("capacity"))


def bag_difference(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows of either bag that the other lacks."""
    return a.exceptAll(b).withColumn("side", F.lit("left")).unionByName(b.exceptAll(a).withColumn("side", F.lit("right")))


def measured_cpu(spark) -> dict[str, int]:
    """CPU and run time in milliseconds of all stages that this application has completed, from the status store."""
    out = {"cpu_ms": 0, "run_ms": 0}
    sc = spark.sparkContext
    stages = sc._jsc.sc().statusStore().stageList(sc._jvm.java.util.ArrayList(), False, False, sc._gateway.new_array(sc._jvm.double, 0), sc._jvm.java.util.ArrayList())
    for i in range(stages.size()):
        s = stages.apply(i)
        out["cpu_ms"] += s.executorCpuTime() // 1_000_000
        out["run_ms"] += s.executorRunTime()
    return out
