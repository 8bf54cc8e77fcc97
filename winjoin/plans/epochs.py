"""Epochs, deliveries and the master's buffer as columns.

Node v of ``n_nodes`` sits in sub-group v mod n_groups at place v div n_groups of its
send order. A sub-group's epochs are shifted by its slot, so what is sent in
slot g holds all arrivals up to then. Times are microseconds, sends nanoseconds.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from winjoin.functions.hashing import floor_div, partition_id
from winjoin.plans.model import ClusterSpec, CostSpec


def floor_div_sql(x: str, width: int) -> str:
    return f"((({x}) - ((({x}) % {width} + {width}) % {width})) // {width})"


def assign_epochs(df: DataFrame, td: int, t0: int = 0, phase: Column | int = 0) -> DataFrame:
    """``df`` with the distribution epoch of t."""
    return df.withColumn("epoch", floor_div(F.col("t") - F.lit(t0) - (phase if isinstance(phase, Column) else F.lit(phase)), td))


def initial_node(pid: Column, n_nodes: int, mode: str = "round_robin", seed: int = 42) -> Column:
    """The node that a partition is dealt to at the start."""
    if mode == "round_robin":
        return F.pmod(pid, F.lit(n_nodes)).cast("int")
    if mode == "random":
        from winjoin.functions.hashing import mix32

        return (mix32(pid * 1000 + seed) % n_nodes).cast("int")
    raise ValueError("mode is 'round_robin' or 'random'")


def slot_of(node: Column, n_groups: int) -> Column:
    return F.pmod(node, F.lit(n_groups)).cast("int")


def phase_of(node: Column, cluster: ClusterSpec) -> Column:
    """Start of a node's slot after the start of the epoch."""
    return (slot_of(node, cluster.n_groups) * F.lit(cluster.td_us) / F.lit(cluster.n_groups)).cast("long")


def route(stream: DataFrame, cluster: ClusterSpec, n_part: int, t0: int, assignment: DataFrame | None = None) -> DataFrame:
    """Tuples with (pid, node, slot, epoch, leave_us): when the master sends them. A given assignment has (pid, node), one row a partition."""
    placed = stream.withColumn("pid", partition_id(F.col("key"), n_part))
    placed = placed.withColumn("node", initial_node(F.col("pid"), cluster.n_nodes)) if assignment is None else placed.join(F.broadcast(assignment), "pid")
    placed = placed.withColumn("slot", slot_of(F.col("node"), cluster.n_groups)).withColumn("_phase", phase_of(F.col("node"), cluster))
    placed = placed.withColumn("epoch", floor_div(F.col("t") - F.lit(t0) - F.col("_phase"), cluster.td_us))
    return placed.withColumn("leave_us", F.lit(t0) + F.col("_phase") + (F.col("epoch") + 1) * F.lit(cluster.td_us)).drop("_phase")


def deliveries(routed: DataFrame, cost: CostSpec) -> DataFrame:
    """One row for each (epoch, node): tuples, bytes, leave_us and the send's length send_ns (message and bytes)."""
    sent = routed.groupBy("epoch", "node", "slot").agg(F.count(F.lit(1)).alias("tuples"), F.min("leave_us").alias("leave_us"))
    return sent.withColumn("bytes", F.col("tuples") * F.lit(cost.tuple_bytes)).withColumn("send_ns", F.lit(cost.ns_per_message) + F.col("bytes") * F.lit(cost.ns_per_byte))


def serial_offsets(sent: DataFrame) -> DataFrame:
    """Deliveries with wait_ns, what the earlier sends of the same slot take."""
    order = Window.partitionBy("epoch", "slot").orderBy("node").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return sent.withColumn("wait_ns", F.sum("send_ns").over(order) - F.col("send_ns"))


def communication(sent: DataFrame, order: str = "fixed") -> DataFrame:
    """Communication time of each node: (node, messages, bytes, comm_ns).

    fixed: a node connects when its place comes and pays its own sends. blocking:
    it waits from the slot's start, so earlier sends count too.
    """
    timed = serial_offsets(sent)
    own = F.col("send_ns") + (F.col("wait_ns") if order == "blocking" else F.lit(0))
    return timed.groupBy("node").agg(F.count(F.lit(1)).alias("messages"), F.sum("bytes").cast("long").alias("bytes"), F.sum(own).cast("long").alias("comm_ns"))


def channels(n_nodes: int, pattern: str = "fixed") -> int:
    """Open channels: master to and from each node, or any node to any other."""
    return 2 * n_nodes if pattern == "fixed" else n_nodes * (n_nodes - 1)


def degree_by_estimate(rate: float, td_s: float, n_nodes: int, cost: CostSpec, share: float = 0.01) -> int:
    """The baseline that fixes the number of nodes once: the most nodes whose messages take at most ``share`` of an epoch,
    at an estimated rate. It is wrong whenever the rate moves."""
    fixed = rate * td_s * cost.tuple_bytes * cost.ns_per_byte
    room = share * td_s * 1e9 - fixed
    return max(1, min(n_nodes, int(room // cost.ns_per_message)))


def state_bytes(held: DataFrame, cost: CostSpec, buckets: DataFrame | None = None) -> DataFrame:
    """What moving a group sends: its window tuples and, where it has a directory, eight bytes for each bucket. (pid, bytes) of (pid, n)."""
    out = held.select("pid", (F.col("n") * F.lit(cost.tuple_bytes)).alias("bytes"))
    if buckets is None:
        return out
    n = buckets.groupBy("pid").agg((F.count(F.lit(1)) * 8).alias("more"))
    return out.join(n, "pid", "left").select("pid", (F.col("bytes") + F.coalesce("more", F.lit(0))).alias("bytes"))


def buffer_bound(rate: float, td_s: float, n_groups: int) -> float:
    """Most tuples of one stream that wait at the master, for even arrivals."""
    return rate * td_s / 2 * (1 + 1 / n_groups)


def buffer_trace(routed: DataFrame) -> DataFrame:
    """Tuples at the master just before each drain: (at, slot, waiting). Arrivals add one, drains take their tuples.

    Aggregated to one row for each (epoch, slot) of arrivals and drains before the running sum.
    """
    arrivals = routed.select(F.col("leave_us"), "t", "slot")
    drains = arrivals.groupBy("slot", F.col("leave_us").alias("at")).agg(F.count(F.lit(1)).alias("n"))
    # an arrival is counted at the first drain instant, of any slot, that follows it
    instants = drains.select("at").distinct()
    order = Window.orderBy("at")
    spans = instants.withColumn("prev", F.lag("at").over(order))
    # arrivals per span: bucket by the finest drain step, bounded by epochs x slots
    step = spans.agg(F.min(F.col("at") - F.col("prev")).alias("s"), F.min("at").alias("a")).first()
    width = int(step.s or 1)
    first = int(step.a or 0)
    came = arrivals.groupBy((F.lit(first) + (floor_div(F.col("t") - F.lit(first), width) + 1) * F.lit(width)).alias("at")).agg(F.count(F.lit(1)).alias("came"))
    went = drains.groupBy("at").agg(F.sum("n").alias("went"))
    both = came.join(went, "at", "full").select("at", F.coalesce("came", F.lit(0)).alias("came"), F.coalesce("went", F.lit(0)).alias("went"))
    run = order.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return both.select("at", (F.sum("came").over(run) - F.sum("went").over(run) + F.col("went")).cast("long").alias("waiting"))


def lindley(work: DataFrame, by: list[str], capacity: Column | int, value: str = "work") -> DataFrame:
    """Backlog of queues without iteration: with S the running sum of work - capacity, B = S - min(0, least S so far).

    An epoch without a row brings no work but has its capacity: it is taken off before the next row's work comes.
    ``capacity`` is the same for all epochs of a queue.
    """
    order = Window.partitionBy(*by).orderBy("epoch")
    run = order.rowsBetween(Window.unboundedPreceding, Window.currentRow)
    cap = capacity if isinstance(capacity, Column) else F.lit(capacity)
    passed = F.col("epoch") - F.coalesce(F.lag("epoch").over(order), F.col("epoch") - 1) - 1
    summed = work.withColumn("_gap", passed * cap).withColumn("_s", F.sum(F.col(value) - cap - F.col("_gap")).over(run))
    # the least S so far is met before a row's work as well, at the end of the gap
    low = F.least(F.lit(0), F.min("_s").over(run), F.min(F.col("_s") - F.col(value) + cap).over(run))
    return summed.withColumn("backlog", F.col("_s") - low).drop("_s", "_gap")
