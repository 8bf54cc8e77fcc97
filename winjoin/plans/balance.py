"""Reorganisation: classes of nodes by buffer occupancy, moves of partition-groups, the number of active nodes.

The rules exist as columns, for one look at a table of loads, and as a fold
over epochs, for whole runs: a group of rows is one scenario, already
aggregated to (epoch, partition), so its history is small.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field
from decimal import Decimal

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from winjoin.functions.hashing import mix32, mix32_int
from winjoin.plans.model import ClusterSpec, CostSpec


def class_of(f: Column, th_con: float, th_sup: float, mem: Column | None = None) -> Column:
    """supplier above th_sup, consumer below th_con, else neutral; with ``mem`` the greater of both loads counts."""
    load = F.greatest(f, mem) if mem is not None else f
    return F.when(load > th_sup, "supplier").when(load < th_con, "consumer").otherwise("neutral")


def classify(load: DataFrame, cluster: ClusterSpec, mem: str | None = None) -> DataFrame:
    return load.withColumn("class", class_of(F.col("f"), cluster.th_con, cluster.th_sup, F.col(mem) if mem else None))


def pair_nodes(classed: DataFrame) -> DataFrame:
    """(rep_epoch, supplier, consumer): the most loaded supplier with the least loaded consumer, and so on; each node once."""
    s = classed.where("class = 'supplier'").select("rep_epoch", F.col("node").alias("supplier"), F.row_number().over(Window.partitionBy("rep_epoch").orderBy(F.col("f").desc(), "node")).alias("k"))
    c = classed.where("class = 'consumer'").select("rep_epoch", F.col("node").alias("consumer"), F.row_number().over(Window.partitionBy("rep_epoch").orderBy("f", "node")).alias("k"))
    return s.join(c, ["rep_epoch", "k"]).select("rep_epoch", "supplier", "consumer")


def plan_moves(pairs: DataFrame, assignment: DataFrame, seed: int = 42) -> DataFrame:
    """(rep_epoch, supplier, consumer, pid): one partition of each supplier, picked by a hash of seed, epoch and partition."""
    mine = pairs.join(assignment, (pairs.supplier == assignment.node)).select(pairs.rep_epoch, "supplier", "consumer", "pid")
    pick = mix32(F.lit(seed) * 7919 + F.col("rep_epoch") * 104729 + F.col("pid"))
    return mine.withColumn("_k", F.row_number().over(Window.partitionBy("rep_epoch", "supplier").orderBy(pick, "pid"))).where("_k = 1").drop("_k")


def apply_moves(assignment: DataFrame, moves: DataFrame) -> DataFrame:
    """The assignment (pid, node) after moves."""
    return assignment.join(moves.select("pid", "consumer"), "pid", "left").select("pid", F.coalesce("consumer", "node").alias("node"))


def decide_degree(classed: DataFrame, beta: float) -> DataFrame:
    """(rep_epoch, n_sup, n_con, decision): shrink without suppliers, grow if suppliers outnumber beta times consumers."""
    n = classed.groupBy("rep_epoch").agg(F.sum((F.col("class") == "supplier").cast("long")).alias("n_sup"), F.sum((F.col("class") == "consumer").cast("long")).alias("n_con"))
    return n.withColumn("decision", F.when(F.col("n_sup") == 0, "shrink").when(F.col("n_sup") > F.lit(beta) * F.col("n_con"), "grow").otherwise("keep"))


#: Occupancies and thresholds of the fold are whole millionths, all else whole nanoseconds, tuples and bytes: sums are exact everywhere.
PPM = 1_000_000
#: Bytes of a directory entry, sent with a group that has been split.
ENTRY_BYTES = 8


@dataclass
class State:
    """What the master knows between two epochs. Backlogs belong to partitions, so a group that moves takes its buffered tuples along."""

    cluster: ClusterSpec
    assignment: dict[int, int]
    active: set[int]
    backlog_ns: dict[int, int] = field(default_factory=dict)
    backlog_tuples: dict[int, int] = field(default_factory=dict)  # in thousandths, as a part of a queue is no whole number
    samples: dict[int, list[int]] = field(default_factory=dict)
    since_change: int = 1 << 30


def start(cluster: ClusterSpec, pids: list[int]) -> State:
    n = cluster.initial_nodes or cluster.n_nodes
    return State(cluster, {p: p % n for p in pids}, set(range(n)))


def reorganise(state: State, rep_epoch: int, held: dict[int, int]) -> list[tuple[int, int, int, int]]:
    """One reorganisation on mean occupancies: moves (pid, from, to, tuples of window and buffer); the state is updated."""
    c = state.cluster
    f = {v: sum(x) // len(x) if (x := state.samples.get(v)) else 0 for v in sorted(state.active)}
    sup = sorted((v for v in f if f[v] > int(c.th_sup * PPM)), key=lambda v: (-f[v], v))
    con = sorted((v for v in f if f[v] < int(c.th_con * PPM)), key=lambda v: (f[v], v))
    moves = []

    def move(pid: int, to: int) -> None:
        moves.append((pid, state.assignment[pid], to, held.get(pid, 0) + state.backlog_tuples.get(pid, 0) // 1000))
        state.assignment[pid] = to

    def groups(node: int) -> list[int]:
        return sorted((p for p, v in state.assignment.items() if v == node), key=lambda p: (mix32_int(c.seed * 7919 + rep_epoch * 104729 + p), p))

    for s, t in zip(sup, con):
        own = groups(s)
        if len(own) > 1 or own and not groups(t):
            move(own[0], t)
    state.since_change += 1
    if c.adaptive and state.since_change > c.cooldown_epochs:
        idle = [v for v in range(c.n_nodes) if v not in state.active]
        if not sup and len(state.active) > 1:
            # the least loaded node leaves; the others take its groups in turn, least loaded first
            gone = min(f, key=lambda v: (f[v], v))
            rest = sorted(state.active - {gone}, key=lambda v: (f[v], v))
            for k, pid in enumerate(groups(gone)):
                move(pid, rest[k % len(rest)])
            state.active.discard(gone)
            state.since_change = 0
        elif sup and len(sup) * PPM > int(c.beta * PPM) * len(con) and idle:
            state.active.add(idle[0])
            state.since_change = 0
    state.samples = {}
    return moves


TRACE = (
    "scenario string, epoch long, node int, active int, tuples long, comparisons long, work_ns long, comm_ns long, idle_ns long, backlog_ns long, occupancy_ppm long, "
    "held long, matches long, delay_us decimal(38,0), moved_groups int, moved_tuples long"
)


COLUMNS = [f.split(" ")[0] for f in TRACE.split(", ")]


def simulate(loads: list[dict], scenario: str, cluster: ClusterSpec, cost: CostSpec) -> Iterator[tuple]:
    """Rows of TRACE for one run.

    ``loads``: rows (epoch, pid, tuples, comparisons, held, matches, wait_us[, buckets]) with
    wait_us the sum over matches of the time that their newer tuple waits for its epoch's end, and
    buckets the entries of the group's directory. A node works off its partitions' queues evenly.
    A move sends window, buffered tuples and directory; it takes time from both nodes, and what is pending for
    nodes that take part waits until the slowest move is acknowledged.
    """
    by_epoch: dict[int, list[dict]] = {}
    for r in loads:
        by_epoch.setdefault(int(r["epoch"]), []).append(r)
    if not by_epoch:
        return
    state = start(cluster, sorted({int(r["pid"]) for r in loads}))
    td_ns, per_rep = cluster.td_us * 1000, (cluster.tr_us // cluster.td_us if cluster.tr_us else None)
    held: dict[int, int] = {}
    buckets: dict[int, int] = {}
    extra_ns: dict[int, int] = {}
    awaited: dict[int, int] = {}
    moved_note: dict[int, tuple[int, int]] = {}
    first = min(by_epoch)
    for epoch in range(first, max(by_epoch) + 1):
        came: dict[int, dict] = {}
        for r in by_epoch.get(epoch, []):
            p = int(r["pid"])
            came[p] = {k: int(r[k]) for k in ("tuples", "comparisons", "matches", "wait_us")}
            held[p], buckets[p] = int(r["held"]), int(r.get("buckets", 0))
        own: dict[int, list[int]] = {v: [] for v in state.active}
        for p, v in state.assignment.items():
            own[v].append(p)
        ahead = [0] * cluster.n_groups
        for v in sorted(state.active):
            mine = [came[p] for p in own[v] if p in came]
            tuples, comps, matches, wait = (sum(r[k] for r in mine) for k in ("tuples", "comparisons", "matches", "wait_us"))
            work = tuples * cost.ns_per_tuple + comps * cost.ns_per_compare
            send = cost.ns_per_message + tuples * cost.tuple_bytes * cost.ns_per_byte
            g = v % cluster.n_groups
            offset = ahead[g]
            ahead[g] += send
            comm = send + (offset if cluster.order == "blocking" else 0) + extra_ns.get(v, 0)
            capacity = max(0, td_ns - comm - cluster.background_us * 1000)
            before = sum(state.backlog_ns.get(p, 0) for p in own[v])
            due = before + work
            after = max(0, due - capacity)
            for p in own[v]:
                r = came.get(p)
                queue = state.backlog_ns.get(p, 0) + (r["tuples"] * cost.ns_per_tuple + r["comparisons"] * cost.ns_per_compare if r else 0)
                waiting = state.backlog_tuples.get(p, 0) + (1000 * r["tuples"] if r else 0)
                state.backlog_ns[p] = queue * after // due if due else 0
                state.backlog_tuples[p] = waiting * after // due if due else 0
            occupancy = min(PPM, sum(state.backlog_tuples[p] for p in own[v]) * cost.tuple_bytes * PPM // (1000 * cluster.buffer_bytes))
            state.samples.setdefault(v, []).append(occupancy)
            # a result leaves after its tuple's wait, an acknowledgement, the sends ahead, the backlog found and half of its batch's work
            delay = wait + matches * (awaited.get(v, 0) + offset + send + before + work // 2) // 1000
            idle = max(0, td_ns - comm - (due - after) - cluster.background_us * 1000)
            yield scenario, epoch, v, len(state.active), tuples, comps, work, comm, idle, sum(state.backlog_ns[p] for p in own[v]), occupancy, sum(held.get(p, 0) for p in own[v]), matches, delay, *moved_note.get(v, (0, 0))
        extra_ns, awaited, moved_note = {}, {}, {}
        if per_rep and (epoch - first + 1) % per_rep == 0:
            moves = reorganise(state, (epoch - first + 1) // per_rep, held)
            prices = [cost.ns_per_message + (n * cost.tuple_bytes + ENTRY_BYTES * buckets.get(p, 0)) * cost.ns_per_byte for p, _, _, n in moves]
            for (_, a, b, n), price in zip(moves, prices):
                for v in (a, b):
                    extra_ns[v] = extra_ns.get(v, 0) + price
                    awaited[v] = max(prices)
                k, m = moved_note.get(b, (0, 0))
                moved_note[b] = (k + 1, m + n)


def simulate_all(loads: DataFrame, scenarios: dict[str, tuple[ClusterSpec, CostSpec]]) -> DataFrame:
    """Traces of several runs; ``loads`` has a column scenario. A scenario is one group: epochs x partitions rows, never tuples.

    delay_us is a product of matches and backlogs, which leaves 64 bits on large streams.
    """

    def run(rows: pd.DataFrame) -> pd.DataFrame:
        name = str(rows.scenario.iloc[0])
        cluster, cost = scenarios[name]
        out = pd.DataFrame(list(simulate(rows.to_dict("records"), name, cluster, cost)), columns=COLUMNS)
        return out.assign(delay_us=[Decimal(int(x)) for x in out.delay_us])

    return loads.groupBy("scenario").applyInPandas(run, TRACE)


def place_operators(work: dict[str, int], n_nodes: int) -> dict[str, int]:
    """The inter-operator baseline: whole joins on nodes, heaviest first on the least loaded node."""
    load = dict.fromkeys(range(n_nodes), 0)
    out = {}
    for name in sorted(work, key=lambda q: (-work[q], q)):
        v = min(load, key=lambda n: (load[n], n))
        out[name] = v
        load[v] += work[name]
    return out
