"""The modelled runs as SQL for another engine: streams, loads, the fold over epochs as a recursive query, measures.

Only the sweeps' definitions (``Case``) are shared with the Spark side; directories, counts, queues,
classes, moves and degrees are said again here, in sets instead of in a loop over nodes.
"""

from __future__ import annotations

from winjoin.functions import hashing as H
from winjoin.plans.cost import MEASURES
from winjoin.plans.experiments import EVENT_SKEW, Case
from winjoin.plans.model import DAY, MINUTE

W, TD, TR = 10 * DAY, 48 * MINUTE, 480 * MINUTE
N_PART, DEPTH, BLOCK, PPM, TUPLE = 12, 8, 4, 1_000_000, 64

#: The setting of the table events; n is the number of clicks and views.
PARAMS = f"""ev AS MATERIALIZED (SELECT event_id AS id, user_id, CASE event_type WHEN 'click' THEN 1 ELSE 2 END AS stream, epoch_us(ts) AS t FROM events WHERE event_type IN ('click', 'view') AND user_id IS NOT NULL AND ts IS NOT NULL),
 whole AS (SELECT count(*) AS n, min(t) AS t0 FROM ev),
 scaled AS (SELECT n, t0, greatest(1, n * 27 // 144) AS per, greatest(1, n * 27 // 2880) AS found, greatest(4, n // 176) AS theta FROM whole),
 prm AS MATERIALIZED (SELECT n, t0, theta, greatest(1, 6 * ({TD} * 1000000 // per) // (10 * found)) AS npc, 3 * ({TD} * 1000000 // per) // 10 AS npt, {TD * 1000 // 200} AS npm,
   greatest(1, {TD} * 1000000 // 50 // per // 64) AS npb, greatest(256, per * 1280 // 1000) AS buffer FROM scaled)"""


def _div(x: str, width: int) -> str:
    """Floor division of numbers of either sign."""
    return f"((({x}) - ((({x}) % {width} + {width}) % {width})) // {width})"


def _streams(name: str, rate: float, skew: float | None) -> str:
    key = "user_id" if skew is None else H.bmodel_key_sql("id", skew, *EVENT_SKEW)
    return f"{name} AS MATERIALIZED (SELECT stream, id, {key} AS key, t - t0 AS t FROM ev, whole WHERE ({H.mix32_sql('id * 2 + 1')} + 0.5::DOUBLE) / 4294967296.0::DOUBLE < {rate / 4!r}::DOUBLE)"


def _loads(x: str, src: str, n_part: int, tuned: bool, factor: float, td: int) -> list[str]:
    """CTEs that end in ``x`` (epoch, pid, tuples, comparisons, held, matches, wait_us, buckets)."""
    pid, bits = H.partition_id_sql("key", n_part), H.mini_bits_sql("key", DEPTH)
    out = [f"{x}_p AS MATERIALIZED (SELECT *, {pid} AS pid, {bits} AS bits, {_div('t', td)} AS epoch FROM {src})"]
    if tuned:
        out += [
            f"{x}_n AS MATERIALIZED (SELECT pid, depth, bits % (1 << depth) AS suffix, count(*) AS n FROM {x}_p, (SELECT CAST(unnest(range({DEPTH + 1})) AS INTEGER) AS depth) WHERE t > (SELECT max(t) FROM {x}_p) - {W} GROUP BY 1, 2, 3)",
            f"{x}_th AS (SELECT greatest({BLOCK}, CAST(floor(theta * {factor!r}::DOUBLE) AS BIGINT)) AS th FROM prm)",
            f"{x}_v AS MATERIALIZED (SELECT a.pid, a.depth, a.suffix FROM {x}_n a, {x}_th WHERE (a.n <= 2 * th OR a.depth = {DEPTH}) AND (a.depth = 0 OR EXISTS (SELECT 1 FROM {x}_n b WHERE b.pid = a.pid AND b.depth = a.depth - 1 AND b.suffix = a.suffix % (1 << greatest(a.depth - 1, 0)) AND b.n > 2 * th)))",
            f"{x}_l AS MATERIALIZED (SELECT p.*, coalesce(v.depth, -1) AS depth, coalesce(v.suffix, 0) AS suffix FROM {x}_p p LEFT JOIN {x}_v v ON v.pid = p.pid AND p.bits % (1 << v.depth) = v.suffix)",
            f"{x}_b AS (SELECT pid, count(*) AS buckets FROM {x}_v GROUP BY pid)",
        ]
    else:
        out += [f"{x}_l AS MATERIALIZED (SELECT *, 0 AS depth, 0 AS suffix FROM {x}_p)", f"{x}_b AS (SELECT DISTINCT pid, 0 AS buckets FROM {x}_p)"]
    older = f"b.t >= a.t - {W} AND (b.t < a.t OR a.stream = 1 AND b.t = a.t)"
    out += [
        f"{x}_s AS MATERIALIZED (SELECT a.stream, a.id, count(b.id) AS c, count(b.id) FILTER (a.key = b.key) AS m FROM {x}_l a LEFT JOIN {x}_l b ON a.pid = b.pid AND a.depth = b.depth AND a.suffix = b.suffix AND a.stream <> b.stream AND {older} GROUP BY 1, 2)",
        f"{x}_a AS (SELECT p.epoch, p.pid, count(*) AS tuples, sum(c) AS comparisons, sum(m) AS matches, sum(m * ((p.epoch + 1) * {td} - p.t)) AS wait_us FROM {x}_p p JOIN {x}_s USING (stream, id) GROUP BY 1, 2)",
        f"{x}_h AS (SELECT a.epoch, a.pid, count(p.id) AS held FROM {x}_a a LEFT JOIN {x}_p p ON p.pid = a.pid AND p.epoch <= a.epoch AND {_div(f'p.t + {W}', td)} >= a.epoch GROUP BY 1, 2)",
        f"{x} AS MATERIALIZED (SELECT a.epoch, a.pid, a.tuples, a.comparisons, h.held, a.matches, a.wait_us, coalesce(b.buckets, 0) AS buckets FROM {x}_a a JOIN {x}_h h USING (epoch, pid) LEFT JOIN {x}_b b ON b.pid = a.pid)",
    ]
    return out


_HASH = H.mix32_sql("(42 * 7919 + z.rep * 104729 + z.i)")

#: One step: from the rows of an epoch to those of the next. kind 0: a partition (i, node), kind 1: a node (i).
_STEP = f"""(WITH cur AS MATERIALIZED (SELECT st.*, st.epoch + 1 AS e, (sc.per_rep IS NOT NULL AND (st.epoch + 2 - sp.f) % coalesce(sc.per_rep, 1) = 0) AS over, (st.epoch + 2 - sp.f) // coalesce(sc.per_rep, 1) AS rep
     FROM st JOIN sc ON sc.id = st.id JOIN sp ON sp.id = st.id WHERE st.epoch < sp.l),
   p1 AS MATERIALIZED (SELECT c.id, c.e, c.over, c.rep, c.i, c.node, c.b_ns, c.b_t, coalesce(l.held, c.held) AS held, coalesce(l.buckets, c.buckets) AS buckets, coalesce(l.tuples, 0) AS tuples, coalesce(l.comparisons, 0) AS comps,
       coalesce(l.matches, 0) AS matches, coalesce(l.wait_us, 0) AS wait_us, coalesce(l.tuples, 0) * prm.npt + coalesce(l.comparisons, 0) * prm.npc AS work
     FROM cur c CROSS JOIN prm LEFT JOIN ld l ON l.id = c.id AND l.pid = c.i AND l.epoch = c.e WHERE c.kind = 0),
   n1 AS (SELECT c.*, coalesce(s.tuples, 0) AS n_tuples, coalesce(s.comps, 0) AS n_comps, coalesce(s.matches, 0) AS n_matches, coalesce(s.wait_us, 0) AS n_wait, coalesce(s.work, 0) AS n_work, coalesce(s.before, 0) AS before,
       coalesce(s.held, 0) AS n_held, prm.npm + coalesce(s.tuples, 0) * {TUPLE} * prm.npb AS send
     FROM cur c CROSS JOIN prm LEFT JOIN (SELECT id, node, sum(tuples) AS tuples, sum(comps) AS comps, sum(matches) AS matches, sum(wait_us) AS wait_us, sum(work) AS work, sum(b_ns) AS before, sum(held) AS held FROM p1 GROUP BY 1, 2) s
       ON s.id = c.id AND s.node = c.i WHERE c.kind = 1),
   n2 AS (SELECT n1.*, sc.td_ns, sc.blocking, CASE WHEN active = 1 THEN coalesce(sum(CASE WHEN active = 1 THEN send ELSE 0 END) OVER (PARTITION BY n1.id, i % sc.n_groups ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) ELSE 0 END AS ahead FROM n1 JOIN sc ON sc.id = n1.id),
   n3 AS (SELECT *, send + blocking * ahead + extra AS comm, before + n_work AS due, greatest(0, before + n_work - greatest(0, td_ns - (send + blocking * ahead + extra))) AS after FROM n2),
   p2 AS MATERIALIZED (SELECT p1.*, CASE WHEN n.due > 0 THEN (p1.b_ns + p1.work) * n.after // n.due ELSE 0 END AS q_ns, CASE WHEN n.due > 0 THEN (p1.b_t + 1000 * p1.tuples) * n.after // n.due ELSE 0 END AS q_t FROM p1 JOIN n3 n ON n.id = p1.id AND n.i = p1.node),
   n4 AS MATERIALIZED (SELECT n.*, coalesce(q.q_ns, 0) AS n_back, CASE WHEN n.active = 1 THEN least({PPM}, coalesce(q.q_t, 0) * {TUPLE} * {PPM} // (1000 * prm.buffer)) ELSE 0 END AS occ, sum(n.active) OVER (PARTITION BY n.id) AS n_active
     FROM n3 n CROSS JOIN prm LEFT JOIN (SELECT id, node, sum(q_ns) AS q_ns, sum(q_t) AS q_t FROM p2 GROUP BY 1, 2) q ON q.id = n.id AND q.node = n.i),
   f AS MATERIALIZED (SELECT n.id, n.i, n.rep, (n.s_sum + n.occ) // (n.s_n + 1) AS f, sc.th_sup, sc.th_con, sc.beta, sc.adaptive, n.n_active FROM n4 n JOIN sc ON sc.id = n.id WHERE n.over AND n.active = 1),
   sup AS (SELECT id, i, row_number() OVER (PARTITION BY id ORDER BY f DESC, i) AS k FROM f WHERE f > th_sup),
   con AS (SELECT id, i, row_number() OVER (PARTITION BY id ORDER BY f, i) AS k FROM f WHERE f < th_con),
   own AS MATERIALIZED (SELECT z.id, z.i, z.node, row_number() OVER (PARTITION BY z.id, z.node ORDER BY {_HASH}, z.i) AS k, count(*) OVER (PARTITION BY z.id, z.node) AS n FROM p2 z WHERE z.over),
   sums AS (SELECT id, any_value(adaptive) AS adaptive, any_value(beta) AS beta, any_value(n_active) AS n_active, count(*) FILTER (f > th_sup) AS n_sup, count(*) FILTER (f < th_con) AS n_con FROM f GROUP BY id),
   low AS (SELECT f.id, f.i, row_number() OVER (PARTITION BY f.id ORDER BY f.f, f.i) AS k, f.n_active FROM f JOIN sums ON sums.id = f.id WHERE sums.adaptive = 1 AND sums.n_sup = 0 AND sums.n_active > 1),
   grown AS (SELECT n.id, min(n.i) AS i FROM n4 n JOIN sums s ON s.id = n.id WHERE n.active = 0 AND s.adaptive = 1 AND s.n_sup > 0 AND s.n_sup * {PPM} > s.beta * s.n_con GROUP BY n.id),
   steps AS (SELECT o.id, o.i AS pid, s.i AS a, c.i AS b FROM sup s JOIN con c ON c.id = s.id AND c.k = s.k JOIN own o ON o.id = s.id AND o.node = s.i AND o.k = 1 WHERE o.n > 1 OR NOT EXISTS (SELECT 1 FROM own x WHERE x.id = c.id AND x.node = c.i)
     UNION ALL SELECT o.id, o.i, g.i, r.i FROM low g JOIN own o ON o.id = g.id AND o.node = g.i JOIN low r ON r.id = g.id AND r.k = 2 + (o.k - 1) % (g.n_active - 1) WHERE g.k = 1),
   moves AS MATERIALIZED (SELECT s.*, p.held + p.q_t // 1000 AS n, prm.npm + ((p.held + p.q_t // 1000) * {TUPLE} + 8 * p.buckets) * prm.npb AS price FROM steps s CROSS JOIN prm JOIN p2 p ON p.id = s.id AND p.i = s.pid),
   cost AS (SELECT id, v, sum(price) AS price FROM (SELECT id, a AS v, price FROM moves UNION ALL SELECT id, b, price FROM moves) GROUP BY 1, 2),
   slow AS (SELECT id, max(price) AS price FROM moves GROUP BY 1), got AS (SELECT id, b, count(*) AS k, sum(n) AS n FROM moves GROUP BY 1, 2)
   SELECT 0 AS kind, p.id, p.e AS epoch, p.i, coalesce(m.b, p.node) AS node, p.q_ns AS b_ns, p.q_t AS b_t, p.held, p.buckets, 0 AS active, 0 AS s_sum, 0 AS s_n, 0 AS extra, 0 AS awaited, 0 AS mk, 0 AS mt,
       0 AS o_on, 0 AS o_active, 0 AS o_tuples, 0 AS o_comps, 0 AS o_work, 0 AS o_comm, 0 AS o_idle, 0 AS o_back, 0 AS o_occ, 0 AS o_held, 0 AS o_matches, 0 AS o_delay, 0 AS o_mk, 0 AS o_mt
     FROM p2 p LEFT JOIN moves m ON m.id = p.id AND m.pid = p.i
   UNION ALL
   SELECT 1, n.id, n.e, n.i, n.i, 0, 0, 0, 0, CASE WHEN g.i IS NOT NULL THEN 1 WHEN w.i IS NOT NULL THEN 0 ELSE n.active END, CASE WHEN n.over OR n.active = 0 THEN 0 ELSE n.s_sum + n.occ END, CASE WHEN n.over OR n.active = 0 THEN 0 ELSE n.s_n + 1 END,
       coalesce(c.price, 0), CASE WHEN c.price IS NULL THEN 0 ELSE s.price END, coalesce(t.k, 0), coalesce(t.n, 0),
       n.active, n.n_active, n.n_tuples, n.n_comps, n.n_work, n.comm, greatest(0, n.td_ns - n.comm - (n.due - n.after)), n.n_back, n.occ, n.n_held, n.n_matches, n.n_wait + n.n_matches * (n.awaited + n.ahead + n.send + n.before + n.n_work // 2) // 1000, n.mk, n.mt
     FROM n4 n LEFT JOIN grown g ON g.id = n.id AND g.i = n.i LEFT JOIN (SELECT * FROM low WHERE k = 1) w ON w.id = n.id AND w.i = n.i LEFT JOIN cost c ON c.id = n.id AND c.v = n.i LEFT JOIN slow s ON s.id = n.id LEFT JOIN got t ON t.id = n.id AND t.b = n.i)"""

_COLUMNS = "kind, id, epoch, i, node, b_ns, b_t, held, buckets, active, s_sum, s_n, extra, awaited, mk, mt, o_on, o_active, o_tuples, o_comps, o_work, o_comm, o_idle, o_back, o_occ, o_held, o_matches, o_delay, o_mk, o_mt".split(", ")


def _trace(cases: list[tuple[str, Case]], base_skew: float | None) -> str:
    """WITH clauses that end in ``trace``, the rows of balance.TRACE of all cases."""
    ctes, srcs, loaded, own, rows = [PARAMS], {}, {}, [], []
    for k, (name, c) in enumerate(cases):
        over, td = dict(c.over), int(TD * c.td_factor)
        skew = c.skew or base_skew
        if (c.rate, skew) not in srcs:
            srcs[c.rate, skew] = f"src{len(srcs)}"
            ctes.append(_streams(srcs[c.rate, skew], c.rate, skew))
        key = (c.rate, skew, c.n_part or N_PART, c.tuned, c.theta_factor if c.tuned else 1.0, td)
        if key not in loaded:
            loaded[key] = f"ld{len(loaded)}"
            ctes += _loads(loaded[key], srcs[c.rate, skew], c.n_part or N_PART, c.tuned, c.theta_factor, td)
        own.append(f"SELECT {k} AS id, * FROM {loaded[key]}")
        tr = TR if c.tr is None else c.tr * td
        ppm = lambda f, d: int(over.get(f, d) * PPM)
        rows.append(f"({k}, '{name}', {c.nodes}, {over.get('initial_nodes') or c.nodes}, {tr // td if tr else 'NULL'}, {td * 1000}, {over.get('n_groups', 1)}, {int(over.get('order') == 'blocking')}, {ppm('th_sup', 0.5)}, {ppm('th_con', 0.01)}, {ppm('beta', 0.5)}, {int(bool(over.get('adaptive')))}, {W // td}, '{c.param}', {float(c.value)!r}::DOUBLE)")
    zero = ", ".join(f"0 AS {c}" for c in _COLUMNS[10:])
    init = f"""(SELECT 0 AS kind, ld.id, sp.f - 1 AS epoch, ld.pid AS i, ld.pid % sc.init AS node, 0 AS b_ns, 0 AS b_t, 0 AS held, 0 AS buckets, 0 AS active, {zero} FROM (SELECT DISTINCT id, pid FROM ld) ld JOIN sc ON sc.id = ld.id JOIN sp ON sp.id = ld.id
      UNION ALL SELECT 1, sc.id, sp.f - 1, v.i, v.i, 0, 0, 0, 0, CASE WHEN v.i < sc.init THEN 1 ELSE 0 END, {zero} FROM sc JOIN sp ON sp.id = sc.id, (SELECT unnest(range(16)) AS i) v WHERE v.i < sc.nodes)"""
    cast = ", ".join(f"CAST({c} AS HUGEINT) AS {c}" for c in _COLUMNS)
    ctes += [
        "ld AS MATERIALIZED (" + " UNION ALL ".join(own) + ")",
        "sc(id, scenario, nodes, init, per_rep, td_ns, n_groups, blocking, th_sup, th_con, beta, adaptive, warm, param, param_value) AS MATERIALIZED (VALUES " + ", ".join(rows) + ")",
        "sp AS MATERIALIZED (SELECT id, min(epoch) AS f, max(epoch) AS l FROM ld GROUP BY id)",
        f"st AS (SELECT {cast} FROM {init} UNION ALL SELECT {cast} FROM {_STEP})",
        """trace AS MATERIALIZED (SELECT sc.scenario, CAST(epoch AS BIGINT) AS epoch, CAST(i AS INTEGER) AS node, CAST(o_active AS INTEGER) AS active, CAST(o_tuples AS BIGINT) AS tuples, CAST(o_comps AS BIGINT) AS comparisons, CAST(o_work AS BIGINT) AS work_ns,
            CAST(o_comm AS BIGINT) AS comm_ns, CAST(o_idle AS BIGINT) AS idle_ns, CAST(o_back AS BIGINT) AS backlog_ns, CAST(o_occ AS BIGINT) AS occupancy_ppm, CAST(o_held AS BIGINT) AS held, CAST(o_matches AS BIGINT) AS matches, CAST(o_delay AS BIGINT) AS delay_us,
            CAST(o_mk AS INTEGER) AS moved_groups, CAST(o_mt AS BIGINT) AS moved_tuples FROM st JOIN sc ON sc.id = st.id WHERE kind = 1 AND o_on = 1)""",
    ]
    return "WITH RECURSIVE " + ",\n ".join(ctes)


def trace_sql(name: str, case: Case, skew: float | None = None) -> str:
    return _trace([(name, case)], skew) + " SELECT * FROM trace"


def measures_sql(workload: str, cases: list[Case], skew: float | None = None) -> str:
    """The rows of ``experiments.run_cases``."""
    def whole(a: str, b: str) -> str:
        return f"floor(CAST({a} AS DOUBLE) / greatest(CAST({b} AS DOUBLE), 1.0::DOUBLE))"

    def ratio(a: str, b: str) -> str:
        return f"round(CAST({a} AS DOUBLE) / greatest(CAST({b} AS DOUBLE), 1.0::DOUBLE), 3)"

    per_node = f"""per_node AS (SELECT scenario, {whole('sum(comm)', 'count(*)')} AS comm_avg_ns, CAST(min(comm) AS DOUBLE) AS comm_min_ns, CAST(max(comm) AS DOUBLE) AS comm_max_ns, CAST(sum(comm) AS DOUBLE) AS comm_all_ns, {whole('sum(idle)', 'count(*)')} AS idle_avg_ns,
        {whole('sum(work)', 'count(*)')} AS cpu_avg_ns, {ratio('max(work) * count(*)', 'sum(work)')} AS imbalance FROM (SELECT scenario, node, sum(comm_ns) AS comm, sum(idle_ns) AS idle, sum(work_ns) AS work FROM own GROUP BY 1, 2) GROUP BY 1)"""
    overall = f"""overall AS (SELECT scenario, {whole('sum(delay_us)', 'sum(matches)')} AS delay_avg_us, CAST(sum(matches) AS DOUBLE) AS results, CAST(sum(comparisons) AS DOUBLE) AS comparisons, {ratio('sum(active)', 'count(*)')} AS degree_avg,
        CAST(max(held) AS DOUBLE) AS window_max, {whole('sum(held)', 'count(*)')} AS window_avg, round(max(occupancy_ppm) / 1000000.0::DOUBLE, 6) AS occupancy_max, CAST(sum(moved_groups) AS DOUBLE) AS moved_groups, CAST(sum(moved_tuples) AS DOUBLE) AS moved_tuples FROM own GROUP BY 1)"""
    ends = """ends AS (SELECT scenario, floor(CAST(max_by(b, epoch) - min_by(b, epoch) AS DOUBLE) / greatest(count(*) - 1, 1)) AS backlog_rise_ns FROM (SELECT scenario, epoch, sum(backlog_ns) AS b FROM own GROUP BY 1, 2) GROUP BY 1)"""
    long = " UNION ALL ".join(f"SELECT scenario, '{m}' AS measure, {m} AS value FROM per_node JOIN overall USING (scenario) JOIN ends USING (scenario)" for m in MEASURES)
    return (
        _trace([(c.name(workload), c) for c in cases], skew) + ",\n own AS MATERIALIZED (SELECT trace.* FROM trace JOIN sc ON sc.scenario = trace.scenario WHERE trace.epoch >= sc.warm),\n " + ",\n ".join((per_node, overall, ends))
        + f"\n SELECT '{workload}' AS workload, m.scenario, sc.param, sc.param_value, m.measure, m.value FROM ({long}) m JOIN sc ON sc.scenario = m.scenario"
    )


def buffer_sql(groups: tuple[int, ...], rate: float, td_factor: float, n_part: int = N_PART) -> str:
    """What waits at the master just before each send, and the bound for even arrivals."""
    td = int(TD * td_factor)
    parts = []
    for g in groups:
        nodes = max(g, 4)
        slot = f"(({H.partition_id_sql('key', n_part)} % {nodes}) % {g})"
        epoch = _div(f"t - {slot} * {td} // {g}", td)
        waits = f"(WITH r AS (SELECT t, {slot} * {td} // {g} + ({epoch} + 1) * {td} AS leave_us FROM src0 WHERE stream = 1), i AS (SELECT DISTINCT leave_us AS at FROM r) SELECT max(n) AS n FROM (SELECT i.at, count(*) AS n FROM i JOIN r ON r.t < i.at AND r.leave_us >= i.at GROUP BY 1))"
        bound = f"(SELECT round((count(*) / greatest(1e-9::DOUBLE, (max(t) - min(t)) / 1e6::DOUBLE)) * {td / 1e6!r}::DOUBLE / 2 * (1 + 1 / {g}::DOUBLE), 3) AS n FROM src0 WHERE stream = 1)"
        for name, x in (("buffer_peak", waits), ("buffer_bound", bound)):
            parts.append(f"SELECT 'w11' AS workload, 'w11/groups={g}' AS scenario, 'groups' AS param, {float(g)!r}::DOUBLE AS param_value, '{name}' AS measure, CAST(n AS DOUBLE) AS value FROM {x}")
    return f"WITH {PARAMS},\n {_streams('src0', rate, None)}\n " + " UNION ALL ".join(parts)
