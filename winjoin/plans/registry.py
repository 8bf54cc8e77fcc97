"""Named queries over the given tables, and the same results as SQL for another engine where SQL can say them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from winjoin.functions import hashing as H
from winjoin.operators import frames as FR
from winjoin.operators import window_join as WJ
from winjoin.operators.block_kernel import replay_join
from winjoin.operators.directory import directory_stats, directory_trace, static_directory
from winjoin.plans import balance as BAL
from winjoin.plans import cost as C
from winjoin.plans import epochs as E
from winjoin.plans import experiments as X
from winjoin.plans import oracle as O
from winjoin.plans.model import DAY, HOUR, MINUTE, ClusterSpec, CostSpec
from winjoin.sources import streams as S
from winjoin.sources.synth import gap_us, thin

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE_SQL: dict[str, str] = {}

# Parameters of the registered queries.
N_PART, THETA, DEPTH, BLOCK = 12, 40, 6, 4
TD, TR = 48 * MINUTE, 8 * HOUR
T0 = 1_704_067_200_000_000  # the first instant of the table events
NODES = 4
CLUSTER = ClusterSpec(NODES, TD, TR, buffer_bytes=2048)
GROUPED = ClusterSpec(NODES, TD, TR, buffer_bytes=2048, n_groups=2)
COST = CostSpec()
#: Skew of the keys where nodes shall differ in load.
SKEW = 0.7


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def keep(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            ORACLE_SQL[name] = sql
        return f

    return keep


def pair(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    return S.events(spark, d, "click"), S.events(spark, d, "view")


def ev(kind: str) -> str:
    return f"(SELECT event_id AS id, user_id AS key, epoch_us(ts) AS t FROM events WHERE event_type = '{kind}')"


def join_sql(l: str, r: str, w1: int, w2: int, more: str = "") -> str:
    return f"SELECT l.id AS l_id, r.id AS r_id, l.key AS key, l.t AS l_t, r.t AS r_t, greatest(l.t, r.t) AS newer_t FROM {l} l JOIN {r} r ON l.key = r.key AND r.t >= l.t - {w2} AND r.t <= l.t + {w1} {more}"


def ev_join(w1: int, w2: int, more: str = "") -> str:
    return join_sql(ev("click"), ev("view"), w1, w2, more)


PID = H.partition_id_sql("key", N_PART)
MERGED = f"(SELECT 1 AS stream, * FROM {ev('click')} UNION ALL SELECT 2 AS stream, * FROM {ev('view')})"


# -- joins ---------------------------------------------------------------------------------------------

for _name, _w in (("10m", 10 * MINUTE), ("1h", HOUR), ("6h", 6 * HOUR), ("1d", DAY)):
    query(f"window_join_ev_{_name}", ev_join(_w, _w))(lambda s, d, w=_w: WJ.window_join(*pair(s, d), w, w))
query("window_join_asym", ev_join(HOUR, 6 * HOUR))(lambda s, d: WJ.window_join(*pair(s, d), HOUR, 6 * HOUR))
for _name in ("naive", "smj", "broadcast", "cells", "partitioned", "salted", "slabs"):
    query(f"window_join_{_name}", ev_join(6 * HOUR, 6 * HOUR))(lambda s, d, n=_name: WJ.window_join(*pair(s, d), 6 * HOUR, 6 * HOUR, n, heavy=50))
query("window_join_endless", f"SELECT key, CAST(count(*) AS BIGINT) AS n FROM ({ev_join(10**17, 10**17)}) GROUP BY key")(lambda s, d: WJ.window_join(*pair(s, d), None, None).groupBy("key").agg(F.count(F.lit(1)).alias("n")))
query("window_join_left_newer", ev_join(0, 6 * HOUR))(lambda s, d: WJ.window_join(*pair(s, d), 6 * HOUR, 6 * HOUR, "cells", "left_newer"))
query("window_join_right_newer", ev_join(6 * HOUR, 0))(lambda s, d: WJ.window_join(*pair(s, d), 6 * HOUR, 6 * HOUR, "cells", "right_newer"))
query("window_join_nested_loop", ev_join(6 * HOUR, 6 * HOUR))(lambda s, d: WJ.nested_loop_window_join(*pair(s, d), 6 * HOUR, 6 * HOUR))
query("window_join_one_partition_per_node", ev_join(6 * HOUR, 6 * HOUR))(lambda s, d: WJ.window_join(*pair(s, d), 6 * HOUR, 6 * HOUR, "partitioned", n_part=NODES))


@query("window_join_tuned", ev_join(6 * HOUR, 6 * HOUR))
def window_join_tuned(s: SparkSession, d: str) -> DataFrame:
    l, r = pair(s, d)
    return WJ.tuned_window_join(l, r, 6 * HOUR, 6 * HOUR, static_directory(S.merge_tagged([l, r]), N_PART, THETA, DEPTH), N_PART, DEPTH)


@query("window_join_blocknl", ev_join(6 * HOUR, 6 * HOUR))
def window_join_blocknl(s: SparkSession, d: str) -> DataFrame:
    return replay_join(*pair(s, d), 6 * HOUR, 6 * HOUR, N_PART, TD, BLOCK)


@query("window_join_blocknl_lazy", ev_join(6 * HOUR, 6 * HOUR))
def window_join_blocknl_lazy(s: SparkSession, d: str) -> DataFrame:
    return replay_join(*pair(s, d), 6 * HOUR, 6 * HOUR, N_PART, TD, BLOCK, "block")


@query("window_join_blocknl_tuned", ev_join(6 * HOUR, 6 * HOUR))
def window_join_blocknl_tuned(s: SparkSession, d: str) -> DataFrame:
    l, r = pair(s, d)
    return replay_join(l, r, 6 * HOUR, 6 * HOUR, N_PART, TD, BLOCK, leaves=static_directory(S.merge_tagged([l, r]), N_PART, THETA, DEPTH), max_depth=DEPTH)


query("window_join_10d", f"SELECT CAST({PID} AS INTEGER) AS pid, CAST(count(*) AS BIGINT) AS n FROM ({ev_join(10 * DAY, 10 * DAY)}) GROUP BY 1")(
    lambda s, d: WJ.window_join(*pair(s, d), 10 * DAY, 10 * DAY).groupBy(H.partition_id(F.col("key"), N_PART).alias("pid")).agg(F.count(F.lit(1)).alias("n")))


def _orders(s: SparkSession, d: str) -> DataFrame:
    return S.as_stream(S.table(s, d, "orders"), "o_orderkey", "o_orderdate", "o_orderkey")


def _lines(s: SparkSession, d: str) -> DataFrame:
    return S.as_stream(S.table(s, d, "lineitem").withColumn("line_id", F.col("l_orderkey") * 10 + F.col("l_linenumber")), "l_orderkey", "l_shipdate", "line_id")


ORDERS = "(SELECT o_orderkey AS id, o_orderkey AS key, epoch_us(o_orderdate) AS t FROM orders)"
LINES = "(SELECT l_orderkey * 10 + l_linenumber AS id, l_orderkey AS key, epoch_us(l_shipdate) AS t FROM lineitem)"
for _n in (7, 30):
    query(f"window_join_ol_{_n}d", join_sql(ORDERS, LINES, _n * DAY, _n * DAY))(lambda s, d, n=_n: WJ.window_join(_orders(s, d), _lines(s, d), n * DAY, n * DAY))
query("window_join_zero", join_sql(ORDERS, LINES, 0, 0))(lambda s, d: WJ.window_join(_orders(s, d), _lines(s, d), 0, 0, "cells"))
query("window_self_join_orders", join_sql(*["(SELECT o_orderkey AS id, o_custkey AS key, epoch_us(o_orderdate) AS t FROM orders)"] * 2, 7 * DAY, 7 * DAY, "AND l.id < r.id"))(
    lambda s, d: WJ.window_self_join(S.as_stream(S.table(s, d, "orders"), "o_custkey", "o_orderdate", "o_orderkey"), 7 * DAY))

JSON = "(SELECT event_id AS id, CAST(json_extract(props, '$.k') AS BIGINT) AS key, epoch_us(ts) AS t FROM events WHERE event_type = '{}')"


def _json(s: SparkSession, d: str, kind: str) -> DataFrame:
    rows = S.table(s, d, "events").where(F.col("event_type") == kind).withColumn("k", F.from_json("props", "k bigint")["k"])
    return S.as_stream(rows, "k", "ts", "event_id")


for _name, _w in (("10m", 10 * MINUTE), ("1h", HOUR)):
    query(f"window_join_json_{_name}", join_sql(JSON.format("click"), JSON.format("view"), _w, _w))(lambda s, d, w=_w: WJ.window_join(_json(s, d, "click"), _json(s, d, "view"), w, w))


@query("window_join_conv", "SELECT u.conv_id AS conv_id, u.turn AS u_turn, a.turn AS a_turn FROM conversations u JOIN conversations a ON u.conv_id = a.conv_id AND u.role = 'user' AND a.role = 'assistant' AND a.turn BETWEEN u.turn - 1 AND u.turn + 1")
def window_join_conv(s: SparkSession, d: str) -> DataFrame:
    c = S.table(s, d, "conversations")
    sides = [S.as_stream(c.where(F.col("role") == r), "conv_id", "turn", "turn") for r in ("user", "assistant")]
    return WJ.window_join(*sides, 1, 1).select(F.col("key").alias("conv_id"), F.col("l_id").alias("u_turn"), F.col("r_id").alias("a_turn"))


_LS = "(SELECT l_orderkey * 10 + l_linenumber AS id, l_suppkey AS key, epoch_us(l_shipdate) AS t FROM lineitem WHERE l_returnflag = '{}')"


@query("window_join_hot", f"SELECT key, CAST(count(*) AS BIGINT) AS n FROM ({join_sql(_LS.format('R'), _LS.format('A'), DAY, DAY)}) GROUP BY key")
def window_join_hot(s: SparkSession, d: str) -> DataFrame:
    lines = S.table(s, d, "lineitem").withColumn("line_id", F.col("l_orderkey") * 10 + F.col("l_linenumber"))
    sides = [S.as_stream(lines.where(F.col("l_returnflag") == f), "l_suppkey", "l_shipdate", "line_id") for f in "RA"]
    return WJ.window_join(*sides, DAY, DAY, "cells").groupBy("key").agg(F.count(F.lit(1)).alias("n"))


for _name, _w in (("6h", 6 * HOUR), ("1d", DAY)):
    query(f"window_join_3way_{_name}", f"""SELECT a.id AS id_1, b.id AS id_2, c.id AS id_3, a.key AS key, greatest(a.t, b.t, c.t) AS newer_t
        FROM {ev('click')} a JOIN {ev('view')} b USING (key) JOIN {ev('purchase')} c USING (key)
        WHERE greatest(a.t, b.t, c.t) - least(a.t, b.t, c.t) <= {_w}""")(
        lambda s, d, w=_w: WJ.window_join_multi([S.events(s, d, k) for k in ("click", "view", "purchase")], [w] * 3))

_IN6 = f"l.key = r.key AND r.t BETWEEN l.t - {6 * HOUR} AND l.t + {6 * HOUR}"
query("window_semi", f"SELECT l.* FROM {ev('click')} l WHERE EXISTS (SELECT 1 FROM {ev('view')} r WHERE {_IN6})")(lambda s, d: WJ.window_join(*pair(s, d), 6 * HOUR, 6 * HOUR, how="left_semi"))
query("window_anti", f"SELECT l.* FROM {ev('click')} l WHERE NOT EXISTS (SELECT 1 FROM {ev('view')} r WHERE {_IN6})")(lambda s, d: WJ.window_join(*pair(s, d), 6 * HOUR, 6 * HOUR, how="left_anti"))
for _how, _type in (("left", "LEFT"), ("right", "RIGHT"), ("full", "FULL")):
    query(f"window_{_how}_outer", f"SELECT l.id AS l_id, r.id AS r_id, coalesce(l.key, r.key) AS key, l.t AS l_t, r.t AS r_t, greatest(l.t, r.t) AS newer_t FROM {ev('click')} l {_type} JOIN {ev('view')} r ON {_IN6}")(
        lambda s, d, h=_how: WJ.window_join(*pair(s, d), 6 * HOUR, 6 * HOUR, how=h))
query("window_band_join", f"SELECT l.id AS l_id, r.id AS r_id, l.key AS l_key, r.key AS r_key, l.t AS l_t, r.t AS r_t FROM {ev('click')} l JOIN {ev('view')} r ON abs(l.key - r.key) <= 1 AND r.t BETWEEN l.t - {HOUR} AND l.t + {HOUR}")(
    lambda s, d: WJ.band_join(*pair(s, d), HOUR, HOUR, F.abs(F.col("l_key") - F.col("r_key")) <= 1))
query("asof_latest", f"""SELECT l.id AS l_id, l.key AS key, l.t AS l_t, r.id AS r_id, r.t AS r_t FROM {ev('click')} l LEFT JOIN {ev('view')} r ON r.key = l.key AND r.t <= l.t AND r.t >= l.t - {DAY}
    QUALIFY row_number() OVER (PARTITION BY l.id ORDER BY r.t DESC NULLS LAST, r.id DESC NULLS LAST) = 1""")(lambda s, d: WJ.asof_latest(*pair(s, d), DAY))
query("lateral_recent_k", f"""SELECT l_id, r_id, key, rank FROM (SELECT l.id AS l_id, r.id AS r_id, l.key AS key, CAST(row_number() OVER (PARTITION BY l.id ORDER BY r.t DESC, r.id DESC) AS INTEGER) AS rank
    FROM {ev('click')} l JOIN {ev('view')} r ON r.key = l.key AND r.t BETWEEN l.t - {2 * DAY} AND l.t) WHERE rank <= 3""")(lambda s, d: WJ.recent_k(*pair(s, d), 2 * DAY, 3))
query("interval_overlap", f"SELECT l.id AS l_id, r.id AS r_id, l.key AS key FROM {ev('click')} l JOIN {ev('view')} r ON l.key = r.key AND l.t <= r.t + {2 * HOUR} AND r.t <= l.t + {HOUR}")(
    lambda s, d: WJ.interval_overlap(*(x.select("id", "key", F.col("t").alias("lo"), (F.col("t") + n * HOUR).alias("hi")) for x, n in zip(pair(s, d), (1, 2))), 6 * HOUR))
query("enrich_nation", f"""SELECT n.n_name AS n_name, CAST(count(*) AS BIGINT) AS n FROM ({join_sql(ORDERS, LINES, 7 * DAY, 7 * DAY)}) j JOIN orders o ON o.o_orderkey = j.l_id JOIN customer c ON c.c_custkey = o.o_custkey JOIN nation n ON n.n_nationkey = c.c_nationkey GROUP BY n.n_name""")(
    lambda s, d: WJ.window_join(_orders(s, d), _lines(s, d), 7 * DAY, 7 * DAY).join(S.table(s, d, "orders").select(F.col("o_orderkey").alias("l_id"), "o_custkey"), "l_id").join(S.table(s, d, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_nationkey"), "o_custkey")
    .join(F.broadcast(S.table(s, d, "nation").select(F.col("n_nationkey").alias("c_nationkey"), "n_name")), "c_nationkey").groupBy("n_name").agg(F.count(F.lit(1)).alias("n")))

# -- counts over windows -------------------------------------------------------------------------------

_OPP = "SELECT l.{g} AS {g}, CAST(count(*) AS BIGINT) AS n FROM {l} l JOIN {r} r ON l.{g} = r.{g} AND r.t BETWEEN l.t - {w} AND l.t + {w} GROUP BY 1"
query("join_size_frame", _OPP.format(g="key", l=ORDERS, r=LINES, w=30 * DAY))(
    lambda s, d: FR.arrival_counts(_orders(s, d), _lines(s, d), 30 * DAY, 30 * DAY, ["key"]).groupBy("key").agg(F.sum("n_opposite").alias("n")).where("n > 0"))


def _placed(df: DataFrame) -> DataFrame:
    return df.withColumn("pid", H.partition_id(F.col("key"), N_PART))


_P = f"(SELECT *, {PID} AS pid FROM {{}})"
query("comparisons_untuned", _OPP.format(g="pid", l=_P.format(ev("click")), r=_P.format(ev("view")), w=10 * DAY))(
    lambda s, d: FR.arrival_counts(*(_placed(x) for x in pair(s, d)), 10 * DAY, 10 * DAY, ["pid"]).groupBy("pid").agg(F.sum("n_opposite").alias("n")).where("n > 0"))

_FINE = f"(SELECT {PID} AS pid, {H.mini_bits_sql('key', DEPTH)} AS bits, count(*) AS c FROM {MERGED} GROUP BY 1, 2)"
_NODES = f"(SELECT pid, depth, bits % (1 << depth) AS suffix, sum(c) AS n FROM {_FINE}, (SELECT CAST(unnest(range({DEPTH + 1})) AS INTEGER) AS depth) GROUP BY 1, 2, 3)"
_LEAVES = f"""(SELECT x.pid AS pid, x.depth AS depth, CAST(x.suffix AS INTEGER) AS suffix, CAST(x.n AS BIGINT) AS n, x.n > {2 * THETA} AS unsplittable FROM {_NODES} x
    WHERE (x.n <= {2 * THETA} OR x.depth = {DEPTH}) AND (x.depth = 0 OR EXISTS (SELECT 1 FROM {_NODES} p WHERE p.pid = x.pid AND p.depth = x.depth - 1 AND p.suffix = x.suffix % (1 << greatest(x.depth - 1, 0)) AND p.n > {2 * THETA})))"""


def _leaves(s: SparkSession, d: str) -> DataFrame:
    return static_directory(S.merge_tagged(pair(s, d)), N_PART, THETA, DEPTH)


query("static_directory", f"SELECT * FROM {_LEAVES}")(_leaves)
query("directory_stats", f"""SELECT CAST(count(*) AS BIGINT) AS leaves, CAST(sum(n) AS BIGINT) AS tuples, CAST(min(n) AS BIGINT) AS smallest, CAST(max(n) AS BIGINT) AS largest, max(depth) AS deepest,
    CAST(count(*) FILTER (n BETWEEN {THETA} AND {2 * THETA}) AS BIGINT) AS in_range, CAST(count(*) FILTER (unsplittable) AS BIGINT) AS unsplittable FROM {_LEAVES}""")(lambda s, d: directory_stats(_leaves(s, d), THETA))


@query("comparisons_tuned", f"""WITH leaves AS MATERIALIZED (SELECT * FROM {_LEAVES}), x AS (SELECT m.*, {PID} AS pid, {H.mini_bits_sql('key', DEPTH)} AS bits FROM {MERGED} m),
    y AS (SELECT x.stream, x.t, v.pid, v.depth, v.suffix FROM x JOIN leaves v ON v.pid = x.pid AND x.bits % (1 << v.depth) = v.suffix)
    SELECT l.pid AS pid, CAST(count(*) AS BIGINT) AS n FROM y l JOIN y r ON l.stream = 1 AND r.stream = 2 AND l.pid = r.pid AND l.depth = r.depth AND l.suffix = r.suffix AND r.t BETWEEN l.t - {10 * DAY} AND l.t + {10 * DAY} GROUP BY 1""")
def comparisons_tuned(s: SparkSession, d: str) -> DataFrame:
    leaves = _leaves(s, d)
    sides = [WJ.locate(x.select(F.col("id").alias("x_id"), F.col("key").alias("x_key"), F.col("t").alias("x_t")), "x", leaves, N_PART, DEPTH).select(F.col("x_id").alias("id"), F.col("x_t").alias("t"), F.col("x_pid").alias("pid"), F.col("x_depth").alias("depth"), F.col("x_suffix").alias("suffix")) for x in pair(s, d)]
    return FR.arrival_counts(*sides, 10 * DAY, 10 * DAY, ["pid", "depth", "suffix"]).groupBy("pid").agg(F.sum("n_opposite").alias("n")).where("n > 0")


@query("blocks_scanned", f"""WITH l AS (SELECT *, {PID} AS pid FROM {ev('click')}), r AS (SELECT *, {PID} AS pid FROM {ev('view')}),
    a AS (SELECT l.id, l.pid, count(r.id) AS n FROM l LEFT JOIN r ON r.pid = l.pid AND r.t BETWEEN l.t - {10 * DAY} AND l.t GROUP BY ALL UNION ALL
          SELECT r.id, r.pid, count(l.id) AS n FROM r LEFT JOIN l ON r.pid = l.pid AND l.t >= r.t - {10 * DAY} AND l.t < r.t GROUP BY ALL)
    SELECT pid, CAST(sum((n + {BLOCK - 1}) // {BLOCK}) AS BIGINT) AS blocks FROM a GROUP BY pid""")
def blocks_scanned(s: SparkSession, d: str) -> DataFrame:
    return C.blocks_scanned(FR.arrival_counts(*(_placed(x) for x in pair(s, d)), 10 * DAY, 10 * DAY, ["pid"]), BLOCK, ["pid"])


query("window_sizes", f"SELECT id, pid, t, CAST(count(*) OVER (PARTITION BY pid ORDER BY t RANGE BETWEEN {10 * DAY} PRECEDING AND CURRENT ROW) AS BIGINT) AS n FROM {_P.format(ev('click'))}")(
    lambda s, d: FR.window_sizes(_placed(S.events(s, d, "click")), 10 * DAY, ["pid"]))
_EP = E.floor_div_sql(f"t - {T0}", TD)
query("window_size_max", f"""WITH x AS (SELECT pid, {_EP} AS epoch, 1 AS d FROM {_P.format(ev('click'))} UNION ALL SELECT pid, {E.floor_div_sql(f't + {10 * DAY} - {T0}', TD)} + 1, -1 FROM {_P.format(ev('click'))}),
    y AS (SELECT pid, epoch, sum(d) AS d FROM x GROUP BY ALL), z AS (SELECT pid, sum(d) OVER (PARTITION BY pid ORDER BY epoch) AS n FROM y) SELECT pid, CAST(max(n) AS BIGINT) AS n FROM z GROUP BY pid""")(
    lambda s, d: FR.held_at(_placed(S.events(s, d, "click")), 10 * DAY, ["pid"], T0, TD).groupBy("pid").agg(F.max("n").alias("n")))
query("arrival_gaps", f"SELECT id, key, t, t - lag(t) OVER (PARTITION BY key ORDER BY t, id) AS gap_us FROM {ev('click')}")(lambda s, d: FR.arrival_gaps(S.events(s, d, "click"), ["key"]))
query("block_numbers", f"SELECT id, pid, CAST(n // {BLOCK} AS BIGINT) AS block_no, CAST(n % {BLOCK} AS INTEGER) AS pos FROM (SELECT id, pid, row_number() OVER (PARTITION BY pid ORDER BY t, id) - 1 AS n FROM {_P.format(ev('click'))})")(
    lambda s, d: FR.block_numbers(_placed(S.events(s, d, "click")), BLOCK, ["pid"]))
_AT = T0 + 15 * DAY
query("window_membership", f"SELECT * FROM {ev('click')} WHERE t BETWEEN {_AT - DAY} AND {_AT}")(lambda s, d: FR.membership(S.events(s, d, "click"), _AT, DAY))

# -- hashing and directories ---------------------------------------------------------------------------

query("hash_partition_id", f"SELECT DISTINCT user_id AS key, {H.mix32_sql('user_id')} AS h, {H.partition_id_sql('user_id', 60)} AS pid FROM events")(
    lambda s, d: S.table(s, d, "events").select(F.col("user_id").alias("key")).distinct().select("key", H.mix32(F.col("key")).alias("h"), H.partition_id(F.col("key"), 60).alias("pid")))
query("partition_group_sizes", f"SELECT {PID} AS pid, CAST(count(*) AS BIGINT) AS n, CAST(count(*) FILTER (stream = 1) AS BIGINT) AS n1, CAST(count(*) FILTER (stream = 2) AS BIGINT) AS n2 FROM {MERGED} GROUP BY 1")(
    lambda s, d: _placed(S.merge_tagged(pair(s, d))).groupBy("pid").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("stream") == 1).alias("n1"), F.count_if(F.col("stream") == 2).alias("n2")))
query("dir_slot", f"SELECT DISTINCT user_id AS key, {H.mini_bits_sql('user_id', 5)} AS bits, {H.reversed_bits_sql(H.mini_bits_sql('user_id', 5), 5)} AS slot FROM events")(
    lambda s, d: S.table(s, d, "events").select(F.col("user_id").alias("key")).distinct().withColumn("bits", H.mini_bits(F.col("key"), 5)).withColumn("slot", H.reversed_bits(F.col("bits"), 5)))


@query("directory_buddies", f"""SELECT DISTINCT local_depth, first_slot, CASE WHEN local_depth > 0 THEN CAST(CASE WHEN (first_slot // width) % 2 = 0 THEN first_slot + width ELSE first_slot - width END AS INTEGER) END AS buddy
    FROM (SELECT CAST(e.event_id % 6 AS INTEGER) AS local_depth, 1 << CAST(5 - e.event_id % 6 AS INTEGER) AS width, CAST(({H.mini_bits_sql('user_id', 5)} >> CAST(5 - e.event_id % 6 AS INTEGER)) << CAST(5 - e.event_id % 6 AS INTEGER) AS INTEGER) AS first_slot FROM events e)""")
def directory_buddies(s: SparkSession, d: str) -> DataFrame:
    e = S.table(s, d, "events").select((F.col("event_id") % 6).cast("int").alias("local_depth"), H.mini_bits(F.col("user_id"), 5).alias("b"))
    width = H.two_to(5 - F.col("local_depth"))
    e = e.select("local_depth", (F.floor(F.col("b") / width) * width).cast("int").alias("first_slot")).distinct()
    return e.withColumn("buddy", H.buddy_slot(F.col("first_slot"), F.col("local_depth"), 5))


@query("directory_trace")
def directory_trace_query(s: SparkSession, d: str) -> DataFrame:
    both = _placed(S.merge_tagged(pair(s, d))).withColumn("bits", H.mini_bits(F.col("key"), DEPTH))
    return directory_trace(FR.held_at(both, 10 * DAY, ["pid", "bits"], T0, TR), THETA, DEPTH)


# -- epochs --------------------------------------------------------------------------------------------

_NODE = f"({PID} % {NODES})"
query("epoch_assignment", f"SELECT {_EP} AS epoch, {PID} AS pid, CAST(count(*) AS BIGINT) AS n FROM {MERGED} GROUP BY 1, 2")(
    lambda s, d: E.assign_epochs(_placed(S.merge_tagged(pair(s, d))), TD, T0).groupBy("epoch", "pid").agg(F.count(F.lit(1)).alias("n")))


def _routed_sql(groups: int) -> str:
    phase = f"(({_NODE} % {groups}) * {TD} // {groups})"
    epoch = E.floor_div_sql(f"t - {T0} - {phase}", TD)
    return f"(SELECT stream, id, key, t, {PID} AS pid, CAST({_NODE} AS INTEGER) AS node, CAST({_NODE} % {groups} AS INTEGER) AS slot, {epoch} AS epoch, {T0} + {phase} + ({epoch} + 1) * {TD} AS leave_us FROM {MERGED})"


def _routed(s: SparkSession, d: str, cluster: ClusterSpec) -> DataFrame:
    return E.route(S.merge_tagged(pair(s, d)), cluster, N_PART, T0)


for _name, _c in (("delivery_delay", CLUSTER), ("slot_delay", GROUPED)):
    query(_name, f"SELECT node, slot, CAST(count(*) AS BIGINT) AS n, CAST(sum(leave_us - t) AS BIGINT) AS wait_us, CAST(max(leave_us - t) AS BIGINT) AS max_us FROM {_routed_sql(_c.n_groups)} GROUP BY 1, 2")(
        lambda s, d, c=_c: _routed(s, d, c).groupBy("node", "slot").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("leave_us") - F.col("t")).alias("wait_us"), F.max(F.col("leave_us") - F.col("t")).alias("max_us")))
query("merge_tagged", f"SELECT stream, id, key, t FROM {MERGED}")(lambda s, d: S.merge_tagged(pair(s, d)))
query("punctuate_decode", f"SELECT {PID} AS pid, stream, id, key, t FROM {MERGED}")(lambda s, d: S.decode_punctuated(S.punctuated(_placed(S.merge_tagged(pair(s, d))), ["pid"]), ["pid"]))
_SENT = f"(SELECT epoch, node, slot, count(*) AS tuples, count(*) * {COST.tuple_bytes} AS bytes, {COST.ns_per_message} + count(*) * {COST.tuple_bytes * COST.ns_per_byte} AS send_ns FROM {_routed_sql(1)} GROUP BY 1, 2, 3)"
_COMM = "SELECT node, CAST(count(*) AS BIGINT) AS messages, CAST(sum(bytes) AS BIGINT) AS bytes, CAST(sum({}) AS BIGINT) AS comm_ns FROM {} GROUP BY node"
query("comm_per_node", _COMM.format("send_ns", _SENT))(lambda s, d: E.communication(E.deliveries(_routed(s, d, CLUSTER), COST)))
query("comm_blocking", _COMM.format("before", f"(SELECT *, sum(send_ns) OVER (PARTITION BY epoch, slot ORDER BY node) AS before FROM {_SENT})"))(lambda s, d: E.communication(E.deliveries(_routed(s, d, CLUSTER), COST), "blocking"))
query("comm_min_avg_max", f"SELECT CAST(min(c) AS BIGINT) AS min_ns, CAST(sum(c) // count(*) AS BIGINT) AS avg_ns, CAST(max(c) AS BIGINT) AS max_ns FROM (SELECT node, sum(send_ns) AS c FROM {_SENT} GROUP BY node)")(
    lambda s, d: E.communication(E.deliveries(_routed(s, d, CLUSTER), COST)).agg(F.min("comm_ns").alias("min_ns"), F.expr("sum(comm_ns) div count(*)").alias("avg_ns"), F.max("comm_ns").alias("max_ns")))


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


_VS = "SELECT CAST({v} AS BIGINT) AS {p}, CAST(count(*) AS BIGINT) AS messages, CAST(count(*) * {m} + sum(n) * {b} AS BIGINT) AS comm_ns FROM (SELECT epoch, node, count(*) AS n FROM (SELECT {e} AS epoch, {pid} % {k} AS node FROM {src}) GROUP BY 1, 2)"
query("comm_vs_nodes", " UNION ALL ".join(_VS.format(v=k, p="nodes", m=COST.ns_per_message, b=COST.tuple_bytes * COST.ns_per_byte, e=_EP, pid=PID, k=k, src=MERGED) for k in (1, 2, 3, 4, 6)))(
    lambda s, d: _union([E.communication(E.deliveries(_routed(s, d, ClusterSpec(k, TD, TR)), COST)).agg(F.sum("messages").alias("messages"), F.sum("comm_ns").alias("comm_ns")).select(F.lit(k).cast("long").alias("nodes"), "messages", "comm_ns") for k in (1, 2, 3, 4, 6)]))
query("comm_vs_epoch", " UNION ALL ".join(_VS.format(v=k, p="td_minutes", m=COST.ns_per_message, b=COST.tuple_bytes * COST.ns_per_byte, e=E.floor_div_sql(f"t - {T0}", k * MINUTE), pid=PID, k=3, src=MERGED) for k in (12, 24, 48, 96)))(
    lambda s, d: _union([E.communication(E.deliveries(_routed(s, d, ClusterSpec(3, k * MINUTE, TR)), COST)).agg(F.sum("messages").alias("messages"), F.sum("comm_ns").alias("comm_ns")).select(F.lit(k).cast("long").alias("td_minutes"), "messages", "comm_ns") for k in (12, 24, 48, 96)]))
query("comm_patterns", " UNION ALL ".join(f"SELECT {k} AS nodes, CAST(2 * count(DISTINCT node) AS BIGINT) AS fixed, CAST(count(DISTINCT node) * (count(DISTINCT node) - 1) AS BIGINT) AS all_to_all FROM (SELECT {PID} % {k} AS node FROM {MERGED})" for k in (2, 4, 8)))(lambda s, d: _patterns(s, d))
_DAILY = "(SELECT CAST(count(*) AS BIGINT) AS n, CAST(max(t) - min(t) AS BIGINT) AS span FROM " + ev("click") + ")"
query("buffer_bound", " UNION ALL ".join(f"SELECT {g} AS n_g, CAST(round(n / (span / 1000000.0::DOUBLE) * 86400.0::DOUBLE / 2 * (1 + 1 / {g}::DOUBLE), 3) AS DOUBLE) AS bound FROM {_DAILY}" for g in (1, 2, 4, 10)))(
    lambda s, d: s.createDataFrame([(n, round(E.buffer_bound(_rate(s, d), 86400.0, n), 3)) for n in (1, 2, 4, 10)], "n_g int, bound double"))


def _patterns(s: SparkSession, d: str) -> DataFrame:
    """Channels between the master and the nodes that get tuples, or among these."""
    used = [(k, _routed(s, d, ClusterSpec(k, TD, TR)).agg(F.count_distinct("node")).first()[0]) for k in (2, 4, 8)]
    return s.createDataFrame([(k, E.channels(n), E.channels(n, "all")) for k, n in used], "nodes int, fixed long, all_to_all long")


def _rate(s: SparkSession, d: str) -> float:
    """Clicks a second."""
    x = S.events(s, d, "click").agg(F.count(F.lit(1)).alias("n"), F.min("t").alias("a"), F.max("t").alias("b")).first()
    return x.n / ((x.b - x.a) / 1000000.0)


query("buffer_trace", f"""WITH r AS {_routed_sql(2)}, i AS (SELECT DISTINCT leave_us AS at FROM r), a AS (SELECT i.at, count(*) AS n FROM i JOIN r ON r.t < i.at AND r.leave_us >= i.at GROUP BY 1) SELECT CAST(max(n) AS BIGINT) AS peak FROM a""")(
    lambda s, d: E.buffer_trace(_routed(s, d, GROUPED)).agg(F.max("waiting").alias("peak")))


query("state_bytes", f"""WITH z AS (SELECT {PID} AS pid, count(*) AS n FROM {MERGED} GROUP BY 1), b AS (SELECT pid, count(*) AS k FROM {_LEAVES} GROUP BY 1)
    SELECT z.pid AS pid, CAST(z.n * 64 + b.k * 8 AS BIGINT) AS bytes FROM z JOIN b ON z.pid = b.pid""")(
    lambda s, d: E.state_bytes(_placed(S.merge_tagged(pair(s, d))).groupBy("pid").agg(F.count(F.lit(1)).alias("n")), COST, _leaves(s, d)))
query("degree_by_estimate", f"SELECT CAST(k AS BIGINT) AS times, CAST(greatest(1, least(8, CAST(floor((0.01::DOUBLE * 2e9::DOUBLE - r * k * 2 * 64 * 8) / 500000) AS INTEGER))) AS INTEGER) AS nodes FROM (VALUES (10000000), (22000000), (25000000)) v(k), (SELECT n / (span / 1000000.0::DOUBLE) AS r FROM {_DAILY})")(
    lambda s, d: s.createDataFrame([(k, E.degree_by_estimate(_rate(s, d) * k, 2, 8, COST)) for k in (10_000_000, 22_000_000, 25_000_000)], "times long, nodes int"))

# -- queues, classes, moves ----------------------------------------------------------------------------

_SK = "(SELECT event_id AS id, " + H.bmodel_key_sql("event_id", SKEW, *X.EVENT_SKEW) + " AS key, epoch_us(ts) AS t FROM events WHERE event_type = '{}')"
_SKM = f"(SELECT 1 AS stream, * FROM {_SK.format('click')} UNION ALL SELECT 2 AS stream, * FROM {_SK.format('view')})"
#: A node takes 1.1 times the mean work of all epochs and nodes; its buffer holds four times as much.
_CAP = f"(SELECT CAST(greatest(1, count(*) * 11 // (10 * {NODES} * (max(e) - min(e) + 1))) AS BIGINT) AS cap, CAST(max(e) - min(e) + 1 AS BIGINT) AS epochs FROM (SELECT {E.floor_div_sql(f't - {T0}', TR)} AS e FROM {_SKM}))"
_WORK = f"(SELECT epoch, node, CAST(count(*) AS BIGINT) AS work, any_value(cap) AS cap, any_value(epochs) AS epochs FROM (SELECT {E.floor_div_sql(f't - {T0}', TR)} AS epoch, CAST({_NODE} AS INTEGER) AS node FROM {_SKM}), {_CAP} GROUP BY 1, 2)"
_BACK = f"""(WITH w AS {_WORK}, a AS (SELECT n.node, e.epoch, any_value(w2.cap) AS cap FROM (SELECT DISTINCT node FROM w) n, (SELECT unnest(range(min(epoch), max(epoch) + 1)) AS epoch FROM w) e, w w2 GROUP BY 1, 2),
    q AS (SELECT a.epoch, a.node, a.cap, w.work, sum(coalesce(w.work, 0) - a.cap) OVER (PARTITION BY a.node ORDER BY a.epoch) AS s FROM a LEFT JOIN w ON w.node = a.node AND w.epoch = a.epoch WHERE a.epoch >= (SELECT min(epoch) FROM w x WHERE x.node = a.node)),
    z AS (SELECT *, s - least(0, min(s) OVER (PARTITION BY node ORDER BY epoch)) AS b FROM q) SELECT epoch, node, work, CAST(b AS BIGINT) AS backlog, cap FROM z WHERE work IS NOT NULL)"""


def _skewed(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    rows = S.table(s, d, "events").withColumn("bkey", H.bmodel_key(F.col("event_id"), SKEW, *X.EVENT_SKEW))
    return tuple(S.as_stream(rows.where(F.col("event_type") == k), "bkey", "ts", "event_id") for k in ("click", "view"))


def _work(s: SparkSession, d: str) -> DataFrame:
    """(epoch, node, work, cap, epochs) of the skewed pair."""
    placed = E.assign_epochs(_placed(S.merge_tagged(_skewed(s, d))).withColumn("node", E.initial_node(F.col("pid"), NODES)), TR, T0)
    work = placed.groupBy("epoch", "node").agg(F.count(F.lit(1)).alias("work"))
    whole = work.agg(F.sum("work").alias("n"), (F.max("epoch") - F.min("epoch") + 1).alias("epochs"))
    return work.join(F.broadcast(whole.select(F.greatest(F.lit(1), F.expr(f"n * 11 div (10 * {NODES} * epochs)")).alias("cap"), "epochs")))


def _backlog(s: SparkSession, d: str) -> DataFrame:
    return E.lindley(_work(s, d), ["node"], F.col("cap"))


query("backlog_lindley", f"SELECT epoch, node, work, backlog FROM {_BACK}")(lambda s, d: _backlog(s, d).select("epoch", "node", "work", "backlog"))
_F = f"(SELECT epoch // 10 AS rep_epoch, node, round(avg(least(1.0::DOUBLE, backlog / (4.0::DOUBLE * cap))), 6) AS f FROM {_BACK} GROUP BY 1, 2)"
_CLASS = f"(SELECT *, CASE WHEN f > 0.5 THEN 'supplier' WHEN f < 0.01 THEN 'consumer' ELSE 'neutral' END AS class FROM {_F})"


def _classes(s: SparkSession, d: str) -> DataFrame:
    f = _backlog(s, d).groupBy(F.expr("epoch div 10").alias("rep_epoch"), "node").agg(F.round(F.avg(F.least(F.lit(1.0), F.col("backlog") / (F.lit(4.0) * F.col("cap")))), 6).alias("f"))
    return BAL.classify(f, CLUSTER)


query("occupancy_classes", f"SELECT rep_epoch, node, f, class FROM {_CLASS}")(_classes)
query("supplier_consumer_pairs", f"""WITH s AS (SELECT rep_epoch, node, row_number() OVER (PARTITION BY rep_epoch ORDER BY f DESC, node) AS k FROM {_CLASS} WHERE class = 'supplier'),
    c AS (SELECT rep_epoch, node, row_number() OVER (PARTITION BY rep_epoch ORDER BY f, node) AS k FROM {_CLASS} WHERE class = 'consumer')
    SELECT s.rep_epoch AS rep_epoch, s.node AS supplier, c.node AS consumer FROM s JOIN c ON s.rep_epoch = c.rep_epoch AND s.k = c.k""")(lambda s, d: BAL.pair_nodes(_classes(s, d)))
query("degree_decision", f"""SELECT rep_epoch, n_sup, n_con, CASE WHEN n_sup = 0 THEN 'shrink' WHEN n_sup > 0.5 * n_con THEN 'grow' ELSE 'keep' END AS decision
    FROM (SELECT rep_epoch, CAST(count(*) FILTER (class = 'supplier') AS BIGINT) AS n_sup, CAST(count(*) FILTER (class = 'consumer') AS BIGINT) AS n_con FROM {_CLASS} GROUP BY 1)""")(lambda s, d: BAL.decide_degree(_classes(s, d), 0.5))


@query("move_cost", f"""WITH p AS (SELECT DISTINCT {PID} AS pid, CAST({_NODE} AS INTEGER) AS node FROM {_SKM}), z AS (SELECT {PID} AS pid, count(*) AS n FROM {_SKM} GROUP BY 1),
    s AS (SELECT rep_epoch, node, row_number() OVER (PARTITION BY rep_epoch ORDER BY f DESC, node) AS k FROM {_CLASS} WHERE class = 'supplier'),
    c AS (SELECT rep_epoch, node, row_number() OVER (PARTITION BY rep_epoch ORDER BY f, node) AS k FROM {_CLASS} WHERE class = 'consumer'),
    m AS (SELECT s.rep_epoch, s.node AS supplier, c.node AS consumer, p.pid, row_number() OVER (PARTITION BY s.rep_epoch, s.node ORDER BY {H.mix32_sql('(42 * 7919 + s.rep_epoch * 104729 + p.pid)')}, p.pid) AS k
          FROM s JOIN c ON s.rep_epoch = c.rep_epoch AND s.k = c.k JOIN p ON p.node = s.node)
    SELECT m.rep_epoch AS rep_epoch, m.supplier AS supplier, m.consumer AS consumer, m.pid AS pid, CAST(z.n AS BIGINT) AS tuples, CAST(z.n * 64 AS BIGINT) AS bytes FROM m JOIN z ON z.pid = m.pid WHERE m.k = 1""")
def move_cost(s: SparkSession, d: str) -> DataFrame:
    sizes = _placed(S.merge_tagged(_skewed(s, d))).groupBy("pid").agg(F.count(F.lit(1)).alias("tuples"))
    assignment = sizes.select("pid", E.initial_node(F.col("pid"), NODES).alias("node"))
    moves = BAL.plan_moves(BAL.pair_nodes(_classes(s, d)), assignment, 42)
    return moves.join(sizes, "pid").select("rep_epoch", "supplier", "consumer", "pid", "tuples", (F.col("tuples") * 64).alias("bytes"))


#: Time units of the idle-time query: a tuple's work, its receipt, a message (sent in every epoch), an epoch per tuple of capacity.
_UNITS = (10, 1, 5, 12)
query("idle_time", f"SELECT node, CAST(sum(greatest(0, {_UNITS[3]} * cap - {_UNITS[0] + _UNITS[1]} * work - {_UNITS[2]})) + (any_value(epochs) - count(*)) * greatest(0, {_UNITS[3]} * any_value(cap) - {_UNITS[2]}) AS BIGINT) AS idle FROM {_WORK} GROUP BY node")(lambda s, d: _idle(s, d))


def _idle(s: SparkSession, d: str) -> DataFrame:
    """What work and communication leave of all epochs, those without arrivals included."""
    work, receive, message, each = _UNITS
    free = F.greatest(F.lit(0), F.col("cap") * each - F.col("work") * (work + receive) - message)
    empty = (F.max("epochs") - F.count(F.lit(1))) * F.greatest(F.lit(0), F.max("cap") * each - message)
    return _work(s, d).groupBy("node").agg((F.sum(free) + empty).cast("long").alias("idle"))


query("imbalance", f"SELECT CAST(max(w) AS BIGINT) AS max_work, round(avg(w), 6) AS mean_work, round(max(w) / avg(w), 6) AS ratio FROM (SELECT node, sum(work) AS w FROM {_WORK} GROUP BY node)")(
    lambda s, d: C.imbalance(_work(s, d).groupBy("node").agg(F.sum("work").alias("work"))).select("max_work", F.round("mean_work", 6).alias("mean_work"), F.round("ratio", 6).alias("ratio")))
#: A backlog that rises by less than a fiftieth of an epoch per epoch is stable.
_STABLE = TD * 1000 // 50
_RATES, _SIZES = (0.5, 1.0, 2.0, 4.0), (2, 4)
query("capacity_grid", f"SELECT variant AS nodes, max(param_value) AS capacity FROM (SELECT split_part(scenario, '/', 2) AS variant, param_value FROM ({O.measures_sql('w1', X.delay_vs_rate(_RATES, _SIZES))}) WHERE measure = 'backlog_rise_ns' AND value <= {_STABLE}) GROUP BY 1")(lambda s, d: _capacity_grid(s, d))


def _capacity_grid(s: SparkSession, d: str) -> DataFrame:
    """The greatest rate multiple that a number of nodes takes without a rising backlog."""
    rise = X.run("w1_delay_vs_rate", X.on_events(s, d), rates=_RATES, nodes=_SIZES).where("measure = 'backlog_rise_ns'")
    return C.capacity(rise.select(F.split_part("scenario", F.lit("/"), F.lit(2)).alias("group"), F.col("param_value").alias("rate"), F.col("value").alias("slope")), _STABLE).withColumnRenamed("group", "nodes")


query("production_delay", f"""SELECT node, CAST(count(*) AS BIGINT) AS n, CAST(sum(emit - newer_t) AS BIGINT) AS sum_us, CAST(max(emit - newer_t) AS BIGINT) AS max_us FROM (
    SELECT j.newer_t, CAST({H.partition_id_sql('j.key', N_PART)} % {NODES} AS INTEGER) AS node, {T0} + ({E.floor_div_sql(f'j.newer_t - {T0}', TD)} + 1) * {TD} AS emit FROM ({ev_join(DAY, DAY)}) j) GROUP BY node""")(
    lambda s, d: C.production_delay(WJ.window_join(*pair(s, d), DAY, DAY).withColumn("node", E.initial_node(H.partition_id(F.col("key"), N_PART), NODES)).withColumn("emit_us", F.lit(T0) + (E.floor_div(F.col("newer_t") - F.lit(T0), TD) + 1) * F.lit(TD)), by=["node"]).select("node", "n", "sum_us", "max_us"))
_U = "((" + H.mix32_sql("id * 2 + 1") + " + 0.5) / 4294967296.0 < {})"
query("shedding_recall", f"SELECT keep, CAST(count(*) FILTER (kept) AS BIGINT) AS found, CAST(count(*) AS BIGINT) AS truth FROM (" + " UNION ALL ".join(f"SELECT CAST({k} AS DOUBLE) AS keep, {_U.format(k).replace('id *', 'l_id *')} AND {_U.format(k).replace('id *', 'r_id *')} AS kept FROM ({ev_join(DAY, DAY)})" for k in (0.25, 0.5, 0.75)) + ") GROUP BY keep")(lambda s, d: _shedding(s, d))


def _shedding(s: SparkSession, d: str) -> DataFrame:
    l, r = pair(s, d)
    truth = WJ.window_join(l, r, DAY, DAY).agg(F.count(F.lit(1)).alias("truth"))
    return _union([WJ.window_join(thin(l, k), thin(r, k), DAY, DAY).agg(F.count(F.lit(1)).alias("found")).join(F.broadcast(truth)).select(F.lit(float(k)).alias("keep"), "found", "truth") for k in (0.25, 0.5, 0.75)])


_JOINS = (("10m", 10 * MINUTE), ("1h", HOUR), ("6h", 6 * HOUR), ("1d", DAY))
query("operator_placement", "WITH RECURSIVE w AS (SELECT name, n, row_number() OVER (ORDER BY n DESC, name) AS k FROM (" + " UNION ALL ".join(f"SELECT '{n}' AS name, count(*) AS n FROM ({ev_join(w, w)})" for n, w in _JOINS) + """)),
    st AS (SELECT CAST(0 AS BIGINT) AS k, CAST(0 AS BIGINT) AS a, CAST(0 AS BIGINT) AS b, '' AS query, 0 AS node UNION ALL SELECT w.k, CASE WHEN a <= b THEN a + n ELSE a END, CASE WHEN a <= b THEN b ELSE b + n END, w.name, CASE WHEN a <= b THEN 0 ELSE 1 END FROM st JOIN w ON w.k = st.k + 1)
    SELECT query, CAST(node AS INTEGER) AS node FROM st WHERE k > 0""")(lambda s, d: s.createDataFrame(list(BAL.place_operators({n: WJ.window_join(*pair(s, d), w, w).count() for n, w in _JOINS}, 2).items()), "query string, node int"))

# -- generator -----------------------------------------------------------------------------------------

query("bmodel_keys", f"SELECT event_id AS id, {H.bmodel_key_sql('event_id')} AS key FROM events")(lambda s, d: S.table(s, d, "events").select(F.col("event_id").alias("id"), H.bmodel_key(F.col("event_id")).alias("key")))
query("poisson_gaps", f"SELECT event_id AS id, CAST(round(-ln(({H.mix32_sql('event_id + 42 * 1000003 + 7')} + 0.5) / 4294967296.0) / 1500.0 * 1e6) AS BIGINT) AS gap_us FROM events")(lambda s, d: S.table(s, d, "events").select(F.col("event_id").alias("id"), gap_us(F.col("event_id"), 1500, 42).alias("gap_us")))


query("window_join_skew", f"SELECT key, CAST(count(*) AS BIGINT) AS n FROM ({join_sql(_SK.format('click'), _SK.format('view'), 6 * HOUR, 6 * HOUR)}) GROUP BY key")(lambda s, d: WJ.window_join(*_skewed(s, d), 6 * HOUR, 6 * HOUR).groupBy("key").agg(F.count(F.lit(1)).alias("n")))

# -- relational surround -------------------------------------------------------------------------------

query("scan_events", "SELECT event_id, user_id, value FROM events WHERE event_type = 'click' AND value > 10")(lambda s, d: S.table(s, d, "events").where("event_type = 'click' AND value > 10").select("event_id", "user_id", "value"))
query("normalize_events", f"SELECT id, key, t FROM {ev('click')}")(lambda s, d: S.events(s, d, "click"))
query("filter_project", f"SELECT event_id AS id, CASE WHEN event_type IN ('click', 'view') THEN 'seen' WHEN event_type LIKE 'p%' THEN 'paid' ELSE 'other' END AS class FROM events WHERE epoch_us(ts) BETWEEN {T0 + DAY} AND {T0 + 3 * DAY}")(
    lambda s, d: S.table(s, d, "events").where(S.micros("ts").between(T0 + DAY, T0 + 3 * DAY)).select(F.col("event_id").alias("id"), F.when(F.col("event_type").isin("click", "view"), "seen").when(F.col("event_type").like("p%"), "paid").otherwise("other").alias("class")))
query("topk_keys", f"SELECT key, CAST(count(*) AS BIGINT) AS n FROM {MERGED} GROUP BY key ORDER BY n DESC, key LIMIT 10")(lambda s, d: S.merge_tagged(pair(s, d)).groupBy("key").agg(F.count(F.lit(1)).alias("n")).orderBy(F.col("n").desc(), "key").limit(10))
query("topk_per_node", f"SELECT node, key, n FROM (SELECT node, key, n, row_number() OVER (PARTITION BY node ORDER BY n DESC, key) AS k FROM (SELECT CAST({_NODE} AS INTEGER) AS node, key, CAST(count(*) AS BIGINT) AS n FROM {MERGED} GROUP BY 1, 2)) WHERE k <= 3")(
    lambda s, d: _placed(S.merge_tagged(pair(s, d))).groupBy(E.initial_node(F.col("pid"), NODES).alias("node"), "key").agg(F.count(F.lit(1)).alias("n")).withColumn("k", F.row_number().over(Window.partitionBy("node").orderBy(F.col("n").desc(), "key"))).where("k <= 3").select("node", "key", "n"))
_CUBE = f"SELECT CAST({_NODE} AS INTEGER) AS node, CAST({E.floor_div_sql(f't - {T0}', 5 * DAY)} AS BIGINT) AS span FROM {MERGED}"
query("cube_load", f"SELECT node, span, CAST(count(*) AS BIGINT) AS n FROM ({_CUBE}) GROUP BY CUBE (node, span)")(lambda s, d: _spans(s, d).cube("node", "span").agg(F.count(F.lit(1)).alias("n")))
query("rollup_comm", f"SELECT node, span, CAST(count(*) * 64 AS BIGINT) AS bytes FROM ({_CUBE}) GROUP BY ROLLUP (node, span)")(lambda s, d: _spans(s, d).rollup("node", "span").agg((F.count(F.lit(1)) * 64).alias("bytes")))
query("pivot_nodes", f"SELECT span, {', '.join(f'CAST(count(*) FILTER (node = {v}) AS BIGINT) AS node_{v}' for v in range(NODES))} FROM ({_CUBE}) GROUP BY span")(
    lambda s, d: _spans(s, d).groupBy("span").pivot("node", list(range(NODES))).count().na.fill(0).select("span", *(F.col(str(v)).alias(f"node_{v}") for v in range(NODES))))
query("delay_by_epoch", f"SELECT {E.floor_div_sql(f't - {T0}', 5 * DAY)} AS span, CAST(sum(leave_us - t) // count(*) AS BIGINT) AS avg_us, CAST(count(DISTINCT key) AS BIGINT) AS keys FROM {_routed_sql(1)} GROUP BY 1")(
    lambda s, d: _routed(s, d, CLUSTER).groupBy(E.floor_div(F.col("t") - F.lit(T0), 5 * DAY).alias("span")).agg(F.expr("sum(leave_us - t) div count(*)").alias("avg_us"), F.count_distinct("key").alias("keys")))


def _spans(s: SparkSession, d: str) -> DataFrame:
    return _placed(S.merge_tagged(pair(s, d))).select(E.initial_node(F.col("pid"), NODES).alias("node"), E.floor_div(F.col("t") - F.lit(T0), 5 * DAY).alias("span"))


query("join_size_by_key", f"SELECT key, CAST(count(*) AS BIGINT) AS n FROM ({ev_join(DAY, DAY)}) GROUP BY key")(lambda s, d: FR.arrival_counts(*pair(s, d), DAY, DAY, ["key"]).groupBy("key").agg(F.sum("n_opposite").alias("n")).where("n > 0"))
query("keys_in_both", f"SELECT key FROM {ev('click')} INTERSECT SELECT key FROM {ev('view')}")(lambda s, d: pair(s, d)[0].select("key").intersect(pair(s, d)[1].select("key")))
query("result_difference_empty", "SELECT CAST(0 AS BIGINT) AS n")(lambda s, d: C.bag_difference(WJ.window_join(*pair(s, d), 6 * HOUR, 6 * HOUR, "cells"), WJ.window_join(*pair(s, d), 6 * HOUR, 6 * HOUR, "naive")).agg(F.count(F.lit(1)).alias("n")))
query("node_ranks", f"SELECT node, w, CAST(rank() OVER (ORDER BY w DESC) AS INTEGER) AS r, CAST(ntile(2) OVER (ORDER BY w DESC, node) AS INTEGER) AS half FROM (SELECT node, CAST(sum(work) AS BIGINT) AS w FROM {_WORK} GROUP BY node)")(
    lambda s, d: _work(s, d).groupBy("node").agg(F.sum("work").alias("w")).select("node", "w", F.rank().over(Window.orderBy(F.col("w").desc())).alias("r"), F.ntile(2).over(Window.orderBy(F.col("w").desc(), "node")).alias("half")))
query("map_assignment", f"SELECT id, CAST({_NODE} AS INTEGER) AS node FROM {ev('click')}")(lambda s, d: _placed(S.events(s, d, "click")).select("id", F.element_at(F.create_map(*(F.lit(x) for p in range(N_PART) for x in (p, p % NODES))), F.col("pid")).alias("node")))
query("roundtrip_json", "SELECT event_id, user_id, event_type FROM events")(
    lambda s, d: S.table(s, d, "events").select(F.from_json(F.to_json(F.struct("event_id", "user_id", "event_type")), "event_id bigint, user_id bigint, event_type string").alias("e")).select("e.*"))
query("payload_passthrough", "SELECT event_id AS id, json_extract_string(props, '$.k') AS k, event_type FROM events WHERE user_id IS NOT NULL")(
    lambda s, d: S.as_stream(S.table(s, d, "events"), "user_id", "ts", "event_id", ["event_type", "props"]).select("id", F.get_json_object("payload.props", "$.k").alias("k"), "payload.event_type"))

# -- whole runs of the modelled cluster -----------------------------------------------------------------

#: Skewed keys at a rate that overloads the nodes of the hot ones, so that groups move.
_MOVING = X.Case("rate", 2.7, 2.7)
_GROWING = X.Case("rate", 4, 4.0, nodes=6, over=(("adaptive", True), ("initial_nodes", 1)))


def _run(s: SparkSession, d: str, name: str, case: X.Case) -> DataFrame:
    setting = X.on_events(s, d, skew=SKEW)
    cluster = case.cluster_of(setting)
    l = X.loads(*setting.streams(case.rate), case.join_of(setting), cluster.td_us, setting.t0).withColumn("scenario", F.lit(name))
    return BAL.simulate_all(l, {name: (cluster, setting.cost)})


query("rebalance_trace", O.trace_sql("rebalance", _MOVING, SKEW))(lambda s, d: _run(s, d, "rebalance", _MOVING).withColumn("delay_us", F.col("delay_us").cast("long")))
query("degree_trace", f"SELECT epoch, max(active) AS active, CAST(sum(moved_groups) AS BIGINT) AS moved FROM ({O.trace_sql('degree', _GROWING, SKEW)}) GROUP BY epoch")(
    lambda s, d: _run(s, d, "degree", _GROWING).groupBy("epoch").agg(F.max("active").alias("active"), F.sum("moved_groups").alias("moved")))

#: Options of the sweeps over the table events; ablations on skewed keys.
_OPTIONS: dict[str, dict] = {"w12_ablations": {"n_part": N_PART}}
_SKEWED = {"w12_ablations"}
for _name, _cases in {**X.WORKLOADS, "grid": X.grid}.items():
    _skew, _more = SKEW if _name in _SKEWED else None, _OPTIONS.get(_name, {})
    query(f"exp_{_name}", O.measures_sql(_name.split("_")[0], _cases(**_more), _skew))(lambda s, d, n=_name, k=_skew, o=_more: X.run(n, X.on_events(s, d, skew=k), **o))
#: An epoch of 3.3 days holds hundreds of tuples.
query("exp_w11_buffer_vs_groups", O.buffer_sql((1, 2, 4), 4.0, 100.0))(lambda s, d: X.buffer_vs_groups(X.on_events(s, d), (1, 2, 4), 4.0, 100.0))
