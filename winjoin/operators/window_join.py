"""Equi-joins of the recent windows of streams, on bounded inputs.

A pair qualifies if the keys are equal and t1 - W2 <= t2 <= t1 + W1: the older
tuple is still inside its own stream's window when the newer one arrives. Both
ends are closed; None as a window is endless. Inputs are tuples (id, key, t).
"""

from __future__ import annotations

from collections.abc import Sequence
from functools import partial

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from winjoin.functions.hashing import floor_div, mini_bits, partition_id, two_to

STRATEGIES = ("auto", "naive", "smj", "broadcast", "cells", "partitioned", "salted", "slabs")


def _side(df: DataFrame, tag: str, extra: Sequence[str] = ()) -> DataFrame:
    return df.select(F.col("id").alias(f"{tag}_id"), F.col("key").alias(f"{tag}_key"), F.col("t").alias(f"{tag}_t"), *(F.col(c).alias(f"{tag}_{c}") for c in extra))


def in_window(w1: int | None, w2: int | None, direction: str = "both") -> Column:
    """The time condition on l_t and r_t."""
    low = F.lit(True) if w2 is None else F.col("r_t") >= F.col("l_t") - F.lit(w2)
    high = F.lit(True) if w1 is None else F.col("r_t") <= F.col("l_t") + F.lit(w1)
    if direction == "left_newer":
        high = F.col("r_t") <= F.col("l_t")
    elif direction == "right_newer":
        low = F.col("r_t") >= F.col("l_t")
    elif direction != "both":
        raise ValueError("direction is 'both', 'left_newer' or 'right_newer'")
    return low & high


def _pairs(df: DataFrame) -> DataFrame:
    return df.select("l_id", "r_id", F.col("l_key").alias("key"), "l_t", "r_t", F.greatest("l_t", "r_t").alias("newer_t"))


def choose(left: DataFrame, right: DataFrame, w1: int | None, w2: int | None) -> str:
    """'cells' where a key has hundreds of tuples over many windows, so that pairs of all times far outnumber those of a window; else 'naive'.

    One pass of small aggregates: the greatest count of a key and the span of time.
    """
    if w1 is None or w2 is None:
        return "naive"
    counts = left.select("key", "t").unionByName(right.select("key", "t"))
    per_key = counts.groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.min("t").alias("a"), F.max("t").alias("b"))
    top = per_key.agg(F.max("n").alias("n"), F.min("a").alias("a"), F.max("b").alias("b")).first()
    if not top.n:
        return "naive"
    windows = (top.b - top.a + 1) / (w1 + w2 + 1)
    return "cells" if windows > 4 and top.n > 256 else "naive"


def window_join(left: DataFrame, right: DataFrame, w1: int | None, w2: int | None, strategy: str = "auto", direction: str = "both", how: str = "inner", n_part: int = 60, salts: int = 8, heavy: int = 100_000, slab_us: int | None = None) -> DataFrame:
    """Rows (l_id, r_id, key, l_t, r_t, newer_t) for inner joins; for semi and anti joins the left tuples; outer joins fill with nulls.

    naive: equi-join on the key, time as residual. smj, broadcast: the same with a
    join hint. cells: key and time cell, so a hot key is cut by time and no key's
    whole history meets. partitioned: on (partition, key). salted: tuples of
    keys above ``heavy`` rows are spread over ``salts`` tasks. slabs: restartable time
    slabs with a halo of the window's length.
    """
    if strategy not in STRATEGIES:
        raise ValueError(f"strategy is one of {STRATEGIES}")
    if strategy == "auto":
        strategy = choose(left, right, w1, w2)
    l, r = _side(left, "l"), _side(right, "r")
    match = (F.col("l_key") == F.col("r_key")) & in_window(w1, w2, direction)
    if how in ("left_semi", "left_anti"):
        if strategy == "cells":  # a left tuple has one cell, and all its partners are copied there
            l, r, same = _in_cells(l, r, w1, w2)
            match = match & same
        return l.join(r, match, how).select(F.col("l_id").alias("id"), F.col("l_key").alias("key"), F.col("l_t").alias("t"))
    if how in ("left", "right", "full"):
        if strategy == "cells":
            return _outer_in_cells(l, r, w1, w2, direction, how)
        out = l.join(r, match, how)
        return out.select("l_id", "r_id", F.coalesce("l_key", "r_key").alias("key"), "l_t", "r_t", F.greatest("l_t", "r_t").alias("newer_t"))
    if how != "inner":
        raise ValueError("how is inner, left_semi, left_anti, left, right or full")
    if strategy == "cells":
        return _pairs(_cells(l, r, w1, w2, direction))
    if strategy == "partitioned":
        l, r = (s.withColumn("pid", partition_id(F.col(f"{tag}_key"), n_part, dict(s.dtypes)[f"{tag}_key"])) for s, tag in ((l, "l"), (r, "r")))
        joined = l.withColumnRenamed("pid", "_p").join(r, (F.col("_p") == F.col("pid")) & match)
        return _pairs(joined)
    if strategy == "salted":
        return _pairs(_salted(l, r, match, salts, heavy))
    if strategy == "slabs":
        return _pairs(_slabs(l, r, w1, w2, direction, slab_us))
    if strategy == "smj":
        l = l.hint("merge")
    if strategy == "broadcast":
        r = bounded_broadcast(r)
    return _pairs(l.join(r, match))


def bounded_broadcast(df: DataFrame, most: int = 5_000_000) -> DataFrame:
    """A side to broadcast, if it has at most ``most`` rows; a larger one stays as it is, and the join is planned without the hint."""
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df


def _cells(l: DataFrame, r: DataFrame, w1: int | None, w2: int | None, direction: str) -> DataFrame:
    l, r, same = _in_cells(l, r, w1, w2)
    return l.join(r, (F.col("l_key") == F.col("r_key")) & same & in_window(w1, w2, direction))


def _in_cells(l: DataFrame, r: DataFrame, w1: int | None, w2: int | None) -> tuple[DataFrame, DataFrame, Column]:
    """Both sides with their cells, and the condition that these are equal."""
    if w1 is None or w2 is None:
        raise ValueError("cells need windows with an end")
    # a left tuple has one cell, so a pair is met once; a right tuple is put into the two or so cells it can meet
    width = max(1, w1 + w2)
    l = l.withColumn("l_cell", floor_div(F.col("l_t"), width))
    r = r.withColumn("r_cell", F.explode(F.sequence(floor_div(F.col("r_t") - F.lit(w1), width), floor_div(F.col("r_t") + F.lit(w2), width))))
    return l, r, F.col("l_cell") == F.col("r_cell")


def _outer_in_cells(l: DataFrame, r: DataFrame, w1: int | None, w2: int | None, direction: str, how: str) -> DataFrame:
    """Left tuples keep themselves in their one cell. Right tuples without a partner come from an anti join with the sides' roles changed."""
    match = (F.col("l_key") == F.col("r_key")) & in_window(w1, w2, direction)
    lc, rc, same = _in_cells(l, r, w1, w2)
    out = lc.join(rc, match & same, "inner" if how == "right" else "left")
    out = out.select("l_id", "r_id", F.coalesce("l_key", "r_key").alias("key"), "l_t", "r_t", F.greatest("l_t", "r_t").alias("newer_t"))
    if how == "left":
        return out
    # one cell for each right tuple, copies of the left ones
    width = max(1, w1 + w2)
    one = r.withColumn("r_cell", floor_div(F.col("r_t"), width))
    copies = l.withColumn("l_cell", F.explode(F.sequence(floor_div(F.col("l_t") - F.lit(w2), width), floor_div(F.col("l_t") + F.lit(w1), width))))
    lone = one.join(copies, match & same, "left_anti")
    kinds = dict(l.dtypes)
    none = lone.select(F.lit(None).cast(kinds["l_id"]).alias("l_id"), "r_id", F.col("r_key").alias("key"), F.lit(None).cast(kinds["l_t"]).alias("l_t"), "r_t", F.col("r_t").alias("newer_t"))
    return out.unionByName(none)


def _salted(l: DataFrame, r: DataFrame, match: Column, salts: int, heavy: int) -> DataFrame:
    """Heavy keys of the left side are dealt over ``salts`` copies of the right side's rows of these keys.

    There are at most (rows / heavy) such keys; the list is broadcast only if it has at most 100,000.
    """
    counts = l.groupBy(F.col("l_key").alias("h_key")).agg(F.count(F.lit(1)).alias("n")).where(F.col("n") >= heavy).select("h_key", F.lit(True).alias("h"))
    counts = F.broadcast(counts) if counts.limit(100_001).count() <= 100_000 else counts
    l = l.join(counts, F.col("l_key") == F.col("h_key"), "left").withColumn("l_salt", F.when(F.col("h"), F.pmod(F.xxhash64("l_id", "l_t"), F.lit(salts)).cast("int")).otherwise(0)).drop("h_key", "h")
    r = r.join(counts, F.col("r_key") == F.col("h_key"), "left").withColumn("r_salt", F.explode(F.when(F.col("h"), F.sequence(F.lit(0), F.lit(salts - 1))).otherwise(F.array(F.lit(0))))).drop("h_key", "h")
    return l.join(r, match & (F.col("l_salt") == F.col("r_salt")))


def _slabs(l: DataFrame, r: DataFrame, w1: int | None, w2: int | None, direction: str, slab_us: int | None) -> DataFrame:
    """A pair belongs to the slab of its newer tuple; older tuples are copied into the slabs that their window reaches."""
    if w1 is None or w2 is None:
        raise ValueError("slabs need windows with an end")
    width = slab_us or max(1, 4 * max(w1, w2))
    floor = partial(floor_div, width=width)
    l = l.withColumn("l_slab", F.explode(F.sequence(floor(F.col("l_t")), floor(F.col("l_t") + F.lit(w1)))))
    r = r.withColumn("r_slab", F.explode(F.sequence(floor(F.col("r_t")), floor(F.col("r_t") + F.lit(w2)))))
    own = F.col("l_slab") == floor(F.greatest("l_t", "r_t"))
    return l.join(r, (F.col("l_key") == F.col("r_key")) & (F.col("l_slab") == F.col("r_slab")) & in_window(w1, w2, direction) & own)


def window_self_join(stream: DataFrame, w: int, dedupe: bool = True, strategy: str = "auto") -> DataFrame:
    """Pairs of one stream within w of each other; with ``dedupe`` each unordered pair once (l_id < r_id)."""
    pairs = window_join(stream, stream, w, w, strategy)
    return pairs.where("l_id < r_id") if dedupe else pairs


def window_join_multi(streams: Sequence[DataFrame], windows: Sequence[int], strategy: str = "auto") -> DataFrame:
    """n-way join: with all keys equal, each pair must satisfy the two-stream condition of its own two windows.

    This says that every tuple is inside its window when the latest one
    arrives. Pairs are pruned as soon as both members are there. Rows (id_1.., key, newer_t).
    With cells (chosen by the first two streams) the first stream's tuple, which all others must be near to, gives the cell.
    """
    if len(streams) != len(windows) or len(streams) < 2:
        raise ValueError("one window for each of two or more streams")
    if strategy == "auto":
        strategy = choose(streams[0], streams[1], windows[0], windows[1])
    width = max(1, windows[0] + max(windows[1:]))
    out = streams[0].select(F.col("id").alias("id_1"), "key", F.col("t").alias("t_1"))
    if strategy == "cells":
        out = out.withColumn("_cell", floor_div(F.col("t_1"), width))
    for k in range(2, len(streams) + 1):
        nxt = streams[k - 1].select(F.col("id").alias(f"id_{k}"), F.col("key").alias("_key"), F.col("t").alias(f"t_{k}"))
        cond = F.col("key") == F.col("_key")
        if strategy == "cells":
            near = F.sequence(floor_div(F.col(f"t_{k}") - F.lit(windows[0]), width), floor_div(F.col(f"t_{k}") + F.lit(windows[k - 1]), width))
            nxt, cond = nxt.withColumn("_at", F.explode(near)), cond & (F.col("_cell") == F.col("_at"))
        for j in range(1, k):
            cond = cond & F.col(f"t_{k}").between(F.col(f"t_{j}") - F.lit(windows[k - 1]), F.col(f"t_{j}") + F.lit(windows[j - 1]))
        out = out.join(nxt, cond).drop("_key", "_at")
    ids, times = [f"id_{k}" for k in range(1, len(streams) + 1)], [f"t_{k}" for k in range(1, len(streams) + 1)]
    return out.select(*ids, "key", F.greatest(*times).alias("newer_t"))


def band_join(left: DataFrame, right: DataFrame, w1: int, w2: int, on: Column) -> DataFrame:
    """Window join by cells of time with a condition of any kind in place of key equality (columns l_key, r_key)."""
    width = max(1, w1 + w2)
    floor = partial(floor_div, width=width)
    l = _side(left, "l").withColumn("l_cell", floor(F.col("l_t")))
    r = _side(right, "r").withColumn("r_cell", F.explode(F.sequence(floor(F.col("r_t") - F.lit(w1)), floor(F.col("r_t") + F.lit(w2)))))
    joined = l.join(r, (F.col("l_cell") == F.col("r_cell")) & in_window(w1, w2) & on)
    return joined.select("l_id", "r_id", "l_key", "r_key", "l_t", "r_t")


def asof_latest(left: DataFrame, right: DataFrame, w: int | None = None) -> DataFrame:
    """Each left tuple with the latest right tuple of its key at or before it, no older than w; of equal times the greatest id.

    One sort of the union by (key, t); no join.
    """
    from pyspark.sql import Window

    rows = left.select(F.lit(1).alias("side"), "id", "key", "t").unionByName(right.select(F.lit(0).alias("side"), "id", "key", "t"))
    order = Window.partitionBy("key").orderBy("t", "side", "id").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    seen = rows.withColumn("m", F.last(F.when(F.col("side") == 0, F.struct(F.col("id"), F.col("t"))), ignorenulls=True).over(order)).where("side = 1")
    fresh = F.lit(True) if w is None else F.col("m.t") >= F.col("t") - F.lit(w)
    return seen.select(F.col("id").alias("l_id"), "key", F.col("t").alias("l_t"), F.when(fresh, F.col("m.id")).alias("r_id"), F.when(fresh, F.col("m.t")).alias("r_t"))


def interval_overlap(left: DataFrame, right: DataFrame, width: int) -> DataFrame:
    """Pairs of intervals (id, key, lo, hi) of equal keys that share an instant, by cells; a pair is kept in the first cell both touch."""
    floor = partial(floor_div, width=width)
    l = left.select(F.col("id").alias("l_id"), F.col("key").alias("l_key"), F.col("lo").alias("l_lo"), F.col("hi").alias("l_hi"), F.explode(F.sequence(floor(F.col("lo")), floor(F.col("hi")))).alias("l_cell"))
    r = right.select(F.col("id").alias("r_id"), F.col("key").alias("r_key"), F.col("lo").alias("r_lo"), F.col("hi").alias("r_hi"), F.explode(F.sequence(floor(F.col("lo")), floor(F.col("hi")))).alias("r_cell"))
    meet = (F.col("l_lo") <= F.col("r_hi")) & (F.col("r_lo") <= F.col("l_hi")) & (F.col("l_cell") == floor(F.greatest("l_lo", "r_lo")))
    return l.join(r, (F.col("l_key") == F.col("r_key")) & (F.col("l_cell") == F.col("r_cell")) & meet).select("l_id", "r_id", F.col("l_key").alias("key"))


def recent_k(left: DataFrame, right: DataFrame, w: int, k: int) -> DataFrame:
    """For each left tuple its k latest right partners within w before it: (l_id, r_id, key, rank)."""
    from pyspark.sql import Window

    pairs = window_join(left, right, 0, w, "auto", "left_newer")
    rank = F.row_number().over(Window.partitionBy("l_id").orderBy(F.col("r_t").desc(), F.col("r_id").desc()))
    return pairs.withColumn("rank", rank).where(F.col("rank") <= k).select("l_id", "r_id", "key", "rank")


def nested_loop_window_join(left: DataFrame, right: DataFrame, w1: int | None, w2: int | None, block: int = 256, most: int = 2_000) -> DataFrame:
    """The baseline of one server: a tuple is held against every tuple of the blocks that it can meet, whatever the key.

    A right side of at most ``most`` tuples is one block. A larger one is dealt into blocks by cells of time and by hash of the
    key, about ``block`` tuples in each, and pairs of blocks that can have no result are not looked at.
    """
    l, r = _side(left, "l"), _side(right, "r")
    cond = (F.col("l_key") <= F.col("r_key")) & (F.col("l_key") >= F.col("r_key")) & in_window(w1, w2)
    size = right.agg(F.count(F.lit(1)).alias("n"), F.min("t").alias("a"), F.max("t").alias("b")).first()
    if size.n <= most:
        return _pairs(l.join(F.broadcast(r), cond))
    cells = 1
    if w1 is not None and w2 is not None:
        cells = max(1, (size.b - size.a) // max(1, w1 + w2)) if size.a is not None else 1
        l, r, same = _in_cells(l, r, w1, w2)
        cond = cond & same
    n = min(1 << 16, -(-size.n // (cells * block)))
    l, r = (x.withColumn(f"{tag}_part", partition_id(F.col(f"{tag}_key"), n, dict(x.dtypes)[f"{tag}_key"])) for x, tag in ((l, "l"), (r, "r")))
    return _pairs(l.join(r, cond & (F.col("l_part") == F.col("r_part"))))


def tuned_window_join(left: DataFrame, right: DataFrame, w1: int, w2: int, leaves: DataFrame, n_part: int, max_depth: int) -> DataFrame:
    """Join per mini-partition: tuples carry the leaf of a static directory (pid, depth, suffix) and meet only within it."""
    leaves = small_directory(leaves)
    l = locate(_side(left, "l"), "l", leaves, n_part, max_depth)
    r = locate(_side(right, "r"), "r", leaves, n_part, max_depth)
    cond = (F.col("l_pid") == F.col("r_pid")) & (F.col("l_depth") == F.col("r_depth")) & (F.col("l_suffix") == F.col("r_suffix")) & (F.col("l_key") == F.col("r_key")) & in_window(w1, w2)
    return _pairs(l.join(r, cond))


def small_directory(leaves: DataFrame, most: int = 1_000_000) -> DataFrame:
    """A directory held once for all its uses, with a broadcast hint if it has at most ``most`` leaves (there are tuples / theta of them)."""
    leaves = leaves.persist()
    return F.broadcast(leaves) if leaves.limit(most + 1).count() <= most else leaves


def locate(side: DataFrame, tag: str, leaves: DataFrame, n_part: int, max_depth: int) -> DataFrame:
    """Tuples with the leaf that holds them."""
    kind = dict(side.dtypes)[f"{tag}_key"]
    keyed = side.withColumn(f"{tag}_pid", partition_id(F.col(f"{tag}_key"), n_part, kind)).withColumn("_bits", mini_bits(F.col(f"{tag}_key"), max_depth, kind))
    d = leaves.select(F.col("pid").alias("_pid"), F.col("depth").alias(f"{tag}_depth"), F.col("suffix").alias(f"{tag}_suffix"))
    fits = F.pmod(F.col("_bits"), two_to(F.col(f"{tag}_depth"))) == F.col(f"{tag}_suffix")
    return keyed.join(d, (F.col(f"{tag}_pid") == F.col("_pid")) & fits, "left").drop("_pid", "_bits")
