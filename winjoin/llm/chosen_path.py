"""Self-join of documents on the Jaccard similarity of their word n-grams, by the chosen-path method.

1. *Sets.* A document's set holds the 64-bit hashes of its n-grams (lower-cased
   words; a text of fewer words is one gram). Equal sets become one
   representative with a count, so exact copies never meet as pairs.
2. *Sketches.* A set is embedded as ``WIDTH`` minwise hashes. Two sets agree in
   a coordinate with probability equal to their similarity, so each
   coordinate with its value is a token and every set has ``WIDTH`` tokens.
3. *Chosen paths.* A run grows a random tree: a path of tokens is extended by
   those tokens of a set that a hash of path (run first) and coordinate chooses, ``FANOUT`` of
   them on average. Whether a set is in a node depends on the set and the path
   alone, so all paths of ``depth`` steps are computed without meeting other
   sets. Nodes of one set die; in others a search compares the sketches of each set that
   a tie has reached with those of all sets that none has reached, so near copies, however
   many, cost a comparison or so each. What the search gives up (more than ``bucket``
   comparisons a set, with no end before ``patience``) and nodes of more than ``widest``
   sets are split further by as many steps, up to ``max_depth``; what is still open
   there holds nearly equal sets, which are all tied to one of them. Runs repeat until a pair at the threshold
   meets with the target recall, which ``runs_for`` derives from the
   branching process. A pair in split nodes only has to meet again deeper, which takes more
   runs: sets of split nodes take part in as many as that depth needs. Each depth may lose its share of what the recall allows.
4. *Exact check.* Ties form candidate components. Members of a component are
   dealt into blocks of at most about ``block`` sets and ``block_bytes`` bytes, block pairs are spread over tasks, and each pair's exact
   similarity is computed on its full sets, which travel once for each block of their component. A task emits links per set and a
   spanning forest of its links, never the pairs.

Results are one row per document: its class (least document id of its
component of links) and its number of linked documents, copies included.

Edge cases: texts without words (null, empty, punctuation) have no n-grams,
no links and a class of their own (for which all of them with one id count as
one); null ids stand as rows with a null class unless they share one with a
document that has an id; repeated rows count as copies of each other; an empty
table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from winjoin.llm import bytetext as B
from winjoin.llm.frames import Forest, connected, fresh, materialize, release, text_of, thin

WIDTH = 64
FANOUT = 1.25
_SALTS = B.mix(np.arange(1, WIDTH + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)


def meet_probability(similarity: float, depth: int) -> float:
    """Chance that one run puts a pair of this similarity into one node at this depth."""
    p = 1.0
    for _ in range(depth):
        p = 1 - math.exp(-FANOUT * similarity * p)
    return p


def runs_for(threshold: float, depth: int, recall: float) -> int:
    """Runs after which a pair at the threshold has met with the target recall.

    Agreement of two sketches varies around the similarity; two standard
    deviations are taken off, so that pairs whose sketches agree less than
    expected are covered too.
    """
    low = threshold - 2 * math.sqrt(threshold * (1 - threshold) / WIDTH)
    return max(1, math.ceil(math.log(1 - recall) / math.log(1 - meet_probability(low, depth))))


def gram_sets(column: pa.Array, n: int) -> list[np.ndarray]:
    """Sorted distinct n-gram hashes of each row."""
    raw, offs = B.flat(column)
    raw = B.LOWER[raw]
    starts, ends, first = B.spans(raw, offs, B.ALNUM)
    rows = B.rows_of(first, len(starts))
    words = B.run_hashes(raw, starts, ends)
    grams, at = B.windows(words, rows, n)
    cut = np.searchsorted(rows[at], np.arange(len(column) + 1))
    out = []
    for k in range(len(column)):
        if cut[k] < cut[k + 1]:
            out.append(np.unique(grams[cut[k] : cut[k + 1]]))
        elif first[k] < first[k + 1]:
            some = words[first[k] : first[k + 1]]
            out.append(B.mix(np.array([np.bitwise_xor.reduce(B.mix(some + np.arange(1, len(some) + 1, dtype=np.uint64)))])))
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def _sketches(sets: list[np.ndarray]) -> np.ndarray:
    """Minwise hashes (32 bits each) of non-empty sets."""
    if not sets:
        return np.zeros((0, WIDTH), np.uint32)
    flat = np.concatenate(sets)
    first = np.concatenate([[0], np.cumsum([len(s) for s in sets])[:-1]])
    out = np.empty((len(sets), WIDTH), np.uint32)
    for j in range(WIDTH):
        h = flat * _SALTS[j]
        h ^= h >> np.uint64(29)
        h *= np.uint64(0xBF58476D1CE4E5B9)
        out[:, j] = (np.minimum.reduceat(h, first) >> np.uint64(32)).astype(np.uint32)
    return out


def _key(s: np.ndarray) -> bytes:
    """128 bits that stand for a whole set."""
    a = np.add.reduce(B.mix(s)) if len(s) else np.uint64(0)
    b = np.add.reduce(B.mix(s ^ np.uint64(0xD6E8FEB86659FD93))) if len(s) else np.uint64(0)
    return np.array([a, b], np.uint64).tobytes()


def paths(sketch: np.ndarray, start: np.ndarray, steps: int) -> tuple[np.ndarray, np.ndarray]:
    """Extend nodes by ``steps``: row i stands at node ``start[i]`` (its run is part of it) with tokens ``sketch[i]``.

    Returns the rows of the entries and their nodes.
    """
    rows, node = np.arange(len(sketch)), start
    most = np.uint64(int(FANOUT / WIDTH * 2**64))
    turn = np.arange(1, WIDTH + 1, dtype=np.uint64)[None] * np.uint64(0x9FB21C651E98DF25)
    for _ in range(steps):
        at, coordinate = np.nonzero(B.mix(node[:, None] + turn) < most)
        token = sketch[rows[at], coordinate].astype(np.uint64) + (coordinate.astype(np.uint64) << np.uint64(32))
        node = B.mix(node[at] * np.uint64(0x9E3779B97F4A7C15) ^ B.mix(token + np.uint64(1)))
        rows = rows[at]
    return rows, node


def _describe(docs: DataFrame, n: int) -> DataFrame:
    """(doc_id, sid, sketch): the key and the sketch of each document's set; no sketch for an empty set."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for p in B.pieces(batch, "text"):
                sets = gram_sets(p.column(1), n)
                some = [k for k, s in enumerate(sets) if len(s)]
                sk = _sketches([sets[k] for k in some])
                held: list[bytes | None] = [None] * len(sets)
                for r, k in enumerate(some):
                    held[k] = sk[r].tobytes()
                yield pa.RecordBatch.from_arrays([p.column(0), pa.array([_key(s) for s in sets], pa.binary()), pa.array(held, pa.binary())], ["doc_id", "sid", "sketch"])
        B.trim()

    return docs.mapInArrow(run, f"doc_id {kind}, sid binary, sketch binary")


def _extend(frame: DataFrame, steps: int, runs: range | None) -> DataFrame:
    """(rid, sketch[, node]) to (rid, node), ``steps`` deeper; these runs from their roots if ``runs`` is given."""

    def grow(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a in range(0, batch.num_rows, 500):
                p = batch.slice(a, 500)
                sk = np.frombuffer(b"".join(p.column(1).to_pylist()), np.uint32).reshape(-1, WIDTH)
                if runs is not None:
                    own = np.tile(np.arange(len(sk)), len(runs))
                    start = B.mix(np.repeat(np.array(runs, np.uint64), len(sk)))
                else:
                    own = np.arange(len(sk))
                    start = p.column(2).to_numpy(zero_copy_only=False).view(np.uint64)
                rows, node = paths(sk[own], start, steps)
                yield pa.RecordBatch.from_arrays([p.column(0).take(pa.array(own[rows])), pa.array(node.view(np.int64))], ["rid", "node"])
        B.trim()

    return frame.mapInArrow(grow, "rid long, node long")


def search(sketch: np.ndarray, least: float, bucket: int, patience: int) -> tuple[list[tuple[int, int]], np.ndarray]:
    """Ties within one node, found by search: a member that a tie has reached is compared with all members that none has reached yet.

    Components are those of all pairs that agree in ``least`` of the coordinates, and near copies of each other are
    reached at once. A node of more than ``bucket`` sets whose search is not over after ``bucket`` comparisons a set, and would
    take more than ``patience``, is given up. Returns the ties and the members that are not compared with all others or tied to them.
    """
    n = len(sketch)
    rest, left, reached, spent, ties = np.arange(1, n), sketch[1:], [0], 0, []
    while len(rest):
        if not reached:
            reached = [int(rest[0])]
            rest, left = rest[1:], left[1:]
            continue
        if n > bucket and spent > bucket * n and spent + len(rest) ** 2 / 2 > patience * n:
            return ties, np.concatenate([np.array(reached, np.int64), rest])
        x = reached.pop()
        spent += len(rest)
        near = (left == sketch[x]).sum(axis=1) >= least * WIDTH
        if near.any():
            hit = rest[near].tolist()
            ties += [(x, y) for y in hit]
            reached += hit
            rest, left = rest[~near], left[~near]
    return ties, rest


def _compare(least: float, bucket: int, patience: int):
    """For rows (node, rid, sketch) in the order of nodes: (a, b) of a spanning forest of each node's pairs whose sketches agree in
    ``least`` of the coordinates, and (a, node, n) of the n members of a node that have to be split further. The last node of a batch waits for the next."""

    def ties(node: np.ndarray, rid: np.ndarray, sk: np.ndarray) -> tuple[list[tuple[int, int]], list[tuple[int, int, int]]]:
        out, more = [], []
        cuts = np.concatenate([[0], np.flatnonzero(node[1:] != node[:-1]) + 1, [len(node)]])
        for a, b in zip(cuts[:-1], cuts[1:]):
            ids = rid[a:b].tolist()
            found, open_ = search(sk[a:b], least, bucket, patience)
            out += [(ids[x], ids[y]) for x, y in found]
            more += [(ids[x], int(node[a]), len(open_)) for x in open_]
        return out, more

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = (np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros((0, WIDTH), np.uint32))
        forest = Forest()

        def emit(new: list[tuple[int, int]], more: list[tuple[int, int, int]]) -> pa.RecordBatch:
            fresh = forest.fresh(new)
            tie, none = [None] * len(fresh), [None] * len(more)
            columns = [x for x, _ in fresh] + [x for x, _, _ in more], [y for _, y in fresh] + none, tie + [v for _, v, _ in more], tie + [n for _, _, n in more]
            return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], ["a", "b", "node", "n"])

        for batch in batches:
            if not batch.num_rows:
                continue
            node = np.concatenate([held[0], batch.column(0).to_numpy(zero_copy_only=False)])
            rid = np.concatenate([held[1], batch.column(1).to_numpy(zero_copy_only=False)])
            sk = np.concatenate([held[2], np.frombuffer(b"".join(batch.column(2).to_pylist()), np.uint32).reshape(-1, WIDTH)])
            cut = len(node) - int((node == node[-1]).sum())
            if cut:
                yield emit(*ties(node[:cut], rid[:cut], sk[:cut]))
            held = (node[cut:], rid[cut:], sk[cut:])
        if len(held[0]):
            yield emit(*ties(*held))
        B.trim()

    return run


def _shared(entries: DataFrame, heavy: int = 1000) -> DataFrame:
    """The entries (rid, node) of nodes of two sets or more, with their number n.

    Sizes are summed before they are shuffled. Nodes with a ``heavy``-th of all entries, at most ``heavy``
    of them, are broadcast, so that none of these meets in one task.
    """
    size = materialize(entries.groupBy("node").agg(F.count(F.lit(1)).alias("n")).where("n > 1"), "jaccard-sizes")
    most = max(2, -(-entries.count() // heavy))
    wide = F.broadcast(size.where(F.col("n") >= most))
    rest = entries.join(wide.select("node"), "node", "left_anti").join(size.where(F.col("n") < most), "node")
    alive = materialize(entries.join(wide, "node").unionByName(rest), "jaccard-nodes")
    release(size)
    return alive


def _tied(large: DataFrame, each: int) -> DataFrame:
    """Ties (a, b) that connect all sets of each node: members are dealt into groups of about ``each`` and
    tied to the least of their group, these to the least of the node."""
    dealt = large.withColumn("group", F.pmod(F.xxhash64("rid"), F.ceil(F.col("n") / each)))
    low = dealt.groupBy("node", "group").agg(F.min("rid").alias("b"))
    near = dealt.join(low, ["node", "group"]).where("rid <> b").select(F.col("rid").alias("a"), "b")
    hub = low.groupBy("node").agg(F.min("b").alias("h"))
    far = low.join(hub, "node").where("b <> h").select(F.col("b").alias("a"), F.col("h").alias("b"))
    return materialize(near.unionByName(far).distinct(), "jaccard-ties")


def _verify(key: tuple, rows: pa.Table, threshold: float) -> pa.Table:
    """A pair of blocks of one component: exact links per set, and a spanning forest of the links."""
    side = np.array(rows.column("side").to_pylist())
    sids, count = rows.column("sid").to_pylist(), np.array(rows.column("copies").to_pylist(), np.int64)
    sets = [np.frombuffer(g, np.uint64) for g in rows.column("grams").to_pylist()]
    left = np.flatnonzero(side <= 1)  # 0: a block with itself, 1 and 2: two blocks
    right = left if (side == 0).all() else np.flatnonzero(side == 2)
    size = np.array([len(s) for s in sets], np.int64)
    values, where = np.unique(np.concatenate([sets[k] for k in right]), return_inverse=True) if len(right) else (np.zeros(0, np.uint64), np.zeros(0, np.int64))
    owner = np.repeat(np.arange(len(right)), size[right])
    order = np.argsort(where, kind="stable")
    begin = np.searchsorted(where[order], np.arange(len(values) + 1))
    owner = owner[order]
    links = np.zeros(len(sids), np.int64)
    pairs = []
    for r, k in enumerate(left):
        at = np.minimum(np.searchsorted(values, sets[k]), len(values) - 1) if len(values) else np.zeros(0, np.int64)
        at = at[values[at] == sets[k]] if len(at) else at
        if len(at):
            take = np.concatenate([owner[begin[x] : begin[x + 1]] for x in at])
            both = np.bincount(take, minlength=len(right))
        else:
            both = np.zeros(len(right), np.int64)
        good = both >= threshold * (size[k] + size[right] - both) - 1e-9
        if right is left:
            good[: r + 1] = False
        for j in np.flatnonzero(good):
            links[k] += count[right[j]]
            links[right[j]] += count[k]
            pairs.append((int(k), int(right[j])))
    forest = Forest().fresh(pairs)
    return pa.table({
        "a": pa.array(sids + [sids[a] for a, _ in forest], pa.binary()),
        "b": pa.array([None] * len(sids) + [sids[b] for _, b in forest], pa.binary()),
        "links": pa.array(np.concatenate([links, np.zeros(len(forest), np.int64)]), pa.int64()),
    })


def similarity_classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", n: int = 5, threshold: float = 0.8, recall: float = 0.999, depth: int = 3, bucket: int = 48, max_depth: int = 6, patience: int = 512, widest: int = 16384, block: int = 512, block_bytes: int = 4 << 20) -> DataFrame:
    """Rows (doc_id, class_id, n_links, sid, class_sid), one for each row of ``docs``.

    sid and class_sid are the keys of the document's set and of its class.
    """
    docs = text_of(docs, id_col, text_col)
    # sketches and keys are written once: every later step reads them
    described = materialize(_describe(docs, n), "jaccard-sets")
    reps = described.where("sketch IS NOT NULL").groupBy("sid").agg(F.count(F.lit(1)).alias("copies"), F.first("sketch").alias("sketch"))
    reps = materialize(reps.withColumn("rid", F.monotonically_increasing_id()), "jaccard-reps")
    sketches = reps.select("rid", "sketch")
    depths = list(range(depth, max(depth, max_depth) + 1, depth))
    runs = [runs_for(threshold, d, 1 - (1 - recall) / len(depths)) for d in depths]
    entries = materialize(_extend(sketches, depth, range(1, runs[0] + 1)), "jaccard-paths")
    ties, kept = [], []
    least = threshold - 4 * math.sqrt(threshold * (1 - threshold) / WIDTH)
    for k in range(len(depths)):
        alive = _shared(entries)
        release(entries)
        whole = alive.where(F.col("n") <= widest).join(sketches, "rid").select("node", "rid", "sketch")
        found = materialize(whole.repartition("node").sortWithinPartitions("node").mapInArrow(_compare(least, bucket, patience), "a long, b long, node long, n long"), "jaccard-ties")
        ties.append(found.where("node IS NULL").select("a", "b"))
        large = alive.where(F.col("n") > widest).select("node", "rid", "n").unionByName(found.where("node IS NOT NULL").select("node", F.col("a").alias("rid"), "n"))
        kept += [alive, found]
        if k + 1 == len(depths) or large.isEmpty():
            break
        deeper = _extend(large.join(sketches, "rid").select("rid", "sketch", "node"), depth, None)
        again = sketches.join(large.select("rid").distinct(), "rid", "left_semi")
        more = _extend(again.select("rid", "sketch"), depths[k + 1], range(runs[k] + 1, runs[k + 1] + 1))
        entries = materialize(deeper.unionByName(more), "jaccard-paths")
    kept.append(_tied(large, block))
    ties.append(kept[-1])
    edges = ties[0]
    for more in ties[1:]:
        edges = edges.unionByName(more)
    comps = materialize(connected(thin(edges)), "jaccard-components")
    release(*kept)

    # exact check: full sets of members only, in pairs of blocks
    members = comps.join(reps.select("rid", "sid", "copies"), comps.node == F.col("rid")).select("sid", "root", "copies")
    chosen = described.groupBy("sid").agg(F.min(F.struct("doc_id")).alias("one"))
    texts = docs.join(chosen.join(members.select("sid"), "sid").select(F.col("one.doc_id").alias("doc_id")).where("doc_id IS NOT NULL").distinct(), "doc_id", "left_semi")
    nulls = docs.where("doc_id IS NULL")
    grams = materialize(_grams(texts.unionByName(nulls), n).dropDuplicates(["sid"]), "jaccard-grams")
    whole = members.join(grams, "sid")
    sized = whole.groupBy("root").agg(F.greatest(F.ceil(F.count(F.lit(1)) / block), F.ceil(F.sum(F.octet_length("grams")) / block_bytes)).cast("int").alias("blocks"))
    whole = whole.join(sized, "root").withColumn("mine", F.pmod(F.xxhash64("sid"), F.col("blocks")).cast("int"))
    pairs = whole.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))).select(
        "root", F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"),
        F.when(F.col("mine") == F.col("other"), 0).when(F.col("mine") < F.col("other"), 1).otherwise(2).alias("side"), "sid", "copies", "grams",
    )
    checked = materialize(pairs.groupBy("root", "i", "j").applyInArrow(lambda key, rows: _verify(key, rows, threshold), "a binary, b binary, links long"), "jaccard-links")
    links = checked.where("b IS NULL").groupBy(F.col("a").alias("sid")).agg(F.sum("links").alias("links"))
    classes = connected(thin(checked.where("b IS NOT NULL")))
    known = reps.select("sid", "copies").join(links, "sid", "left").join(classes.withColumnRenamed("node", "sid"), "sid", "left")
    known = known.select("sid", (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"), F.coalesce("root", "sid").alias("class_sid"))
    # the least id of each class: per set first, so that no class meets as a list
    least_id = described.groupBy("sid").agg(F.min("doc_id").alias("low")).join(known, "sid").groupBy("class_sid").agg(F.min("low").alias("class_id"))
    by_set = materialize(known.join(least_id, "class_sid").select("sid", "n_links", "class_sid", "class_id"), "jaccard-classes")
    out = described.select("doc_id", "sid", F.col("sketch").isNull().alias("blank")).join(by_set, "sid", "left")
    release(comps, grams, checked)
    return out.select(
        "doc_id", F.when(F.col("blank"), F.col("doc_id")).otherwise(F.col("class_id")).alias("class_id"), F.when(F.col("blank"), 0).otherwise(F.col("n_links")).cast("long").alias("n_links"),
        "sid", F.when(F.col("blank"), F.encode(F.concat(F.lit("blank:"), F.coalesce(F.col("doc_id").cast("string"), F.lit("null"))), "utf-8")).otherwise(F.col("class_sid")).alias("class_sid"),
    )


def _grams(docs: DataFrame, n: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for p in B.pieces(batch, "text"):
                sets = gram_sets(p.column(1), n)
                yield pa.RecordBatch.from_arrays([pa.array([_key(s) for s in sets], pa.binary()), pa.array([s.tobytes() for s in sets], pa.binary())], ["sid", "grams"])
        B.trim()

    return docs.select("doc_id", "text").mapInArrow(run, "sid binary, grams binary")


def keep_one_of_each(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """``docs`` (all columns) with one document of each class: that of the least id; all rows of null id whose class has none other stay as one."""
    found = similarity_classes(docs, id_col, text_col, **options)
    some = found.where("doc_id IS NOT NULL").groupBy("class_sid").agg(F.min(F.struct("doc_id", "sid")).alias("m"))
    none = found.groupBy("class_sid").agg(F.max("doc_id").alias("any"), F.min("sid").alias("sid")).where("any IS NULL")
    names = docs.columns
    sid, keep_id, keep_sid = fresh(names, "_sid", "_keep_id", "_keep_sid")
    low = some.select(F.col("m.doc_id").alias(keep_id), F.col("m.sid").alias(keep_sid)).unionByName(none.select(F.lit(None).cast(found.schema["doc_id"].dataType).alias(keep_id), F.col("sid").alias(keep_sid)))
    low = low.distinct()

    def keyed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for p in B.pieces(batch, text_col):
                sets = gram_sets(p.column(p.schema.get_field_index(text_col)), options.get("n", 5))
                yield pa.RecordBatch.from_arrays([*p.columns, pa.array([_key(s) for s in sets], pa.binary())], [*p.schema.names, sid])
        B.trim()

    wide = docs.mapInArrow(keyed, T.StructType([*docs.schema.fields, T.StructField(sid, T.BinaryType())]))
    stays = wide.join(low, (F.col(f"`{id_col}`").eqNullSafe(F.col(keep_id))) & (F.col(sid) == F.col(keep_sid)))
    # repeated rows of the kept id and set: one of them
    return stays.dropDuplicates([id_col, sid]).select(*(F.col(f"`{c}`") for c in names))
