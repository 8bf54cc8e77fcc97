"""Language model of any order with Katz backoff, counted, normalised and evaluated as partitioned tables.

Tokens are the runs of non-blank bytes of a text with A-Z lower-cased, then one
end token; start tokens stand before the first. A word is known by a 64-bit
hash of its bytes, a context of several words by one of theirs, oldest first.

*Counting.* A task counts the tokens and n-grams of its rows with sorted arrays
and ships per partition one packed block, so that a frequent word or n-gram
travels once a task, however often it occurs. Words are dealt by their hash,
n-grams by their context; a frequent context (at most ``4 * partitions``
of one length can be so frequent) is spread by its followers, over as many places as its count calls for.

*Model.* Good-Turing discounts apply to counts up to ``gt_max``: d(r) is the
ratio of the adjusted to the raw count, renormalised so that the mass that
discounting frees equals that of the counts of one. Where the counts of counts
give no ratio in (0, 1), ``absolute`` is subtracted instead, and what all counts lose is scaled to free that same mass.
Every n-gram of training is kept. Unigrams are discounted likewise, what that frees goes to one unknown word.
Weights are exact: alpha(h) = (1 - sum p*(w|h)) / (1 - sum P(w|h')), both sums over
the followers of h, h' being h without its oldest word and P(w) without any context p*(w); where the followers leave nothing, they are scaled by n/(n+1), n being the context's count.
Each length has a table of its own. It stays packed: a partition's blocks hold its n-grams with their counts,
the counts of their followers (for bigrams, asked once a block and word from the partition that
counts the word) or the P(w|h') of each (asked from the partition of the shorter n-gram), from which scoring derives p* and alpha.
Only contexts spread over partitions have their sums added up beforehand.

*Evaluation.* P(w|h) is p*(w|h) if the n-gram is known, else alpha(h) P(w|h'), down to p*(w) if w is known,
else that of the unknown word. As log P(w|h) is log P(w|h') + log alpha(h), and for known n-grams the log of
p* / (alpha(h) P(w|h')) on top, every length adds its part by itself. Tasks ship each
context, follower and the rows they occur in once per block; a partition looks
up its blocks in its slice of a length's table and returns partial sums per row. The rows
are scored in ``passes`` passes, so that the requests of one pass at a time are on disk.

Edge cases: null and empty texts have the end token alone; rows of equal ids are
scored each; null ids train and are not held out; with no training rows every
token is unknown and has probability one; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from winjoin.llm import bytetext as B
from winjoin.llm.frames import bounded_rows, materialize, release, text_of

#: Stand-ins for the end token and the start context; they hash no word's bytes.
END = B.mix(np.array([0x656E64], np.uint64))[0]
START = B.mix(np.array([0x7374617274], np.uint64))[0]
_TURN = np.uint64(0x9E3779B97F4A7C15)
#: Bigrams in one packed row at most.
BLOCK = 1_000_000
#: Packed rows are large: the writer looks at its page and row group after each, not after a hundred.
_LARGE_ROWS = {"parquet.block.size": 16 << 20, "parquet.page.size.row.check.min": 1, "parquet.block.size.row.check.min": 1}


def tokens(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Token hashes of all rows, ends included, and each row's first token."""
    raw, offs = B.flat(column)
    raw = B.LOWER[raw]
    starts, ends, first = B.spans(raw, offs, B.NONSPACE)
    words = B.run_hashes(raw, starts, ends)
    rows = len(column)
    out = np.empty(len(words) + rows, np.uint64)
    out[np.arange(len(words)) + B.rows_of(first, len(words))] = words
    out[first[1:] + np.arange(rows)] = END
    return out, first + np.arange(rows + 1)


def _part_of_word(word: np.ndarray, parts: int) -> np.ndarray:
    return ((word >> np.uint64(20)) % np.uint64(parts)).astype(np.int32)


@dataclass
class Spread:
    """The contexts of one length whose followers are spread over partitions, sorted; their counts and numbers of places."""

    ctx: np.ndarray
    n: np.ndarray
    places: np.ndarray

    @staticmethod
    def of(ctx: np.ndarray, n: np.ndarray, total: int, parts: int) -> Spread:
        """A place for each 1 / (4 * parts) of all tokens."""
        ctx, at = np.unique(ctx, return_index=True)
        n = n[at]
        return Spread(ctx, n, np.maximum(1, -(-n * 4 * parts // max(total, 1))).astype(np.uint64))


def _part_of_pair(ctx: np.ndarray, word: np.ndarray, spread: Spread, parts: int) -> np.ndarray:
    """The partition of an n-gram: that of its context, or of one of its context's places by the follower. Work space is bounded."""
    if len(ctx) > 500_000:
        return np.concatenate([_part_of_pair(ctx[a : a + 500_000], word[a : a + 500_000], spread, parts) for a in range(0, len(ctx), 500_000)])
    at, wide = _find(spread.ctx, ctx)
    if not wide.any():
        return _part_of_word(B.mix(ctx), parts)
    salted = np.where(wide, ctx + (word % spread.places[at] + np.uint64(1)) * _TURN, ctx)
    return _part_of_word(B.mix(salted), parts)


def _longer(ctx: np.ndarray, word: np.ndarray) -> np.ndarray:
    """The context of a context's words and one more behind them."""
    return B.mix(ctx * _TURN ^ word)


def _pack(part: np.ndarray, columns: dict[str, np.ndarray]) -> Iterator[dict]:
    """Rows of one partition as one row of bytes; the arrays come sorted by partition."""
    cuts = np.concatenate([[0], np.flatnonzero(part[1:] != part[:-1]) + 1, [len(part)]])
    for a, b in zip(cuts[:-1], cuts[1:]):
        if a < b:
            yield {"part": int(part[a])} | {k: v[a:b].tobytes() for k, v in columns.items()}


def _unique_counts(values: np.ndarray, weight: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    if weight is None:
        u, c = np.unique(values, return_counts=True)
        return u, c.astype(np.int64)
    u, inv = np.unique(values, return_inverse=True)
    return u, np.bincount(inv, weights=weight, minlength=len(u)).astype(np.int64)


def _counts(docs: DataFrame, parts: int, flush: int) -> DataFrame:
    """Token counts (word, n), each word in one row."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []
        size = 0

        def out() -> pa.RecordBatch:
            word, n = _unique_counts(np.concatenate(held))
            part = _part_of_word(word, parts)
            order = np.argsort(part, kind="stable")
            rows = list(_pack(part[order], {"word": word[order], "n": n[order].astype(np.uint32)}))
            return pa.RecordBatch.from_pylist(rows, pa.schema([("part", pa.int32()), ("word", pa.binary()), ("n", pa.binary())]))

        for batch in batches:
            for p in B.pieces(batch, "text"):
                held.append(tokens(p.column(p.schema.get_field_index("text")))[0])
                size += len(held[-1])
                if size >= flush:
                    yield out()
                    held, size = [], 0
        if size:
            yield out()
        B.trim()

    def merge(key: tuple, rows: pa.Table) -> pa.Table:
        word = np.frombuffer(b"".join(rows.column("word").to_pylist()), np.uint64)
        n = np.frombuffer(b"".join(rows.column("n").to_pylist()), np.uint32)
        word, n = _unique_counts(word, n)
        return pa.table({"word": word.view(np.int64), "n": n})

    return docs.select("text").mapInArrow(count, "part int, word binary, n binary").groupBy("part").applyInArrow(merge, "word long, n long")


def _pairs(values: tuple[np.ndarray, np.ndarray], order: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Contexts of order - 1 words, the same without their oldest word (none: 0) and followers, of tokens with row starts."""
    word, first = values
    before = []  # nearest first
    for j in range(1, order):
        back = np.full_like(word, START)
        back[j:] = word[:-j] if len(word) > j else word[:0]
        for k in range(j):  # the j tokens that open a row
            at = first[:-1] + k
            back[at[at < first[1:]]] = START
        before.append(back)

    def joined(n: int) -> np.ndarray:
        ctx = before[n - 1]
        for j in range(n - 2, -1, -1):
            ctx = _longer(ctx, before[j])
        return ctx

    return joined(order - 1), joined(order - 2) if order > 2 else None, word


def _opening(order: int) -> np.uint64:
    """The context before the first token of a row."""
    ctx = np.array([START])
    for _ in range(order - 2):
        ctx = _longer(ctx, np.array([START]))
    return ctx[0]


_BLOCKS = pa.schema([("part", pa.int32()), ("ctx", pa.binary()), ("low", pa.binary()), ("fan", pa.binary()), ("word", pa.binary()), ("n", pa.binary())])


def _pair_blocks(docs: DataFrame, order: int, spread: Spread, parts: int, flush: int) -> DataFrame:
    """Counts of n-grams in blocks (part, ctx, low: the shorter contexts, followers of each context, word, n)."""
    shipped = docs.sparkSession.sparkContext.broadcast(spread)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, ...]] = []
        size = 0

        def out() -> Iterator[pa.RecordBatch]:
            # bigrams have no shorter context: nothing is held for it
            ctx, word, *low = (np.concatenate([h[k] for h in held]) for k in ((0, 2, 1) if order > 2 else (0, 2)))
            held.clear()
            part = _part_of_pair(ctx, word, shipped.value, parts)
            for a, b, ctx, word, *low in _by_part(part, parts, ctx, word, *low):
                at = np.lexsort((word, ctx))
                ctx, word = ctx[at], word[at]
                new = np.ones(len(ctx), bool)
                new[1:] = (ctx[1:] != ctx[:-1]) | (word[1:] != word[:-1])
                starts = np.flatnonzero(new)
                n = np.diff(np.append(starts, len(ctx)))
                ctx, word, low = ctx[starts], word[starts], low[0][at[starts]] if order > 2 else None
                head = _heads(ctx)
                yield pa.RecordBatch.from_pylist([{"part": a, "ctx": ctx[head].tobytes(), "low": low[head].tobytes() if order > 2 else b"", "fan": _small(np.diff(np.append(head, len(ctx)))), "word": word.tobytes(), "n": _small(n)}], _BLOCKS)

        for batch in batches:
            for p in B.pieces(batch, "text"):
                held.append(_pairs(tokens(p.column(p.schema.get_field_index("text"))), order))
                size += len(held[-1][0])
                if size >= flush:
                    yield from out()
                    held, size = [], 0
        if size:
            yield from out()
        held.clear()
        B.trim()

    return docs.select("text").mapInArrow(count, "part int, ctx binary, low binary, fan binary, word binary, n binary")


def _by_part(part: np.ndarray, parts: int, *columns: np.ndarray) -> Iterator[tuple]:
    order = np.argsort(part, kind="stable")
    cuts = np.searchsorted(part[order], np.arange(parts + 1))
    for k in range(parts):
        if cuts[k] < cuts[k + 1]:
            at = order[cuts[k] : cuts[k + 1]]
            yield (k, len(at), *(c[at] for c in columns))


def _small(n: np.ndarray) -> bytes:
    """Counts in one byte each, larger ones behind them as (255, then 8 bytes in order)."""
    big = n >= 255
    return np.where(big, 255, n).astype(np.uint8).tobytes() + n[big].astype(np.int64).tobytes()


def _unsmall(data: bytes, size: int) -> np.ndarray:
    n = np.frombuffer(data, np.uint8, size).astype(np.int64)
    big = n == 255
    if big.any():
        n[big] = np.frombuffer(data, np.int64, int(big.sum()), offset=size)
    return n


def _merge_pairs(order: int, top: int, often: int):
    """The n-grams of a partition, packed. The first block has the numbers of those seen 0 to ``top`` times, and those seen ``often`` or more, as contexts of one word more, with their counts."""

    def run(key: tuple, rows: pa.Table) -> pa.Table:
        ctxs, lows, words, ns = [], [], [], []
        for ctx, low, fan, word, n in zip(*(rows.column(c).to_pylist() for c in ("ctx", "low", "fan", "word", "n"))):
            words.append(np.frombuffer(word, np.uint64))
            c = np.frombuffer(ctx, np.uint64)
            fan = _unsmall(fan, len(c))
            ctxs.append(np.repeat(c, fan))
            if order > 2:
                lows.append(np.repeat(np.frombuffer(low, np.uint64), fan))
            ns.append(_unsmall(n, len(words[-1])))
        ctx, word, n = np.concatenate(ctxs), np.concatenate(words), np.concatenate(ns)
        low = np.concatenate(lows) if order > 2 else None
        at = np.lexsort((word, ctx))
        ctx, word, n = ctx[at], word[at], n[at]
        starts = np.flatnonzero(np.concatenate([[True], (ctx[1:] != ctx[:-1]) | (word[1:] != word[:-1])]))
        ctx, word, n = ctx[starts], word[starts], np.add.reduceat(n, starts)
        low = low[at[starts]] if order > 2 else None
        seen = np.bincount(n[n <= top], minlength=top + 1)
        many = np.flatnonzero((n >= often) & (word != END))
        out = []
        for k, a in enumerate(range(0, max(len(ctx), 1), BLOCK)):
            c, w = ctx[a : a + BLOCK], word[a : a + BLOCK]
            head = _heads(c)
            out.append({
                "part": key[0].as_py(), "block": k, "ctx": c[head].tobytes(), "low": low[a : a + BLOCK][head].tobytes() if order > 2 else b"", "fan": _small(np.diff(np.append(head, len(c)))), "word": w.tobytes(), "n": _small(n[a : a + BLOCK]),
                "seen": seen.tolist() if k == 0 else None, "often": _longer(ctx[many], word[many]).tobytes() + n[many].tobytes() if k == 0 else None,
            })
        B.trim()
        return pa.Table.from_pylist(out, _PAIRS)

    return run


_PAIRS = pa.schema([*((c, pa.int32()) for c in ("part", "block")), *((c, pa.binary()) for c in ("ctx", "low", "fan", "word", "n")), ("seen", pa.list_(pa.int64())), ("often", pa.binary())])
_PAIRS_DDL = "part int, block int, ctx binary, low binary, fan binary, word binary, n binary, seen array<long>, often binary"
#: Packed n-grams of one length; others: counts of followers (codes into values), or P(w|h') of each; block -1: words that are no context here.
_MODEL = pa.schema([("part", pa.int32()), ("block", pa.int32()), *((c, pa.binary()) for c in ("ctx", "fan", "ctx_n", "word", "n", "codes", "values", "spread"))])
_MODEL_DDL = "part int, block int, ctx binary, fan binary, ctx_n binary, word binary, n binary, codes binary, values binary, spread binary"


def _heads(ctx: np.ndarray) -> np.ndarray:
    """Where runs of equal contexts begin."""
    new = np.ones(len(ctx), bool)
    new[1:] = ctx[1:] != ctx[:-1]
    return np.flatnonzero(new)


def _asked_words(ctx: bytes, word: bytes, parts: int) -> tuple[np.ndarray, np.ndarray]:
    """The distinct words of a block, contexts included, by the partition that counts them, and these partitions."""
    u = np.unique(np.concatenate([np.frombuffer(ctx, np.uint64), np.frombuffer(word, np.uint64)]))
    own = _part_of_word(u, parts)
    order = np.argsort(own, kind="stable")
    return u[order], own[order]


def _word_counts(pairs: DataFrame, words: DataFrame, parts: int) -> DataFrame:
    """Counts of the words of each block (part, block, own, n), in the order of ``_asked_words``; and of each partition its own words (part, block -1, word, n)."""

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, block, ctx, word in zip(*(c.to_pylist() for c in batch.columns)):
                u, own = _asked_words(ctx, word, parts)
                rows = [{"own": r["part"], "part": part, "block": block, "word": r["word"]} for r in _pack(own, {"word": u})]
                yield pa.RecordBatch.from_pylist(rows, pa.schema([("own", pa.int32()), ("part", pa.int32()), ("block", pa.int32()), ("word", pa.binary())]))
        B.trim()

    def reply(key: tuple, asked: pa.Table, counted: pa.Table) -> pa.Table:
        own = key[0].as_py()
        word, n = counted.column("word").to_numpy().view(np.uint64), counted.column("n").to_numpy()
        order = np.argsort(word)
        word, n = word[order], n[order]
        out = [{"part": own, "block": -1, "own": own, "word": word.tobytes(), "n": _small(n)}]
        for part, block, wanted in zip(*(asked.column(c).to_pylist() for c in ("part", "block", "word"))):
            at, there = _find(word, np.frombuffer(wanted, np.uint64))
            out.append({"part": part, "block": block, "own": own, "n": _small(np.where(there, n[at], 0) if len(n) else np.zeros(len(at), np.int64))})
        B.trim()
        return pa.Table.from_pylist(out, pa.schema([("part", pa.int32()), ("block", pa.int32()), ("own", pa.int32()), ("word", pa.binary()), ("n", pa.binary())]))

    asked = pairs.select("part", "block", "ctx", "word").mapInArrow(ask, "own int, part int, block int, word binary")
    own = F.pmod(F.shiftrightunsigned("word", 20), F.lit(parts)).cast("int").alias("own")
    return asked.groupBy("own").cogroup(words.select(own, "word", "n").groupBy("own")).applyInArrow(reply, "part int, block int, own int, word binary, n binary")


@dataclass
class Rates:
    """Probabilities by count: of a word, and of an n-gram before the division by its context's count."""

    words: np.ndarray
    scale: float

    def word(self, n: np.ndarray) -> np.ndarray:
        return np.where(n < len(self.words), self.words[np.minimum(n, len(self.words) - 1)], 1.0) * n * self.scale


def _discounted(rates: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Adjusted counts."""
    return np.where(n < len(rates), rates[np.minimum(n, len(rates) - 1)], 1.0) * n


def _weights(s: np.ndarray, q: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """log10 of alpha and of f / alpha of contexts from their sums of p* and p and their counts.

    A context whose followers are all frequent frees no mass: one count more then stands for the unseen.
    """
    f = np.where(s > 1 - 1e-9, n / (n + 1.0) / np.where(s > 0, s, 1.0), 1.0)
    a = (1 - s * f) / (1 - q)
    return np.log10(a), np.log10(f / a)


def _resolve(rates: Rates, ratio: np.ndarray, spread: Spread, starts: int, parts: int):
    """A partition's bigrams with the counts of their followers (codes into values) and contexts; its words that are no context in it
    as block -1; the sums of its spread contexts (context, sum of p*, sum of p) in column spread."""

    def run(key: tuple, pairs: pa.Table, counts: pa.Table) -> pa.Table:
        part = key[0].as_py()
        replies: dict[int, list] = {}
        own = (b"", b"")
        for block, frm, word, n in zip(*(counts.column(c).to_pylist() for c in ("block", "own", "word", "n"))):
            if block < 0:
                own = (word, n)
            else:
                replies.setdefault(block, []).append((frm, n))
        out, contexts = [], [np.zeros(0, np.uint64)]
        for block, ctx, fan, word, n in zip(*(pairs.column(c).to_pylist() for c in ("block", "ctx", "fan", "word", "n"))):
            u, frm = _asked_words(ctx, word, parts)
            sizes = np.bincount(frm, minlength=parts) if len(u) else np.zeros(parts, np.int64)
            of = np.concatenate([_unsmall(d, int(sizes[k])) for k, d in sorted(replies.get(block, []))] or [np.zeros(0, np.int64)])
            order = np.argsort(u)
            u, of = u[order], of[order]
            h, w = np.frombuffer(ctx, np.uint64), np.frombuffer(word, np.uint64)
            ctx_n = np.where(h == START, starts, of[np.searchsorted(u, h)])
            values, code = np.unique(of, return_inverse=True)
            code = code.astype(np.uint16 if len(values) <= 65536 else np.uint32)[np.searchsorted(u, w)]
            contexts.append(h)
            sums = _sums_of(h, _unsmall(fan, len(h)), ctx_n, _discounted(ratio, _unsmall(n, len(w))), rates.word(values[code]), spread)
            out.append({"part": part, "block": block, "ctx": ctx, "fan": fan, "ctx_n": _small(ctx_n), "word": word, "n": n, "codes": code.tobytes(), "values": values.tobytes(), "spread": sums})
        word = np.frombuffer(own[0], np.uint64)
        n = _unsmall(own[1], len(word))
        rest = ~np.isin(word, np.concatenate(contexts))
        out.append({"part": part, "block": -1, "word": word[rest].tobytes(), "n": _small(n[rest])})
        B.trim()
        return pa.Table.from_pylist(out, _MODEL)

    return run


def _sums_of(h: np.ndarray, fan: np.ndarray, ctx_n: np.ndarray, adjusted: np.ndarray, lower: np.ndarray, spread: Spread) -> bytes:
    """Context, sum of p* and sum of P(w|h') of the spread contexts of a block, as bytes."""
    _, wide = _find(spread.ctx, h)
    if not wide.any():
        return b""
    first = np.cumsum(fan) - fan
    s, q = np.add.reduceat(adjusted, first) / ctx_n, np.add.reduceat(lower, first)
    return h[wide].tobytes() + s[wide].tobytes() + q[wide].tobytes()


def _asked_pairs(row: dict, spread: Spread, parts: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """The shorter n-grams of a block (context, word) by the partition that holds them, these partitions, and the order that was."""
    ctx = np.frombuffer(row["low"], np.uint64)
    low, word = np.repeat(ctx, _unsmall(row["fan"], len(ctx))), np.frombuffer(row["word"], np.uint64)
    own = _part_of_pair(low, word, spread, parts)
    at = np.argsort(own, kind="stable")
    return low[at], word[at], own[at], at


def _lower_values(pairs: DataFrame, level: Level, model: KatzModel) -> DataFrame:
    """P(w|h') of every n-gram of ``pairs`` from the level of the shorter ones: (part, block, own, p), in the order of ``_asked_pairs``."""
    shipped = pairs.sparkSession.sparkContext.broadcast((level, model.rates, model.parts))

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        level, _, parts = shipped.value
        for batch in batches:
            for row in batch.to_pylist():
                low, word, own, _ = _asked_pairs(row, level.spread, parts)
                out = [{"own": r["part"], "part": row["part"], "block": row["block"], "low": r["low"], "word": r["word"]} for r in _pack(own, {"low": low, "word": word})]
                yield pa.RecordBatch.from_pylist(out, pa.schema([("own", pa.int32()), ("part", pa.int32()), ("block", pa.int32()), ("low", pa.binary()), ("word", pa.binary())]))
        B.trim()

    def reply(key: tuple, asked: pa.Table, held: pa.Table) -> pa.Table:
        level, rates, _ = shipped.value
        x = _slice(level, rates, held)
        out = []
        for part, block, low, word in zip(*(asked.column(c).to_pylist() for c in ("part", "block", "low", "word"))):
            rank, there = _find(x.ctx, np.frombuffer(low, np.uint64))
            at, hit = _followers(x, rank, there, np.frombuffer(word, np.uint64))
            out.append({"part": part, "block": block, "own": key[0].as_py(), "p": np.where(hit, x.p[np.minimum(at, len(x.p) - 1)], 0.0).tobytes()})
        B.trim()
        return pa.Table.from_pylist(out, pa.schema([("part", pa.int32()), ("block", pa.int32()), ("own", pa.int32()), ("p", pa.binary())]))

    asked = pairs.select("part", "block", "low", "fan", "word").mapInArrow(ask, "own int, part int, block int, low binary, word binary")
    return asked.groupBy("own").cogroup(level.blocks.groupBy("part")).applyInArrow(reply, "part int, block int, own int, p binary").where("block IS NOT NULL")


def _resolve_longer(ratio: np.ndarray, spread: Spread, below: Spread, parts: int):
    """A partition's n-grams of three words or more with their P(w|h') and the counts of their contexts, which are sums as every n-gram is kept."""

    def run(key: tuple, pairs: pa.Table, replies: pa.Table) -> pa.Table:
        got: dict[int, list] = {}
        for block, own, p in zip(*(replies.column(c).to_pylist() for c in ("block", "own", "p"))):
            got.setdefault(block, []).append((own, p))
        rows = sorted(pairs.to_pylist(), key=lambda r: r["block"])
        # a context may go on in the next block
        whole: dict[int, int] = {}
        for r in rows:
            h = np.frombuffer(r["ctx"], np.uint64)
            if len(h):
                fan = _unsmall(r["fan"], len(h))
                r["sum"] = np.add.reduceat(_unsmall(r["n"], int(fan.sum())), np.cumsum(fan) - fan)
                for k in {0, len(h) - 1}:
                    whole[int(h[k])] = whole.get(int(h[k]), 0) + int(r["sum"][k])
        out = []
        for r in rows:
            h = np.frombuffer(r["ctx"], np.uint64)
            if not len(h):
                continue
            ctx_n = r["sum"].copy()
            for k in {0, len(h) - 1}:
                ctx_n[k] = whole[int(h[k])]
            at, wide = _find(spread.ctx, h)
            ctx_n = np.where(wide, spread.n[np.minimum(at, max(len(spread.n) - 1, 0))] if len(spread.n) else 0, ctx_n)
            *_, order = _asked_pairs(r, below, parts)
            lower = np.empty(len(order))
            lower[order] = np.concatenate([np.frombuffer(p, np.float64) for _, p in sorted(got[r["block"]])])
            sums = _sums_of(h, _unsmall(r["fan"], len(h)), ctx_n, _discounted(ratio, _unsmall(r["n"], len(lower))), lower, spread)
            out.append({"part": key[0].as_py(), "block": r["block"], "ctx": r["ctx"], "fan": r["fan"], "ctx_n": _small(ctx_n), "word": r["word"], "n": r["n"], "codes": b"", "values": lower.tobytes(), "spread": sums})
        B.trim()
        return pa.Table.from_pylist(out, _MODEL)

    return run


def _spread_sums(model: DataFrame) -> DataFrame:
    """Sums (ctx, s, q) of the contexts that are spread over partitions."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for x in batch.column(0).to_pylist():
                k = len(x or b"") // 24
                yield pa.RecordBatch.from_arrays([pa.array(np.frombuffer(x, t, k, offset=8 * k * i)) for i, t in enumerate((np.int64, np.float64, np.float64))], ["ctx", "s", "q"])

    return model.where("spread IS NOT NULL").select("spread").mapInArrow(run, "ctx long, s double, q double").groupBy("ctx").agg(F.sum("s").alias("s"), F.sum("q").alias("q"))


def discounts(counts: dict[int, int], gt_max: int, absolute: float) -> list[float]:
    """Good-Turing discount ratios d(0..gt_max) (d(0) unused): together they free the mass of the counts of one, as far as ratios stay above zero."""
    out = [1.0] * (gt_max + 1)
    n1 = counts.get(1, 0)
    common = (gt_max + 1) * counts.get(gt_max + 1, 0) / n1 if n1 else 1.0
    plain = True
    for r in range(1, gt_max + 1):
        nr, nx = counts.get(r, 0), counts.get(r + 1, 0)
        ratio = -1.0
        if nr and nx and 0 <= common < 1:
            ratio = ((r + 1) * nx / (r * nr) - common) / (1 - common)
        plain &= 0 < ratio < 1
        out[r] = ratio if 0 < ratio < 1 else (r - absolute) / r
    if plain or not n1:
        return out
    # some ratios are stand-ins: what each count loses is scaled until all lose the mass of the counts of one; none loses nearly all of its own
    lost = {r: 1 - out[r] for r in range(1, gt_max + 1) if counts.get(r, 0)}
    for _ in range(gt_max):
        full = {r for r in lost if lost[r] >= 0.95}
        want = n1 - sum(counts[r] * r * 0.95 for r in full)
        have = sum(counts[r] * r * x for r, x in lost.items() if r not in full)
        if want <= 0 or have <= 0:
            break
        lost = {r: 0.95 if r in full else x * want / have for r, x in lost.items()}
        if all(x < 0.95 for r, x in lost.items() if r not in full):
            break
    for r, x in lost.items():
        out[r] = 1 - min(x, 0.95)
    return out


@dataclass
class Level:
    """N-grams of one length: packed blocks, the spread contexts with log10 alpha and log10 f / alpha and f, and the discount ratios."""

    order: int
    blocks: DataFrame | None
    spread: Spread
    weights: tuple[np.ndarray, np.ndarray]
    ratio: np.ndarray

    def __getstate__(self) -> dict:
        return self.__dict__ | {"blocks": None}  # workers get the rest


@dataclass
class KatzModel:
    """Levels of lengths 2 and up; counts of words stand with the bigrams."""

    levels: list[Level]
    rates: Rates
    parts: int
    total: int
    distinct: int
    ends: int  # count of the end token
    unknown: float  # log10 probability of the unknown word

    def release(self) -> None:
        release(*(x.blocks for x in self.levels))


def partitions_for(docs: DataFrame, bytes_each: int = 16 << 20) -> int:
    """A number of partitions that grows with the bytes of text."""
    size = docs.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    return max(16, -(-int(size) // bytes_each))


def _finished(level: Level) -> Level:
    """Adds the sums of spread contexts up."""
    spread = level.spread
    rows = bounded_rows(_spread_sums(level.blocks), len(spread.ctx), "spread contexts")
    s, q = np.zeros(len(spread.ctx)), np.zeros(len(spread.ctx))
    at = np.searchsorted(spread.ctx, np.array([r.ctx for r in rows], np.int64).view(np.uint64))
    s[at], q[at] = [r.s for r in rows], [r.q for r in rows]
    level.weights = _weights(s, q, spread.n)
    return level


def _ratios(pairs: DataFrame, gt_max: int, absolute: float) -> np.ndarray:
    seen = pairs.where("seen IS NOT NULL").select(F.posexplode("seen").alias("n", "k")).groupBy("n").agg(F.sum("k").alias("k")).where("k > 0").collect()
    return np.array(discounts({int(r.n): int(r.k) for r in seen}, gt_max, absolute))


def train(docs: DataFrame, parts: int, order: int = 3, gt_max: int = 5, absolute: float = 0.75, flush: int = 6_000_000) -> KatzModel:
    """Count and normalise over the rows of ``docs`` (columns text, and any others), n-grams of 2 to ``order`` words (2 at least)."""
    if order < 2:
        raise ValueError("order is at least 2")
    words = materialize(_counts(docs, parts, flush), "katz-words")
    total, distinct = words.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count(F.lit(1))).first()
    total, distinct = int(total), int(distinct)
    often = max(1, -(-total // (4 * parts)))
    heavy = words.where(F.col("n") >= often).collect()  # 4 * parts at most
    n_rows = int(words.where(F.col("word") == int(END.view(np.int64))).agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0])
    by_count = {int(r.n): int(r.k) for r in words.where(F.col("n").between(1, gt_max + 1)).groupBy("n").agg(F.count(F.lit(1)).alias("k")).collect()}
    scale = max(total, 1)
    rates = Rates(np.array(discounts(by_count, gt_max, absolute)), 1.0 / scale)
    # counts above gt_max are not discounted
    mass = (sum(rates.word(np.array([n]))[0] * k for n, k in by_count.items() if n <= gt_max) + float(words.where(F.col("n") > gt_max).agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]) / scale)
    unknown = 1.0 - mass
    if unknown <= 1e-12:  # no word was seen rarely: keep one count's worth for the unknown word
        unknown = 1.0 / (scale + 1.0)
        rates.scale *= (1.0 - unknown) / mass if mass else 1.0
    model = KatzModel([], rates, parts, total, distinct, n_rows, math.log10(unknown) if total else 0.0)

    # a word is a context as often as it occurs, but the end never; the opening context stands before every row
    ctx, n = np.array([r.word for r in heavy], np.int64).view(np.uint64), np.array([r.n for r in heavy], np.int64)
    for k in range(2, order + 1):
        spread = Spread.of(np.append(ctx, _opening(k)), np.append(n, n_rows).astype(np.int64), total, parts)
        pairs = materialize(_pair_blocks(docs, k, spread, parts, flush).groupBy("part").applyInArrow(_merge_pairs(k, gt_max + 1, often), _PAIRS_DDL), f"katz-{k}-grams", _LARGE_ROWS)
        ratio = _ratios(pairs, gt_max, absolute)
        found = [np.frombuffer(r.often, np.uint64) for r in pairs.where("octet_length(often) > 0").select("often").collect()]  # 4 * parts contexts at most
        ctx = np.concatenate([np.zeros(0, np.uint64), *(x[: len(x) // 2] for x in found)])
        n = np.concatenate([np.zeros(0, np.int64), *(x[len(x) // 2 :].view(np.int64) for x in found)])
        if k == 2:
            replies = materialize(_word_counts(pairs, words, parts), "katz-word-counts", _LARGE_ROWS)
            resolve = _resolve(rates, ratio, spread, n_rows, parts)
        else:
            below = model.levels[-1]
            replies = materialize(_lower_values(pairs, below, model), f"katz-{k}-lower", _LARGE_ROWS)
            resolve = _resolve_longer(ratio, spread, below.spread, parts)
        blocks = pairs.drop("seen", "often").groupBy("part").cogroup(replies.groupBy("part")).applyInArrow(resolve, _MODEL_DDL)
        model.levels.append(_finished(Level(k, materialize(blocks, f"katz-{k}-model", _LARGE_ROWS), spread, (), ratio)))
        release(pairs, replies)
    release(words)
    return model


_ASK = pa.schema([("part", pa.int32()), ("block", pa.int64()), ("ctx", pa.binary()), ("fan", pa.binary()), ("word", pa.binary()), ("n", pa.binary()), ("at", pa.binary()), ("sizes", pa.binary())])


def _requests(docs: DataFrame, order: int, spread: Spread, parts: int, flush: int) -> DataFrame:
    """Blocks of rows as the n-grams they hold and where, dealt like the model, and with the bigrams for each block its ids and row sizes.

    A block's number comes from its task and its place there. The input must give
    a task the same rows in the same order when it runs again, as scans of files do.
    """
    shipped = docs.sparkSession.sparkContext.broadcast(spread)
    kind = docs.schema["doc_id"].dataType

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        block = TaskContext.get().partitionId() << 24
        held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        ids: list[pa.Array] = []
        sizes: list[np.ndarray] = []
        size = rows = 0

        def batch_of(row: dict, own: pa.Array | None = None) -> pa.RecordBatch:
            names = pa.ListArray.from_arrays(pa.array([0, len(own)], pa.int32()), own) if own is not None else pa.nulls(1, pa.list_(id_type))
            return pa.RecordBatch.from_arrays([pa.array([row.get(f.name)], f.type) for f in _ASK] + [names], [*_ASK.names, "ids"])

        def out() -> Iterator[pa.RecordBatch]:
            ctx, word, row = (np.concatenate([h[k] for h in held]) for k in (0, 1, 2))
            held.clear()
            for k, _, c, w, r in _by_part(_part_of_pair(ctx, word, shipped.value, parts), parts, ctx, word, row):
                at = np.lexsort((r, w, c))
                c, w, r = c[at], w[at], r[at]
                head = np.flatnonzero(np.concatenate([[True], (c[1:] != c[:-1]) | (w[1:] != w[:-1])]))
                n = np.diff(np.append(head, len(w)))
                c, w = c[head], w[head]
                top = _heads(c)
                yield batch_of({"part": k, "block": block, "ctx": c[top].tobytes(), "fan": _small(np.diff(np.append(top, len(c)))), "word": w.tobytes(), "n": _small(n), "at": r.tobytes()})
            if order == 2:
                yield batch_of({"part": block % parts, "block": block, "sizes": np.concatenate(sizes).astype(np.int64).tobytes()}, pa.concat_arrays(ids))

        id_type = None
        for batch in batches:
            id_type = batch.schema.field("doc_id").type
            for p in B.pieces(batch, "text"):
                for a in range(0, p.num_rows, 8192):
                    q = p.slice(a, 8192)
                    if size and (size >= flush or rows + q.num_rows > 65535):
                        yield from out()
                        held, ids, sizes, size, rows = [], [], [], 0, 0
                        block += 1
                    word, first = tokens(q.column(1))
                    ctx, _, word = _pairs((word, first), order)
                    held.append((ctx, word, np.repeat((np.arange(q.num_rows) + rows).astype(np.uint16), np.diff(first))))
                    ids.append(q.column(0))
                    sizes.append(np.diff(first))
                    size += len(word)
                    rows += q.num_rows
        if size:
            yield from out()
        held.clear()
        B.trim()

    return docs.select("doc_id", "text").mapInArrow(ask, f"part int, block long, ctx binary, fan binary, word binary, n binary, at binary, sizes binary, ids array<{kind.simpleString()}>")


def _find(keys: np.ndarray, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of ``wanted`` in sorted distinct ``keys``, and whether they are there."""
    if not len(keys):
        return np.zeros(len(wanted), np.int64), np.zeros(len(wanted), bool)
    at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
    return at, keys[at] == wanted


@dataclass
class Slice:
    """A partition of a level: contexts, their log10 alphas and where their followers begin and end; followers, their P(w|h) and gains,
    log10 of p*(w|h) / (alpha(h) P(w|h')). With bigrams, the words that are counted here and their counts."""

    ctx: np.ndarray
    alpha: np.ndarray
    begin: np.ndarray
    end: np.ndarray
    word: np.ndarray
    p: np.ndarray
    gain: np.ndarray
    known: np.ndarray
    known_n: np.ndarray


def _slice(level: Level, rates: Rates, rows: pa.Table) -> Slice:
    words, counts, ctxs, ctx_ns, fans, followers, ns, lowers = [], [], [], [], [], [], [], []
    names = ("block", "ctx", "fan", "ctx_n", "word", "n", "codes", "values")
    for block, ctx, fan, ctx_n, word, n, codes, values in sorted(zip(*(rows.column(c).to_pylist() for c in names)), key=lambda r: r[0]):
        word = np.frombuffer(word, np.uint64)
        n = _unsmall(n, len(word))
        if block < 0:
            words.append(word)
            counts.append(n)
            continue
        ctx = np.frombuffer(ctx, np.uint64)
        ctxs.append(ctx)
        fans.append(_unsmall(fan, len(ctx)))
        ctx_ns.append(_unsmall(ctx_n, len(ctx)))
        followers.append(word)
        ns.append(n)
        if level.order == 2:
            values = np.frombuffer(values, np.int64)
            lowers.append(rates.word(values)[np.frombuffer(codes, np.uint16 if len(values) <= 65536 else np.uint32)])
        else:
            lowers.append(np.frombuffer(values, np.float64))

    def joined(arrays: list, kind: type) -> np.ndarray:
        return np.concatenate(arrays) if arrays else np.zeros(0, kind)

    word, lower = joined(followers, np.uint64), joined(lowers, np.float64)
    ctx, fan, ctx_n = joined(ctxs, np.uint64), joined(fans, np.int64), joined(ctx_ns, np.int64)
    own = _heads(ctx)  # a context may go on in the next block
    if len(ctx):
        fan, ctx, ctx_n = np.add.reduceat(fan, own), ctx[own], ctx_n[own]
    end = np.cumsum(fan)
    begin = end - fan
    lowers.clear()
    star = joined([_discounted(level.ratio, n) for n in ns], np.float64)
    ns.clear()
    star /= np.repeat(ctx_n, fan)
    spread = level.spread
    if len(ctx):
        s = np.add.reduceat(star, begin)
        alpha, over = _weights(s, np.add.reduceat(lower, begin), ctx_n)
        at, shared = _find(spread.ctx, ctx)
        alpha, over = np.where(shared, level.weights[0][at], alpha), np.where(shared, level.weights[1][at], over)
    else:
        alpha = over = np.zeros(0)
    gain = star / lower
    gain = np.log10(gain, out=gain)
    star *= np.repeat(10.0 ** (over + alpha), fan)
    gain += np.repeat(over, fan)
    # words without followers in training have no weight; counts of contexts of one word are counts of words
    known, known_n = joined(words, np.uint64), joined(counts, np.int64)
    if level.order == 2:
        known, known_n = np.concatenate([known, ctx]), np.concatenate([known_n, np.where(ctx == START, 0, ctx_n)])
        known, at = np.unique(known, return_index=True)
        known_n = known_n[at]
    return Slice(ctx, alpha, begin, end, word, star, gain, known, known_n)


def _followers(x: Slice, rank: np.ndarray, there: np.ndarray, want: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of ``want`` among the followers of the contexts at ``rank`` (where ``there``), and whether they are followers."""
    at, hit = np.zeros(len(want), np.int64), np.zeros(len(want), bool)
    look = np.flatnonzero(there)
    if len(look):
        rank, want = rank[look], want[look]
        lo, hi = x.begin[rank], x.end[rank]
        while True:  # binary search of all at once
            open_ = lo < hi
            if not open_.any():
                break
            mid = (lo + hi) >> 1
            less = open_ & (x.word[np.minimum(mid, len(x.word) - 1)] < want)
            lo = np.where(less, mid + 1, lo)
            hi = np.where(open_ & ~less, mid, hi)
        at[look] = lo
        hit[look] = (lo < x.end[rank]) & (x.word[np.minimum(lo, len(x.word) - 1)] == want)
    return at, hit


def _answer(model: KatzModel, level: Level, backoff: bool):
    """Per block and partition: for rows that hold its n-grams, the sums over their contexts and gains (known, base, score).

    A word's own probability is added with the bigrams, where the word is the context; without ``backoff`` only that.
    """
    shipped = level.blocks.sparkSession.sparkContext.broadcast((level, model.rates, model.unknown, math.log10(model.total + model.distinct + 1)))

    def run(key: tuple, asked: pa.Table, held: pa.Table) -> pa.Table:
        level, rates, unknown, base = shipped.value
        x = _slice(level, rates, held)
        spread = level.spread
        out: dict[str, list] = {"block": [], "rows": [], "sums": [], "sizes": []}
        for block, c, fan, words, n, at, sizes in zip(*(asked.column(k).to_pylist() for k in ("block", "ctx", "fan", "word", "n", "at", "sizes"))):
            out["block"].append(block)
            out["sizes"].append(sizes)
            if sizes is not None:
                out["rows"].append(None)
                out["sums"].append(None)
                continue
            c, words = np.frombuffer(c, np.uint64), np.frombuffer(words, np.uint64)
            fan = _unsmall(fan, len(c))
            times = _unsmall(n, len(words))
            rows = np.frombuffer(at, np.uint16).astype(np.int64)
            rank, there = _find(x.ctx, c)
            alpha = np.where(there, x.alpha[rank], 0.0) if len(x.ctx) else np.zeros(len(c))
            k, wide = _find(spread.ctx, c)
            if wide.any():  # known everywhere, with followers here or not
                alpha = np.where(wide, level.weights[0][k], alpha)
            value = [np.zeros(len(c)), np.zeros(len(c)), alpha if backoff else np.zeros(len(c))]
            if level.order == 2:
                k2, seen = _find(x.known, c)
                n_c = np.where(seen, x.known_n[k2], 0) if len(x.known) else np.zeros(len(c), np.int64)
                first = c == START
                if wide.any():
                    n_c = np.where(wide & ~first, spread.n[k], n_c)
                known = n_c > 0
                lp = np.where(known, np.log10(np.where(known, rates.word(n_c), 1.0)), unknown)
                value = [known.astype(float), np.where(first, 0.0, np.log10(n_c + 1.0) - base), np.where(first, 0.0, lp) + value[2]]
            gain = np.zeros(len(words))
            if backoff:
                where, hit = _followers(x, np.repeat(rank, fan), np.repeat(there, fan), words)
                gain[hit] = x.gain[where[hit]]
            ctx_times = np.add.reduceat(times, np.cumsum(fan) - fan) if len(c) else times
            per_row = [np.bincount(rows, weights=np.repeat(v, ctx_times)) for v in value[:2]]
            per_row.append(np.bincount(rows, weights=np.repeat(np.repeat(value[2], fan) + gain, times)))
            some = np.unique(rows)
            out["rows"].append(some.astype(np.uint16).tobytes())
            out["sums"].append(np.stack([v[some] for v in per_row]).tobytes())
        B.trim()
        return pa.table({"block": pa.array(out["block"], pa.int64()), "rows": pa.array(out["rows"], pa.binary()), "sums": pa.array(out["sums"], pa.binary()), "sizes": pa.array(out["sizes"], pa.binary()), "ids": asked.column("ids")})

    return run


def _gather(end: tuple[float, float, float]):
    """All of a block: its rows with the sums of every partition and length and the end token's share."""

    def run(key: tuple, rows: pa.Table) -> pa.Table:
        sizes = next(s for s in rows.column("sizes").to_pylist() if s is not None)
        sizes = np.frombuffer(sizes, np.int64)
        total = np.tile(np.array(end)[:, None], (1, len(sizes)))
        for at, sums in zip(rows.column("rows").to_pylist(), rows.column("sums").to_pylist()):
            if at is not None:
                where = np.frombuffer(at, np.uint16)
                total[:, where] += np.frombuffer(sums, np.float64).reshape(3, -1)
        ids = rows.column("ids").combine_chunks()
        own = ids.filter(pa.array(np.asarray(ids.is_valid()))).flatten()
        return pa.table({"doc_id": own, "n_tokens": sizes, "n_known": np.rint(total[0]).astype(np.int64), "base_score": total[1], "score": total[2]})

    return run


def score(docs: DataFrame, model: KatzModel, flush: int = 6_000_000, passes: int = 3, order: int | None = None) -> DataFrame:
    """Rows (doc_id, n_tokens, n_known, base_score, score), one for each row of ``docs`` (doc_id, text), by n-grams of up to ``order`` words (1: words alone)."""
    base = math.log10(model.total + model.distinct + 1)
    n = np.array([model.ends])
    of_end = (1.0, math.log10(model.ends + 1.0) - base, float(np.log10(model.rates.word(n))[0])) if model.ends else (0.0, -base, model.unknown)
    kind = docs.schema["doc_id"].dataType.simpleString()
    order = order or len(model.levels) + 1
    out = None
    for k in range(passes):
        mine = docs.where(F.pmod(F.xxhash64("doc_id"), F.lit(passes)) == k)
        answers = None
        for level in model.levels[: max(1, order - 1)]:
            asked = _requests(mine, level.order, level.spread, model.parts, flush)
            got = asked.groupBy("part").cogroup(level.blocks.groupBy("part")).applyInArrow(_answer(model, level, order > 1), f"block long, rows binary, sums binary, sizes binary, ids array<{kind}>")
            # the answers of a length are small; written, they leave its requests and table behind
            got = got if len(model.levels) == 1 else materialize(got, "katz-answers")
            answers = got if answers is None else answers.unionByName(got)
        scored = materialize(answers.where("block IS NOT NULL").groupBy("block").applyInArrow(_gather(of_end), f"doc_id {kind}, n_tokens long, n_known long, base_score double, score double"), "katz-scores")
        out = scored if out is None else out.unionByName(scored)
    return out


def katz_scores(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", order: int = 3, folds: int = 7, held_fold: int = 2, gt_max: int = 5, absolute: float = 0.75, flush: int = 6_000_000, parts: int | None = None) -> DataFrame:
    """Train on all rows outside the held-out fold and score every row, by n-grams of up to ``order`` words."""
    src = text_of(docs, id_col, text_col)
    held = F.coalesce(F.crc32(F.col("doc_id").cast("string")) % folds == held_fold, F.lit(False))
    parts = parts or partitions_for(src)
    model = train(src.where(~held), parts, max(order, 2), gt_max, absolute, flush)
    out = score(src, model, flush, order=order)
    model.release()
    return out.select("doc_id", held.alias("held_out"), "n_tokens", "n_known", F.lit(model.total).cast("long").alias("train_tokens"), "base_score", "score")
