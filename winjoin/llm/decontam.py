"""Benchmark decontamination by a broadcast hash set of normalised n-grams.

Texts are lower-cased (A-Z) and cut into words of digits, letters a-z and all
non-ASCII characters. A window is any ``n`` consecutive words of an item; an
item of fewer words (but not none) is one window. Document words are scanned
as rolling hashes on the raw bytes of an Arrow batch, candidates are looked up
in the sorted set of window hashes, and every hit is verified on its words.

The set is broadcast only while it holds at most ``most_windows`` windows; a
larger benchmark is cut into as many parts, each scanned by a pass of its own
and joined by row, so no item is dropped and no broadcast grows.

Edge cases: null texts have no words; null item ids are ignored; equal ids
of several items count once; repeated document rows are judged each; an empty
benchmark hits nothing; other columns, whatever their names, are ignored or kept.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from winjoin.llm import bytetext as B
from winjoin.llm.frames import fresh


class WindowSet:
    """The windows of benchmark items: hashes for scanning, words for verifying."""

    def __init__(self, items: list[tuple[str, str]], n: int):
        texts = pa.array([t for _, t in items], pa.string())
        raw, offs = B.flat(texts)
        raw = B.LOWER[raw]
        starts, ends, first = B.spans(raw, offs, B.ALNUM)
        self.items = [i for i, _ in items]
        self.of: dict[bytes, set[int]] = {}
        for k in range(len(items)):
            words = [raw[s:e].tobytes() for s, e in zip(starts[first[k] : first[k + 1]], ends[first[k] : first[k + 1]])]
            size = min(n, len(words))
            for a in range(len(words) - size + 1 if size else 0):
                self.of.setdefault(b" ".join(words[a : a + size]), set()).add(k)
        self.by_size: dict[int, np.ndarray] = {}
        sized: dict[int, list[bytes]] = {}
        for w in self.of:
            sized.setdefault(w.count(b" ") + 1, []).append(w)
        for size, ws in sized.items():
            raw, offs = B.flat(pa.array(ws, pa.binary()).cast(pa.large_binary()).view(pa.large_string()))
            starts, ends, first = B.spans(raw, offs, B.ALNUM)
            h, _ = B.windows(B.run_hashes(raw, starts, ends), B.rows_of(first, len(starts)), size)
            self.by_size[size] = np.unique(h)

    def scan(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray, list[set[int]], tuple]:
        """Words and hit words of each row, the items met in each row, and (starts, ends, first, hit) of the words."""
        raw, offs = B.flat(column)
        raw = B.LOWER[raw]
        starts, ends, first = B.spans(raw, offs, B.ALNUM)
        rows = B.rows_of(first, len(starts))
        hashes = B.run_hashes(raw, starts, ends)
        delta = np.zeros(len(starts) + 1, np.int64)
        met: list[set[int]] = [set() for _ in range(len(column))]
        for size, known in self.by_size.items():
            h, at = B.windows(hashes, rows, size)
            if not len(h):
                continue
            pos = np.minimum(np.searchsorted(known, h), len(known) - 1)
            for a in at[known[pos] == h].tolist():
                owners = self.of.get(b" ".join(raw[starts[j] : ends[j]].tobytes() for j in range(a, a + size)))
                if owners:
                    delta[a] += 1
                    delta[a + size] -= 1
                    met[rows[a]] |= owners
        hit = np.cumsum(delta)[:-1] > 0
        total = np.concatenate([[0], np.cumsum(hit)])
        return np.diff(first), total[first[1:]] - total[first[:-1]], met, (starts, ends, first, hit)


def _parts(bench: DataFrame, id_col: str, text_col: str, n: int, most_windows: int) -> list[DataFrame]:
    """The benchmark, cut into parts of at most about ``most_windows`` windows each."""
    items = bench.select(F.col(f"`{id_col}`").cast("string").alias("item"), F.coalesce(F.col(f"`{text_col}`"), F.lit("")).alias("item_text")).where("item IS NOT NULL")
    # a window starts at a word and a word takes two bytes with its separator: bytes / 2 bounds the windows
    bytes_ = items.agg(F.coalesce(F.sum(F.octet_length("item_text")), F.lit(0))).first()[0]
    parts = 1 + int(bytes_ // (2 * most_windows))
    return [items if parts == 1 else items.where(F.pmod(F.xxhash64("item", "item_text"), F.lit(parts)) == p) for p in range(parts)]


def _scan(docs: DataFrame, part: DataFrame, text_col: str, n: int, spans: bool) -> DataFrame:
    """``docs`` with three columns behind its own (words, hit words, items of this part; names that no other column has) and, if asked, the text without hit words."""
    spark = docs.sparkSession
    added = fresh(docs.columns, "n_words", "n_hit", "items")
    rows = [(r.item, r.item_text) for r in part.toLocalIterator()]  # bounded by _parts
    shipped = spark.sparkContext.broadcast((rows, n))
    schema = T.StructType([*docs.schema.fields, *(T.StructField(c, k) for c, k in zip(added, (T.LongType(), T.LongType(), T.ArrayType(T.StringType()))))])
    at = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = WindowSet(*shipped.value)
        for batch in batches:
            for p in B.pieces(batch, text_col):
                n_words, n_hit, met, (starts, ends, first, hit) = known.scan(p.column(at))
                columns = list(p.columns)
                if spans and n_hit.any():
                    columns[at] = _without(p.column(at), starts, ends, first, hit)
                names = pa.array([sorted({known.items[k] for k in m}) for m in met], pa.list_(pa.string()))
                yield pa.RecordBatch.from_arrays([*columns, pa.array(n_words, pa.int64()), pa.array(n_hit, pa.int64()), names], [*p.schema.names, *added])
        B.trim()

    return docs.mapInArrow(run, schema)


def _without(column: pa.Array, starts: np.ndarray, ends: np.ndarray, first: np.ndarray, hit: np.ndarray) -> pa.Array:
    """The texts without runs of hit words (and what separates these words)."""
    raw, offs = B.flat(column)
    out = []
    for k in range(len(column)):
        a, b = first[k], first[k + 1]
        if not hit[a:b].any():
            out.append(column[k].as_py())
            continue
        kept, at, j = [], offs[k], a
        while j < b:
            if hit[j]:
                kept.append(raw[at : starts[j]].tobytes())
                while j + 1 < b and hit[j + 1]:
                    j += 1
                at = ends[j]
            j += 1
        kept.append(raw[at : offs[k + 1]].tobytes())
        out.append(b"".join(kept).decode("utf-8", "replace"))
    return pa.array(out, column.type)


def contamination(docs: DataFrame, bench: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", n: int = 10, most_windows: int = 4_000_000) -> DataFrame:
    """Rows (doc_id, n_words, n_hit, items, contaminated), one for each row of ``docs``.

    With a benchmark of several parts n_hit is counted on spans united over the
    parts, which takes one more scan of the rows that several parts hit.
    """
    src = docs.select(F.col(f"`{id_col}`").alias("doc_id"), F.col(f"`{text_col}`").alias("text"))
    parts = _parts(bench, item_col, item_text_col, n, most_windows)
    if len(parts) == 1:
        return _scan(src, parts[0], "text", n, False).selectExpr("doc_id", "n_words", "n_hit", "items", "n_hit > 0 AS contaminated")
    # several parts: each pass takes the words that it hits out of a copy of the text but leaves their number, so hits add up;
    # items are looked for in the whole text
    left = src.select("doc_id", "text", F.lit(0).cast("long").alias("n_words"), F.lit(0).cast("long").alias("n_hit"), F.array().cast("array<string>").alias("items"), F.array().cast("array<struct<a:long,b:long>>").alias("hits"))
    for part in parts:
        left = _scan_spans(left, part, n)
    return left.selectExpr("doc_id", "n_words", "n_hit", "items", "n_hit > 0 AS contaminated")


def _scan_spans(docs: DataFrame, part: DataFrame, n: int) -> DataFrame:
    """One pass of several: unites this part's runs of hit words (word numbers) and its items with those so far."""
    shipped = docs.sparkSession.sparkContext.broadcast(([(r.item, r.item_text) for r in part.toLocalIterator()], n))
    columns = docs.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = WindowSet(*shipped.value)
        for batch in batches:
            for p in B.pieces(batch, "text"):
                n_words, _, met, (_, _, first, hit) = known.scan(p.column(1))
                names, runs, n_hit = [], [], []
                for k, (so_far, old) in enumerate(zip(p.column("items").to_pylist(), p.column("hits").to_pylist())):
                    mine = hit[first[k] : first[k + 1]].copy()
                    for r in old:
                        mine[r["a"] : r["b"]] = True
                    edges = np.flatnonzero(np.diff(np.concatenate([[0], mine.astype(np.int8), [0]])))
                    runs.append([{"a": int(a), "b": int(b)} for a, b in zip(edges[::2], edges[1::2])])
                    n_hit.append(int(mine.sum()))
                    names.append(sorted(set(so_far) | {known.items[i] for i in met[k]}))
                yield pa.RecordBatch.from_arrays([p.column(0), p.column(1), pa.array(n_words, pa.int64()), pa.array(n_hit, pa.int64()), pa.array(names, pa.list_(pa.string())), pa.array(runs, pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64())])))], columns)

    return docs.mapInArrow(run, docs.schema)


def decontaminate(docs: DataFrame, bench: DataFrame, text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", n: int = 10, most_windows: int = 4_000_000, remove: str = "documents") -> DataFrame:
    """``docs`` (all columns) without what is in the benchmark: whole documents, or the spans of hit words."""
    if remove not in ("documents", "spans"):
        raise ValueError("remove is 'documents' or 'spans'")
    columns = docs.columns
    for part in _parts(bench, item_col, item_text_col, n, most_windows):
        found = _scan(docs, part, text_col, n, remove == "spans")
        docs = (found.where(F.col(f"`{found.columns[-2]}`") == 0) if remove == "documents" else found).select(*(F.col(f"`{c}`") for c in columns))
    return docs


def items_digest(items: F.Column) -> F.Column:
    """SHA-256 (hex) of sorted item ids, comma-joined."""
    return F.sha2(F.array_join(F.array_sort(items), ","), 256)


def digest_of(ids: list[str]) -> str:
    """The same in Python, for tests."""
    return hashlib.sha256(",".join(sorted(ids)).encode()).hexdigest()
