"""Document quality from a linear-chain conditional random field over lines.

Every non-empty line is good or bad. A line's score is linear in its own
features and those of the lines before and after it; a 2 x 2 table scores
neighbouring labels. Forward-backward gives each line's probability of being
good; weighted by length in bytes these average to the document's quality,
which a logistic curve fitted on the training documents turns into a score.

Learning uses document labels only: at first every line carries its document's
label, then lines of bad documents that the model finds good are relabelled
(never all lines of one document) and the model is fitted again. The fit takes
a bounded sample, ``train_docs`` labelled documents of least hash, chains of
``chain`` lines, and of a document with more than ``train_lines`` lines as many chains as make up that number, evenly
spaced over all of it; scoring is distributed and reads whole texts.

Edge cases: null and empty texts, and texts of newlines only, have no lines
and quality 0, scored like any other quality; a label table without both
classes leaves every score at the share of good labels (0.5 if there are none);
null ids are scored and count as not held out; repeated rows are scored each;
repeated labels of an id count once (the least); other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from winjoin.llm import bytetext as B
from winjoin.llm.frames import text_of

_NOT_NEWLINE = np.ones(256, bool)
_NOT_NEWLINE[10] = False
#: Byte classes whose shares of a line are features: capitals, digits, symbols, other punctuation, non-ASCII.
_CLASSES = [np.isin(np.arange(256), c) for c in (list(range(65, 91)), list(range(48, 58)), [ord(c) for c in "#$%&*|!~^=<>{}[]\\@_+"], [ord(c) for c in ",.;:?'\"()-/"])] + [np.arange(256) >= 128]
OWN = len(_CLASSES) + 6


def line_features(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Features of all non-empty lines of a string column, their bytes, and each row's first line."""
    raw, offs = B.flat(column)
    starts, ends, first = B.spans(raw, offs, _NOT_NEWLINE)
    size = (ends - starts).astype(np.float64)
    own = np.zeros((len(starts), OWN), np.float32)
    if not len(starts):
        return np.zeros((0, 3 * OWN), np.float32), size, first
    for k, cls in enumerate(_CLASSES):
        run = np.concatenate([[0], np.cumsum(cls[raw], dtype=np.int32)])
        own[:, k] = (run[ends] - run[starts]) / size
    ws, we, _ = B.spans(raw, offs, B.NONSPACE)
    words = B.run_hashes(raw, ws, we)
    line = np.searchsorted(starts, ws, side="right") - 1
    n = np.bincount(line, minlength=len(starts)).astype(np.float64)
    same = np.zeros(len(words), bool)
    same[1:] = (words[1:] == words[:-1]) & (line[1:] == line[:-1])
    keyed = B.mix(words ^ (line.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)))
    _, at = np.unique(keyed, return_index=True)
    distinct = np.bincount(line[at], minlength=len(starts))
    some = np.maximum(n, 1)
    k = len(_CLASSES)
    own[:, k] = np.bincount(line, weights=same, minlength=len(starts)) / some
    own[:, k + 1] = np.where(n > 5, 1 - distinct / some, 0)
    own[:, k + 2] = np.minimum(size / some, 40) / 20
    own[:, k + 3] = np.log1p(size) / 8
    own[:, k + 4] = own[:, k] > 0.2
    own[:, k + 5] = own[:, 2] > 0.05
    out = np.zeros((len(starts), 3 * OWN), np.float32)
    out[:, :OWN] = own
    row = B.rows_of(first, len(starts))
    follows = np.flatnonzero(row[1:] == row[:-1])
    out[follows + 1, OWN : 2 * OWN] = own[follows]
    out[follows, 2 * OWN :] = own[follows + 1]
    return out, size, first


@dataclass
class LineModel:
    """Standardised line weights, transition scores [from, to] (0 bad, 1 good), and the curve of the document score."""

    mean: np.ndarray
    scale: np.ndarray
    weight: np.ndarray
    bias: float
    table: np.ndarray
    slope: float
    offset: float
    constant: float | None = None

    def marginals(self, feats: np.ndarray, first: np.ndarray) -> np.ndarray:
        """P(good) of every line."""
        return _chains((feats - self.mean) / self.scale @ self.weight + self.bias, self.table, first)[0]

    def quality(self, column: pa.Array) -> np.ndarray:
        """Length-weighted mean of the lines' marginals, for each row."""
        feats, size, first = line_features(column)
        if self.constant is not None:
            return np.full(len(column), self.constant)
        return _weighted(self.marginals(feats, first), size, first)

    def score(self, column: pa.Array) -> np.ndarray:
        if self.constant is not None:
            return np.full(len(column), self.constant)
        return 1 / (1 + np.exp(-np.clip(self.slope * self.quality(column) + self.offset, -60, 60)))


def _weighted(p: np.ndarray, size: np.ndarray, first: np.ndarray) -> np.ndarray:
    got = np.concatenate([[0.0], np.cumsum(p * size)])
    all_ = np.concatenate([[0.0], np.cumsum(size)])
    return np.clip((got[first[1:]] - got[first[:-1]]) / np.maximum(all_[first[1:]] - all_[first[:-1]], 1), 0, 1)


def _chains(unary: np.ndarray, table: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
    """Forward-backward over all chains at once: P(good) of each line, expected label pairs, log partition.

    ``unary`` is the score of good against bad. Chains are the runs between
    consecutive ``first``; step t advances all chains longer than t.
    """
    size = np.diff(first)
    order = np.argsort(-size, kind="stable")
    size, begin = size[order], first[:-1][order]
    steps = int(size[0]) if len(size) else 0
    live = np.searchsorted(-size, -np.arange(1, steps + 1), side="right")  # chains of at least t lines
    n = len(unary)
    fwd, back = np.zeros((n, 2)), np.zeros((n, 2))
    for t in range(steps):
        at = begin[: live[t]] + t
        if t:
            prev = fwd[at - 1]
            step = prev[:, :, None] + table[None]
            fwd[at] = np.logaddexp(step[:, 0], step[:, 1])
        fwd[at, 1] += unary[at]
    for t in range(steps - 2, -1, -1):
        at = begin[: live[t + 1]] + t
        nxt = back[at + 1].copy()
        nxt[:, 1] += unary[at + 1]
        step = table[None] + nxt[:, None, :]
        back[at] = np.logaddexp(step[:, :, 0], step[:, :, 1])
    both = fwd + back
    total = np.logaddexp(both[:, 0], both[:, 1])
    good = np.exp(both[:, 1] - total)
    inner = np.ones(n, bool)
    inner[begin[size > 0]] = False
    at = np.flatnonzero(inner)
    ahead = back[at].copy()
    ahead[:, 1] += unary[at]
    pairs = np.exp(fwd[at - 1][:, :, None] + table[None] + ahead[:, None, :] - total[at][:, None, None]).sum(axis=0)
    return good, pairs, float(total[begin[size > 0]].sum())


def fit(docs: list[tuple[np.ndarray, np.ndarray, int]], chain: int = 64, rounds: int = 120, ridge: float = 1e-3) -> LineModel:
    """Fit on (line features, line bytes, label) of documents."""
    labels = np.array([y for _, _, y in docs], float)
    share = float(labels.mean()) if len(labels) else 0.5
    zero = np.zeros(3 * OWN)
    if not len(labels) or share in (0.0, 1.0) or not sum(len(f) for f, _, _ in docs):
        return LineModel(zero, zero + 1, zero, 0.0, np.zeros((2, 2)), 0.0, 0.0, share)
    feats = np.concatenate([f for f, _, _ in docs]).astype(np.float64)
    size = np.concatenate([s for _, s, _ in docs])
    first = np.concatenate([[0], np.cumsum([len(f) for f, _, _ in docs])])
    cuts = np.unique(np.concatenate([np.arange(a, b, chain) for a, b in zip(first[:-1], first[1:])] + [first[-1:]]).astype(np.int64))
    mean, scale = feats.mean(axis=0), feats.std(axis=0) + 1e-3
    x = (feats - mean) / scale
    doc = np.repeat(np.arange(len(docs)), np.diff(first))
    given = labels[doc] > 0
    y = given.copy()
    params = np.zeros(x.shape[1] + 5)
    inner = np.ones(len(x), bool)
    inner[cuts[:-1]] = False
    inner = np.flatnonzero(inner)
    for again in range(2):
        pairs_seen = np.zeros((2, 2))
        np.add.at(pairs_seen, (y[inner - 1].astype(int), y[inner].astype(int)), 1)
        step, power = np.zeros_like(params), np.zeros_like(params)
        for r in range(1, rounds + 1):
            w, b, table = params[: x.shape[1]], params[x.shape[1]], params[-4:].reshape(2, 2)
            good, pairs, _ = _chains(x @ w + b, table, cuts)
            gap = y - good
            grad = np.concatenate([x.T @ gap, [gap.sum()], (pairs_seen - pairs).ravel()]) / len(x) - ridge * params
            step = 0.9 * step + 0.1 * grad
            power = 0.99 * power + 0.01 * grad**2
            params = params + 0.1 * (step / (1 - 0.9**r)) / (np.sqrt(power / (1 - 0.99**r)) + 1e-8)
        model = LineModel(mean, scale, params[: x.shape[1]], float(params[x.shape[1]]), params[-4:].reshape(2, 2), 0.0, 0.0)
        if not again:
            good = model.marginals(feats, first)
            y = given | (good > 0.5)
            # a bad document keeps its worst line bad
            fine = np.flatnonzero((labels == 0) & (np.bincount(doc, weights=~y, minlength=len(docs)) == 0) & (np.diff(first) > 0))
            for k in fine:
                y[first[k] + int(np.argmin(good[first[k] : first[k + 1]]))] = False
    q = _weighted(model.marginals(feats, first), size, first)
    model.slope, model.offset = _curve(q, labels)
    return model


def _curve(q: np.ndarray, labels: np.ndarray) -> tuple[float, float]:
    """Logistic regression of labels on one variable by Newton steps, with targets drawn in from 0 and 1."""
    up, down = labels.sum(), (1 - labels).sum()
    target = np.where(labels > 0, (up + 1) / (up + 2), 1 / (down + 2))
    x = np.stack([q, np.ones_like(q)], axis=1)
    beta = np.zeros(2)
    for _ in range(60):
        p = 1 / (1 + np.exp(-np.clip(x @ beta, -30, 30)))
        hess = (x * (p * (1 - p))[:, None]).T @ x + 1e-3 * np.eye(2)
        move = np.linalg.solve(hess, x.T @ (target - p) - 1e-3 * beta)
        beta = beta + np.clip(move, -4, 4)
        if np.abs(move).max() < 1e-8:
            break
    return max(float(beta[0]), 1e-6), float(beta[1])


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", folds: int = 4, held_fold: int = 2, train_docs: int = 4000, train_lines: int = 256, chain: int = 64) -> LineModel:
    """Fit on the ``train_docs`` labelled documents of least id hash, all outside the held-out fold.

    At most ``train_docs * train_lines`` lines of 132 bytes come to the driver.
    """
    if train_lines < chain:
        raise ValueError("train_lines holds at least one chain")
    spark = docs.sparkSession
    picked = (
        labels.select(F.col(f"`{id_col}`").alias("doc_id"), F.col(f"`{label_col}`").cast("int").alias("label"))
        .where(F.col("doc_id").isNotNull() & F.col("label").isNotNull() & (F.crc32(F.col("doc_id").cast("string")) % folds != held_fold))
        .groupBy("doc_id").agg(F.min("label").alias("label"))
        .orderBy(F.xxhash64("doc_id"), "doc_id").limit(train_docs)
    )
    bounded = spark.createDataFrame(picked.collect(), picked.schema)  # at most train_docs rows
    chosen = text_of(docs, id_col, text_col).join(F.broadcast(bounded), "doc_id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for p in B.pieces(batch, "text"):
                feats, size, first = line_features(p.column(0))
                feats, size, first = _spaced(feats, size, first, train_lines, chain)
                yield pa.RecordBatch.from_arrays(
                    [p.column(1), p.column(2), pa.array([feats[a:b].tobytes() for a, b in zip(first[:-1], first[1:])], pa.binary()), pa.array([size[a:b].tobytes() for a, b in zip(first[:-1], first[1:])], pa.binary())],
                    ["order", "label", "feats", "size"],
                )
        B.trim()

    rows = chosen.select("text", F.xxhash64("doc_id", "text").alias("order"), "label").mapInArrow(run, "order long, label int, feats binary, size binary").dropDuplicates().collect()
    rows.sort(key=lambda r: (r.order, r.label))
    return fit([(np.frombuffer(r.feats, np.float32).reshape(-1, 3 * OWN), np.frombuffer(r["size"], np.float64), int(r.label > 0)) for r in rows], chain)


def _spaced(feats: np.ndarray, size: np.ndarray, first: np.ndarray, most: int, chain: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of rows with more than ``most`` lines evenly spaced chains, the first and the last among them."""
    n = np.diff(first)
    if not (n > most).any():
        return feats, size, first
    kept = []
    for a, k in zip(first[:-1], n):
        if k <= most:
            kept.append(np.arange(a, a + k))
            continue
        begin = np.linspace(0, k - chain, most // chain).astype(np.int64)
        kept.append(np.unique(a + (begin[:, None] + np.arange(chain)).ravel()))
    at = np.concatenate(kept)
    return feats[at], size[at], np.concatenate([[0], np.cumsum([len(x) for x in kept])])


def quality_scores(docs: DataFrame, model: LineModel, text_col: str = "text", keep: list[str] | None = None, out: str = "quality_score") -> DataFrame:
    """``docs`` (columns ``keep``, default all) with a column ``out``, which takes the place of one of that name."""
    names = [c for c in (docs.columns if keep is None else keep) if c.lower() != out.lower()]
    # the text travels once: as one of the kept columns, or behind them
    extra = [] if text_col in names else [text_col]
    src = docs.select(*(F.col(f"`{c}`") for c in [*names, *extra]))
    at = src.columns.index(text_col)
    shipped = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for p in B.pieces(batch, at):
                scores = shipped.value.score(p.column(at))
                yield pa.RecordBatch.from_arrays([*p.columns[: len(names)], pa.array(scores, pa.float64())], [*p.schema.names[: len(names)], out])
        B.trim()

    return src.mapInArrow(run, T.StructType([*src.schema.fields[: len(names)], T.StructField(out, T.DoubleType())]))
