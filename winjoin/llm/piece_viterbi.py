"""SentencePiece encoding and decoding with an Aho-Corasick automaton and a single-pass Viterbi.

All normal pieces of a vocabulary file stand in one automaton. Reading a text
once, each position follows the output links of the automaton's state, longest
piece first, and relaxes the best score of the position; only a strictly
better score replaces one, so among equal scores the longest last piece wins.
A character that no one-character piece covers may be taken at the score of
the worst piece less ten; it becomes its UTF-8 byte pieces.

No piece holds a blank behind another character, which is read off the
vocabulary and else makes the whole text one segment. Segments (blanks, then
what follows up to the next blank) therefore have separate best paths, and a
worker keeps the paths of segments it has met, up to a fixed number.

Edge cases: null and empty texts have no pieces and decode to the empty text;
repeated rows are encoded each; other columns are ignored.
"""

from __future__ import annotations

import re
from array import array
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from winjoin.llm import bytetext as B
from winjoin.llm.frames import text_of
from winjoin.llm.token_resync import read_model

NORMAL, UNKNOWN, BYTE = 1, 2, 6


class PieceCodec:
    """Best-scoring segmentation by the pieces and scores of a vocabulary file."""

    def __init__(self, model: bytes, remember: int = 120_000):
        import ahocorasick
        from sentencepiece import sentencepiece_model_pb2 as pb

        proto = pb.ModelProto()
        proto.ParseFromString(model)
        if proto.normalizer_spec.precompiled_charsmap or proto.normalizer_spec.remove_extra_whitespaces:
            raise ValueError("only vocabularies without text normalisation round-trip")
        self.dummy = proto.normalizer_spec.add_dummy_prefix
        self.pieces = [p.piece for p in proto.pieces]
        self.kinds = [p.type for p in proto.pieces]
        normal = [(i, p) for i, p in enumerate(proto.pieces) if p.type == NORMAL]
        #: Text of a piece; None for bytes and the unknown piece, which need their neighbours or a mark; control pieces have none.
        self.surface = [None if p.type in (BYTE, UNKNOWN) else p.piece if p.type == NORMAL else "" for p in proto.pieces]
        self.floor = min(p.score for _, p in normal) - 10.0
        self.single = {p.piece for _, p in normal if len(p.piece) == 1}
        self.bytes = {int(p.piece[3:5], 16): i for i, p in enumerate(proto.pieces) if p.type == BYTE}
        self.unknown = next(i for i, p in enumerate(proto.pieces) if p.type == UNKNOWN)
        self.separable = not any("▁" in p.piece.lstrip("▁") for _, p in normal)
        self.automaton = ahocorasick.Automaton()
        for i, p in normal:
            self.automaton.add_word(p.piece, (len(p.piece), p.score, i))
        self.automaton.make_automaton()
        self.remember = remember
        #: Paths of segments: those met lately, and those met before, which go when the first are many.
        self.paths: dict[str, tuple[bytes, float]] = {}
        self.older: dict[str, tuple[bytes, float]] = {}
        # line ends and tabs that no piece holds are segments of their own
        alone = "".join(c for c in "\n\t\r" if not any(c in p.piece for _, p in normal))
        self.cut = re.compile(f"▁*[^▁{alone}]+|[{alone}]|▁+" if alone else "▁*[^▁]+|▁+")

    def best_path(self, segment: str) -> tuple[list[int], float]:
        """Piece ids and score of the best path through one segment (blanks as ▁)."""
        n = len(segment)
        score = [0.0] + [-np.inf] * n
        begin = [0] * (n + 1)
        taken = [-1] * (n + 1)  # piece of the best path that ends here; -1: one character by itself
        # ends up to here are settled; if every character is a piece, each end is that of a match
        reached = n if self.single.issuperset(segment) else 0

        def by_character(upto: int) -> None:
            nonlocal reached
            while reached < upto:
                reached += 1
                if segment[reached - 1] not in self.single and score[reached - 1] + self.floor > score[reached]:
                    score[reached], begin[reached], taken[reached] = score[reached - 1] + self.floor, reached - 1, -1

        for last, (length, worth, piece) in self.automaton.iter(segment):
            if reached < last:
                by_character(last)  # all positions before this end
            end = last + 1
            total = score[end - length] + worth
            if total > score[end]:
                score[end] = total
                begin[end] = end - length
                taken[end] = piece
        by_character(n)
        ids: list[int] = []
        at = n
        while at:
            start, piece = begin[at], taken[at]
            if piece >= 0:
                ids.append(piece)
            elif self.bytes:
                ids.extend(self.bytes[b] for b in reversed(segment[start:at].encode("utf-8", "surrogatepass")))
            else:
                ids.append(self.unknown)
            at = start
        return ids[::-1], score[n]

    def encode(self, text: str) -> tuple[bytes, float]:
        """Piece ids (as 32-bit integers) and total score of a whole text."""
        if not text:
            return b"", 0.0
        text = text.replace(" ", "▁")
        if self.dummy:
            text = "▁" + text
        if not self.separable:
            return self._path(text)
        known = self.paths
        segments = self.cut.findall(text)
        paths = [known.get(x) for x in segments]
        if None in paths:
            paths = [p or self._path(x) for p, x in zip(paths, segments)]
        return b"".join([p[0] for p in paths]), sum([p[1] for p in paths])

    def _path(self, segment: str) -> tuple[bytes, float]:
        """The best path of a segment, which short segments leave for the next time."""
        path = self.paths.get(segment) or self.older.get(segment)
        if path is None:
            ids, score = self.best_path(segment)
            path = array("i", ids).tobytes(), score
        if len(segment) <= 64:
            if len(self.paths) >= self.remember:
                self.older, self.paths = self.paths, {}
            self.paths[segment] = path
        return path

    def forget(self) -> None:
        """Drop the older generation of paths."""
        self.older = {}

    def decode(self, ids: list[int]) -> str:
        """The text of piece ids."""
        surface = self.surface
        if (plain := [surface[i] for i in ids]).count(None) == 0:
            text = "".join(plain).replace("▁", " ")
            return text[1:] if self.dummy and text[:1] == " " else text
        out, run = [], bytearray()
        for i in ids:
            if self.kinds[i] == BYTE:
                run.append(int(self.pieces[i][3:5], 16))
                continue
            if run:
                out.append(run.decode("utf-8", "replace"))
                run = bytearray()
            if self.kinds[i] == NORMAL:
                out.append(self.pieces[i])
            elif self.kinds[i] == UNKNOWN:
                out.append(" ⁇ ")
        if run:
            out.append(run.decode("utf-8", "replace"))
        text = "".join(out).replace("▁", " ")
        return text[1:] if self.dummy and text[:1] == " " else text


@lru_cache(maxsize=2)
def _codec(model: bytes) -> PieceCodec:
    return PieceCodec(model)


def piece_encode(docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text", decoded: bool = False) -> DataFrame:
    """Rows (doc_id, piece_ids, n_pieces, path_score), one for each row of ``docs``; with ``decoded`` also text, decoded from the ids in the same pass."""
    src = text_of(docs, id_col, text_col)
    shipped = docs.sparkSession.sparkContext.broadcast(read_model(model_path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = _codec(shipped.value)
        for batch in batches:
            for a in range(0, batch.num_rows, 500):  # ids of few rows at a time
                part = batch.slice(a, 500)
                flat, sizes, scores = [], [], []
                for text in part.column(1).to_pylist():
                    ids, score = codec.encode(text)
                    flat.append(ids)
                    sizes.append(len(ids) // 4)
                    scores.append(score)
                offsets = np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32)
                lists = pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.frombuffer(b"".join(flat), np.int32)))
                columns = [part.column(0), lists, pa.array(sizes, pa.int64()), pa.array(scores, pa.float64())]
                if decoded:
                    columns.append(pa.array([codec.decode(np.frombuffer(ids, np.int32).tolist()) for ids in flat], pa.string()))
                yield pa.RecordBatch.from_arrays(columns, names[: len(columns)])
        codec.forget()
        B.trim()

    names = ["doc_id", "piece_ids", "n_pieces", "path_score", "text"]
    kind = src.schema["doc_id"].dataType.simpleString()
    return src.mapInArrow(run, f"doc_id {kind}, piece_ids array<int>, n_pieces long, path_score double" + ", text string" * decoded)


def piece_decode(encoded: DataFrame, model_path: str, ids_col: str = "piece_ids", text_col: str = "text") -> DataFrame:
    """``encoded`` (all columns) with ``text_col``, the texts of lists of piece ids (null: empty); it takes the place of a column of that name."""
    encoded = encoded.select(*(F.col(f"`{c}`") for c in encoded.columns if c.lower() != text_col.lower()))
    shipped = encoded.sparkSession.sparkContext.broadcast(read_model(model_path))
    at = encoded.columns.index(ids_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = _codec(shipped.value)
        for batch in batches:
            for a in range(0, batch.num_rows, 500):
                part = batch.slice(a, 500)
                texts = [codec.decode(ids or []) for ids in part.column(at).to_pylist()]
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(texts, pa.string())], [*part.schema.names, text_col])

    return encoded.mapInArrow(run, T.StructType([*encoded.schema.fields, T.StructField(text_col, T.StringType())]))
