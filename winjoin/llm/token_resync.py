"""Token counts of whole texts, huge ones by overlapping chunks that are spliced exactly.

Short texts are encoded whole. A text above ``chunk_chars`` is encoded in
chunks that overlap; two neighbouring encodings are joined at a *stable*
boundary inside the overlap. A boundary between characters x and y is stable
if no piece of the vocabulary contains x directly followed by y: a merge over
it would have to build such a piece, so what stands left of it and what stands
right of it are encoded independently whatever surrounds them. Both encodings
therefore show a token boundary there, which is checked with their offsets.
If the overlap holds no stable boundary it is doubled, up to the whole rest of
the text, which is then encoded in one go. The count is always that of the
whole text. Vocabularies for which this cannot be proven (no merges, text
normalisation, user-defined pieces) have every text encoded in one go.

Edge cases: null and empty texts have 0 bytes and 0 tokens; repeated rows are
counted each; other columns are ignored; an empty table gives an empty result.
Null ids are kept.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from winjoin.llm import bytetext as B
from winjoin.llm.frames import text_of

SCHEMA = "doc_id {id}, n_bytes long, n_tokens long, over_limit boolean"


class Resync:
    """A sentencepiece BPE model with its stable boundaries."""

    def __init__(self, model: bytes):
        import sentencepiece as spm
        from sentencepiece import sentencepiece_model_pb2 as pb

        proto = pb.ModelProto()
        proto.ParseFromString(model)
        spec = proto.normalizer_spec
        #: Splicing needs the text to reach the merges unchanged but for blanks.
        self.spliceable = proto.trainer_spec.model_type == 2 and not spec.precompiled_charsmap and not spec.remove_extra_whitespaces and spec.escape_whitespaces and not proto.trainer_spec.treat_whitespace_as_suffix and not any(p.type == 4 for p in proto.pieces)
        self.dummy = spec.add_dummy_prefix
        self.codec = spm.SentencePieceProcessor(model_proto=model)
        kinds = {1, 4}  # normal and user-defined pieces are the ones merges build
        self.joined = {a + b for p in proto.pieces if p.type in kinds for a, b in zip(p.piece, p.piece[1:])}

    def stable(self, text: str, at: int) -> bool:
        pair = text[at - 1 : at + 1].replace(" ", "▁")
        return pair not in self.joined

    def starts(self, chunk: str) -> np.ndarray:
        """Character offsets at which the tokens of a chunk begin."""
        proto = self.codec.encode(chunk, return_type="proto")
        at = np.fromiter((p.begin for p in proto.pieces), np.int64, len(proto.pieces))
        if not chunk.isascii():  # the library counts bytes
            size = np.fromiter((len(c.encode("utf-8", "surrogatepass")) for c in chunk), np.int64, len(chunk))
            at = np.searchsorted(np.concatenate([[0], np.cumsum(size)]), at)
        return at

    def count(self, text: str, chunk_chars: int, overlap: int) -> int:
        """Tokens of the whole text."""
        if len(text) <= chunk_chars or not self.spliceable:
            return len(self.codec.encode(text))
        total, begin, splice, wide, left = 0, 0, 0, overlap, None
        while True:
            end = min(len(text), begin + max(chunk_chars, 2 * wide))
            if left is None:
                left = self.starts(text[begin:end])
            if end == len(text):
                return total + int((left >= splice - begin).sum() if splice else len(left))
            nxt = max(splice, begin, end - wide)
            stop = min(len(text), nxt + max(chunk_chars, 2 * wide))
            right = self.starts(text[nxt:stop])
            at = self._common(text, begin, end, left, nxt, right)
            if at is None:
                # no proven boundary in the overlap: widen it; once the chunk itself must grow, encode it anew
                wide *= 2
                if 2 * wide > chunk_chars:
                    left = None
                continue
            total += int(((left < at - begin) & (left >= splice - begin)).sum() if splice else (left < at - begin).sum())
            splice, begin, left, wide = at, nxt, right, overlap
            if stop - begin != min(len(text) - begin, max(chunk_chars, 2 * wide)):
                left = None

    def _common(self, text: str, begin: int, end: int, left: np.ndarray, nxt: int, right: np.ndarray) -> int | None:
        """The last stable boundary of the overlap at which both encodings begin a token."""
        shared = np.intersect1d(left + begin, right + nxt, assume_unique=False)
        for at in shared[(shared > nxt) & (shared < end)][::-1].tolist():
            if self.stable(text, at):
                return at
        return None


@lru_cache(maxsize=2)
def _resync(model: bytes) -> Resync:
    return Resync(model)


def read_model(path: str, most_mb: int = 64) -> bytes:
    """A vocabulary file as bytes; its size is checked before it is broadcast."""
    with open(path, "rb") as f:
        data = f.read((most_mb << 20) + 1)
    if len(data) > most_mb << 20:
        raise ValueError(f"{path} is larger than {most_mb} MB")
    return data


def token_counts(docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text", limit: int = 4096, chunk_chars: int = 16384, overlap: int = 128) -> DataFrame:
    """Rows (doc_id, n_bytes, n_tokens, over_limit), one for each row of ``docs``."""
    src = text_of(docs, id_col, text_col)
    shipped = docs.sparkSession.sparkContext.broadcast(read_model(model_path))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codec = _resync(shipped.value)
        for batch in (p for b in batches for p in B.pieces(b, 1, 8 << 20)):
            texts = batch.column(1).to_pylist()
            counts = np.zeros(len(texts), np.int64)
            short = [i for i, t in enumerate(texts) if len(t) <= chunk_chars]
            for a in range(0, len(short), 256):
                part = short[a : a + 256]
                counts[part] = [len(x) for x in codec.codec.encode([texts[i] for i in part], num_threads=1)]
            for i, t in enumerate(texts):
                if len(t) > chunk_chars:
                    counts[i] = codec.count(t, chunk_chars, overlap)
            sizes = pc.binary_length(batch.column(1)).cast(pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), sizes, pa.array(counts), pa.array(counts > limit)], ["doc_id", "n_bytes", "n_tokens", "over_limit"])

    return src.mapInArrow(run, SCHEMA.format(id=src.schema["doc_id"].dataType.simpleString()))
