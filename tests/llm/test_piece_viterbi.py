import numpy as np
import public_tokenizers
import pytest

from winjoin.llm.piece_viterbi import PieceCodec, piece_decode, piece_encode

PATH = public_tokenizers.path("piece_bpe_32k.model")
CASES = ["", " ", "a", "hello world", "  two  blanks ", "line\nbreak\ttab", "日本語テキスト", "é́", "▁x", "the " * 50, "x" * 300, "\x00", "mixed ÄÖÜ ñandú 12345 !!"]


@pytest.fixture(scope="module")
def codec():
    with open(PATH, "rb") as f:
        return PieceCodec(f.read())


def test_score_against_brute_force(codec):
    worth = {p: s for _, (_, s, i) in codec.automaton.items() for p in [codec.pieces[i]]}

    def brute(segment):
        best = [0.0] + [float("-inf")] * len(segment)
        for end in range(1, len(segment) + 1):
            for start in range(end):
                s = worth.get(segment[start:end])
                if s is None and end - start == 1:
                    s = codec.floor
                if s is not None:
                    best[end] = max(best[end], best[start] + s)
        return best[-1]

    for t in CASES[1:]:
        assert codec.encode(t)[1] == brute("▁" + t.replace(" ", "▁"))


def test_segments_equal_the_undivided_text(codec):
    for t in CASES[1:]:
        ids, score = codec.best_path("▁" + t.replace(" ", "▁"))
        assert (np.frombuffer(codec.encode(t)[0], np.int32).tolist(), codec.encode(t)[1]) == (ids, score)


def test_round_trip(spark):
    rows = [(i, t, "x") for i, t in enumerate(CASES)] + [(99, None, None), (1, " ", None), (None, "a", None)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, piece_ids string")
    enc = piece_encode(docs, PATH)
    dec = piece_decode(enc, PATH).collect()
    want = sorted(((i, t or "") for i, t, _ in rows), key=str)
    assert sorted(((r.doc_id, r.text) for r in dec), key=str) == sorted(((i, t.replace("▁", " ")) for i, t in want), key=str)
    assert all(len(r.piece_ids) == r.n_pieces for r in enc.collect())
    assert piece_encode(docs.limit(0), PATH).collect() == []
