import random

import public_tokenizers
import sentencepiece as spm

from winjoin.llm.token_resync import Resync, token_counts

PATH = public_tokenizers.path("piece_bpe_32k.model")


def test_splices_are_exact():
    with open(PATH, "rb") as f:
        codec = Resync(f.read())
    assert codec.spliceable
    rnd = random.Random(5)
    texts = ["a" * 3000, "é" * 2000, "x " * 1500, " " * 2500, "\n" * 1200, "日本語" * 800, "ab" * 900 + " " + "c" * 900]
    texts += ["".join(rnd.choice(alphabet) for _ in range(3000)) for alphabet in ("ab ", "theand ,\n", "▁ é", "abcdefgh")]
    for chunk, overlap in ((64, 4), (257, 5), (1000, 64)):
        for t in texts:
            assert codec.count(t, chunk, overlap) == len(codec.codec.encode(t)), (chunk, overlap, t[:20])


def test_rows(spark):
    library = spm.SentencePieceProcessor(model_file=PATH)
    rows = [(1, "hello  wörld"), (1, "hello  wörld"), (2, None), (3, ""), (None, "x"), (4, "the cat " * 5000), (5, "<s> special </s>")]
    docs = spark.createDataFrame([(i, t, 7) for i, t in rows], "doc_id long, text string, n_bytes int")
    got = sorted((tuple(r) for r in token_counts(docs, PATH, chunk_chars=1000, overlap=16).collect()), key=str)
    want = [(i, len((t or "").encode()), n := len(library.encode(t or "")), n > 4096) for i, t in rows]
    assert got == sorted(want, key=str)
    assert token_counts(docs.limit(0), PATH).collect() == []
