import re

import corpus_pipeline as C
import public_tokenizers
import pytest
from pyspark.sql import functions as F

from winjoin.llm.decontam import contamination
from winjoin.llm.pii_bootstrap import find_spans
from winjoin.llm.queries import PIECE_MODEL, QUERIES, table

SF = "/root/testdata/sf0.001"


def grams(text):
    w = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (text or "").lower())
    return frozenset(tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))) if w else frozenset()


def test_stages_against_brute_force(spark, tmp_path):
    docs = table(spark, SF, "documents")
    labels = {r.doc_id: r.quality for r in table(spark, SF, "labels").collect()}
    for k, (_, stage) in enumerate(C.STAGES):
        before = {r.doc_id: r.text for r in docs.collect()}
        out = stage(spark, docs, SF)
        out.write.parquet(path := str(tmp_path / str(k)))
        got = spark.read.parquet(path)
        after = {r.doc_id: r.text for r in got.collect()}
        if k < 4:
            assert got.columns == docs.columns
        if k == 0:
            judged = [i for i in before if i in labels]
            assert sum((i in after) == bool(labels[i]) for i in judged) >= 0.97 * len(judged)
        elif k == 1:
            sets = {i: grams(t) for i, t in before.items()}
            root = {i: i for i in before}

            def find(x):
                while root[x] != x:
                    x = root[x]
                return x

            ids = sorted(before)
            for a in ids:
                for b in ids:
                    if b < a and sets[a] and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
                        x, y = sorted((find(a), find(b)))
                        root[y] = x
            assert set(after) == {find(i) for i in ids}
        elif k == 2:
            hit = {r.doc_id for r in contamination(docs, table(spark, SF, "benchmark")).where("contaminated").collect()}
            assert set(after) == set(before) - hit
        elif k == 3:
            assert set(after) == set(before)
            assert not find_spans(got).where("exists(spans, s -> s.base)").collect()
        else:
            assert after == before and all(r.n_pieces == len(r.piece_ids) for r in got.collect())
        docs = got


def test_registry():
    assert [k.split("_")[0] for k in QUERIES] == [f"op{n}" for n in range(1, 11)]


def test_odd_rows_and_empty_tables(spark, tmp_path):
    good = "the quiet river runs below the old stone bridge and nobody counts its many slow turns today"
    rows = [(1, good, "en", "s", 9, "x"), (1, good, "en", "s", 9, "x"), (2, None, None, None, None, None), (None, good + " now", "en", "s", 3, "y"), (3, "", "en", None, 0, ""), (4, "JUNK!! " * 40, "en", "s", 5, "z"), (None, None, None, None, None, None)]
    schema = "doc_id long, text string, lang string, source string, n_chars long, quality_score string"
    labels = [(i, int(i % 3 > 0)) for i in range(60)]
    many = [(i + 10, good + f" {i} " + " ".join(f"w{(i * 7 + k) % 97}" for k in range(30)) if i % 3 else "BAD!! " * (20 + i), "en", "s", 1, "q") for i in range(60)]
    for name, docs in (("some", rows + many), ("none", [])):
        d = f"{tmp_path}/{name}"
        spark.createDataFrame(docs, schema).write.parquet(f"{d}/documents.parquet")
        spark.createDataFrame([(i + 10, q, 0) for i, q in labels], "doc_id long, quality int, toxic int").write.parquet(f"{d}/labels.parquet")
        spark.createDataFrame([(1, "a benchmark item of some ten words that nobody has copied here")] if docs else [], "item_id long, text string").write.parquet(f"{d}/benchmark.parquet")
        got = C.run(spark, d).collect()
        assert bool(got) == bool(docs)
        if docs:
            ids = [r.doc_id for r in got]
            assert ids.count(1) == 1 and 4 not in ids and all(r.n_pieces == len(r.piece_ids) for r in got)
    for d in ("some", "none"):
        spark.createDataFrame([(1, "http://a.b.de/x", f"<html lang='de'><p>{good}</p></html>"), (1, None, None), (None, "", "")] if d == "some" else [], "page_id long, url string, html string").write.parquet(f"{tmp_path}/{d}/pages.parquet")
        assert len(QUERIES["op5_language"](spark, f"{tmp_path}/{d}").collect()) == (3 if d == "some" else 0)
    for name in ("op1_license_scan", "op2_token_counts", "op3_jaccard_join", "op4_decontamination", "op6_piece_encoding", "op7_katz", "op8_quality", "op9_winnowing", "op10_pii"):
        n = len(QUERIES[name](spark, f"{tmp_path}/some").collect())
        assert n == len(rows) + len(many) or name == "op1_license_scan", name
        assert QUERIES[name](spark, f"{tmp_path}/none").collect() == [], name


CLASHES = "n_words n_hit items _n_hit _items _sid _keep_id _keep_sid _spans _text_hash _key quality_score piece_ids n_pieces path_score text_ _range _ghost _tie _row m kind start end base sid sketch root node rid fingerprint held word Part".split()


@pytest.fixture(scope="module")
def clashing(spark):
    """The smallest documents with string ids beside columns of every name that the operators use within."""
    docs = table(spark, SF, "documents").limit(60)
    return docs.select("*", *(F.lit(k).cast("string").alias(c) for k, c in enumerate(CLASHES))).persist()


@pytest.mark.parametrize("k", range(5))
def test_stages_with_clashing_names(spark, clashing, k):
    name, stage = C.STAGES[k]
    want = {r.doc_id for r in stage(spark, table(spark, SF, "documents").limit(60), SF).collect()}
    got = stage(spark, clashing, SF)
    rows = got.collect()
    assert {r.doc_id for r in rows} == want and want
    if k < 4:
        assert got.columns == clashing.columns
        # a classifier's score has a name of its own; what else a row has stays
        assert all(r["n_hit"] == "1" and r["_sid"] == str(CLASHES.index("_sid")) and r["_spans"] == str(CLASHES.index("_spans")) for r in rows)


@pytest.mark.parametrize("name", [n for n in QUERIES if n != "op5_language"])
def test_operators_with_clashing_names_and_string_ids(spark, clashing, tmp_path, name):
    d = str(tmp_path)
    clashing.withColumn("doc_id", F.concat(F.lit("d"), F.col("doc_id"))).write.parquet(f"{d}/documents.parquet")
    table(spark, SF, "benchmark").withColumn("items", F.lit(1)).write.parquet(f"{d}/benchmark.parquet")
    table(spark, SF, "labels").withColumn("doc_id", F.concat(F.lit("d"), F.col("doc_id"))).withColumn("text", F.lit("x")).write.parquet(f"{d}/labels.parquet")
    got = QUERIES[name](spark, d)
    rows = got.collect()
    assert got.schema["doc_id"].dataType.simpleString() == "string"
    assert len(rows) == 60 or name == "op1_license_scan"


def test_outputs_take_the_place_of_columns_of_their_name(spark, clashing):
    from winjoin.llm.line_crf import quality_scores, train
    from winjoin.llm.piece_viterbi import piece_decode, piece_encode

    scored = quality_scores(clashing, train(clashing, table(spark, SF, "labels")))
    assert scored.columns.count("quality_score") == 1 and scored.select("quality_score").dtypes == [("quality_score", "double")]
    coded = piece_encode(clashing, public_tokenizers.path(PIECE_MODEL)).withColumn("text", F.lit("old"))
    back = {r.doc_id: r.text for r in piece_decode(coded, public_tokenizers.path(PIECE_MODEL)).collect()}
    assert back == {r.doc_id: r.text or "" for r in clashing.collect()}
