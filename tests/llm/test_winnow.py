import hashlib
import random

from pyspark.sql import functions as F

from winjoin.llm.winnow import WORD, code_point, edited_likeness, fingerprints, with_next


def rows_of(n=150):
    rnd = random.Random(9)
    v = ["".join(rnd.choice("abcdé") for _ in range(rnd.randint(1, 6))) for _ in range(60)]
    rows = [(i * 7, " ".join(rnd.choice(v) for _ in range(rnd.randint(0, 60)))) for i in range(n)]
    return rows + [(10_000, None), (10_001, ""), (10_002, "!?"), (10_003, "日本語" * 30), (10_004, rows[3][1]), (3, "same id"), (3, "same id"), (3, "other")]


def test_edited_texts_and_next(spark):
    rows = rows_of()
    got = edited_likeness(spark.createDataFrame([(i, t, 1) for i, t in rows], "doc_id long, text string, _range int").repartition(5)).collect()
    assert len(got) == len(rows)
    ids = sorted({i for i, _ in rows}, reverse=True)
    texts = {i: t or "" for i, t in rows}
    alone = [i for k, i in enumerate(ids) if 3 not in (i, ids[(k + 1) % len(ids)])]
    by = {r.doc_id: r for r in got}
    for k, i in enumerate(ids):
        if i in alone:
            t, nxt = texts[i], texts[ids[(k + 1) % len(ids)]]
            cut = len(t) // 3
            assert by[i].edited_sha256 == hashlib.sha256((t[: len(t) - cut] + nxt[:cut]).encode()).hexdigest()
            assert by[i].n_chars == len(t)
    assert all(0 <= r.near_edited <= 1 and 0 <= r.near_next <= 1 for r in got)
    assert by[10_004].fingerprint == by[21].fingerprint
    assert by[10_002].fingerprint == "" and by[10_003].fingerprint != ""


def test_selection_against_brute_force(spark):
    k, w = 3, 4
    texts = [(i, t or "") for i, t in rows_of(40)]
    df = spark.createDataFrame(texts, "doc_id long, text string")
    grams = df.select("doc_id", F.transform(F.regexp_extract_all(F.lower("text"), F.lit(WORD), F.lit(0)), lambda x: F.xxhash64(x)).alias("h"))
    # three pieces: a hash of the hash of two and of the third
    grams = grams.select("doc_id", "h", F.when(F.size("h") >= k, F.transform(F.sequence(F.lit(0), F.size("h") - k), lambda i: F.xxhash64(F.xxhash64(F.get("h", i), F.get("h", i + 1)), F.get("h", i + 2)))).alias("g"), F.xxhash64("h").alias("all"))
    want = []
    for r in grams.collect():
        g = [(x >> 32) & 0xFFFFFFFF for x in (r.g if r.g is not None else [r["all"]] if r.h else [])]
        picked = set()
        for a in range(max(1, len(g) - w + 1) if g else 0):
            part = g[a : a + w]
            picked.add(max((a + j for j, x in enumerate(part) if x == min(part))))
        want.append((r.doc_id, tuple(sorted((p, g[p]) for p in picked))))
    got = [(r.doc_id, tuple(sorted(((1 << 31) - 1 - (v & ((1 << 31) - 1)), v >> 31) for v in r.fingerprint))) for r in fingerprints(df, k=k, window=w).collect()]
    assert sorted(got) == sorted(want)


def test_shared_runs_share_a_hash(spark):
    shared = " ".join("s%d" % i for i in range(8))
    df = spark.createDataFrame([(1, "a b c " + shared + " d e"), (2, "x y z q " + shared)], "doc_id long, text string")
    one, two = (set(v >> 31 for v in r.fingerprint) for r in fingerprints(df).orderBy("doc_id").collect())
    assert one & two


def test_one_row_null_ids_and_none(spark):
    one = edited_likeness(spark.createDataFrame([(None, "a b c d e f")], "doc_id long, text string")).collect()
    assert len(one) == 1 and one[0].near_next == 1.0
    assert edited_likeness(spark.createDataFrame([], "doc_id long, text string")).collect() == []


def test_no_python_in_the_plan(spark):
    df = edited_likeness(spark.createDataFrame([(1, "a")], "doc_id long, text string"))
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan


def test_equal_windows_have_equal_grams_for_every_size(spark):
    words = ["w%d" % i for i in range(40)]
    df = spark.createDataFrame([(1, " ".join(words)), (2, "x y " + " ".join(words) + " z")], "doc_id long, text string")
    for k, w in ((1, 1), (2, 3), (4, 4), (6, 5), (7, 2), (8, 7), (13, 6)):
        one, two = ({v >> 31: (1 << 31) - 1 - (v & ((1 << 31) - 1)) for v in r.fingerprint} for r in fingerprints(df, k=k, window=w).orderBy("doc_id").collect())
        shared = one.keys() & two.keys()
        assert len(shared) >= len(one) - 2 and all(two[h] - one[h] == 2 for h in shared)


def test_positions_lead_to_code_points(spark):
    import re

    text = "É, the longest-word \U0001f600 of 日本語日本語 (all) 12345"
    pieces = [m for m in re.finditer(r"[^\W_]{1,4}", text.lower())]
    df = spark.createDataFrame([(text, i) for i in range(len(pieces))], "text string, i int")
    assert {r.i: r.at for r in df.select("i", code_point(F.col("text"), F.col("i")).alias("at")).collect()} == {i: m.start() for i, m in enumerate(pieces)}


def test_ids_of_other_types_hot_ids_and_many_ranges(spark, monkeypatch):
    from winjoin.llm import winnow

    rows = [(f"d{i:03d}", f"text number {i} of some few words here") for i in range(90)]
    rows += [("d050", "hot id %d" % i) for i in range(60)] + [("d051", "same row")] * 40
    df = spark.createDataFrame(rows, "doc_id string, text string")
    monkeypatch.setattr(winnow, "_GROUP", 4)
    for parts in (1, 64):
        got = with_next(df, least=parts).collect()
        follow = {}
        for r in range(parts):
            own = sorted((x for x in got if x._range == r), key=lambda x: (x._ghost, [-ord(c) for c in x.doc_id], x._tie))
            assert not own or [x._ghost for x in own].count(1) == 1 and own[-1]._ghost == 1
            for a, b in zip(own, own[1:]):
                follow.setdefault((a.doc_id, a.text), []).append((b.doc_id, b.text))
        order = sorted({(x.doc_id, x.text, x._tie) for x in got}, key=lambda x: ([-ord(c) for c in x[0]], x[2]))
        order = [x[:2] for x in order]
        assert sum(map(len, follow.values())) == len(rows)
        for a, b in zip(order, order[1:] + order[:1]):
            assert [x for x in follow[a] if x != a] == [b]
    out = edited_likeness(df).collect()
    assert len(out) == len(rows)
