import random
import re

from winjoin.llm.decontam import contamination, decontaminate, digest_of, items_digest

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def words(t):
    return WORD.findall("".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or ""))


def brute(docs, bench, n):
    out = []
    for i, t in docs:
        w, hit, items = words(t), set(), set()
        for item, it in bench:
            v = words(it)
            size = min(n, len(v))
            for a in range(len(v) - size + 1 if size else 0):
                for b in range(len(w) - size + 1):
                    if w[b : b + size] == v[a : a + size]:
                        hit |= set(range(b, b + size))
                        items.add(str(item))
        out.append((i, len(w), len(hit), len(items), digest_of(list(items)), bool(hit)))
    return sorted(out, key=str)


def data():
    rnd = random.Random(2)
    bench = [(k, " ".join(rnd.choice("ab Cé9") + rnd.choice("xy") for _ in range(size))) for k, size in enumerate([14, 4, 10, 11, 3, 25, 2, 0])] + [(3, "dup 1 item"), (8, None), (9, bench_copy := "é8 tA tb"), (10, bench_copy)]
    docs = [(1, None), (2, ""), (3, "no words !!"), (3, "no words !!"), (None, "dup 1 ITEM")]
    for k in range(40):
        t = [rnd.choice("ab Cé9") + rnd.choice("xy") for _ in range(rnd.randint(0, 60))]
        if k % 2:
            at = rnd.randint(0, len(t))
            t[at:at] = (bench[rnd.randrange(len(bench))][1] or "").upper().replace("É", "é").split(" ")
        docs.append((10 + k, rnd.choice([" ", "\n", ", "]).join(t)))
    return docs, bench


def test_against_brute_force(spark):
    docs, bench = data()
    d = spark.createDataFrame([(i, t, "z") for i, t in docs], "doc_id long, text string, item_id string")
    b = spark.createDataFrame(bench, "item_id long, text string")
    for most in (10**6, 40):  # one part, several parts
        got = contamination(d, b, most_windows=most).select("doc_id", "n_words", "n_hit", "items", "contaminated")
        got = got.withColumn("sha", items_digest(got.items)).collect()
        assert sorted(((r.doc_id, r.n_words, r.n_hit, len(r["items"]), r.sha, r.contaminated) for r in got), key=str) == brute(docs, bench, 10)
        kept = decontaminate(d, b, most_windows=most)
        assert kept.columns == d.columns
        assert sorted(map(str, [r.doc_id for r in kept.collect()])) == sorted(str(r[0]) for r in brute(docs, bench, 10) if not r[5])


def test_spans_go_and_the_rest_stays(spark):
    d = spark.createDataFrame([(1, "Keep, this. ONE two; three! and that.", 5)], "doc_id long, text string, x int")
    b = spark.createDataFrame([(1, "one two three")], "item_id long, text string")
    r = decontaminate(d, b, remove="spans").first()
    assert (r.text, r.x) == ("Keep, this. ! and that.", 5)


def test_empty_tables(spark):
    docs, bench = data()
    d = spark.createDataFrame(docs, "doc_id long, text string")
    b = spark.createDataFrame(bench, "item_id long, text string")
    assert contamination(d.limit(0), b).collect() == []
    assert contamination(d, b.limit(0)).where("contaminated").collect() == []


def test_query_equals_sql(spark):
    import duckdb

    from winjoin.llm.queries import ORACLE_SQL, op4_decontamination

    con = duckdb.connect()
    for name in ("documents", "benchmark"):
        con.sql(f"CREATE VIEW {name} AS SELECT * FROM '/root/testdata/sf0.01/{name}.parquet'")
    want = con.sql(ORACLE_SQL["op4_decontamination"])
    got = op4_decontamination(spark, "/root/testdata/sf0.01")
    assert got.columns == want.columns
    assert sorted(map(tuple, got.collect())) == sorted(want.fetchall()) and any(r[2] for r in want.fetchall())
