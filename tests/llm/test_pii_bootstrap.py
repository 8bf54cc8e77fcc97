import hashlib
import random
import re

import pytest

from winjoin.llm.pii_bootstrap import KINDS, find_spans, redact, spans_text

FORMS = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def luhn(d):
    return sum(int(c) if i % 2 == 0 else sum(divmod(int(c) * 2, 10)) for i, c in enumerate(reversed(d))) % 10 == 0


def ok(kind, m):
    d = re.sub("[^0-9]", "", m)
    if kind == "ip":
        return all(int(p) <= 255 for p in m.split("."))
    return kind == "email" or kind == "card" and 16 <= len(d) <= 19 and luhn(d) or kind == "phone" and 8 <= len(d) <= 15


def base(t):
    return [f"{k}:{m.start()}:{m.end()}" for k in KINDS for m in re.finditer(FORMS[k], t or "") if ok(k, m.group())]


def rows_of():
    rnd = random.Random(12)
    alphabet = ["a@b.c", "@", ".", "1", "255", "256", "0", "+1 (504) 555-2652", "4539 1488 0343 6467", "4539-1488-0343-6468", " ", " ", "é", "😀", "\n", "x_y%z", "-", "10.0.0.1", "c.d", "(", ")"]
    rows = [(i, "".join(rnd.choice(alphabet) for _ in range(rnd.randint(0, 25)))) for i in range(400)]
    return rows + [(900, None), (901, ""), (902, "a@b.c-d.e_f@g.h"), (902, "a@b.c-d.e_f@g.h"), (None, "1.2.3.4.5.6.7.8"), (903, "00000000000000000001.2.3.0255"), (904, "+" * 50 + "1" * 30)]


def test_base_spans_against_python(spark):
    rows = rows_of()
    docs = spark.createDataFrame([(i, t, "k") for i, t in rows], "doc_id long, text string, kind string").repartition(4)
    got = find_spans(docs).selectExpr("doc_id", "filter(spans, s -> s.base) AS b").select("doc_id", spans_text("b").alias("b")).collect()
    assert sorted(((r.doc_id, r.b) for r in got), key=str) == sorted(((i, ",".join(base(t))) for i, t in rows), key=str)


def test_patterns_reach_unseen_identifiers(spark):
    rnd = random.Random(1)
    word = lambda: "".join(rnd.choice("abcdefg") for _ in range(5))
    rows = []
    for i in range(40):
        secret = hashlib.sha1(str(i).encode()).hexdigest()
        rows.append((i, f'{word()} {word()} token = "{secret}" {word()}'))
        rows.append((100 + i, f"{word()} call us: +1 (504) 555-{2000 + i} {word()}"))
    rows.append((500, 'so token = "XK-77-REST-0099-ab" ends'))  # no form knows it
    rows.append((501, "now call us: 504-5552-999 please"))
    rows.append((502, "model name Widget-2000-extra is fine"))
    rows.append((503, "again XK-77-REST-0099-ab elsewhere"))
    got = {r.doc_id: r for r in find_spans(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    span = lambda i: [(s.kind, dict(rows)[i][s.start : s.end]) for s in got[i].spans]
    assert span(500) == [("secret", "XK-77-REST-0099-ab")] and span(503) == [("secret", "XK-77-REST-0099-ab")]
    assert span(501) == [("phone", "504-5552-999")]
    assert span(502) == [] and span(3) == [("secret", hashlib.sha1(b"3").hexdigest())]


def test_redaction(spark):
    rows = [(1, "mail a@b.co now 😀 10.0.0.1!", 3), (2, "clean", 4), (3, None, 5)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, x int")
    got = redact(docs).orderBy("doc_id").collect()
    assert [tuple(r) for r in got] == [(1, "mail [EMAIL] now 😀 [IP]!", 3), (2, "clean", 4), (3, None, 5)]
    assert redact(docs.limit(0)).collect() == [] and redact(docs).columns == docs.columns
    plan = find_spans(docs)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan


def test_long_chains_of_patterns_are_followed_to_their_end(spark):
    names = ["alpha", "beta", "gamma", "delta", "epsilon", "zeta"]
    ids = [[hashlib.sha1(str(i).encode()).hexdigest() for i in range(9)]] + [[f"ID-{k}{i:02d}-zzq" for i in range(9)] for k in range(1, 6)]
    # the strings of a level stand behind its own name and behind the one before it
    texts = [f"{names[j]} {m}" for k, level in enumerate(ids) for m in level for j in {k, max(k - 1, 0)}]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {r.doc_id: [(s.kind, texts[r.doc_id][s.start : s.end]) for s in r.spans] for r in find_spans(docs).collect()}
    assert all(got[i] == [("secret", t.split()[1])] for i, t in enumerate(texts))
    with pytest.raises(RuntimeError, match="did not settle"):
        find_spans(docs, rounds=3)


def test_groups_right_contexts_and_long_tokens(spark):
    rnd = random.Random(3)
    word = lambda: "".join(rnd.choice("abcdefg") for _ in range(5))
    long = "q" * 500
    rows = [(i, f"{word()} {word()} +1 (504) 555-{2000 + i} is my number {word()}") for i in range(30)]
    rows += [(100 + i, f"{word()} {long} {hashlib.sha1(str(i).encode()).hexdigest()} {word()}") for i in range(30)]
    rows += [(200 + i, f"order {rnd.randrange(10**7, 10**8)} shipped to {word()}") for i in range(30)]
    rows += [(500, "now (0171) 555 2000 is my number"), (501, f"so {long} key-of-mine-without-any-digit-for-a-long-long-while-but-then-77 end"), (502, "order 0044 555 2000 shipped")]
    got = {r.doc_id: r for r in find_spans(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    span = lambda i: [(s.kind, dict(rows)[i][s.start : s.end]) for s in got[i].spans]
    assert span(500) == [("phone", "(0171) 555 2000")]
    assert span(501) == [("secret", "key-of-mine-without-any-digit-for-a-long-long-while-but-then-77")]
    assert span(502) == [] and span(200) == []


def test_rounds_label_strings_of_the_given_documents(spark):
    """A third of the labelled kinds' strings hidden from the forms: patterns give most of the secrets back."""
    from winjoin.llm import pii_bootstrap as P

    found = P.instances(spark.read.parquet("/root/testdata/sf0.1/documents.parquet")).cache()
    hide = "m rlike '^[0-9a-f]{40}$' AND crc32(m) % 3 = 0"
    masked = found.selectExpr("rid", "doc_id", "text_hash", "kind", "start", "end", f"CASE WHEN {hide} THEN concat('x-', substring(m, 1, 12), '-z9') ELSE m END AS m", "left", "right", "base")
    n = masked.where("m LIKE 'x-%-z9'").select("m").distinct().count()
    got = P.bootstrap(masked).where("m LIKE 'x-%-z9' AND label = 'secret' AND round > 0").count()
    assert n > 20 and got == n
