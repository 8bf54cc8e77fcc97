import math
from collections import defaultdict

import numpy as np
import pyarrow as pa
import pytest

from winjoin.llm import language_fusion as L

EN, DE = "the cat and the dog with this house ", "der hund und die katze mit diesem haus "


def page(text, lang=None):
    return f"<!DOCTYPE html><html{'' if lang is None else f' lang={chr(34)}{lang}{chr(34)}'}><head><script>var der = 'die';</script></head><body><nav>und der</nav><!-- die --><p>{text}</p></body></html>"


PAGES = [
    (1, "http://a.x.de/1", page(DE * 5, "de")), (2, "http://a.x.de/2", page(DE * 5, "en")), (3, "http://a.x.de/3", page("", "de")), (4, "http://b.x.de/", page(DE, None)),
    (5, "https://c.y.com/en", page(EN * 5, "en-US")), (6, "https://c.y.com/2", page(EN * 9, "en")), (7, "https://c.y.com/3", page("", None)), (8, None, None), (9, "", ""), (10, "http://[bad", page(EN, "de")),
    (6, "https://c.y.com/2", page(EN * 9, "en")), (None, "http://a.x.de/1", page(DE * 5, "de")),
]


def test_pieces():
    assert L.address("https://Www.News.example.org:80/x?y") == ("www.news.example.org", "example.org", "org")
    assert L.address(None) == ("", "", "")
    assert L.declared_code("<html class=a lang='pt-BR'>") == "pt" and L.declared_code("<p>") == ""
    assert L.visible_text(page("a &amp; b")).split() == ["a", "&", "b"]
    b, first = L.trigram_buckets(pa.array(["abcd", None, "ab", "xyz", "a   b"]))
    assert list(np.diff(np.append(first[:-1], len(b)))) == [2, 0, 0, 1, 1]


def test_fusion_against_python(spark):
    texts = spark.createDataFrame([("en", EN * 20, 1), ("de", DE * 20, 2), (None, "zzz", 3), ("en", None, 4)], "lang string, text string, host int")
    pages = spark.createDataFrame([(*p, "x") for p in PAGES], "page_id long, url string, html string, lang string").repartition(3)
    langs, table = L.train_text(texts)
    assert langs == ["de", "en"] and np.allclose(np.exp(table).sum(axis=1), 1)
    ev = L.text_evidence(pages, langs, table).collect()
    t = []
    for r in ev:
        e = [math.exp(x) for x in r.ll]
        t.append([x / sum(e) for x in e])
    g, s, d, h, c = [sum(x[i] for x in t) for i in (0, 1)], defaultdict(lambda: [0, 0]), defaultdict(lambda: [0, 0]), defaultdict(lambda: [0, 0]), defaultdict(lambda: [0, 0])
    for r, x in zip(ev, t):
        for box, k in ((s, r.suffix), (d, r.domain), (h, r.host), (c, r.declared)):
            box[k] = [box[k][i] + x[i] for i in (0, 1)]
    smooth = lambda n, p: [(n[i] + 4 * p[i]) / (sum(n) + 4) for i in (0, 1)]
    base = [(g[i] + 0.5) / (sum(g) + 1) for i in (0, 1)]
    want = []
    for r, x in zip(ev, t):
        pd = smooth(d[r.domain], smooth(s[r.suffix], base))
        ph = smooth([max(h[r.host][i] - x[i], 0) for i in (0, 1)], pd)
        pc = [(c[r.declared][i] + 4 * sum(c[r.declared]) / sum(g)) / (g[i] + 4) for i in (0, 1)]
        z = [x[i] * ph[i] / sum(ph) * pc[i] for i in (0, 1)]
        z = [v / sum(z) for v in z]
        want.append((r.page_id, "de" if z[0] >= z[1] else "en", max(z)))
    got = [(r.page_id, r.lang, r.probability) for r in L.page_languages(pages, texts).collect()]
    for a, b in zip(sorted(got, key=str), sorted(want, key=str)):
        assert a[:2] == b[:2] and a[2] == pytest.approx(b[2])
    by = {i: lang for i, lang, _ in got}
    assert [by[i] for i in (1, 2, 3, 5, 6, 7)] == ["de", "de", "de", "en", "en", "en"]


def test_no_texts_and_no_pages(spark):
    pages = spark.createDataFrame(PAGES, "page_id long, url string, html string")
    none = spark.createDataFrame([], "lang string, text string")
    got = L.page_languages(pages, none).collect()
    assert len(got) == len(PAGES) and all(r.lang is None and r.probability == 0 for r in got)
    texts = spark.createDataFrame([("en", EN)], "lang string, text string")
    assert L.page_languages(pages.limit(0), texts).collect() == []
    assert all(r.lang == "en" for r in L.page_languages(pages, texts).collect())
