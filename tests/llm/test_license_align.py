import random

from winjoin.llm.license_align import TEMPLATES, _increasing, align, license_scan


def lcs(a, b):
    row = [0] * (len(b) + 1)
    for x in a:
        prev = row[:]
        for j, y in enumerate(b):
            row[j + 1] = prev[j] + 1 if x == y else max(prev[j + 1], row[j])
    return row[-1]


def test_alignment_is_common_and_close_to_the_longest():
    rnd = random.Random(2)
    for _ in range(200):
        template = [rnd.randrange(30) for _ in range(25)]
        text = [rnd.randrange(-5, 60) for _ in range(10)] + [w for w in template if rnd.random() < 0.9] + [rnd.randrange(-5, 60) for _ in range(10)]
        pairs = align(text, template)
        assert all(text[p] == template[q] for p, q in pairs)
        assert all(p < r and q < s for (p, q), (r, s) in zip(pairs, pairs[1:]))
        assert len(pairs) <= lcs(text, template)
    assert align([1, 2, 3], [1, 2, 3]) == [(0, 0), (1, 1), (2, 2)]
    assert align([7, 7, 7], [7, 7, 7]) == [(0, 0), (1, 1), (2, 2)]


def test_increasing():
    for values in ([3, 1, 2, 5, 4], [], [1], [2, 2, 1], list(range(9))):
        got = [values[k] for k in _increasing(values)]
        assert got == sorted(set(got))
        best = max((bin(m).count("1") for m in range(1 << len(values)) if (s := [v for k, v in enumerate(values) if m >> k & 1]) == sorted(set(s))), default=0)
        assert len(got) == best


def test_occurrences(spark):
    rnd = random.Random(4)
    filler = lambda n: " ".join(rnd.choice(["the", "of", "and", "to", "is", "under", "be", "en", "x%d" % rnd.randrange(99)]) for _ in range(n))
    mit = TEMPLATES["MIT-text"].split(" ")
    edited = " ".join(w for k, w in enumerate(mit) if k % 9)
    rows = [
        (1, filler(3000) + "\n" + TEMPLATES["Apache-2.0"] + "\n" + filler(3000)),
        (2, filler(500) + " " + TEMPLATES["MIT-text"].upper() + " " + filler(800) + " " + edited + filler(100)),
        (3, "\n".join([TEMPLATES["MIT"]] * 3)),
        (4, filler(5000)), (5, None), (6, ""), (7, "..."), (8, "Licensed under nothing"), (None, "Été: Released under the MIT License."),
        (3, "\n".join([TEMPLATES["MIT"]] * 3)),
    ]
    docs = spark.createDataFrame([(i, t, "q") for i, t in rows], "doc_id long, text string, license string")
    got = license_scan(docs).collect()
    by = {}
    for r in got:
        by.setdefault(r.doc_id, []).append((r.license, r.coverage))
    assert by[1] == [("Apache-2.0", 1.0)]
    assert [n for n, _ in sorted(by[2])] == ["MIT-text"] * 2 and max(c for _, c in by[2]) == 1.0
    assert by[3] == [("MIT", 1.0)] * 6
    assert by[None] == [("MIT", 1.0)] and not {4, 5, 6, 7, 8} & by.keys()
    texts = dict(rows)
    for r in got:
        cut = texts[r.doc_id].encode()[r.start : r.end].decode()
        assert cut.split(" ")[0].lower() in TEMPLATES[r.license].lower()
    assert license_scan(docs, {}).collect() == [] and license_scan(docs.limit(0)).collect() == []
