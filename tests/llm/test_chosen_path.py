import random
import re
from collections import Counter

import pytest

from winjoin.llm.chosen_path import keep_one_of_each, runs_for, similarity_classes

WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def grams(text):
    w = WORD.findall((text or "").lower())
    return frozenset(tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))) if w else frozenset()


def brute(rows, least=0.8):
    """n_links by row, and components by least id, over all pairs."""
    sets = [grams(t) for _, t in rows]
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    links = [0] * len(rows)
    for a in range(len(rows)):
        for b in range(a):
            if sets[a] and sets[b] and len(sets[a] & sets[b]) >= least * len(sets[a] | sets[b]):
                links[a] += 1
                links[b] += 1
                root[find(a)] = find(b)
    low = {}
    for k, (i, _) in enumerate(rows):
        if sets[k] and i is not None:
            low[find(k)] = min(i, low.get(find(k), i))
    return [(i, low.get(find(k)) if sets[k] else i, links[k]) for k, (i, _) in enumerate(rows)]


def corpus():
    rnd = random.Random(8)
    vocabulary = ["w%d" % k for k in range(400)]
    rows = [(-1, None), (-2, ""), (-3, "!!!"), (-4, "one two"), (-5, "One TWO"), (-6, "two one"), (None, "one two"), (None, None)]
    i = 0
    for size, near in [(60, 3), (80, 0), (40, 6), (200, 2), (7, 3), (90, 120), (30, 1)] * 2:
        base = [rnd.choice(vocabulary) for _ in range(size)]
        rows.append((i, " ".join(base)))
        for _ in range(near):
            i += 1
            w = list(base)
            for _ in range(rnd.randint(0, max(1, size // 40))):
                w[rnd.randrange(size)] = rnd.choice(vocabulary)
            rows.append((i, " ".join(w)))
        i += 1
    for _ in range(60):
        rows.append((i, " ".join(rnd.choice(vocabulary) for _ in range(rnd.randint(1, 120)))))
        i += 1
    return rows + rows[20:24]


@pytest.mark.parametrize("options", [{}, {"bucket": 4, "block": 7, "max_depth": 6}])
def test_against_all_pairs(spark, options):
    rows = corpus()
    docs = spark.createDataFrame([(i, t, 1) for i, t in rows], "doc_id long, text string, sid int")
    got = similarity_classes(docs, **options).select("doc_id", "class_id", "n_links").collect()
    assert Counter(map(tuple, got)) == Counter(brute(rows))


def test_one_of_each_stays(spark):
    rows = corpus()
    docs = spark.createDataFrame([(i, t, 1) for i, t in rows], "doc_id long, text string, sid int")
    kept = keep_one_of_each(docs)
    assert kept.columns == docs.columns
    want = {(c, "") if t else (i, t) for (i, c, _), (_, t) in zip(brute(rows), [(r, grams(r[1]) and "x") for r in rows])}
    ids = Counter(r.doc_id for r in kept.collect())
    classes = {c for (_, c, _), (_, t) in zip(brute(rows), rows) if grams(t)}
    blanks = {i for i, t in rows if not grams(t)}
    assert want and ids == Counter(list(classes | {b for b in blanks if b is not None}) + [None])


def test_empty_and_runs(spark):
    docs = spark.createDataFrame([], "doc_id long, text string")
    assert similarity_classes(docs).collect() == []
    assert runs_for(0.8, 3, 0.999) > runs_for(0.8, 3, 0.99) > runs_for(0.9, 3, 0.99)


def test_components(spark):
    from winjoin.llm.frames import connected

    rnd = random.Random(3)
    edges = [(rnd.randrange(300), rnd.randrange(300)) for _ in range(160)] + [(1000 + i, 1001 + i) for i in range(60)] + [(2000, 2000 + i) for i in range(1, 50)] + [(7, 7)]
    root = {}

    def find(x):
        root.setdefault(x, x)
        while root[x] != x:
            x = root[x]
        return x

    for a, b in edges:
        ra, rb = find(a), find(b)
        if a != b:
            root[max(ra, rb)] = min(ra, rb)
    touched = {x for a, b in edges if a != b for x in (a, b)}
    got = connected(spark.createDataFrame(edges, "a long, b long")).collect()
    assert sorted(map(tuple, got)) == sorted((x, find(x)) for x in touched)


def test_no_link_of_the_given_documents_is_lost(spark):
    """All links of sf0.1 against an exact count from an inverted index of the sets."""
    from collections import Counter, defaultdict

    from winjoin.llm.chosen_path import _key, gram_sets

    docs = spark.read.parquet("/root/testdata/sf0.1/documents.parquet").select("doc_id", "text")
    table = docs.toArrow()
    sets = {}
    copies = Counter()
    of = {}
    for b in table.to_batches():
        for i, s in zip(b.column(0).to_pylist(), gram_sets(b.column(1), 5)):
            of[i] = _key(s) if len(s) else None
            if len(s):
                sets[of[i]] = s.tolist()
                copies[of[i]] += 1
    # prefix filter: sets of similarity 0.8 share one of the rarest (1 - 0.8) of the grams
    n = Counter(g for s in sets.values() for g in s)
    index = defaultdict(list)
    pairs = set()
    for k, s in sorted(sets.items(), key=lambda x: len(x[1])):
        rare = sorted(s, key=lambda g: (n[g], g))[: len(s) - -(-len(s) * 4 // 5) + 1]
        pairs.update((o, k) for g in rare for o in index[g])
        for g in rare:
            index[g].append(k)
    links = Counter({k: c - 1 for k, c in copies.items()})
    for a, b in pairs:
        x, y = set(sets[a]), set(sets[b])
        both = len(x & y)
        if both >= 0.8 * (len(x) + len(y) - both) - 1e-9:
            links[a] += copies[b]
            links[b] += copies[a]
    got = {r.doc_id: r.n_links for r in similarity_classes(docs).collect()}
    want = {i: links[k] if k else 0 for i, k in of.items()}
    assert sum(want.values()) > 1000 and got == want


@pytest.mark.parametrize("agreement", [0.7, 0.8])
def test_pairs_in_split_nodes_meet_deeper(agreement):
    """Pairs of sketches of a given agreement, all of whose shallow nodes are split: nearly all meet at the last depth."""
    import numpy as np

    from winjoin.llm import bytetext as B
    from winjoin.llm.chosen_path import WIDTH, paths

    rnd = np.random.default_rng(5)
    pairs = 1500
    one = rnd.integers(0, 2**32, (pairs, WIDTH), dtype=np.uint32)
    same = np.argsort(rnd.random((pairs, WIDTH)), axis=1) < round(agreement * WIDTH)
    two = np.where(same, one, rnd.integers(0, 2**32, (pairs, WIDTH), dtype=np.uint32))
    runs = runs_for(0.8, 6, 0.9995)

    def nodes(sketch):
        start = B.mix(np.repeat(np.arange(1, runs + 1, dtype=np.uint64), pairs))
        rows, node = paths(np.tile(sketch, (runs, 1)), start, 6)
        return set(zip((rows % pairs).tolist(), node.tolist()))

    met = {pair for pair, _ in nodes(one) & nodes(two)}
    assert len(met) >= 0.99 * pairs


def test_near_copies_are_tied_without_going_deeper():
    """Many near copies in one node: the search ties them as all pairs would, and opens none for further steps."""
    import numpy as np

    from winjoin.llm.chosen_path import WIDTH, search

    rnd = np.random.default_rng(2)
    base = rnd.integers(0, 2**32, (1, WIDTH), dtype=np.uint32)
    copies = np.where(rnd.random((600, WIDTH)) < 0.85, base, rnd.integers(0, 2**32, (600, WIDTH), dtype=np.uint32))
    others = rnd.integers(0, 2**32, (30, WIDTH), dtype=np.uint32)
    sketch = np.concatenate([others[:15], copies, others[15:]])
    ties, left = search(sketch, 0.6, 48, 512)
    assert len(left) == 0 and len(ties) == 599
    assert {x for t in ties for x in t} == set(range(15, 615))
    for x, y in ties:
        assert (sketch[x] == sketch[y]).sum() >= 0.6 * WIDTH


def test_a_search_without_end_leaves_what_is_open():
    import numpy as np

    from winjoin.llm.chosen_path import WIDTH, search

    sketch = np.random.default_rng(3).integers(0, 2**32, (400, WIDTH), dtype=np.uint32)
    sketch[399] = sketch[0]
    ties, left = search(sketch, 0.6, 4, 16)
    assert ties == [(0, 399)] and 300 < len(left) < 400 and 0 not in left
    assert len(search(sketch, 0.6, 4, 512)[1]) == 0


@pytest.mark.parametrize("options", [{"bucket": 2, "patience": 2, "block": 7}, {"bucket": 2, "patience": 3, "widest": 20}])
def test_open_nodes_against_all_pairs(spark, options):
    rows = corpus()
    docs = spark.createDataFrame([(i, t, 1) for i, t in rows], "doc_id long, text string, sid int")
    got = similarity_classes(docs, **options).select("doc_id", "class_id", "n_links").collect()
    assert Counter(map(tuple, got)) == Counter(brute(rows))
